"""Corruption of records: edits, character confusions and phonetic rewrites at keyed places."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from fuzzcount.functions.digest import num

OPS = ("insert", "delete", "substitute", "transpose", "ocr", "phonetic")
#: Characters that are confused, and rewrites that keep the sound.
OCR = ("olsbzg", "015829")
PHONETIC = (("ph", "f"), ("ck", "k"), ("w", "v"), ("ie", "y"), ("c", "k"))


def edit(text: Column, op: str, key: Column) -> Column:
    """One edit at the place that the key draws; a text too short for it stays."""
    n = F.length(text)
    at = F.pmod(num(F.concat(F.lit("at|"), key)), F.greatest(n - (1 if op == "transpose" else 0), F.lit(1))) + 1
    at = at.cast("int")
    letter = F.substring(F.lit("abcdefghijklmnopqrstuvwxyz"), (F.pmod(num(F.concat(F.lit("letter|"), key)), F.lit(26)) + 1).cast("int"), F.lit(1))
    head, tail = F.substring(text, F.lit(1), at - 1), F.substring(text, at, n)
    if op == "insert":
        return F.concat(head, letter, tail)
    if op == "delete":
        return F.when(n < 2, text).otherwise(F.concat(head, F.substring(text, at + 1, n)))
    if op == "substitute":
        return F.when(n < 1, text).otherwise(F.concat(head, letter, F.substring(text, at + 1, n)))
    return F.when(n < 2, text).otherwise(F.concat(head, F.substring(text, at + 1, F.lit(1)), F.substring(text, at, F.lit(1)), F.substring(text, at + 2, n)))


def ocr(text: Column) -> Column:
    return F.translate(text, *OCR)


def phonetic(text: Column) -> Column:
    for was, now in PHONETIC:
        text = F.replace(text, F.lit(was), F.lit(now))
    return text


def corrupted(panel: DataFrame, percent: int, key: str = "c") -> DataFrame:
    """`panel` with exactly that share of its records changed: one attribute, one operation each, by keyed rank.

    The rank is taken inside blocks of owners, so the work is split; extra columns `op` and `attr` tell what was done.
    """
    draw = num(F.concat_ws("|", F.lit(key), F.col("owner"), F.col("rec_id").cast("string")))
    order, block = Window.partitionBy("owner").orderBy("draw", "rec_id"), Window.partitionBy("owner")
    ranked = panel.withColumn("draw", draw).withColumn("rank", F.row_number().over(order)).withColumn("n", F.count("*").over(block))
    id_text = F.col("rec_id").cast("string")
    attrs = ("given", "surname", "suburb")
    chosen = F.element_at(F.array(*map(F.lit, attrs)), (F.pmod(num(F.concat(F.lit("attr|"), id_text)), F.lit(len(attrs))) + 1).cast("int"))
    done = F.element_at(F.array(*map(F.lit, OPS)), (F.pmod(num(F.concat(F.lit("op|"), id_text)), F.lit(len(OPS))) + 1).cast("int"))
    hit = F.col("rank") <= F.round(percent * F.col("n") / 100)
    marked = ranked.withColumn("attr", F.when(hit, chosen)).withColumn("op", F.when(hit, done))

    def changed(name: str) -> Column:
        text, out = F.col(name), F.col(name)
        for op in OPS:
            new = ocr(text) if op == "ocr" else phonetic(text) if op == "phonetic" else edit(text, op, id_text)
            out = F.when((F.col("attr") == name) & (F.col("op") == op), new).otherwise(out)
        return out

    return marked.withColumns({a: changed(a) for a in attrs}).drop("draw", "rank", "n")
