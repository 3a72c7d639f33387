"""Benchmark decontamination with a positional inverted index.

A window is `WIDTH` consecutive words of an item; an item of fewer words is one window.  For each window
the rarest of its terms in the corpus is looked up: the index stores the postings (document, place) of
those terms only, and a posting shifted back by the term's place in the item names a diagonal, that is an
alignment of document and item.  Postings of the rarest and of the next rarest term of a window are
intersected on the diagonal; what remains is compared word by word along the diagonal, and runs of equal
words at least a window long are the exact matches.  `proximity_matches` uses the same index for terms that
stand within a distance of each other, in any order.

All of it is DataFrame operations.  The item side (a benchmark) is broadcast while it has at most
`BROADCAST_WORDS` words, beyond that the same joins shuffle.

Edge cases: null or empty texts have no words and match nothing; items without words have no window;
several items with equal windows all match; rows that repeat a document id are matched as one document
per distinct text and reported per row; a null id is reported like any other row; empty tables on either side give no
matches.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from fuzzcount.llm.text import BETWEEN_WORDS, lowered, trimmed_words
from fuzzcount.sources.tables import cut

WIDTH = 10
BROADCAST_WORDS = 1_000_000


def words_of(text: Column) -> Column:
    """The words of a text, in order."""
    return F.filter(F.split(lowered(text), BETWEEN_WORDS), lambda w: w != "")


def item_windows(items: DataFrame, width: int) -> tuple[DataFrame, DataFrame]:
    """Items with their words, and one row per window and place in it."""
    texts = items.select(F.col("item_id"), words_of(F.col("text")).alias("item")).where(F.size("item") > 0)
    size = F.least(F.size("item"), F.lit(width))
    starts = texts.withColumn("size", size).withColumn("first", F.explode(F.sequence(F.lit(0), F.size("item") - size)))
    places = starts.select("item_id", "first", "size", "item", F.explode(F.sequence(F.lit(0), F.col("size") - 1)).alias("at"))
    return texts, places.select("item_id", "first", (F.col("first") + F.col("at")).alias("place"), F.element_at("item", F.col("first") + F.col("at") + 1).alias("term"))


def corpus_frequency(docs: DataFrame, terms: DataFrame) -> DataFrame:
    """How often each of `terms` stands in the corpus."""
    tokens = docs.select(F.explode(F.split(trimmed_words(F.col("text")), " ")).alias("term"))
    return tokens.join(terms, "term", "left_semi").groupBy("term").agg(F.count("*").alias("seen"))


def anchors(places: DataFrame, seen: DataFrame, count: int = 2) -> DataFrame:
    """Of each window the `count` rarest places, as (item, place, term, rank, window)."""
    order = Window.partitionBy("item_id", "first").orderBy("seen", "term", "place")
    rated = places.join(seen, "term", "left").withColumn("seen", F.coalesce("seen", F.lit(0)))
    return rated.withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= count)


def postings(docs: DataFrame, terms: DataFrame) -> DataFrame:
    """The index: (row, term, place) of every occurrence of the terms."""
    tokens = docs.select("row", F.posexplode(F.split(F.trim(trimmed_words(F.col("text"))), " ")).alias("place", "term"))
    return tokens.join(terms, "term", "left_semi")


def phrase_matches(docs: DataFrame, items: DataFrame, width: int = WIDTH) -> DataFrame:
    """Runs of equal words as (row, item_id, start, stop): words of the document from start to before stop.

    `docs` has (row, text) with distinct rows; `items` has (item_id, text).
    """
    items = items.select("item_id", "text")
    texts, places = item_windows(items, width)
    texts, places = cut(texts), cut(places)
    small = (texts.agg(F.sum(F.size("item")).alias("n")).first()["n"] or 0) <= BROADCAST_WORDS
    sent = F.broadcast if small else (lambda df: df)
    chosen = cut(anchors(places, corpus_frequency(docs, sent(places.select("term").distinct()))))
    index = cut(postings(docs, sent(chosen.select("term").distinct())))

    lone = chosen.groupBy("item_id", "first").agg(F.count("*").alias("ranks"))
    chosen = cut(chosen.join(lone, ["item_id", "first"]).select("item_id", "first", "term", "rank", "ranks", F.col("place").alias("item_place")))

    def diagonals(rank: int) -> DataFrame:
        found = index.join(sent(chosen.where(F.col("rank") == rank)), "term")
        return found.select("row", "item_id", "first", "ranks", (F.col("place") - F.col("item_place")).alias("diagonal"))

    rarest = diagonals(1).where(F.col("diagonal") + F.col("first") >= 0)
    both = rarest.where("ranks > 1").join(diagonals(2), ["row", "item_id", "first", "diagonal"], "left_semi")
    aligned = cut(both.unionByName(rarest.where("ranks = 1")).select("row", "item_id", "diagonal").distinct())

    wanted = aligned.groupBy("row").agg(F.count("*").alias("alignments")).select("row")
    text_words = cut(docs.join(wanted, "row", "left_semi").select("row", words_of(F.col("text")).alias("words")))
    pairs = aligned.join(text_words, "row").join(sent(texts), "item_id")
    # Places of the item that agree with the document along the diagonal; -1 ends the last run.
    low, high = F.greatest(F.lit(0), -F.col("diagonal")), F.least(F.size("item"), F.size("words") - F.col("diagonal"))
    pairs = pairs.select("row", "item_id", "diagonal", low.alias("low"), F.least(F.size("item"), F.lit(width)).alias("least"), F.slice("item", low + 1, high - low).alias("item"), F.slice("words", low + F.col("diagonal") + 1, high - low).alias("words"))
    equal = F.zip_with("item", "words", lambda a, b: F.when(a == b, F.lit("1")).otherwise(F.lit("0")))
    runs = pairs.select("row", "item_id", "least", (F.col("low") + F.col("diagonal")).alias("base"), F.array_join(equal, "").alias("equal"))
    starts = runs.select(
        "row", "item_id", "least", "base",
        F.explode(F.filter(
            F.transform(F.sequence(F.lit(1), F.length("equal")), lambda i: F.when(
                (F.substring("equal", i, F.lit(1)) == "1") & ((i == 1) | (F.substring("equal", i - 1, F.lit(1)) == "0")),
                F.struct((i - 1).alias("at"), F.length(F.regexp_extract(F.substring("equal", i, F.length("equal")), "^1+", 0)).alias("size")))),
            lambda r: r.isNotNull())).alias("run"),
    )
    return starts.where("run.size >= least").select("row", "item_id", (F.col("base") + F.col("run.at")).alias("start"), (F.col("base") + F.col("run.at") + F.col("run.size")).alias("stop"))


def covered(spans: DataFrame) -> DataFrame:
    """(row, n_hit): words inside any span, overlaps counted once."""
    earlier = Window.partitionBy("row").orderBy("start", "stop").rowsBetween(Window.unboundedPreceding, -1)
    added = spans.select("row", "start", "stop").distinct().withColumn("reach", F.coalesce(F.max("stop").over(earlier), F.lit(0)))
    return added.groupBy("row").agg(F.sum(F.greatest(F.lit(0), F.col("stop") - F.greatest("start", "reach"))).cast("bigint").alias("n_hit"))


def n_words(text: Column) -> Column:
    """How many words a text has."""
    normal = F.trim(trimmed_words(text))
    return F.when(normal == "", 0).otherwise(F.length(normal) - F.length(F.replace(normal, F.lit(" "), F.lit(""))) + 1).cast("bigint")


def row_key(row_id: Column, text: Column) -> Column:
    """A key that is equal for rows with equal id and text, without nulls inside."""
    return F.struct(F.coalesce(row_id.cast("string"), F.lit("")).alias("id"), row_id.isNull().alias("none"), F.xxhash64(F.coalesce(text, F.lit(""))).alias("text"))


def contamination(docs: DataFrame, items: DataFrame, width: int = WIDTH) -> DataFrame:
    """One row per row of `docs` (doc_id, text): n_words, n_hit, n_items, items_sha256, contaminated."""
    rows = docs.select("doc_id", F.coalesce("text", F.lit("")).alias("text")).withColumn("row", row_key(F.col("doc_id"), F.col("text")))
    spans = cut(phrase_matches(rows.select("row", "text"), items, width))
    hits = covered(spans)
    named = spans.select("row", F.col("item_id").cast("string").alias("item")).distinct().groupBy("row").agg(F.count("*").alias("n_items"), F.sha2(F.array_join(F.array_sort(F.collect_list("item")), ","), 256).alias("items_sha256"))
    found = cut(hits.join(named, "row"))
    counted = rows.select("doc_id", "row", n_words(F.col("text")).alias("n_words"))
    return counted.join(found, "row", "left").select(
        "doc_id", "n_words", F.coalesce("n_hit", F.lit(0)).cast("bigint").alias("n_hit"), F.coalesce("n_items", F.lit(0)).cast("bigint").alias("n_items"),
        F.coalesce("items_sha256", F.sha2(F.lit(""), 256)).alias("items_sha256"), (F.coalesce("n_hit", F.lit(0)) > 0).alias("contaminated"),
    )


def proximity_matches(docs: DataFrame, terms: list[str], distance: int) -> DataFrame:
    """(row, start, stop) of places where all terms stand within `distance` words, from the rarest term's postings."""
    terms = sorted(set(terms))
    table = docs.sparkSession.createDataFrame([(t,) for t in terms], "term string")
    index = cut(postings(docs, F.broadcast(table)))
    seen = {r["term"]: r["n"] for r in index.groupBy("term").agg(F.count("*").alias("n")).collect()}  # one row per term asked for
    if len(seen) < len(terms):
        return index.where("false").select("row", F.col("place").alias("start"), F.col("place").alias("stop"))
    rarest = min(terms, key=lambda t: (seen[t], t))
    centre = index.where(F.col("term") == rarest).select("row", F.col("place").alias("centre"), F.floor(F.col("place") / distance).alias("cell"))
    others = index.where(F.col("term") != rarest).select("row", "term", "place", F.explode(F.array(*(F.floor(F.col("place") / distance) + i for i in (-1, 0, 1)))).alias("cell"))
    close = centre.join(others, ["row", "cell"]).where(F.abs(F.col("place") - F.col("centre")) <= distance)
    nearest = close.groupBy("row", "centre", "term").agg(F.min_by("place", F.abs(F.col("place") - F.col("centre"))).alias("place"))
    spans = nearest.groupBy("row", "centre").agg(F.count("*").alias("n"), F.min("place").alias("lo"), F.max("place").alias("hi")).where(F.col("n") == len(terms) - 1)
    return spans.select("row", F.least("centre", "lo").alias("start"), (F.greatest("centre", "hi") + 1).alias("stop"))


def drop_contaminated(docs: DataFrame, items: DataFrame, width: int = WIDTH, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """`docs` without the rows that hold any window of an item."""
    named = docs.withColumn("__row", row_key(F.col(id_col), F.col(text_col)))
    rows = named.select(F.col("__row").alias("row"), F.coalesce(F.col(text_col), F.lit("")).alias("text"))
    hit = cut(phrase_matches(rows, items, width).select(F.col("row").alias("__row")).distinct())
    return named.join(hit, "__row", "left_anti").select(*docs.columns)
