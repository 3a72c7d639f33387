"""Bytes covered by long strings that occur more than once: suffix-array deduplication in bins.

Every string of `LENGTH` bytes is assigned to the least hash among its substrings of `ANCHOR` bytes (its
minimiser), so equal strings meet in one bin wherever they stand.  Neighbouring strings with the same
minimiser are kept as one stretch of text.  A stretch whose bytes occur elsewhere as a whole is repeated
throughout and needs no comparison.  Distinct stretches that share a minimiser are compared inside their
bin on a Burrows-Wheeler transform: a breadth-first backward extension visits the intervals of common
prefixes by increasing length and marks where a longer one ends; it stops at `LENGTH`, and what it has not
marked by then are neighbours in suffix order that share at least `LENGTH` bytes.
A bin with more than `BIN_BYTES` of distinct stretches is not put into one task: its stretches are split
further, where the next least hash inside a string changes, and equal strings meet in a smaller bin; parts
that are equal as a whole are repeated throughout, and one of them goes on.
Bins that stay as large after `LEVELS` such splits (hundreds of strings that are equal but for a few bytes)
are counted by a 128-bit hash of each string instead, which gives the same marks.

Stretches are taken as equal if their minimisers, lengths and 128-bit hashes are.

Texts that are equal as wholes are represented by one of them; if they are long enough all their bytes go.
Spans are judged on the input; matches never cross documents; overlaps and the same document count.

Edge cases: a null text is empty; texts shorter than `LENGTH` keep all bytes; rows that share an id are
treated each for itself; very long runs of one byte are stretches like any other; an empty table gives no rows.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator
from functools import reduce

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from fuzzcount.sources.tables import cut, drop

LENGTH, ANCHOR = 400, 64
BIN_BYTES, BATCH, TASK_BYTES, LEVELS = 1 << 18, 1 << 20, 8 << 20, 4
PIECE = 1 << 22
_U = np.uint64
_B, _B2 = _U(0x9E3779B97F4A7C15), _U(0xC2B2AE3D27D4EB4F)


def window_hashes(data: np.ndarray, width: int, base: np.uint64 = _B) -> np.ndarray:
    """A 64-bit polynomial hash of each substring of `width` bytes, by doubling."""
    n = len(data)
    if n < width:
        return np.empty(0, _U)
    table = (np.arange(1, 257, dtype=_U) * _U(0xBF58476D1CE4E5B9)) ^ _U(0x94D049BB133111EB)
    level, size, factor = table[data], 1, int(base)
    result, covered = None, 0
    while True:
        if width & size:
            if result is None:
                result, covered = level, size
            else:  # what is covered so far, followed by this level's block
                m = n - covered - size + 1
                result, covered = result[:m] * _U(factor) + level[covered : covered + m], covered + size
        if size * 2 > width:
            break
        m = n - 2 * size + 1
        level = level[:m] * _U(factor) + level[size : size + m]
        size, factor = size * 2, factor * factor & 0xFFFFFFFFFFFFFFFF
    return _spread(result[: n - width + 1])


def _spread(x: np.ndarray) -> np.ndarray:
    x = (x ^ (x >> _U(32))) * _U(0xD6E8FEB86659FD93)
    x = (x ^ (x >> _U(32))) * _U(0xD6E8FEB86659FD93)
    return x ^ (x >> _U(32))


def sliding_minimum(values: np.ndarray, width: int) -> np.ndarray:
    """The least of each `width` neighbours."""
    size, level = 1, values
    while size * 2 <= width:
        level = np.minimum(level[:-size], level[size:])
        size *= 2
    rest = width - size
    return np.minimum(level[: len(level) - rest], level[rest:]) if rest else level


def stretches(data: np.ndarray) -> Iterator[tuple[int, int, int, bool]]:
    """(minimiser, start, length, twice) of maximal stretches whose strings of `LENGTH` bytes share a minimiser.

    `twice` says that the minimiser stands there more than once; else no string does.
    """
    if len(data) < LENGTH:
        return
    for at in range(0, len(data) - LENGTH + 1, PIECE):
        part = data[at : at + PIECE + LENGTH - 1]
        hashes = window_hashes(part, ANCHOR)
        least = sliding_minimum(hashes, LENGTH - ANCHOR + 1)
        starts = np.flatnonzero(np.r_[True, least[1:] != least[:-1]])
        ends = np.r_[starts[1:], len(least)]
        for start, end, value in zip(starts.tolist(), ends.tolist(), least[starts].tolist(), strict=True):
            twice = np.count_nonzero(hashes[start : end + LENGTH - ANCHOR] == value) > 1
            yield value, at + start, end - start + LENGTH - 1, twice


def suffix_order(symbols: np.ndarray, depth: int) -> np.ndarray:
    """Suffixes sorted by their first `depth` symbols at least, by doubling."""
    n, size = len(symbols), 1
    rank = symbols.astype(np.int64)
    order = np.argsort(rank, kind="stable")
    while True:
        steps = np.cumsum(np.r_[False, np.diff(rank[order]) != 0])
        rank[order] = steps
        if size >= depth or steps[-1] == n - 1:
            return order
        rank *= n + 1
        rank[: n - size] += rank[size:] // (n + 1) + 1
        order = np.argsort(rank)
        size *= 2


def long_neighbours(symbols: np.ndarray, length: int) -> np.ndarray:
    """Marks each suffix that shares `length` symbols with another one.

    `marked[i]` says that the suffixes at i - 1 and i of the order share fewer symbols.  An interval of
    suffixes with a common prefix is extended by each symbol that stands before one of them; where the
    end of the new interval is not marked yet, its common prefix ends there, it is marked and the
    interval goes on.  Runs of equal symbols in the transform are taken as one.
    """
    n = len(symbols)
    order = suffix_order(symbols, length + 1)
    before = symbols[order - 1]
    by_symbol = np.argsort(before, kind="stable")
    step = np.empty(n, np.int64)
    step[by_symbol] = np.arange(n)
    run_starts = np.flatnonzero(np.r_[True, before[1:] != before[:-1]])
    run_ends = np.r_[run_starts[1:], n] - 1
    run_of = np.cumsum(np.r_[True, before[1:] != before[:-1]]) - 1
    symbol_of, width = before[run_starts].astype(np.int64), int(before.max()) + 1
    marked = np.zeros(n + 1, bool)
    marked[0] = marked[n] = True
    low, high = np.array([0]), np.array([n - 1])
    for _ in range(length):
        if not len(low):
            break
        first = run_of[low]
        counts = run_of[high] - first + 1
        owner = np.repeat(np.arange(len(low)), counts)
        runs = np.arange(len(owner)) - np.repeat(np.cumsum(counts) - counts, counts) + first[owner]
        key = owner * width + symbol_of[runs]
        by_key = np.argsort(key, kind="stable")
        key = key[by_key]
        heads = np.flatnonzero(np.r_[True, key[1:] != key[:-1]])
        a, b = by_key[heads], by_key[np.r_[heads[1:], len(key)] - 1]
        new_low = step[np.maximum(run_starts[runs[a]], low[owner[a]])]
        new_high = step[np.minimum(run_ends[runs[b]], high[owner[b]])]
        go = ~marked[new_high + 1]
        low, high = new_low[go], new_high[go]
        marked[high + 1] = True
    at = np.flatnonzero(~marked)
    out = np.zeros(n, bool)
    out[order[at]] = True
    out[order[at - 1]] = True
    return out


def ranges(flags: np.ndarray) -> list[tuple[int, int]]:
    """(start, end) of each run of true values."""
    edges = np.flatnonzero(np.diff(np.r_[False, flags, False].astype(np.int8)))
    return list(zip(edges[::2].tolist(), edges[1::2].tolist(), strict=True))


def repeated_starts(texts: list[bytes], length: int) -> list[list[tuple[int, int]]]:
    """Of each text the ranges of starts whose string of `length` bytes occurs elsewhere in `texts`."""
    sizes = np.array([len(t) for t in texts])
    begins = np.cumsum(sizes + 1) - sizes - 1
    symbols = np.empty(int((sizes + 1).sum()), np.int32)
    for i, (text, at) in enumerate(zip(texts, begins.tolist(), strict=True)):
        symbols[at : at + len(text)] = np.frombuffer(text, np.uint8)
        symbols[at + len(text)] = 256 + i  # a symbol of its own, so that no match runs over it
    found = long_neighbours(symbols, length)
    return [ranges(found[at : at + size]) for at, size in zip(begins.tolist(), sizes.tolist(), strict=True)]


KEY = "struct<id:bigint,text:bigint>"
STRETCHES = f"key {KEY}, minimisers array<bigint>, hashes array<binary>, starts array<int>, lengths array<int>, weights array<int>"


def _stretch_rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        for at in range(0, batch.num_rows, 500):
            part = batch.slice(at, 500)
            found, ends = [], [0]
            for text in part.column(1).cast(pa.binary()):
                view = text.as_buffer()
                if view is not None and len(view) >= LENGTH:
                    data = memoryview(view)
                    found += [(m, xxhash.xxh3_128_digest(data[s : s + n]), s, n, 1 + twice) for m, s, n, twice in stretches(np.frombuffer(view, np.uint8))]
                ends.append(len(found))
            offsets = pa.array(ends, pa.int32())
            columns = list(zip(*found, strict=True)) or [()] * 5
            arrays = [pa.array(np.array(columns[0], np.uint64).view(np.int64)), pa.array(columns[1], pa.binary()), *(pa.array(np.array(c, np.int32)) for c in columns[2:])]
            yield pa.RecordBatch.from_arrays([part.column(0), *(pa.ListArray.from_arrays(offsets, c) for c in arrays)], names=["key", "minimisers", "hashes", "starts", "lengths", "weights"])


#: Stretches or parts of them: `bin` says what they are compared with, `at` where they begin in the stretch.
BODIES = "bin bigint, minimiser bigint, hash binary, at int, bytes binary"
MARKS = "minimiser bigint, hash binary, first int, end int"
_BODY = pa.schema([("bin", pa.int64()), ("minimiser", pa.int64()), ("hash", pa.binary()), ("at", pa.int32()), ("bytes", pa.binary())])
_PART = _BODY.append(pa.field("part", pa.binary()))
_MARK = pa.schema([("minimiser", pa.int64()), ("hash", pa.binary()), ("first", pa.int32()), ("end", pa.int32())])


def _table(rows: list[tuple], schema: pa.Schema) -> pa.RecordBatch:
    columns = list(zip(*rows, strict=True)) or [()] * len(schema)
    return pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(columns, schema.types, strict=True)], schema=schema)


def _cut_out(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """(text, wanted) to the bytes of each wanted stretch."""
    for batch in batches:
        for at in range(0, batch.num_rows, 200):
            part, rows = batch.slice(at, 200), []
            for text, wanted in zip(part.column(0).cast(pa.binary()), part.column(1), strict=True):
                data = text.as_py()
                rows += [(w["minimiser"], w["minimiser"], w["hash"], 0, data[w["start"] : w["start"] + w["length"]]) for w in wanted.as_py()]
            yield _table(rows, _BODY)


def narrower(data: np.ndarray, level: int) -> Iterator[tuple[int, int, int]]:
    """(hash, start, length) of maximal parts whose strings of `LENGTH` bytes agree in their `level` + 1 least distinct hashes."""
    hashes = window_hashes(data, ANCHOR)
    width = LENGTH - ANCHOR + 1
    if level == 1:  # all strings of a stretch share the least one
        left = np.where(hashes == sliding_minimum(hashes, width)[0], np.iinfo(_U).max, hashes)
        next_least = sliding_minimum(left, width)
    else:
        least = (np.unique(hashes[i : i + width])[: level + 1] for i in range(len(hashes) - width + 1))  # fewer in periodic strings
        next_least = np.array([(x * _B ** np.arange(1, len(x) + 1, dtype=_U)).sum() for x in least], _U)
    starts = np.flatnonzero(np.r_[True, next_least[1:] != next_least[:-1]])
    ends = np.r_[starts[1:], len(next_least)]
    for start, end, value in zip(starts.tolist(), ends.tolist(), next_least[starts].view(np.int64).tolist(), strict=True):
        yield value, start, end - start + LENGTH - 1


def _narrowed(level: int):
    """Rows of bodies to rows of their parts in smaller bins, with a digest of each part."""

    def split(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for at in range(0, batch.num_rows, 100):
                rows = []
                for _, minimiser, name, offset, data in zip(*(batch.slice(at, 100).column(i).to_pylist() for i in range(5)), strict=True):
                    for value, start, length in narrower(np.frombuffer(data, np.uint8), level):
                        key = xxhash.xxh3_64_intdigest(value.to_bytes(8, "little", signed=True) + minimiser.to_bytes(8, "little", signed=True), level)
                        part = data[start : start + length]
                        rows.append((key - (1 << 63), minimiser, name, offset + start, part, xxhash.xxh3_128_digest(part)))
                yield _table(rows, _PART)

    return split


def _compare(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Rows of bodies, sorted by bin, to the repeated starts of each stretch."""

    def marks(rows: list[tuple]) -> pa.RecordBatch:
        found = repeated_starts([r[4] for r in rows], LENGTH)
        return _table([(r[1], r[2], r[3] + a, r[3] + b) for r, spans in zip(rows, found, strict=True) for a, b in spans], _MARK)

    held: list[tuple] = []
    size = 0
    for batch in batches:
        for row in zip(*(batch.column(i).to_pylist() for i in range(5)), strict=True):
            if size >= BATCH and row[0] != held[-1][0]:
                yield marks(held)
                held, size = [], 0
            held.append(row)
            size += len(row[4])
    if held:
        yield marks(held)


def _strings(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Rows of bodies to two hashes of each string of `LENGTH` bytes in them."""
    for batch in batches:
        for _, minimiser, name, at, data in zip(*(batch.column(i).to_pylist() for i in range(5)), strict=True):
            data = np.frombuffer(data, np.uint8)
            one, two = (window_hashes(data, LENGTH, base).view(np.int64) for base in (_B, _B2))
            n = len(one)
            yield pa.RecordBatch.from_arrays(
                [pa.array(np.full(n, minimiser)), pa.array([name] * n, pa.binary()), pa.array(np.arange(at, at + n, dtype=np.int32)), pa.array(one), pa.array(two)], names=["minimiser", "hash", "first", "one", "two"]
            )


def _without(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """(doc_id, text, spans) to what is left of the text."""
    for batch in batches:
        rows = []
        for doc_id, text, spans in zip(batch.column(0).to_pylist(), batch.column(1).cast(pa.binary()), batch.column(2), strict=True):
            removed, n_spans, reach, kept = 0, 0, 0, hashlib.sha256()
            view, wanted = memoryview(text.as_py()), sorted((s["start"], s["stop"]) for s in spans.as_py() or ())
            last = -1
            for start, stop in wanted:
                if start > last:
                    n_spans += 1
                    kept.update(view[reach:start])
                    removed += stop - start
                    reach = last = stop
                elif stop > last:
                    removed += stop - last
                    reach = last = stop
            kept.update(view[reach:])
            rows.append((doc_id, len(view), removed, n_spans, kept.hexdigest()))
        columns = list(zip(*rows, strict=True)) or [()] * 5
        yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(columns, (*[pa.int64()] * 4, pa.string()), strict=True)], names=["doc_id", "n_bytes", "n_removed", "n_spans", "kept_sha256"])


def keyed(docs: DataFrame) -> DataFrame:
    """`docs` (doc_id, text) with a key that is equal for equal rows, and no null."""
    text = F.coalesce("text", F.lit(""))
    id_or_none = F.coalesce(F.col("doc_id").cast("bigint"), F.lit(-(1 << 63)))
    return docs.select(F.struct(id_or_none.alias("id"), F.xxhash64(text).alias("text")).alias("key"), F.col("doc_id").cast("bigint").alias("doc_id"), text.alias("text"))


def marks_by_count(bodies: DataFrame) -> DataFrame:
    """What `_compare` gives, by counting the strings of all stretches: for bins that no split makes small enough for a task."""
    strings = cut(bodies.mapInArrow(_strings, "minimiser bigint, hash binary, first int, one bigint, two bigint"))
    often = cut(strings.groupBy("minimiser", "one", "two").agg(F.count("*").alias("n")).where("n > 1").select("minimiser", "one", "two"))  # a join of its own can be split
    found = strings.join(often, ["minimiser", "one", "two"]).select("minimiser", "hash", "first").distinct()
    order = Window.partitionBy("minimiser", "hash").orderBy("first")
    found = found.withColumn("island", F.col("first") - F.row_number().over(order))
    return found.groupBy("minimiser", "hash", "island").agg(F.min("first").alias("first"), (F.max("first") + 1).alias("end")).drop("island")


def compared(bodies: DataFrame) -> list[DataFrame]:
    """Tables of marks (minimiser, hash, first, end) of all `bodies`; bins too large for a task are split before."""
    spark, found, level = bodies.sparkSession, [], 0
    while True:
        loads = bodies.groupBy("bin").agg(F.sum(F.octet_length("bytes")).alias("load"))
        sizes = loads.agg(F.sum(F.when(F.col("load") <= BIN_BYTES, F.col("load"))).alias("small"), F.max("load").alias("most")).first()
        large = (sizes["most"] or 0) > BIN_BYTES
        hot = cut(loads.where(F.col("load") > BIN_BYTES).select("bin")) if large else None
        tasks = max(-(-(sizes["small"] or 0) // TASK_BYTES), int(spark.conf.get("spark.sql.shuffle.partitions")))
        small = bodies.join(hot, "bin", "left_anti") if large else bodies
        found.append(cut(small.repartition(tasks, "bin").sortWithinPartitions("bin").mapInArrow(_compare, MARKS)))
        if not large:
            return found
        rest, level = bodies.join(hot, "bin", "left_semi"), level + 1
        if level > LEVELS:
            return [*found, cut(marks_by_count(rest))]
        parts = cut(rest.mapInArrow(_narrowed(level), f"{BODIES}, part binary"))
        same = cut(parts.groupBy("bin", "part").agg(F.count("*").alias("n"), F.min(F.struct("minimiser", "hash", "at")).alias("one")).where("n > 1").select("bin", "part", "one"))
        copies = parts.join(same, ["bin", "part"])
        found.append(cut(copies.select("minimiser", "hash", F.col("at").alias("first"), (F.col("at") + F.octet_length("bytes") - LENGTH + 1).alias("end"))))
        first = F.col("one").isNull() | (F.col("one") == F.struct("minimiser", "hash", "at"))
        drop(bodies, hot)
        bodies = cut(parts.join(same, ["bin", "part"], "left").where(first).select("bin", "minimiser", "hash", "at", "bytes"))
        drop(parts, same)


def repeated_spans(texts: DataFrame) -> DataFrame:
    """`texts` (key, text) to (key, start, stop) of bytes in repeated strings; spans may overlap."""
    stretched = cut(texts.mapInArrow(_stretch_rows, STRETCHES))
    each = stretched.select("key", F.inline(F.arrays_zip("minimisers", "hashes", "starts", "lengths", "weights"))).toDF("key", "minimiser", "hash", "start", "length", "weight")
    shared = cut(each.groupBy("minimiser").agg(F.sum("weight").alias("n")).where("n > 1").select("minimiser"))
    places = cut(each.join(shared, "minimiser"))
    drop(stretched, shared)
    kinds = cut(places.groupBy("minimiser", "hash", "length").agg(F.count("*").alias("copies"), F.max("weight").alias("weight"), F.min(F.struct("key", "start")).alias("at")))
    whole = kinds.where("copies > 1").select("minimiser", "hash", F.lit(0).alias("first"), (F.col("length") - LENGTH + 1).alias("end"))

    several = kinds.groupBy("minimiser").agg(F.count("*").alias("kinds"), F.max("weight").alias("weight")).where("kinds > 1 OR weight > 1").select("minimiser")
    wanted = kinds.join(several, "minimiser").groupBy(F.col("at.key").alias("key")).agg(F.collect_list(F.struct("minimiser", "hash", F.col("at.start").alias("start"), "length")).alias("wanted"))
    bodies = cut(texts.join(wanted, "key").select("text", "wanted").mapInArrow(_cut_out, BODIES))
    found = compared(bodies)
    marks = cut(reduce(DataFrame.unionByName, found, whole))
    drop(bodies, kinds, *found)
    return places.join(marks, ["minimiser", "hash"]).select("key", (F.col("start") + F.col("first")).alias("start"), (F.col("start") + F.col("end") - 1 + LENGTH).alias("stop"))


CLEANED = "doc_id bigint, n_bytes bigint, n_removed bigint, n_spans bigint, kept_sha256 string"


def removed(docs: DataFrame) -> DataFrame:
    """One row per row of `docs` (doc_id, text): n_bytes, n_removed, n_spans, kept_sha256."""
    texts = keyed(docs)
    spans = cut(repeated_spans(texts.select("key", "text")).groupBy("key").agg(F.collect_set(F.struct("start", "stop")).alias("spans")))
    return texts.join(spans, "key", "left").select("doc_id", "text", "spans").mapInArrow(_without, CLEANED)
