"""Exact deduplication behind a cuckoo filter.

Texts are equal when they are identical after A-Z is lower-cased; of equal texts the row with the
largest id stays.  A partition offers its rows to a `LiveIndex`: a cuckoo filter says at once that a
digest is new; a hit is verified against the content bucket of that digest, since a fingerprint may
agree by chance.  When a later copy takes over, the earlier digest is deleted and the later one
inserted, so the filter always describes the live rows.  When no slot is free the filter is rebuilt
at twice the size from the stored keys.

Copies are folded twice, first where the rows are and then by digest, so a group with a third of
all rows sends a few rows per partition through the shuffle.  The first fold passes its index on and starts
a new one whenever `MOST_LIVE` digests are live; the second has so many tasks that none gets many more, so
neither's memory grows with the corpus.  The join back to the rows splits large groups.

Edge cases: a null text counts as empty; empty texts are equal to each other; rows that share id and
text are copies of each other and are all kept as rows of the result (each with the same `keep_id`);
a null id loses to any other id, and is null where a group has no other; an empty table gives no rows.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from fuzzcount.llm.text import lowered
from fuzzcount.sources.tables import cut

SLOTS, MAX_KICKS = 4, 256
#: Digests that an index of one task holds, about 400 bytes each.
MOST_LIVE = 250_000


class CuckooFilter:
    """Fingerprints of 16 bits in buckets of four; supports lookup, insertion and deletion."""

    def __init__(self, buckets: int = 1024):
        self.mask = buckets - 1
        assert buckets & self.mask == 0, "a power of two"
        self.table = np.zeros((buckets, SLOTS), np.uint16)
        self.turn = 0

    @staticmethod
    def fingerprint(digest: bytes) -> int:
        return int.from_bytes(digest[8:10], "little") or 1

    def homes(self, digest: bytes) -> tuple[int, int, int]:
        mark = self.fingerprint(digest)
        first = int.from_bytes(digest[:8], "little") & self.mask
        return mark, first, self.other(first, mark)

    def other(self, bucket: int, mark: int) -> int:
        return (bucket ^ (mark * 0x5BD1E995)) & self.mask

    def __contains__(self, digest: bytes) -> bool:
        mark, a, b = self.homes(digest)
        return mark in self.table[a] or mark in self.table[b]

    def insert(self, digest: bytes) -> bool:
        """False when no slot could be freed; the filter must then be rebuilt."""
        mark, a, b = self.homes(digest)
        for bucket in (a, b):
            free = np.flatnonzero(self.table[bucket] == 0)
            if len(free):
                self.table[bucket, free[0]] = mark
                return True
        bucket = b
        for _ in range(MAX_KICKS):
            self.turn = (self.turn + 1) % SLOTS
            mark, self.table[bucket, self.turn] = int(self.table[bucket, self.turn]), mark
            bucket = self.other(bucket, mark)
            free = np.flatnonzero(self.table[bucket] == 0)
            if len(free):
                self.table[bucket, free[0]] = mark
                return True
        return False

    def delete(self, digest: bytes) -> bool:
        mark, a, b = self.homes(digest)
        for bucket in (a, b):
            at = np.flatnonzero(self.table[bucket] == mark)
            if len(at):
                self.table[bucket, at[0]] = 0
                return True
        return False


class LiveIndex:
    """The live row of each digest: `offer` copies, `remove` digests, `items` what is live."""

    def __init__(self, buckets: int = 1024):
        self.content: dict[int, list[list]] = {}
        self.size = self.resizes = self.false_hits = 0
        self._start(buckets)

    def _start(self, buckets: int) -> None:
        self.filter, self.buckets = CuckooFilter(buckets), buckets

    def _bucket(self, digest: bytes) -> int:
        return int.from_bytes(digest[:8], "little") & (self.buckets - 1)

    def _grow(self) -> None:
        """Twice the buckets, and again until every stored key has a slot."""
        kept = [entry for bucket in self.content.values() for entry in bucket]
        buckets = self.buckets
        while True:
            buckets *= 2
            self.resizes += 1
            self._start(buckets)
            if all(self.filter.insert(entry[0]) for entry in kept):
                break
        self.content = {}
        for entry in kept:
            self.content.setdefault(self._bucket(entry[0]), []).append(entry)

    def _add(self, digest: bytes) -> None:
        if self.size >= self.buckets * SLOTS * 0.9:
            self._grow()
        while not self.filter.insert(digest):
            self._grow()

    def find(self, digest: bytes) -> list | None:
        """The live entry [digest, id, copies]; a filter hit counts only if the content agrees."""
        if digest not in self.filter:
            return None
        for entry in self.content.get(self._bucket(digest), ()):
            if entry[0] == digest:
                return entry
        self.false_hits += 1
        return None

    def offer(self, digest: bytes, row_id: int | None, copies: int = 1) -> None:
        entry = self.find(digest)
        if entry is None:
            self._add(digest)
            self.content.setdefault(self._bucket(digest), []).append([digest, row_id, copies])
            self.size += 1
            return
        copies += entry[2]
        if row_id is not None and (entry[1] is None or row_id > entry[1]):
            self.remove(digest)
            self._add(digest)
            self.content.setdefault(self._bucket(digest), []).append([digest, row_id, copies])
            self.size += 1
        else:
            entry[2] = copies

    def remove(self, digest: bytes) -> bool:
        entry = self.find(digest)
        if entry is None:
            return False
        self.filter.delete(digest)
        self.content[self._bucket(digest)].remove(entry)
        self.size -= 1
        return True

    def items(self) -> Iterator[list]:
        for bucket in self.content.values():
            yield from bucket


FOLDED = "digest binary, keep_id bigint, group_size bigint"


def _told(index: LiveIndex) -> Iterator[pa.RecordBatch]:
    found = list(index.items())
    for at in range(0, len(found), 20_000):
        part = found[at : at + 20_000]
        yield pa.RecordBatch.from_arrays(
            [pa.array([e[0] for e in part], pa.binary()), pa.array([e[1] for e in part], pa.int64()), pa.array([e[2] for e in part], pa.int64())],
            names=["digest", "keep_id", "group_size"],
        )


def _folding(most: float):
    """Rows of `FOLDED` to one row for each digest; with more than `most` of them live, what is known so far goes on first."""

    def fold(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        index = LiveIndex()
        for batch in batches:
            for digest, row_id, copies in zip(*(batch.column(i).to_pylist() for i in range(3)), strict=True):
                index.offer(digest, row_id, copies)
            if index.size >= most:
                yield from _told(index)
                index = LiveIndex()
        yield from _told(index)

    return fold


def exact_groups(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row per row of `docs`: its id, `keep_id`, `group_size`, `kept` and `text_sha256`."""
    rows = cut(docs.select(F.col(id_col).cast("bigint").alias("doc_id"), F.unhex(F.sha2(lowered(F.col(text_col)), 256)).alias("digest")))
    tasks = max(int(docs.sparkSession.conf.get("spark.sql.shuffle.partitions")), -(-rows.count() // MOST_LIVE))
    near = rows.select("digest", F.col("doc_id").alias("keep_id"), F.lit(1).cast("bigint").alias("group_size")).mapInArrow(_folding(MOST_LIVE), FOLDED)
    groups = cut(near.repartition(tasks, "digest").mapInArrow(_folding(float("inf")), FOLDED))
    return rows.join(groups, "digest").select(
        "doc_id",
        "keep_id",
        "group_size",
        F.col("doc_id").eqNullSafe(F.col("keep_id")).alias("kept"),
        F.lower(F.hex("digest")).alias("text_sha256"),
    )


def drop_exact_copies(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """`docs` without the rows that a later copy replaces; rows with a null id stay only where no copy has an id.

    Rows that repeat both id and text are reduced to one.
    """
    none = -(1 << 63)
    stay = exact_groups(docs, id_col, text_col).where("kept").groupBy(F.coalesce("doc_id", F.lit(none)).alias("__id"), F.col("text_sha256").alias("__digest"))
    stay = cut(stay.agg(F.count("*").alias("__rows")))
    named = docs.withColumn("__digest", F.sha2(lowered(F.col(text_col)), 256)).withColumn("__id", F.coalesce(F.col(id_col).cast("bigint"), F.lit(none)))
    kept = named.join(stay, ["__id", "__digest"])
    if stay.where("__rows > 1").limit(1).count():
        kept = kept.where("__rows = 1").unionByName(kept.where("__rows > 1").dropDuplicates(["__id", "__digest"]))
    return kept.select(*docs.columns)
