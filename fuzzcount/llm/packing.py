"""Mixture-controlled packing of token sequences by deficit round robin.

Every document is encoded once, followed by an end token, and cut into chunks of at most `CHUNK` tokens.
Chunks are dealt evenly over shards of about `SHARD` tokens.  A shard keeps one queue per source; each
window of `window` tokens credits every source its target share and serves it that share in whole tokens,
more or less by a part of it (`PAYBACK`) where it was served too little or too much before.  Only a source whose
share is under a least piece waits for later windows, so that documents are not cut into slivers.  What a source
is owed stays in its deficit.  Deficits are carried across shards too: a shard starts with
what the shards before it leave owing, which follows from the token totals of shards and sources alone
(a running sum), without packing them one after the other.

The targets default to the token shares of the sources, at which all queues end together; other targets
steer the order, and a source that runs dry leaves its share to the others, so that nothing is dropped.
A shard's last tokens, short of a window, form sequences whose lengths are powers of two: no padding.

Edge cases: a null text is the end token alone; a null source is a source of its own; rows that share an id
are packed each for itself; long texts are cut into chunks that go to different shards; an empty table
gives no rows; columns other than id, text and source are ignored.
"""

from __future__ import annotations

import base64
import zlib
from collections import deque
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from fuzzcount.sources.tables import cut

WINDOW, LEAST_PIECE = 2048, 16
#: By so much of its share a window may serve a source more or less, to make up for what went before.
PAYBACK = 0.25
CHUNK, SHARD, BLOCK = 1 << 16, 1 << 22, 4096
SPECIAL = {"<|endoftext|>": 50256}

CHUNKS = "doc_id bigint, source string, row bigint, start bigint, n bigint, doc_tokens bigint, ids binary"
PIECES = "doc_id bigint, start bigint, length bigint, ids_crc32 bigint, doc_tokens bigint, sequence_id bigint, offset bigint, source string, ids binary"

_ENCODERS: dict = {}


def encoder(ranks_path: str, pattern: str):
    """The byte-level encoder of a rank file; its ids are those of the same vocabulary in other libraries."""
    if ranks_path not in _ENCODERS:
        import tiktoken

        with open(ranks_path, "rb") as file:
            ranks = {base64.b64decode(token): int(rank) for token, rank in map(bytes.split, file)}
        _ENCODERS[ranks_path] = tiktoken.Encoding("packing", pat_str=pattern, mergeable_ranks=ranks, special_tokens=SPECIAL)
    return _ENCODERS[ranks_path]


def encode(docs: DataFrame, ranks_path: str, pattern: str, end_id: int) -> DataFrame:
    """One row per chunk of a document's ids (little-endian unsigned 16-bit), the end token included."""

    def chunks(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encoding = encoder(ranks_path, pattern)
        for batch in batches:
            rows: list[tuple] = []
            for doc_id, source, row, text in zip(*(batch.column(i) for i in range(4)), strict=True):
                ids = np.append(encoding.encode_to_numpy(text.as_py(), allowed_special="all"), end_id).astype("<u2")
                for start in range(0, len(ids), CHUNK):
                    part = ids[start : start + CHUNK]
                    rows.append((doc_id.as_py(), source.as_py(), row.as_py(), start, len(part), len(ids), part.tobytes()))
            yield pa.RecordBatch.from_arrays(
                [pa.array(x, kind) for x, kind in zip(zip(*rows, strict=True) if rows else [()] * 7, (pa.int64(), pa.string(), pa.int64(), pa.int64(), pa.int64(), pa.int64(), pa.binary()), strict=True)],
                names=["doc_id", "source", "row", "start", "n", "doc_tokens", "ids"],
            )

    named = docs.select(F.col("doc_id").cast("bigint").alias("doc_id"), F.col("source").cast("string").alias("source"), F.monotonically_increasing_id().alias("row"), F.coalesce("text", F.lit("")).alias("text"))
    return named.mapInArrow(chunks, CHUNKS)


class Shard:
    """Packs the chunks of one shard; `deficit` says what each source is owed when it starts."""

    def __init__(self, shares: dict, deficit: dict, window: int = WINDOW, least: int = LEAST_PIECE):
        self.window, self.least = window, least
        self.order = sorted(shares, key=lambda s: (s is None, s or ""))
        self.share = np.array([shares[s] for s in self.order], float)
        self.credit = np.array([deficit.get(s, 0.0) for s in self.order], float)
        self.first = 0

    def allot(self, left: np.ndarray, size: int) -> np.ndarray:
        """The tokens of each source in a window of `size`; `left` says how many it has."""
        weight = self.share[left > 0].sum()
        fair = np.where(left > 0, size * (self.share / weight if weight else 1 / (left > 0).sum()), 0.0)
        self.credit += fair
        least = np.minimum(self.least, left)
        low = np.where((1 - PAYBACK) * fair >= least, (1 - PAYBACK) * fair, 0.0)
        claim = np.minimum(np.clip(self.credit, low, np.maximum((1 + PAYBACK) * fair, least)), left)
        claim[claim < least] = 0
        if claim.sum() > size:
            claim *= size / claim.sum()
        give = np.floor(claim).astype(np.int64)
        give[give < least] = 0
        while room := size - int(give.sum()):  # what is over goes to those that are owed most, a share at a time
            still = np.flatnonzero(give < left)
            still = still[np.lexsort((give[still] - self.credit[still], fair[still] == 0))]
            part = np.floor(room * fair[still] / (fair[still].sum() or 1.0))
            more = np.minimum(np.maximum(part, np.maximum(least[still] - give[still], 1)), left[still] - give[still]).astype(np.int64)
            before = np.cumsum(more) - more
            give[still] += np.clip(room - before, 0, more)
        self.credit -= give
        return give

    def pack(self, queues: dict[str, deque], left: dict[str, int]) -> Iterator[tuple]:
        """(source, chunk, start in the chunk, length, window number, offset); queues hold (chunk, tokens)."""
        at = {s: 0 for s in queues}  # tokens of the queue's head that are gone
        rest = np.array([left.get(s, 0) for s in self.order], np.int64)
        total, number = int(rest.sum()), 0
        while total:
            size = min(self.window, total)
            if size < self.window:
                size = 1 << (size.bit_length() - 1)
            give, offset = self.allot(rest, size), 0
            rest -= give
            served = np.flatnonzero(give)
            for i in np.roll(served, -(self.first % len(served))):  # starting one source further each time
                s, amount = self.order[i], int(give[i])
                while amount:
                    chunk, tokens = queues[s][0]
                    take = min(amount, tokens - at[s])
                    yield s, chunk, at[s], take, number, offset
                    at[s] += take
                    if at[s] == tokens:
                        queues[s].popleft()
                        at[s] = 0
                    offset, amount = offset + take, amount - take
            self.first += 1
            total -= size
            number += 1


def shard_totals(chunks: DataFrame) -> DataFrame:
    return chunks.groupBy("shard", "source").agg(F.sum("n").alias("tokens"))


def opening_deficits(totals: DataFrame, total: int, targets: dict[str | None, float] | None = None) -> DataFrame:
    """Per shard and source with tokens there: its share, and what the shards before it leave the source owing.

    That is its share of all tokens before, less its own tokens before.  The running sums go over
    shards of a block and over blocks, so no task sees all shards.
    """
    sizes = totals.groupBy("shard").agg(F.sum("tokens").alias("size")).withColumn("block", F.floor(F.col("shard") / BLOCK))
    to_here = lambda *by: Window.partitionBy(*by).rowsBetween(Window.unboundedPreceding, -1)
    blocks = sizes.groupBy("block").agg(F.sum("size").alias("size"))
    blocks = blocks.select("block", F.coalesce(F.sum("size").over(to_here().orderBy("block")), F.lit(0)).alias("earlier"))
    sizes = sizes.select("shard", "block", F.coalesce(F.sum("size").over(to_here("block").orderBy("shard")), F.lit(0)).alias("before")).join(blocks, "block")
    share = F.sum("tokens").over(Window.partitionBy("source")) / F.lit(total)
    own = totals.select("shard", "source", share.alias("share"), F.coalesce(F.sum("tokens").over(to_here("source").orderBy("shard")), F.lit(0)).alias("own"))
    if targets:
        table = totals.sparkSession.createDataFrame([(s, float(t)) for s, t in targets.items()], "name string, target double")
        own = own.join(F.broadcast(table), F.col("source").eqNullSafe(F.col("name")), "left").withColumn("share", F.coalesce("target", F.lit(0.0)))  # the caller's own rows
    cells = own.join(sizes, "shard").select("shard", "source", "share", "own", (F.col("before") + F.col("earlier")).alias("before"))
    return cells.groupBy("shard").agg(F.collect_list(F.struct("source", "share", "own", "before")).alias("plan"))


def pack(docs: DataFrame, ranks_path: str, pattern: str, end_id: int = 1, targets: dict[str, float] | None = None, window: int = WINDOW, least: int = LEAST_PIECE) -> DataFrame:
    """One row per piece, with its ids; see the module's text."""
    encoded = cut(encode(docs, ranks_path, pattern, end_id))
    total = encoded.agg(F.sum("n").alias("n")).first()["n"] or 0
    shards = max(1, -(-total // SHARD))
    dealt = encoded.withColumn("shard", F.pmod(F.xxhash64("row", "start"), F.lit(shards)))
    plans = cut(opening_deficits(shard_totals(dealt), total, targets))
    tasks = max(shards, int(docs.sparkSession.conf.get("spark.sql.shuffle.partitions")))  # a shard or so each
    grouped = dealt.repartition(tasks, "shard").groupBy("shard").cogroup(plans.repartition(tasks, "shard").groupBy("shard"))

    def fill(key: tuple, chunks, plan):
        import pandas as pd

        if chunks.empty:
            return pd.DataFrame(columns=["doc_id", "start", "length", "ids_crc32", "doc_tokens", "sequence_id", "offset", "source", "ids"])
        cells = plan["plan"].iloc[0]
        chunks = chunks.sort_values(["row", "start"], kind="stable")
        columns = [chunks[c].tolist() for c in ("doc_id", "source", "start", "n", "doc_tokens", "ids")]
        queues: dict = {}
        left: dict = {}
        for i, (source, n) in enumerate(zip(columns[1], columns[3], strict=True)):
            queues.setdefault(source, deque()).append((i, n))
            left[source] = left.get(source, 0) + n
        here = {c["source"]: c["share"] for c in cells}
        shard = Shard(here, {c["source"]: here[c["source"]] * c["before"] - c["own"] for c in cells}, window, least)
        rows = []
        for _, i, at, length, number, offset in shard.pack(queues, left):
            ids = columns[5][i][2 * at : 2 * (at + length)]
            wide = np.frombuffer(ids, "<u2").astype("<u4").tobytes()
            rows.append((columns[0][i], columns[2][i] + at, length, zlib.crc32(wide), columns[4][i], (int(key[0]) << 32) + number, offset, columns[1][i], ids))
        out = pd.DataFrame(rows, columns=["doc_id", "start", "length", "ids_crc32", "doc_tokens", "sequence_id", "offset", "source", "ids"])
        out["doc_id"] = out["doc_id"].astype("Int64")
        return out

    return grouped.applyInPandas(fill, PIECES)
