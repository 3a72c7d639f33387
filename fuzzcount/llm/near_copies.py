"""Near-duplicate documents: MinHash with tensored banding, confirmed on whole shingle sets.

A document's set holds its distinct word shingles.  Table keys combine one of `halves` left and one of
`halves` right groups of `PER_HALF` minhashes each, so `halves` squared tables need only
2 * halves * PER_HALF minhash functions; the number of halves follows from the similarity and `MISS`,
the chance that a pair just at the similarity meets in no table.

Documents with equal sets are one node.  In each bucket every node is checked against its hub, the least
node.  Nodes of buckets that still hold several components are searched for the rest of their links without
forming the pairs of a bucket: linked sets share a shingle among the first few of each, the rarest first,
and what is left of both sets from there on bounds what they share, as does a sketch of the parities of
their shingles: it differs in no more bits than the sets do in shingles.  A node whose first shingles nobody
else has, or whose bound no node of another component can meet, is out before any pair is formed.  Where
many pairs pass even so, a group's nodes are checked against its smallest node and some drawn ones, in turns
that draw more each, and the components are joined: a node that few others can be linked with is left for
the later turns, so a turn forms few pairs for each node.  As soon as all pairs that pass and are still apart
are no more than a turn would look at, they are checked, each formed once.  Every linked pair of such nodes is
found, so no link between candidates is lost.

Edge cases: a null text, or one without words, has an empty set and is linked with nothing; a text with
fewer words than a shingle is one shingle; rows that share an id are one document; a row with a null id
gets a null component; an empty table gives no rows.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
import xxhash
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from fuzzcount.llm.components import components, merged
from fuzzcount.sources.tables import cut, drop

PER_HALF = 2
MISS = 2e-4
#: Nodes of each token that the first turn draws; each further turn draws `MORE` times as many.
DRAWN, MORE = 16, 8
#: All pairs are looked at once they are no more than `FEW` and `MANY` times those a turn would look at.
MANY = 1
FEW = 1 << 16
BLOCK = 1 << 15
#: So many shingles before each one are compared, so that a pair is formed at the first that both nodes have.
BEFORE = 32
#: 64-bit words of a sketch; it tells sets of up to about as many shingles as it has bits apart well, larger ones less.
SKETCH = 16
WORDS_CACHED = 100_000
_U = np.uint64


def halves_for(similarity: float) -> int:
    """So many groups on each side that a pair at the similarity finds none on one side with chance `MISS` / 2 or so."""
    return max(2, math.ceil(math.log(MISS) / math.log(1 - similarity**PER_HALF)))


def mix(x: np.ndarray) -> np.ndarray:
    """A bijection of 64 bits that spreads every input bit."""
    x = (x ^ (x >> _U(30))) * _U(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> _U(27))) * _U(0x94D049BB133111EB)
    return x ^ (x >> _U(31))


class Shingler:
    """Sorted distinct 64-bit hashes of the word shingles of whole texts."""

    def __init__(self, size: int):
        self.size, self.known = size, {}

    def of(self, lowered: bytes) -> np.ndarray:
        words = lowered.split()  # at the ASCII blanks 0x20 and 0x09 to 0x0D
        if not words:
            return np.empty(0, np.uint64)
        hashes = list(map(self.known.get, words))
        if None in hashes:
            if len(self.known) > WORDS_CACHED:
                self.known.clear()
            for i, h in enumerate(hashes):
                if h is None:
                    hashes[i] = self.known[words[i]] = xxhash.xxh64_intdigest(words[i], 7)
        h = np.array(hashes, np.uint64)
        size = min(self.size, len(h))
        out = np.full(len(h) - size + 1, size, np.uint64)
        for i in range(size):
            out = mix(out * _U(0x9E3779B97F4A7C15) + h[i : len(h) - size + 1 + i])
        return np.unique(out)


class Halves:
    """The codes of the left and right halves of a set's table keys."""

    def __init__(self, halves: int, seed: int = 11):
        n = 2 * halves * PER_HALF
        rng = np.random.default_rng(seed)
        self.halves = halves
        self.factors = rng.integers(0, 1 << 63, n, np.uint64) * _U(2) + _U(1)
        self.shifts = rng.integers(0, 1 << 63, n, np.uint64)

    def of(self, found: np.ndarray) -> np.ndarray:
        least = np.full(len(self.factors), np.iinfo(np.uint64).max, np.uint64)
        for at in range(0, len(found), BLOCK):
            part = found[at : at + BLOCK]
            for i in range(len(least)):
                least[i] = min(least[i], (part * self.factors[i] + self.shifts[i]).min())
        halves = least.reshape(2, self.halves, PER_HALF)
        codes = np.full((2, self.halves), 3, np.uint64)
        for i in range(PER_HALF):
            codes = mix(codes * _U(0x9E3779B97F4A7C15) + halves[:, :, i])
        return codes.ravel()


def sketch_of(found: np.ndarray) -> np.ndarray:
    """Of each bit whether an odd number of hashes fall on it."""
    odd = np.bincount((found >> _U(48)).astype(np.int64) % (64 * SKETCH), minlength=64 * SKETCH) & 1
    return np.packbits(odd.astype(np.uint8), bitorder="little").view(np.int64)


def sliced(batch: pa.RecordBatch, rows: int = 256) -> Iterator[pa.RecordBatch]:
    return (batch.slice(at, rows) for at in range(0, batch.num_rows, rows))


def _lowered(column: pa.Array) -> list[bytes]:
    return pc.ascii_lower(column).cast(pa.binary()).to_pylist()


def _lists(rows: list[np.ndarray]) -> pa.ListArray:
    ends = np.cumsum([0, *map(len, rows)], dtype=np.int32)
    return pa.ListArray.from_arrays(pa.array(ends), pa.array(np.concatenate(rows) if rows else np.empty(0, np.int64)))


def described(docs: DataFrame, size: int, halves: int) -> DataFrame:
    """doc_id, n_shingles, set_key (16 bytes, null for an empty set), `codes`, the halves of its table keys, and `sketch`."""

    def describe(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        shingler, tables = Shingler(size), Halves(halves)
        for batch in (part for whole in batches for part in sliced(whole)):
            counts, names, codes, sketches = [], [], [], []
            for text in _lowered(batch.column(1)):
                found = shingler.of(text)
                counts.append(len(found))
                names.append(xxhash.xxh3_128_digest(found.tobytes()) if len(found) else None)
                codes.append(tables.of(found).view(np.int64) if len(found) else np.empty(0, np.int64))
                sketches.append(sketch_of(found))
            yield pa.RecordBatch.from_arrays(
                [batch.column(0), pa.array(counts, pa.int64()), pa.array(names, pa.binary()), _lists(codes), _lists(sketches)], names=["doc_id", "n_shingles", "set_key", "codes", "sketch"]
            )

    return docs.mapInArrow(describe, "doc_id bigint, n_shingles bigint, set_key binary, codes array<bigint>, sketch array<bigint>")


def table_keys(nodes: DataFrame, halves: int) -> DataFrame:
    """(id, key) of each table: every left half combined with every right one."""
    left = nodes.select("id", F.posexplode(F.slice("codes", 1, halves)).alias("i", "l"), F.slice("codes", halves + 1, halves).alias("right"))
    return left.select("id", "i", "l", F.posexplode("right").alias("j", "r")).select("id", F.xxhash64("i", "l", "j", "r").alias("key"))


def shingle_sets(docs: DataFrame, size: int) -> DataFrame:
    """doc_id and its whole set."""

    def sets(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        shingler = Shingler(size)
        for whole in batches:
            for part in sliced(whole):
                yield pa.RecordBatch.from_arrays([part.column(0), _lists([shingler.of(text).view(np.int64) for text in _lowered(part.column(1))])], names=["id", "shingles"])

    return docs.mapInArrow(sets, "id bigint, shingles array<bigint>")


def links(pairs: DataFrame, sets: DataFrame, percent: int) -> DataFrame:
    """(u, v) of the `pairs` (a, b) whose whole sets are similar enough."""
    both = pairs.join(sets.select(F.col("id").alias("b"), F.col("shingles").alias("right")), "b")
    both = both.join(sets.select(F.col("id").alias("a"), F.col("shingles").alias("left")), "a")
    sized = both.select("a", "b", (F.size("left") + F.size("right")).alias("total"), F.size(F.array_intersect("left", "right")).alias("shared"))
    return sized.where((100 + percent) * F.col("shared") >= percent * F.col("total")).select(F.col("a").alias("u"), F.col("b").alias("v"))


def could_be_linked(x: str, y: str, percent: int) -> Column:
    """Whether two rows (n, sketch) may be similar enough, by the sizes of their sets and the bits in which their sketches differ."""
    n, m = F.col(f"{x}.n"), F.col(f"{y}.n")
    differ = sum((F.bit_count(F.get(F.col(f"{x}.sketch"), i).bitwiseXOR(F.get(F.col(f"{y}.sketch"), i))) for i in range(SKETCH)), F.lit(0))
    return (100 * F.least(n, m) >= percent * F.greatest(n, m)) & ((100 + percent) * (n + m - differ) >= 2 * percent * (n + m))


def placed(rows: DataFrame, groups: DataFrame) -> DataFrame:
    """`rows` (id, ...) with the component of each id."""
    return rows.join(groups.select(F.col("node").alias("id"), "component"), "id", "left").withColumn("component", F.coalesce("component", "id"))


def still_open(rows: DataFrame, by: str) -> DataFrame:
    """The groups of `rows` that hold more than one component."""
    return rows.groupBy(by).agg(F.min("component").alias("lo"), F.max("component").alias("hi")).where("lo < hi").select(by)


def first_shingles(nodes: DataFrame, sets: DataFrame, percent: int) -> DataFrame:
    """(id, n, token, rest, reach): the first shingles of each node's set, those that fewest nodes have first.

    A linked set shares at least `percent` of this one, so it has one of the first `n - share + 1`.  `rest`
    counts the shingles from there on, `reach` is the size of the largest set that could be linked if this
    is the first one both have.  Shingles that one node alone has come first and match nothing.
    """
    tokens = nodes.join(sets, "id").select("id", F.size("shingles").alias("n"), F.explode("shingles").alias("token"), "row")
    often = tokens.groupBy("token").agg(F.count("*").alias("nodes")).where("nodes > 1")
    ordered = tokens.join(often, "token").groupBy("row", "id", "n").agg(F.array_sort(F.collect_list(F.struct("nodes", "token"))).alias("shared"))
    ordered = ordered.withColumn("alone", F.col("n") - F.size("shared")).withColumn("first", F.expr(f"n - ({percent} * n + 99) div 100 + 1")).where("alone < first")
    rows = ordered.select("id", "n", "alone", F.posexplode(F.slice("shared", F.lit(1), F.col("first") - F.col("alone"))).alias("at", "one"))
    rows = rows.select("id", "n", F.col("one.token").alias("token"), (F.col("n") - F.col("alone") - F.col("at")).alias("rest"))
    return rows.withColumn("reach", F.expr(f"({100 + percent} * rest - {percent} * n) div {percent}"))


def ahead(rows: DataFrame) -> DataFrame:
    """Per token the size `n1` and component `c1` of the smallest node, and `n2`, the smallest size in another component."""
    each = rows.groupBy("token", "component").agg(F.min("n").alias("n"))
    ranked = each.withColumn("rank", F.row_number().over(Window.partitionBy("token").orderBy("n", "component"))).where("rank <= 2")
    of = lambda rank, name: F.max(F.when(F.col("rank") == rank, F.col(name)))
    return ranked.groupBy("token").agg(of(1, "n").alias("n1"), of(1, "component").alias("c1"), of(2, "n").alias("n2"))


def within_reach(rows: DataFrame) -> DataFrame:
    """The `rows` (id, n, token, rest, reach, component) that a node of another component could be linked with."""
    return rows.join(ahead(rows), "token").where("reach >= if(component = c1, n2, n1)").select(*rows.columns)


def from_few(rows: DataFrame, percent: int, turn: int, drawn: int = 1) -> DataFrame:
    """(a, b) of nodes and some of each token, its smallest and `drawn` others, of another component, that the bounds allow to be linked."""
    by_token = Window.partitionBy("token")
    small = rows.withColumn("rank", F.row_number().over(by_token.orderBy("n", "id"))).where("rank = 1")
    others = rows.withColumn("rank", F.row_number().over(by_token.orderBy(F.xxhash64(F.lit(turn), "token", "id"), "id"))).where(F.col("rank") <= drawn)
    both = rows.alias("x").join(small.unionByName(others).alias("y"), "token").where(_allowed(percent))
    return both.select(F.greatest("x.id", "y.id").alias("a"), F.least("x.id", "y.id").alias("b")).distinct()


def _allowed(percent: int) -> Column:
    return (F.col("x.component") != F.col("y.component")) & (F.col("y.n") <= F.col("x.reach")) & (F.col("x.n") <= F.col("y.reach")) & could_be_linked("x", "y", percent)


def meetings(rows: DataFrame, percent: int) -> DataFrame:
    """(a, b) of nodes of different components that the bounds allow to be linked, formed at the first token both have.

    The nodes outside a token's largest component are joined with all of its nodes, so that one large
    component is not joined with itself.  A pair allowed at a token is allowed at every earlier one of both,
    where `rest` and `reach` are larger, so it is left out where the `BEFORE` last ones of both have a token
    in common; only a pair with a longer gap between its tokens is formed again.
    """
    counts = rows.groupBy("token", "component").agg(F.count("*").alias("nodes"))
    largest = counts.groupBy("token").agg(F.max(F.struct("nodes", "component"))["component"].alias("largest"))
    last = Window.partitionBy("id").orderBy(F.desc("rest")).rowsBetween(-BEFORE, -1)
    marked = rows.withColumn("before", F.collect_list("token").over(last)).join(largest, "token").withColumn("outside", F.col("component") != F.col("largest"))
    x, y = marked.where("outside").alias("x"), marked.alias("y")
    once = (~F.col("y.outside") | (F.col("x.id") < F.col("y.id"))) & ~F.arrays_overlap("x.before", "y.before")
    return x.join(y, "token").where(_allowed(percent) & once).select(F.greatest("x.id", "y.id").alias("a"), F.least("x.id", "y.id").alias("b"))


def apart(rows: DataFrame, percent: int) -> DataFrame:
    """(a, b) of nodes of different components that the bounds allow to be linked, each pair once."""
    return meetings(rows, percent).distinct()


def crossing(rows: DataFrame) -> tuple[int, int]:
    """How many `rows` there are, and how many pairs `apart` looks at."""
    each = rows.groupBy("token", "component").agg(F.count("*").alias("nodes"))
    tokens = each.groupBy("token").agg(F.sum("nodes").alias("n"), F.max("nodes").alias("most"))
    found = tokens.agg(F.coalesce(F.sum("n"), F.lit(0)).alias("rows"), F.coalesce(F.sum((F.col("n") - F.col("most")) * F.col("n")), F.lit(0)).alias("pairs")).first()
    return found["rows"], found["pairs"]


def closed(rows: DataFrame, groups: DataFrame, nodes: DataFrame, sets: DataFrame, percent: int) -> DataFrame:
    """`groups` (node, component) after all links among the nodes of `rows` (id, n, token, rest, reach)."""
    turn, last = 0, False
    while True:
        near = cut(within_reach(placed(rows, groups)))  # cut here, so that a token's rows can be split in either join
        live = cut(within_reach(near).join(nodes.select("id", "sketch"), "id"))
        drop(near)
        n, pairs = crossing(live)
        if not pairs:
            drop(live)
            return groups
        drawn = DRAWN * MORE**turn
        last, turn = last or pairs <= FEW + MANY * drawn * n, turn + 1
        found = cut(links(apart(live, percent) if last else from_few(live, percent, turn, drawn), sets, percent))
        new = merged(groups, found)
        drop(live, found)
        if last:
            return new
        last = new is groups and turn > 2  # many draws join nothing more
        if new is not groups:
            drop(groups)
        groups = new


def near_groups(docs: DataFrame, size: int, percent: int, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row per row of `docs`: its id, `n_shingles`, `component_id`, `kept`; similarity in percent."""
    halves = halves_for(percent / 100)
    docs = docs.select(F.col(id_col).cast("bigint").alias("doc_id"), F.coalesce(F.col(text_col), F.lit("")).alias("text"))
    rows = cut(described(docs, size, halves))
    nodes = cut(rows.where("doc_id IS NOT NULL AND set_key IS NOT NULL").groupBy("set_key").agg(F.min("doc_id").alias("id"), F.max("n_shingles").alias("n"), F.min_by(F.struct("codes", "sketch"), "doc_id").alias("of")).select("set_key", "id", "n", "of.*"))
    keys = table_keys(nodes, halves)
    buckets = cut(keys.groupBy("key").agg(F.min("id").alias("hub"), F.max("id").alias("last")).where("hub < last").select("key", "hub"))
    members = cut(keys.join(buckets, "key"))
    stars = members.where("id <> hub").select(F.col("id").alias("a"), F.col("hub").alias("b")).distinct()
    stars = stars.join(nodes.alias("x"), F.col("a") == F.col("x.id")).join(nodes.alias("y"), F.col("b") == F.col("y.id")).where(could_be_linked("x", "y", percent)).select("a", "b")
    needed = members.select(F.col("id").alias("doc_id")).distinct()
    sets = cut(shingle_sets(docs.join(needed, "doc_id", "left_semi"), size).withColumn("row", F.monotonically_increasing_id()))
    found = cut(links(stars, sets, percent))
    groups = components(found)
    here = placed(members.select("id", "key"), groups)
    first = cut(first_shingles(here.join(still_open(here, "key"), "key").select("id").distinct(), sets, percent))
    drop(buckets, members, found)
    groups = closed(first, groups, nodes, sets, percent)
    drop(first, sets)
    labelled = nodes.join(groups, nodes["id"] == groups["node"], "left").select("set_key", F.coalesce("component", "id").alias("component"))
    return rows.select("doc_id", "n_shingles", "set_key").join(labelled, "set_key", "left").select(
        "doc_id", "n_shingles", F.coalesce("component", "doc_id").alias("component_id"), F.coalesce(F.col("doc_id") == F.coalesce("component", "doc_id"), F.lit(False)).alias("kept")
    )


def drop_near_copies(docs: DataFrame, size: int = 5, percent: int = 80, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """`docs` with one document of each group: the one with the least id.  Rows with a null id stay."""
    gone = near_groups(docs, size, percent, id_col, text_col).where("NOT kept AND doc_id IS NOT NULL").select(F.col("doc_id").alias(id_col)).distinct()
    return docs.join(gone, id_col, "left_anti").select(*docs.columns)
