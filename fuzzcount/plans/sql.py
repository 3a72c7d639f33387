"""Pieces of the DuckDB twins: the same definitions as the Spark plans, in SQL."""

from __future__ import annotations

from fuzzcount.functions.noise import flip_rate
from fuzzcount.sources.fixtures import GIVEN, PERSONS, SUBURB, SURNAME

LANES = ("w0", "w1", "w2", "w3")


def num(text: str) -> str:
    return f"CAST('0x' || substr(md5({text}), 1, 8) AS BIGINT)"


def _pick(field: str, names: list[str]) -> str:
    return f"list_extract([{', '.join(repr(n) for n in names)}], CAST({num(repr(field + '|') + ' || c_custkey')} % {len(names)} AS INT) + 1)"


PEOPLE = f"""people AS (SELECT c_custkey AS entity_id, {_pick('given', GIVEN)} AS given, {_pick('surname', SURNAME)} AS surname, {_pick('suburb', SUBURB)} AS suburb,
    CAST(27000 + {num("'postcode|' || c_custkey")} % 1000 AS VARCHAR) AS postcode, CASE WHEN c_custkey % 2 = 0 THEN 'f' ELSE 'm' END AS gender FROM customer)"""
VISITS = """visits AS (SELECT o_orderkey AS rec_id, 'o' || (o_orderkey % 3) AS owner, o_custkey AS entity_id, n_name AS nation, c_mktsegment AS segment, o_orderdate AS visit_ts
    FROM orders JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey)"""
#: One record of every person at each owner, and the same of the experiments' persons alone.
RECORDS = f"""{PEOPLE}, panel AS (SELECT entity_id * 3 + n AS rec_id, 'o' || n AS owner, entity_id, given, surname, suburb, postcode, gender
    FROM people, range(3) r(n))"""
PANEL = RECORDS.replace("range(3) r(n)", f"range(3) r(n) WHERE entity_id < {PERSONS}")


def grams(text: str) -> str:
    return f"CASE WHEN length({text}) = 0 THEN []::VARCHAR[] WHEN length({text}) < 2 THEN [{text}] ELSE [substr({text}, i, 2) for i in range(1, length({text}))] END"


_TOKENS = ", tok AS (SELECT owner, rec_id, entity_id, list_distinct(list_concat(" + ", ".join(
    f"['{f}|' || g for g in {grams(f)}]" for f in ("given", "surname", "suburb", "postcode")
) + ", ['gender|' || gender])) AS tokens FROM panel)"
_POSITIONS = f", pos AS (SELECT DISTINCT owner, rec_id, entity_id, {num("'k|' || t || '|' || i")} % 200 AS p FROM (SELECT owner, rec_id, entity_id, unnest(tokens) AS t FROM tok), range(20) r(i))"


def lanes_of(bit: str) -> str:
    return ", ".join(f"CAST(coalesce(sum(CASE WHEN {bit} // 50 = {i} THEN CAST(1 AS BIGINT) << CAST({bit} % 50 AS INT) END), 0) AS BIGINT) AS w{i}" for i in range(4))


_ENCODED = f", enc AS (SELECT owner, rec_id, entity_id, {lanes_of('p')} FROM pos GROUP BY ALL)"
TOKENS, POSITIONS = RECORDS + _TOKENS, RECORDS + _TOKENS + _POSITIONS
ENCODED, PANEL_ENCODED = POSITIONS + _ENCODED, PANEL + _TOKENS + _POSITIONS + _ENCODED


def flips(name: str, source: str, ids: str, prefix: str, share: float) -> str:
    """A relation like `source` (ids, lanes) with keyed bits flipped."""
    masks = f"SELECT {ids}, {lanes_of('b')} FROM {source}, range(200) r(b) WHERE {num(prefix + " || '|' || b")} < {int(share * 2**32)} GROUP BY {ids}"
    return f"{name} AS (SELECT s.* REPLACE ({', '.join(f'xor(s.{w}, coalesce(m.{w}, 0)) AS {w}' for w in LANES)}) FROM {source} s LEFT JOIN ({masks}) m USING ({ids}))"


def released(epsilon: float, source: str = "enc") -> str:
    return flips("rel", source, "owner, rec_id", "'k|' || owner || '|' || rec_id", flip_rate(epsilon))


def pool(method: str, epsilon: float, p_flip: float, base: str = PANEL_ENCODED) -> str:
    """All relations up to `pool`, for n_ref = a tenth of the records and n_dum = a tenth of the references."""
    lanes = ", ".join(LANES)
    n_ref = "(SELECT CAST(round(0.1 * count(*)) AS BIGINT) FROM rel)"
    if method == "A":
        refs = f"refs AS (SELECT ref_id, {lanes_of('b')} FROM (SELECT ref_id, CASE WHEN {num("'k|refA|' || ref_id || '|' || b")} < {2**31} THEN b END AS b FROM (SELECT unnest(range({n_ref})) AS ref_id), range(200) r(b)) GROUP BY ref_id)"
    else:
        refs = f"refs AS (SELECT n - 1 AS ref_id, {lanes} FROM (SELECT *, row_number() OVER (ORDER BY {num("'k|refB|' || owner || '|' || rec_id")}, owner, rec_id) AS n FROM rel) WHERE n <= {n_ref})"
    copies = f"copies AS (SELECT ref_id, dum_no, {lanes} FROM refs, (SELECT unnest(range((SELECT CAST(round(0.1 * count(*)) AS BIGINT) FROM refs))) AS dum_no))"
    return f"""{base}, {released(epsilon)}, {refs}, {copies}, {flips('dums', 'copies', 'ref_id, dum_no', "'k|dum|' || ref_id || '|' || dum_no", p_flip)},
        pool AS (SELECT 'real|' || owner || '|' || rec_id AS row_id, 'real' AS kind, CAST(NULL AS BIGINT) AS ref_id, {lanes} FROM rel
                 UNION ALL SELECT 'ref|' || ref_id, 'ref', ref_id, {lanes} FROM refs UNION ALL SELECT 'dum|' || ref_id || '|' || dum_no, 'dum', ref_id, {lanes} FROM dums)"""


def hamming(a: str, b: str) -> str:
    return "(" + " + ".join(f"CAST(bit_count(xor({a}.{w}, {b}.{w})) AS BIGINT)" for w in LANES) + ")"


def common(a: str, b: str) -> str:
    return "(" + " + ".join(f"CAST(bit_count({a}.{w} & {b}.{w}) AS BIGINT)" for w in LANES) + ")"


def size(a: str) -> str:
    return "(" + " + ".join(f"CAST(bit_count({a}.{w}) AS BIGINT)" for w in LANES) + ")"


def sweep(method: str, epsilon: float, p_flip: float, k_max: str = "(SELECT count(*) FROM rel)") -> str:
    """All relations up to `labels` (k, row_id, kind, ref_id, label) and `per_ref`, `curve`."""
    return f"""{pool(method, epsilon, p_flip)},
        seeds AS (SELECT * FROM (SELECT *, row_number() OVER (ORDER BY {num("'k|seed|' || row_id")}, row_id) AS rank FROM pool) WHERE rank <= {k_max}),
        labels AS (SELECT s.rank AS k, x.row_id, x.kind, x.ref_id, min({hamming('x', 's')} * 1000000 + s.rank) OVER (PARTITION BY x.row_id ORDER BY s.rank ROWS UNBOUNDED PRECEDING) % 1000000 AS label FROM pool x, seeds s),
        sizes AS (SELECT k, label, count(*) AS n_c FROM labels GROUP BY ALL),
        own AS (SELECT k, ref_id, label, count(*) AS x FROM labels WHERE kind = 'dum' GROUP BY ALL),
        nd AS (SELECT k, ref_id, count(*) AS n_dum FROM labels WHERE kind = 'dum' GROUP BY ALL),
        per_ref AS (SELECT r.k, r.ref_id, r.label, CASE WHEN n_dum + n_c - 1 - coalesce(x, 0) = 0 THEN 0.0 ELSE coalesce(x, 0) / (n_dum + n_c - 1 - coalesce(x, 0)) END AS purity
                    FROM labels r JOIN sizes USING (k, label) JOIN nd ON nd.k = r.k AND nd.ref_id = r.ref_id LEFT JOIN own ON own.k = r.k AND own.ref_id = r.ref_id AND own.label = r.label WHERE r.kind = 'ref'),
        curve AS (SELECT k, sum(purity) AS purity, avg(purity) AS mean_purity, count(*) AS n_ref FROM per_ref GROUP BY k)"""
