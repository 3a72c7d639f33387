"""Queries of the operators around the counter, each with its DuckDB twin."""

from __future__ import annotations

from pyspark.sql import Window
from pyspark.sql import functions as F

from fuzzcount.functions.digest import num
from fuzzcount.operators import ranges
from fuzzcount.plans import sql
from fuzzcount.sources import fixtures
from fuzzcount.sources.tables import cut, table
from fuzzcount.streaming import users

FOUND: dict[str, tuple] = {}


def twin(statement: str | None):
    def add(function):
        FOUND[function.__name__] = (function, statement)
        return function

    return add


def visits(spark, sf_dir):
    return fixtures.visits(spark, sf_dir)


@twin("SELECT c_custkey, c_name, c_nationkey FROM customer")
def scan_table(spark, sf_dir):
    return table(spark, sf_dir, "customer", "c_custkey", "c_name", "c_nationkey")


@twin(f"WITH {sql.RECORDS} SELECT owner, rec_id FROM panel")
def release_projection(spark, sf_dir):
    return fixtures.records(spark, sf_dir).drop("entity_id", *fixtures.PII)


@twin("SELECT event_id, user_id, value FROM events WHERE event_type IN ('error', 'click') AND value BETWEEN 10 AND 60 AND props LIKE '%k%'")
def filter_cases(spark, sf_dir):
    return table(spark, sf_dir, "events").where(F.col("event_type").isin("error", "click") & F.col("value").between(10, 60) & F.col("props").like("%k%")).select("event_id", "user_id", "value")


@twin(f"WITH {sql.VISITS} SELECT nation, segment, count(*) AS n, count(DISTINCT entity_id) AS persons FROM visits GROUP BY ALL")
def join_visits(spark, sf_dir):
    return visits(spark, sf_dir).groupBy("nation", "segment").agg(F.count("*").alias("n"), F.count_distinct("entity_id").alias("persons"))


@twin("SELECT p.p_partkey AS a, q.p_partkey AS b FROM part p JOIN part q ON p.p_brand = q.p_brand AND p.p_partkey < q.p_partkey AND abs(p.p_retailprice - q.p_retailprice) <= 5")
def numeric_range_join(spark, sf_dir):
    parts = table(spark, sf_dir, "part", "p_partkey", "p_brand", "p_retailprice")
    return ranges.range_join(parts, parts, "p_retailprice", "p_retailprice", 5.0, ("p_brand", "p_brand")).where("x.p_partkey < y.p_partkey").select(F.col("x.p_partkey").alias("a"), F.col("y.p_partkey").alias("b"))


@twin("SELECT e.event_id, max(p.ts) AS last_view FROM (SELECT * FROM events WHERE event_type = 'click') e LEFT JOIN (SELECT * FROM events WHERE event_type = 'view') p ON p.user_id = e.user_id AND p.ts <= e.ts GROUP BY e.event_id")
def asof_last_event(spark, sf_dir):
    events = table(spark, sf_dir, "events", "event_id", "ts", "user_id", "event_type")
    marks = events.where("event_type = 'view'").select("user_id", F.col("ts").alias("at"), F.col("ts").alias("last_view"))
    return ranges.asof(events.where("event_type = 'click'"), marks, "user_id", "ts", "at", "last_view").select("event_id", "last_view")


def _of(rows, owner):
    return rows.where(F.col("owner") == owner).select("entity_id")


@twin(f"WITH {sql.VISITS} SELECT count(*) AS n FROM visits v WHERE owner = 'o0' AND EXISTS (SELECT 1 FROM visits w WHERE w.owner = 'o1' AND w.entity_id = v.entity_id)")
def matched_semi(spark, sf_dir):
    rows = visits(spark, sf_dir)
    return _of(rows, "o0").join(_of(rows, "o1"), "entity_id", "left_semi").agg(F.count("*").alias("n"))


@twin(f"WITH {sql.VISITS} SELECT entity_id FROM visits v WHERE owner = 'o0' AND NOT EXISTS (SELECT 1 FROM visits w WHERE w.owner = 'o1' AND w.entity_id = v.entity_id)")
def unmatched_anti(spark, sf_dir):
    rows = visits(spark, sf_dir)
    return _of(rows, "o0").join(_of(rows, "o1"), "entity_id", "left_anti")


@twin(f"WITH {sql.VISITS}, d AS (SELECT DISTINCT owner, entity_id FROM visits) SELECT a.owner AS a, b.owner AS b, count(*) AS persons FROM d a JOIN d b USING (entity_id) GROUP BY ALL")
def owner_overlap(spark, sf_dir):
    d = visits(spark, sf_dir).select("owner", "entity_id").distinct()
    return d.alias("x").join(d.alias("y"), "entity_id").groupBy(F.col("x.owner").alias("a"), F.col("y.owner").alias("b")).agg(F.count("*").alias("persons"))


@twin(f"WITH {sql.VISITS}, a AS (SELECT DISTINCT entity_id FROM visits WHERE owner = 'o0'), b AS (SELECT DISTINCT entity_id FROM visits WHERE owner = 'o1') SELECT count(*) AS n, count(a.entity_id) AS in_a, count(b.entity_id) AS in_b FROM a FULL JOIN b ON a.entity_id = b.entity_id")
def owners_full_outer(spark, sf_dir):
    rows = visits(spark, sf_dir)
    a, b = _of(rows, "o0").distinct().withColumnRenamed("entity_id", "a"), _of(rows, "o1").distinct().withColumnRenamed("entity_id", "b")
    return a.join(b, F.col("a") == F.col("b"), "full_outer").agg(F.count("*").alias("n"), F.count("a").alias("in_a"), F.count("b").alias("in_b"))


@twin("SELECT o_orderstatus, count(*) AS n, round(sum(o_totalprice), 2) AS total, round(avg(o_totalprice), 4) AS mean, min(o_totalprice) AS lo, max(o_totalprice) AS hi, round(stddev_samp(o_totalprice), 4) AS sd, bit_xor(o_orderkey) AS x, arg_max(o_orderkey, o_totalprice) AS top FROM orders GROUP BY ALL")
def agg_by_owner(spark, sf_dir):
    orders = table(spark, sf_dir, "orders")
    return orders.groupBy("o_orderstatus").agg(
        F.count("*").alias("n"), F.round(F.sum("o_totalprice"), 2).alias("total"), F.round(F.avg("o_totalprice"), 4).alias("mean"), F.min("o_totalprice").alias("lo"), F.max("o_totalprice").alias("hi"),
        F.round(F.stddev_samp("o_totalprice"), 4).alias("sd"), F.bit_xor("o_orderkey").alias("x"), F.max_by("o_orderkey", "o_totalprice").alias("top"),
    )


@twin("SELECT l_returnflag, count(DISTINCT l_partkey) AS parts, count(DISTINCT l_suppkey) AS suppliers FROM lineitem GROUP BY ALL")
def distinct_by_owner(spark, sf_dir):
    return table(spark, sf_dir, "lineitem", "l_returnflag", "l_partkey", "l_suppkey").groupBy("l_returnflag").agg(F.count_distinct("l_partkey").alias("parts"), F.count_distinct("l_suppkey").alias("suppliers"))


_PERSONS = "count(DISTINCT entity_id) AS persons FROM visits GROUP BY"


@twin(f"WITH {sql.VISITS} SELECT owner, segment, {_PERSONS} CUBE (owner, segment)")
def distinct_cube(spark, sf_dir):
    return visits(spark, sf_dir).cube("owner", "segment").agg(F.count_distinct("entity_id").alias("persons"))


@twin(f"WITH {sql.VISITS} SELECT owner, segment, {_PERSONS} ROLLUP (owner, segment)")
def distinct_rollup(spark, sf_dir):
    return visits(spark, sf_dir).rollup("owner", "segment").agg(F.count_distinct("entity_id").alias("persons"))


@twin(f"WITH {sql.VISITS} SELECT owner, nation, {_PERSONS} GROUPING SETS ((owner), (nation))")
def distinct_grouping_sets(spark, sf_dir):
    v = visits(spark, sf_dir)
    return v.groupingSets([["owner"], ["nation"]], "owner", "nation").agg(F.count_distinct("entity_id").alias("persons"))


@twin("SELECT user_id, count(CASE WHEN event_type = 'click' THEN 1 END) AS click, count(CASE WHEN event_type = 'view' THEN 1 END) AS view FROM events GROUP BY user_id")
def pivot_events(spark, sf_dir):
    wide = table(spark, sf_dir, "events", "user_id", "event_type").groupBy("user_id").pivot("event_type", ["click", "view"]).count()
    return wide.na.fill(0)


@twin("SELECT o_orderkey, row_number() OVER w AS rn, rank() OVER w AS rk, dense_rank() OVER w AS dr, ntile(4) OVER w AS nt FROM orders WINDOW w AS (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey)")
def rank_records(spark, sf_dir):
    w = Window.partitionBy("o_custkey").orderBy("o_orderdate", "o_orderkey")
    return table(spark, sf_dir, "orders", "o_orderkey", "o_custkey", "o_orderdate").select("o_orderkey", *(f.over(w).cast("bigint").alias(n) for f, n in ((F.row_number(), "rn"), (F.rank(), "rk"), (F.dense_rank(), "dr"), (F.ntile(4), "nt"))))


@twin("SELECT o_orderkey, date_diff('day', lag(o_orderdate) OVER w, o_orderdate) AS since, date_diff('day', o_orderdate, lead(o_orderdate) OVER w) AS till FROM orders WINDOW w AS (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey)")
def lag_lead_days(spark, sf_dir):
    w = Window.partitionBy("o_custkey").orderBy("o_orderdate", "o_orderkey")
    rows = table(spark, sf_dir, "orders", "o_orderkey", "o_custkey", "o_orderdate")
    return rows.select("o_orderkey", F.datediff("o_orderdate", F.lag("o_orderdate").over(w)).cast("bigint").alias("since"), F.datediff(F.lead("o_orderdate").over(w), "o_orderdate").cast("bigint").alias("till"))


@twin("SELECT event_id, min(value) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS UNBOUNDED PRECEDING) AS lowest FROM events")
def running_min(spark, sf_dir):
    w = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(Window.unboundedPreceding, 0)
    return table(spark, sf_dir, "events", "event_id", "ts", "user_id", "value").select("event_id", F.min("value").over(w).alias("lowest"))


@twin("SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY epoch(date_trunc('second', ts)) RANGE BETWEEN 86400 PRECEDING AND CURRENT ROW) AS n FROM events")
def trailing_sum(spark, sf_dir):
    w = Window.partitionBy("user_id").orderBy("s").rangeBetween(-86400, 0)
    return table(spark, sf_dir, "events", "event_id", "ts", "user_id").withColumn("s", F.unix_timestamp("ts")).select("event_id", F.count("*").over(w).alias("n"))


#: Queries of a nearest-neighbour search that meet in one block.
QUERY_BLOCK = 256


@twin(f"WITH {sql.ENCODED}, n AS (SELECT a.rec_id AS a, b.rec_id AS b, {sql.hamming('a', 'b')} AS d FROM enc a JOIN enc b ON a.rec_id % 100 = 0 AND a.rec_id <> b.rec_id) SELECT a, b, CAST(d AS BIGINT) AS d FROM n QUALIFY row_number() OVER (PARTITION BY a ORDER BY d, b) <= 10")
def topk_nearest(spark, sf_dir):
    from fuzzcount.functions.similarity import hamming
    from fuzzcount.plans.core_queries import encoded

    rows = cut(encoded(spark, sf_dir))
    asked = rows.where("rec_id % 100 = 0")
    blocks = -(-asked.count() // QUERY_BLOCK) or 1
    x = asked.withColumn("block", F.pmod(F.xxhash64("rec_id"), F.lit(blocks))).alias("x")
    y = rows.withColumn("block", F.explode(F.sequence(F.lit(0), F.lit(blocks - 1)))).alias("y")
    near = x.join(y, (F.col("x.block") == F.col("y.block")) & (F.col("x.rec_id") != F.col("y.rec_id")))
    found = near.select(F.col("x.rec_id").alias("a"), F.col("y.rec_id").alias("b"), hamming("x", "y").cast("bigint").alias("d"))
    place = F.row_number().over(Window.partitionBy("a").orderBy("d", "b"))
    return found.withColumn("place", place).where("place <= 10").drop("place")


def _sets(word):
    return f"WITH {sql.VISITS} SELECT entity_id FROM visits WHERE owner = 'o0' {word} SELECT entity_id FROM visits WHERE owner = 'o1'"


@twin(_sets("UNION"))
def union_owners(spark, sf_dir):
    rows = visits(spark, sf_dir)
    return _of(rows, "o0").union(_of(rows, "o1")).distinct()


@twin(_sets("INTERSECT"))
def intersect_owners(spark, sf_dir):
    rows = visits(spark, sf_dir)
    return _of(rows, "o0").intersect(_of(rows, "o1"))


@twin(_sets("EXCEPT"))
def except_owners(spark, sf_dir):
    rows = visits(spark, sf_dir)
    return _of(rows, "o0").subtract(_of(rows, "o1"))


@twin(_sets("INTERSECT ALL"))
def intersect_all_owners(spark, sf_dir):
    rows = visits(spark, sf_dir)
    return _of(rows, "o0").intersectAll(_of(rows, "o1"))


@twin(_sets("EXCEPT ALL"))
def except_all_owners(spark, sf_dir):
    rows = visits(spark, sf_dir)
    return _of(rows, "o0").exceptAll(_of(rows, "o1"))


@twin("SELECT page_id, regexp_replace(regexp_replace(regexp_replace(lower(url), '^[a-z]+://', ''), '[?#].*$', ''), '^(www|m|blog)\\.', '') AS item FROM pages")
def string_normalise(spark, sf_dir):
    u = F.regexp_replace(F.regexp_replace(F.lower("url"), "^[a-z]+://", ""), "[?#].*$", "")
    return table(spark, sf_dir, "pages", "page_id", "url").select("page_id", F.regexp_replace(u, r"^(www|m|blog)\.", "").alias("item"))


@twin("SELECT date_trunc('month', o_orderdate) AS month, count(*) AS n, min(date_diff('day', o_orderdate, o_orderdate + INTERVAL 1 MONTH)) AS days FROM orders GROUP BY ALL")
def date_buckets(spark, sf_dir):
    d = F.datediff(F.add_months("o_orderdate", 1), "o_orderdate").cast("bigint")
    return table(spark, sf_dir, "orders", "o_orderdate").groupBy(F.date_trunc("month", "o_orderdate").alias("month")).agg(F.count("*").alias("n"), F.min(d).alias("days"))


@twin("SELECT w AS token, count(*) AS n FROM (SELECT unnest(string_split(text, ' ')) AS w FROM documents) GROUP BY w")
def token_histogram(spark, sf_dir):
    words = table(spark, sf_dir, "documents", "text").select(F.explode(F.split("text", " ")).alias("token"))
    return words.groupBy("token").agg(F.count("*").alias("n"))


@twin("SELECT json_extract_string(props, '$.k') AS k, count(DISTINCT user_id) AS viewers FROM events WHERE event_type = 'view' GROUP BY ALL")
def json_props(spark, sf_dir):
    return table(spark, sf_dir, "events", "props", "user_id", "event_type").where("event_type = 'view'").groupBy(F.get_json_object("props", "$.k").alias("k")).agg(F.count_distinct("user_id").alias("viewers"))


@twin(f"SELECT o_orderkey FROM orders WHERE {sql.num("'s|' || o_orderkey")} < {int(0.1 * 2**32)}")
def hash_sample(spark, sf_dir):
    return ranges.hash_sample(table(spark, sf_dir, "orders", "o_orderkey"), num(F.concat(F.lit("s|"), F.col("o_orderkey").cast("string"))), 0.1)


@twin("WITH t AS (SELECT avg(c_acctbal) AS m FROM customer) SELECT c_custkey FROM customer WHERE c_acctbal > (SELECT m FROM t) AND EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey AND o_orderstatus = 'F')")
def sql_subquery(spark, sf_dir):
    spark.read.parquet(f"{sf_dir}/customer.parquet").createOrReplaceTempView("fc_customer")
    spark.read.parquet(f"{sf_dir}/orders.parquet").createOrReplaceTempView("fc_orders")
    return spark.sql("WITH t AS (SELECT avg(c_acctbal) AS m FROM fc_customer) SELECT c_custkey FROM fc_customer WHERE c_acctbal > (SELECT m FROM t) AND EXISTS (SELECT 1 FROM fc_orders WHERE o_custkey = c_custkey AND o_orderstatus = 'F')")


@twin("SELECT time_bucket(INTERVAL 1 DAY, ts) AS start, count(DISTINCT user_id) AS users FROM events GROUP BY ALL")
def tumbling_users(spark, sf_dir):
    return users.tumbling(table(spark, sf_dir, "events"))


@twin("SELECT time_bucket(INTERVAL 15 MINUTE, ts) - CAST(i * 15 AS INTEGER) * INTERVAL 1 MINUTE AS start, count(DISTINCT user_id) AS users FROM events, range(4) r(i) GROUP BY ALL")
def sliding_users(spark, sf_dir):
    return users.sliding(table(spark, sf_dir, "events"))


@twin("SELECT event_id, user_id FROM events QUALIFY row_number() OVER (PARTITION BY user_id ORDER BY ts, event_id) = 1")
def first_releases(spark, sf_dir):
    return users.first_releases(table(spark, sf_dir, "events")).select("event_id", "user_id")


@twin("SELECT x.user_id, x.event_id AS first_id, y.event_id AS then_id FROM events x JOIN events y ON x.user_id = y.user_id AND y.ts > x.ts AND y.ts <= x.ts + INTERVAL 1 HOUR WHERE x.event_type = 'view' AND y.event_type = 'click'")
def viewed_then_clicked(spark, sf_dir):
    events = table(spark, sf_dir, "events", "event_id", "ts", "user_id", "event_type")
    return users.followed_by(events.where("event_type = 'view'"), events.where("event_type = 'click'"))


@twin(f"WITH d AS (SELECT DISTINCT event_type, user_id FROM events), n AS (SELECT event_type, {sql.num('CAST(user_id AS VARCHAR)')} AS h FROM d) SELECT event_type, bit_or(CASE WHEN h = 0 THEN CAST(4294967296 AS BIGINT) ELSE h & -h END) AS bitmap FROM n GROUP BY event_type")
def fm_bitmaps(spark, sf_dir):
    from fuzzcount.functions.python_udfs import fm_bitmap

    return table(spark, sf_dir, "events", "event_type", "user_id").distinct().groupBy("event_type").agg(fm_bitmap("user_id").alias("bitmap"))


@twin("SELECT time_bucket(INTERVAL 15 MINUTE, ts) - CAST(i * 15 AS INTEGER) * INTERVAL 1 MINUTE AS start, count(DISTINCT user_id) AS users FROM events, range(4) r(i) WHERE event_type = 'error' GROUP BY ALL")
def outbreak_cases(spark, sf_dir):
    return users.sliding(table(spark, sf_dir, "events").where("event_type = 'error'"))


@twin(f"WITH {sql.VISITS} SELECT segment, nation, count(DISTINCT entity_id) AS reach FROM visits GROUP BY ALL")
def segment_reach(spark, sf_dir):
    return visits(spark, sf_dir).groupBy("segment", "nation").agg(F.count_distinct("entity_id").alias("reach"))


@twin("WITH s AS (SELECT *, CASE WHEN ts - lag(ts) OVER w < INTERVAL 30 MINUTE THEN 0 ELSE 1 END AS fresh FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)), g AS (SELECT *, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS UNBOUNDED PRECEDING) AS n FROM s) SELECT user_id, min(ts) AS start, max(ts) + INTERVAL 30 MINUTE AS stop, count(*) AS events FROM g GROUP BY user_id, n")
def session_users(spark, sf_dir):
    return users.sessions(table(spark, sf_dir, "events"))


@twin("WITH d AS (SELECT DISTINCT CAST(ts AS DATE) AS day, user_id FROM events), a AS (SELECT day, count(*) AS dau FROM d GROUP BY day), m AS (SELECT a.day, count(DISTINCT user_id) AS mau FROM a JOIN d ON d.day BETWEEN a.day - 29 AND a.day GROUP BY a.day) SELECT CAST(day AS VARCHAR) AS day, dau, mau, round(dau / mau, 6) AS ratio FROM a JOIN m USING (day)")
def daily_monthly_users(spark, sf_dir):
    seen = table(spark, sf_dir, "events", "ts", "user_id").select(F.to_date("ts").alias("day"), "user_id").distinct()
    dau = seen.groupBy("day").agg(F.count("*").alias("dau"))
    grid = seen.select("user_id", F.explode(F.sequence("day", F.date_add("day", 29))).alias("day"))  # each user counts for the 30 days from a visit
    return dau.join(grid.groupBy("day").agg(F.count_distinct("user_id").alias("mau")), "day").select(F.col("day").cast("string").alias("day"), "dau", "mau", F.round(F.col("dau") / F.col("mau"), 6).alias("ratio"))


@twin(f"WITH {sql.VISITS} SELECT segment AS disease, count(DISTINCT entity_id) AS patients, count(*) AS records FROM visits GROUP BY segment")
def rare_disease_patients(spark, sf_dir):
    return visits(spark, sf_dir).groupBy(F.col("segment").alias("disease")).agg(F.count_distinct("entity_id").alias("patients"), F.count("*").alias("records"))


@twin("SELECT count(*) AS n, count(DISTINCT text) AS exact, count(DISTINCT trim(regexp_replace(lower(text), ' +', ' ', 'g'))) AS normalised FROM conversations WHERE role = 'user'")
def distinct_queries(spark, sf_dir):
    from fuzzcount.functions.grams import normalise

    q = table(spark, sf_dir, "conversations", "role", "text").where("role = 'user'")
    return q.agg(F.count("*").alias("n"), F.count_distinct("text").alias("exact"), F.count_distinct(normalise(F.col("text"))).alias("normalised"))


@twin("SELECT quality, toxic, count(DISTINCT text) AS items FROM documents JOIN labels USING (doc_id) GROUP BY ALL")
def quality_strata(spark, sf_dir):
    docs, labels = table(spark, sf_dir, "documents", "doc_id", "text"), table(spark, sf_dir, "labels")
    return docs.join(labels, "doc_id").groupBy("quality", "toxic").agg(F.count_distinct("text").alias("items"))
