"""One query for each operator family around the methods, on the given tables, each as a term that runs
incrementally: the rows arrive in ten batches (partners of joins apart), state is folded, and the answer is read
once at the end."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from deltafold.functions import monoids as m
from deltafold.plans.algebra import static, stream
from deltafold.session import checkpoint_folder, cut
from deltafold.sources.tables import arrive_by_key, arrive_by_time, table
from deltafold.workloads.incremental import _run

QUERIES: dict = {}
ORACLE_SQL: dict[str, str] = {}
CENTS = "CAST(ROUND({} * 100) AS BIGINT)"
QTY = "CAST(l_quantity AS BIGINT)"
HOUR = "unix_micros(CAST(date_trunc('hour', ts) AS TIMESTAMP))"
#: Streams with what orders their arrival: a key's remainder, or a time (@).
LATE = {"orders": "@o_orderdate", "lineitem": "@l_shipdate"}


def run(spark, sf_dir: str, query, streams: dict[str, str], invariant=(), gone: dict[str, str] | None = None, **options) -> DataFrame:
    """The answer of a term after ten batches of its streams (and the deletion of the rows in ``gone``)."""
    batches = {}
    for name, by in streams.items():
        rows = table(spark, sf_dir, name)
        batches[name] = arrive_by_time(rows, by[1:]) if by[0] == "@" else arrive_by_key(rows, by, 10)
    deletes = [{n: table(spark, sf_dir, n).where(c) for n, c in gone.items()}] if gone else None
    return _run(spark, query, batches, {n: table(spark, sf_dir, n) for n in invariant}, deletes, **options)


def micros(ts):
    """Microseconds since the epoch of a timestamp with or without time zone."""
    return F.unix_micros((F.col(ts) if isinstance(ts, str) else ts).cast("timestamp"))


def query(sql: str):
    """Registers a query under its function's name, with its SQL."""

    def keep(f):
        QUERIES[f.__name__] = f
        ORACLE_SQL[f.__name__] = sql
        return f

    return keep


@query("SELECT l_returnflag, l_linestatus, CAST(SUM(CAST(l_quantity AS BIGINT)) AS BIGINT) AS qty FROM lineitem WHERE l_quantity >= 25 GROUP BY ALL")
def scan_prune_lineitem(spark, sf_dir):
    return run(spark, sf_dir, stream("lineitem").where("l_quantity >= 25").group_by("l_returnflag", "l_linestatus").agg(qty=m.sum_(QTY)), {"lineitem": "l_orderkey"})


@query(f"SELECT l_orderkey, l_linenumber, {CENTS.format('l_extendedprice')} AS cents, CASE WHEN l_quantity > 40 THEN 'big' WHEN l_quantity BETWEEN 20 AND 40 THEN 'mid' ELSE 'small' END AS size FROM lineitem WHERE (l_returnflag IN ('A', 'R') AND l_discount IS NOT NULL) OR l_linestatus LIKE 'F%'")
def filter_project_lineitem(spark, sf_dir):
    q = stream("lineitem").flat_map(where="(l_returnflag IN ('A', 'R') AND l_discount IS NOT NULL) OR l_linestatus LIKE 'F%'", l_orderkey="l_orderkey", l_linenumber="l_linenumber", cents=CENTS.format("l_extendedprice"), size="CASE WHEN l_quantity > 40 THEN 'big' WHEN l_quantity BETWEEN 20 AND 40 THEN 'mid' ELSE 'small' END")
    return run(spark, sf_dir, q, {"lineitem": "l_orderkey"})


@query(r"SELECT w AS word, COUNT(*) AS n FROM (SELECT UNNEST(string_split(text, ' ')) AS w FROM documents) WHERE w <> '' GROUP BY w")
def unnest_document_words(spark, sf_dir):
    q = stream("documents").flat_map(explode=("word", "split(text, ' ')"), word="word").where("word <> ''").group_by("word").agg(n=m.count())
    return run(spark, sf_dir, q, {"documents": "doc_id"})


@query("SELECT i AS dim, COUNT(*) AS n, COUNT(*) FILTER (v > 0) AS positive FROM (SELECT UNNEST(range(len(embedding))) AS i, UNNEST(embedding) AS v FROM embeddings) GROUP BY i")
def unnest_embedding_dims(spark, sf_dir):
    cells = "transform(sequence(0, size(embedding) - 1), i -> named_struct('dim', CAST(i AS BIGINT), 'v', embedding[i]))"
    q = stream("embeddings").flat_map(explode=("e", cells), dim="e.dim", v="e.v").group_by("dim").agg(n=m.count(), positive=m.count_if("v > 0"))
    return run(spark, sf_dir, q, {"embeddings": "vec_id"})


@query("SELECT o_orderpriority, COUNT(*) AS n FROM orders JOIN lineitem ON o_orderkey = l_orderkey GROUP BY o_orderpriority")
def join_orders_lineitem(spark, sf_dir):
    q = stream("orders").join(stream("lineitem"), {"o_orderkey": "l_orderkey"}).group_by("o_orderpriority").agg(n=m.count())
    return run(spark, sf_dir, q, LATE)


@query("SELECT n_name, COUNT(*) AS customers FROM customer JOIN nation ON c_nationkey = n_nationkey GROUP BY n_name")
def join_broadcast_nation(spark, sf_dir):
    q = stream("customer").join(static("nation"), {"c_nationkey": "n_nationkey"}).group_by("n_name").agg(customers=m.count())
    return run(spark, sf_dir, q, {"customer": "c_custkey"}, ["nation"])


@query("SELECT o_orderkey, COUNT(l_orderkey) AS lines FROM orders LEFT JOIN lineitem ON o_orderkey = l_orderkey GROUP BY o_orderkey")
def left_outer_orders_lines(spark, sf_dir):
    lines = stream("lineitem").group_by("l_orderkey").agg(c=m.count())
    q = stream("orders").select(o_orderkey="o_orderkey").join(lines, {"o_orderkey": "l_orderkey"}, "left").select(o_orderkey="o_orderkey", lines="coalesce(c, 0L)")
    return run(spark, sf_dir, q, LATE)


@query("SELECT COALESCE(d.doc_id, l.doc_id) AS doc_id, d.lang, l.quality FROM documents d FULL JOIN labels l ON d.doc_id = l.doc_id")
def full_outer_docs_labels(spark, sf_dir):
    q = stream("documents").select(d_id="doc_id", lang="lang").join(stream("labels").select(l_id="doc_id", quality="quality"), {"d_id": "l_id"}, "full_outer")
    return run(spark, sf_dir, q.select(doc_id="coalesce(d_id, l_id)", lang="lang", quality="quality"), {"documents": "doc_id", "labels": "quality"})


@query("SELECT c_custkey FROM customer WHERE EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey AND o_orderstatus = 'F')")
def semi_customers_with_orders(spark, sf_dir):
    q = stream("customer").select(c_custkey="c_custkey").nested(stream("orders").where("o_orderstatus = 'F'"), {"c_custkey": "o_custkey"})
    return run(spark, sf_dir, q, {"customer": "c_custkey", "orders": "@o_orderdate"})


@query("SELECT o_orderkey FROM orders WHERE NOT EXISTS (SELECT 1 FROM lineitem WHERE l_orderkey = o_orderkey)")
def anti_orders_without_lines(spark, sf_dir):
    q = stream("orders").select(o_orderkey="o_orderkey").nested(stream("lineitem"), {"o_orderkey": "l_orderkey"}, "not_exists")
    return run(spark, sf_dir, q, LATE)


@query("SELECT band, COUNT(*) AS parts FROM part JOIN (SELECT UNNEST(range(0, 30)) AS band) ON p_retailprice >= band * 100 AND p_retailprice < band * 100 + 150 GROUP BY band")
def range_parts_price_band(spark, sf_dir):
    """Overlapping price bands (an invariant side): bucketed by the band's width, so it is an equi-join."""
    from deltafold.operators.time_joins import range_join

    bands = spark.range(30).select(F.col("id").alias("band"), (F.col("id") * 100.0).alias("lo"), (F.col("id") * 100.0 + 150).alias("hi"))
    q = stream("part").group_by("p_retailprice").agg(n=m.count())
    q = q.then(lambda df: range_join(df, bands, "p_retailprice", "lo", "hi", 150.0).groupBy("band").agg(F.sum("n").alias("parts")), ["band", "parts"], "range join with bands")
    return run(spark, sf_dir, q, {"part": "p_partkey"})


@query("SELECT e.event_id, p.event_id AS purchase_id FROM (SELECT * FROM events WHERE event_type <> 'purchase') e ASOF LEFT JOIN (SELECT user_id, event_id, ts FROM events WHERE event_type = 'purchase' QUALIFY ROW_NUMBER() OVER (PARTITION BY user_id, ts ORDER BY event_id DESC) = 1) p ON e.user_id = p.user_id AND e.ts >= p.ts")
def asof_event_prev_purchase(spark, sf_dir):
    from deltafold.operators.time_joins import asof_join

    def newest(e: DataFrame) -> DataFrame:
        bought = e.where("event_type = 'purchase'").select("user_id", "ts", F.col("event_id").alias("purchase_id"))
        return asof_join(e.where("event_type <> 'purchase'"), bought, "user_id", "ts", "purchase_id").select("event_id", "purchase_id")

    q = stream("events").select(event_id="event_id", user_id="user_id", ts="ts", event_type="event_type").then(newest, ["event_id", "purchase_id"], "newest purchase")
    return run(spark, sf_dir, q, {"events": "event_id"})


@query("SELECT a.event_id AS click_id, b.event_id AS buy_id FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts BETWEEN a.ts AND a.ts + INTERVAL 1 HOUR WHERE a.event_type = 'click' AND b.event_type = 'purchase'")
def interval_click_purchase(spark, sf_dir):
    a = stream("events").flat_map(where="event_type = 'click'", a_user="user_id", a_ts="ts", click_id="event_id")
    b = stream("events").flat_map(where="event_type = 'purchase'", b_user="user_id", b_ts="ts", buy_id="event_id")
    q = a.join(b, {"a_user": "b_user"}).flat_map(where="b_ts BETWEEN a_ts AND a_ts + INTERVAL 1 HOUR", click_id="click_id", buy_id="buy_id")
    return run(spark, sf_dir, q, {"events": "event_id"})


@query("SELECT a.l_partkey AS p1, b.l_partkey AS p2, COUNT(*) AS n FROM lineitem a JOIN lineitem b ON a.l_orderkey = b.l_orderkey AND a.l_partkey < b.l_partkey GROUP BY ALL HAVING COUNT(*) > 1")
def self_join_same_order_parts(spark, sf_dir):
    a = stream("lineitem").select(k1="l_orderkey", p1="l_partkey")
    b = stream("lineitem").select(k2="l_orderkey", p2="l_partkey")
    q = a.join(b, {"k1": "k2"}).where("p1 < p2").group_by("p1", "p2").agg(n=m.count()).where("n > 1")
    return run(spark, sf_dir, q, {"lineitem": "l_partkey"})


@query(f"SELECT n_name, CAST(SUM({CENTS.format('l_extendedprice')}) AS BIGINT) AS cents FROM region JOIN nation ON r_regionkey = n_regionkey JOIN customer ON c_nationkey = n_nationkey JOIN orders ON o_custkey = c_custkey JOIN lineitem ON l_orderkey = o_orderkey JOIN supplier ON s_suppkey = l_suppkey AND s_nationkey = c_nationkey GROUP BY n_name")
def q5_like_region_revenue(spark, sf_dir):
    o = stream("orders").select(o_orderkey="o_orderkey", o_custkey="o_custkey").join(static("customer"), {"o_custkey": "c_custkey"}).join(static("nation"), {"c_nationkey": "n_nationkey"}).join(static("region"), {"n_regionkey": "r_regionkey"})
    li = stream("lineitem").select(l_orderkey="l_orderkey", l_suppkey="l_suppkey", v=CENTS.format("l_extendedprice")).join(static("supplier"), {"l_suppkey": "s_suppkey"})
    q = o.join(li, {"o_orderkey": "l_orderkey", "c_nationkey": "s_nationkey"}).group_by("n_name").agg(cents=m.sum_("v"))
    return run(spark, sf_dir, q, LATE, ["customer", "nation", "region", "supplier"])


def _sets(sql_sets: str) -> str:
    return f"SELECT l_returnflag, l_linestatus, CAST(GROUPING(l_returnflag) * 2 + GROUPING(l_linestatus) AS BIGINT) AS gid, COUNT(*) AS n FROM lineitem GROUP BY {sql_sets}"


@query(_sets("CUBE (l_returnflag, l_linestatus)"))
def cube_flag_status(spark, sf_dir):
    q = stream("lineitem").grouping_sets([["l_returnflag", "l_linestatus"], ["l_returnflag"], ["l_linestatus"], []], ["l_returnflag", "l_linestatus"]).group_by("l_returnflag", "l_linestatus", "gid").agg(n=m.count())
    return run(spark, sf_dir, q, {"lineitem": "l_orderkey"})


@query("SELECT n_name, c_mktsegment, COUNT(*) AS n FROM customer JOIN nation ON c_nationkey = n_nationkey GROUP BY ROLLUP (n_name, c_mktsegment)")
def rollup_nation_segment(spark, sf_dir):
    both = ["n_name", "c_mktsegment"]
    q = stream("customer").join(static("nation"), {"c_nationkey": "n_nationkey"}).grouping_sets([both, ["n_name"], []], both).group_by(*both, "gid").agg(n=m.count()).select(n_name="n_name", c_mktsegment="c_mktsegment", n="n")
    return run(spark, sf_dir, q, {"customer": "c_custkey"}, ["nation"])


@query("SELECT o_orderpriority, o_orderstatus, COUNT(*) AS n FROM orders GROUP BY GROUPING SETS ((o_orderpriority), (o_orderstatus), ())")
def grouping_sets_priority_status(spark, sf_dir):
    both = ["o_orderpriority", "o_orderstatus"]
    q = stream("orders").grouping_sets([both[:1], both[1:], []], both).group_by(*both, "gid").agg(n=m.count()).select(o_orderpriority="o_orderpriority", o_orderstatus="o_orderstatus", n="n")
    return run(spark, sf_dir, q, {"orders": "o_orderkey"})


@query("SELECT user_id, COUNT(*) FILTER (event_type = 'click') AS click, COUNT(*) FILTER (event_type = 'purchase') AS purchase FROM events GROUP BY user_id")
def pivot_event_types(spark, sf_dir):
    q = stream("events").group_by("user_id").agg(click=m.count_if("event_type = 'click'"), purchase=m.count_if("event_type = 'purchase'"))
    return run(spark, sf_dir, q, {"events": "event_id"})


@query("SELECT p_partkey, k, v FROM (SELECT p_partkey, 'size' AS k, CAST(p_size AS BIGINT) AS v FROM part UNION ALL SELECT p_partkey, 'cents', CAST(ROUND(p_retailprice * 100) AS BIGINT) FROM part)")
def unpivot_part(spark, sf_dir):
    cells = f"array(named_struct('k', 'size', 'v', CAST(p_size AS BIGINT)), named_struct('k', 'cents', 'v', {CENTS.format('p_retailprice')}))"
    return run(spark, sf_dir, stream("part").flat_map(explode=("e", cells), p_partkey="p_partkey", k="e.k", v="e.v"), {"part": "p_partkey"})


@query(f"SELECT CAST(SUM({CENTS.format('l_extendedprice')}) AS BIGINT) AS cents, COUNT(*) AS n, COUNT(DISTINCT l_partkey) AS parts FROM lineitem")
def global_revenue(spark, sf_dir):
    q = stream("lineitem").agg(cents=m.sum_(CENTS.format("l_extendedprice")), n=m.count(), parts=m.count_distinct("l_partkey"))
    return run(spark, sf_dir, q, {"lineitem": "l_orderkey"})


@query("SELECT o_custkey, COUNT(*) AS n FROM orders GROUP BY o_custkey HAVING COUNT(*) >= 15")
def having_big_customers(spark, sf_dir):
    return run(spark, sf_dir, stream("orders").group_by("o_custkey").agg(n=m.count()).where("n >= 15"), {"orders": "o_orderkey"})


@query("SELECT c_custkey, CAST(ROW_NUMBER() OVER w AS BIGINT) AS rn, CAST(RANK() OVER (PARTITION BY c_nationkey ORDER BY c_mktsegment) AS BIGINT) AS rk, CAST(DENSE_RANK() OVER (PARTITION BY c_nationkey ORDER BY c_mktsegment) AS BIGINT) AS dr, CAST(NTILE(4) OVER w AS BIGINT) AS quarter FROM customer WINDOW w AS (PARTITION BY c_nationkey ORDER BY c_acctbal DESC, c_custkey)")
def rank_customers_in_nation(spark, sf_dir):
    def ranked(df: DataFrame) -> DataFrame:
        w, s = Window.partitionBy("c_nationkey").orderBy(F.desc("c_acctbal"), "c_custkey"), Window.partitionBy("c_nationkey").orderBy("c_mktsegment")
        c = lambda x, n: x.cast("long").alias(n)
        return df.select("c_custkey", c(F.row_number().over(w), "rn"), c(F.rank().over(s), "rk"), c(F.dense_rank().over(s), "dr"), c(F.ntile(4).over(w), "quarter"))

    q = stream("customer").select(c_custkey="c_custkey", c_nationkey="c_nationkey", c_acctbal="c_acctbal", c_mktsegment="c_mktsegment").then(ranked, ["c_custkey", "rn", "rk", "dr", "quarter"], "ranks")
    return run(spark, sf_dir, q, {"customer": "c_custkey"})


@query("SELECT event_id, epoch_us(ts) - epoch_us(LAG(ts) OVER w) AS gap, LEAD(event_id) OVER w AS following, FIRST_VALUE(event_id) OVER w AS first_id FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)")
def lag_event_gap(spark, sf_dir):
    def gaps(df: DataFrame) -> DataFrame:
        w = Window.partitionBy("user_id").orderBy("ts", "event_id")
        return df.select("event_id", (micros("ts") - micros(F.lag("ts").over(w))).alias("gap"), F.lead("event_id").over(w).alias("following"), F.first("event_id").over(w).alias("first_id"))

    q = stream("events").select(event_id="event_id", user_id="user_id", ts="ts").then(gaps, ["event_id", "gap", "following", "first_id"], "neighbours")
    return run(spark, sf_dir, q, {"events": "event_id"})


@query("SELECT day, n, CAST(SUM(n) OVER (ORDER BY day) AS BIGINT) AS running FROM (SELECT CAST(CAST(ts AS DATE) AS VARCHAR) AS day, COUNT(*) AS n FROM events GROUP BY day)")
def running_total_daily(spark, sf_dir):
    days = stream("events").group_by(day="date_format(ts, 'yyyy-MM-dd')").agg(n=m.count())
    q = days.then(lambda df: df.withColumn("running", F.sum("n").over(Window.orderBy("day"))), ["day", "n", "running"], "running total")  # one row a day
    return run(spark, sf_dir, q, {"events": "event_id"})


@query("SELECT user_id, day, CAST(SUM(n) OVER (PARTITION BY user_id ORDER BY day RANGE BETWEEN 6 PRECEDING AND CURRENT ROW) AS BIGINT) AS n7 FROM (SELECT user_id, CAST(date_diff('day', DATE '1970-01-01', CAST(ts AS DATE)) AS BIGINT) AS day, COUNT(*) AS n FROM events GROUP BY ALL)")
def moving_avg_7d(spark, sf_dir):
    days = stream("events").group_by(user_id="user_id", day="CAST(unix_date(to_date(ts)) AS BIGINT)").agg(n=m.count())
    week = Window.partitionBy("user_id").orderBy("day").rangeBetween(-6, 0)
    q = days.then(lambda df: df.select("user_id", "day", F.sum("n").over(week).alias("n7")), ["user_id", "day", "n7"], "seven days")
    return run(spark, sf_dir, q, {"events": "event_id"})


@query(f"SELECT o_orderkey, {CENTS.format('o_totalprice')} AS cents FROM orders ORDER BY cents DESC, o_orderkey LIMIT 25 OFFSET 5")
def topk_orders_by_price(spark, sf_dir):
    q = stream("orders").select(o_orderkey="o_orderkey", cents=CENTS.format("o_totalprice")).then(lambda df: df.orderBy(F.desc("cents"), "o_orderkey").offset(5).limit(25), ["o_orderkey", "cents"], "top")
    return run(spark, sf_dir, q, {"orders": "o_orderkey"})


@query("SELECT c_mktsegment, c_custkey FROM (SELECT *, ROW_NUMBER() OVER (PARTITION BY c_mktsegment ORDER BY c_acctbal DESC, c_custkey) AS r FROM customer) WHERE r <= 3")
def topk_per_segment(spark, sf_dir):
    w = Window.partitionBy("c_mktsegment").orderBy(F.desc("c_acctbal"), "c_custkey")
    top = lambda df: df.withColumn("r", F.row_number().over(w)).where("r <= 3").select("c_mktsegment", "c_custkey")
    q = stream("customer").select(c_mktsegment="c_mktsegment", c_custkey="c_custkey", c_acctbal="c_acctbal").then(top, ["c_mktsegment", "c_custkey"], "top of each")
    return run(spark, sf_dir, q, {"customer": "c_custkey"})


@query("SELECT o_orderkey AS k FROM orders UNION ALL SELECT l_orderkey FROM lineitem")
def union_all_keys(spark, sf_dir):
    return run(spark, sf_dir, stream("orders").select(k="o_orderkey").union(stream("lineitem").select(k="l_orderkey")), LATE)


@query("SELECT c_nationkey AS k FROM customer INTERSECT SELECT s_nationkey FROM supplier")
def intersect_customer_supplier_nations(spark, sf_dir):
    both = stream("customer").select(k="c_nationkey", side="0").union(stream("supplier").select(k="s_nationkey", side="1"))
    q = both.group_by("k").agg(a=m.count_if("side = 0"), b=m.count_if("side = 1")).flat_map(where="a > 0 AND b > 0", k="k")
    return run(spark, sf_dir, q, {"customer": "c_custkey", "supplier": "s_suppkey"})


@query("SELECT l_partkey AS k FROM lineitem EXCEPT ALL SELECT p_partkey FROM part")
def except_all_parts(spark, sf_dir):
    both = stream("lineitem").select(k="l_partkey", side="0").union(stream("part").select(k="p_partkey", side="1"))
    q = both.group_by("k").agg(a=m.count_if("side = 0"), b=m.count_if("side = 1")).flat_map(where="a > b", explode=("copy", "sequence(1L, a - b)"), k="k")
    return run(spark, sf_dir, q, {"lineitem": "l_orderkey", "part": "p_partkey"})


@query("SELECT p_partkey, upper(p_brand) AS brand, substr(p_type, 1, 3) AS kind, length(trim(p_name)) AS chars, concat(p_brand, '/', p_type) AS path, regexp_replace(p_name, '[aeiou]', '_', 'g') AS masked FROM part")
def str_brand_prefix(spark, sf_dir):
    q = stream("part").select(p_partkey="p_partkey", brand="upper(p_brand)", kind="substring(p_type, 1, 3)", chars="CAST(length(trim(p_name)) AS BIGINT)", path="concat_ws('/', p_brand, p_type)", masked="regexp_replace(p_name, '[aeiou]', '_')")
    return run(spark, sf_dir, q, {"part": "p_partkey"})


@query("SELECT regexp_extract(url, '^https?://([^/]+)', 1) AS host, COUNT(*) AS n FROM pages GROUP BY host")
def url_host_counts(spark, sf_dir):
    return run(spark, sf_dir, stream("pages").group_by(host="regexp_extract(url, '^https?://([^/]+)', 1)").agg(n=m.count()), {"pages": "page_id"})


@query(f"SELECT year(l_shipdate) AS y, month(l_shipdate) AS m, CAST(SUM({CENTS.format('l_extendedprice')}) AS BIGINT) AS cents FROM lineitem GROUP BY ALL")
def monthly_revenue(spark, sf_dir):
    q = stream("lineitem").group_by(y="CAST(year(l_shipdate) AS BIGINT)", m="CAST(month(l_shipdate) AS BIGINT)").agg(cents=m.sum_(CENTS.format("l_extendedprice")))
    return run(spark, sf_dir, q, {"lineitem": "l_orderkey"})


@query("SELECT CAST(ROUND(l_discount * 100) AS BIGINT) % 4 AS b, CAST(FLOOR(l_quantity / 10) AS BIGINT) AS f, CAST(SUM(ABS(CAST(l_linenumber AS BIGINT) - 4)) AS BIGINT) AS d, COUNT(*) AS n FROM lineitem GROUP BY ALL")
def math_discount_buckets(spark, sf_dir):
    q = stream("lineitem").group_by(b="pmod(CAST(ROUND(l_discount * 100) AS BIGINT), 4)", f="CAST(floor(l_quantity / 10) AS BIGINT)").agg(d=m.sum_("abs(CAST(l_linenumber AS BIGINT) - 4)"), n=m.count())
    return run(spark, sf_dir, q, {"lineitem": "l_orderkey"})


@query("SELECT vec_id, len(list_filter(embedding, lambda x: x > 0)) AS positive, CAST(list_sum(list_transform(embedding, lambda x: CAST(ROUND(CAST(x AS DOUBLE) * 1000) AS BIGINT) * CAST(ROUND(CAST(x AS DOUBLE) * 1000) AS BIGINT))) AS BIGINT) AS norm FROM embeddings")
def array_dot_norm_embeddings(spark, sf_dir):
    q = stream("embeddings").select(vec_id="vec_id", positive="CAST(size(filter(embedding, x -> x > 0)) AS BIGINT)", norm="aggregate(transform(embedding, x -> CAST(ROUND(CAST(x AS DOUBLE) * 1000) AS BIGINT)), 0L, (a, x) -> a + x * x)")
    return run(spark, sf_dir, q, {"embeddings": "vec_id"})


@query("SELECT CAST(json_extract(props, '$.k') AS BIGINT) AS k, COUNT(*) AS n FROM events GROUP BY k")
def json_props_histogram(spark, sf_dir):
    return run(spark, sf_dir, stream("events").group_by(k="from_json(props, 'k BIGINT').k").agg(n=m.count()), {"events": "event_id"})


@query("SELECT conv_id, COUNT(*) AS turns, string_agg(role, '>' ORDER BY turn) AS roles FROM conversations GROUP BY conv_id")
def ordered_roles(spark, sf_dir):
    q = stream("conversations").group_by("conv_id").agg(turns=m.count(), roles=m.string_agg("role", "turn", ">"))
    return run(spark, sf_dir, q, {"conversations": "turn"})


@query("SELECT epoch_us(date_trunc('hour', ts)) AS start, COUNT(*) AS n FROM events GROUP BY start")
def tumbling_hour_events(spark, sf_dir):
    return run(spark, sf_dir, stream("events").group_by(start=HOUR).agg(n=m.count()), {"events": "event_id"})


@query("SELECT start, COUNT(*) AS n FROM (SELECT UNNEST([epoch_us(date_trunc('hour', ts)), epoch_us(date_trunc('hour', ts)) - 3600000000]) AS start FROM events) GROUP BY start")
def sliding_events(spark, sf_dir):
    q = stream("events").flat_map(explode=("start", f"array({HOUR}, {HOUR} - 3600000000L)"), start="start").group_by("start").agg(n=m.count())
    return run(spark, sf_dir, q, {"events": "event_id"})


@query("""WITH g AS (SELECT user_id, ts, CASE WHEN ts - LAG(ts) OVER (PARTITION BY user_id ORDER BY ts) < INTERVAL 6 HOUR THEN 0 ELSE 1 END AS new FROM events),
  s AS (SELECT user_id, ts, SUM(new) OVER (PARTITION BY user_id ORDER BY ts, new DESC ROWS UNBOUNDED PRECEDING) AS sid FROM g)
  SELECT user_id, epoch_us(MIN(ts)) AS start, COUNT(*) AS n FROM s GROUP BY user_id, sid""")
def session_user_events(spark, sf_dir):
    def sessions(df: DataFrame) -> DataFrame:
        return df.groupBy("user_id", F.session_window("ts", "6 hours").alias("w")).agg(F.count("*").alias("n")).select("user_id", micros("w.start").alias("start"), "n")

    return run(spark, sf_dir, stream("events").select(user_id="user_id", ts="ts").then(sessions, ["user_id", "start", "n"], "sessions"), {"events": "event_id"})


@query("SELECT (l_quantity - 25) * (l_quantity - 25) + (ROUND(l_discount * 100) - 5) * (ROUND(l_discount * 100) - 5) AS d, COUNT(*) AS n FROM lineitem GROUP BY d")
def udf_square_distance(spark, sf_dir):
    """A user function over Arrow batches."""
    from deltafold.functions.user import square_distance

    spark.udf.register("square_distance", square_distance)
    q = stream("lineitem").select(d="square_distance(l_quantity, round(l_discount * 100))").group_by("d").agg(n=m.count())
    return run(spark, sf_dir, q, {"lineitem": "l_orderkey"})


@query("SELECT o_custkey, CAST(SUM(o_orderkey) AS BIGINT) AS s, MAX(o_orderkey) AS hi FROM orders GROUP BY o_custkey")
def udaf_user_monoid(spark, sf_dir):
    """A user monoid (sum and greatest) by its zero, lift and merge, with partial aggregation."""
    from deltafold.functions.user import aggregate_by

    both = lambda df: aggregate_by(df, "o_custkey", "o_orderkey", (0, -1), lambda x: (x, x), lambda a, b: (a[0] + b[0], max(a[1], b[1]))).selectExpr("key AS o_custkey", "value[0] AS s", "value[1] AS hi")
    q = stream("orders").select(o_custkey="o_custkey", o_orderkey="o_orderkey").then(both, ["o_custkey", "s", "hi"], "user monoid")
    return run(spark, sf_dir, q, {"orders": "o_orderkey"})


@query("SELECT c AS token, COUNT(*) AS n FROM (SELECT UNNEST(string_split(p_name, ' ')) AS c FROM part) GROUP BY c")
def udtf_tokens(spark, sf_dir):
    from deltafold.functions.user import Tokens

    spark.udtf.register("tokens_of", Tokens)

    def tokens(df: DataFrame) -> DataFrame:
        df.createOrReplaceTempView("parts_for_tokens")
        return spark.sql("SELECT token, SUM(n) AS n FROM (SELECT token, n FROM parts_for_tokens, LATERAL tokens_of(p_name)) GROUP BY token")

    return run(spark, sf_dir, stream("part").group_by("p_name").agg(n=m.count()).then(tokens, ["token", "n"], "tokens"), {"part": "p_partkey"})


@query("SELECT c_custkey FROM customer WHERE EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey AND o_orderstatus = 'F' AND o_orderkey % 3 <> 0) AND c_custkey % 7 <> 2")
def delete_semi_customers(spark, sf_dir):
    """Both sides of a semi-join lose rows."""
    q = stream("customer").select(c_custkey="c_custkey").nested(stream("orders").where("o_orderstatus = 'F'"), {"c_custkey": "o_custkey"})
    return run(spark, sf_dir, q, {"customer": "c_custkey", "orders": "@o_orderdate"}, gone={"customer": "c_custkey % 7 = 2", "orders": "o_orderkey % 3 = 0"})


@query(_sets("CUBE (l_returnflag, l_linestatus)").replace("FROM lineitem", "FROM lineitem WHERE l_linenumber <> 2"))
def delete_cube_flag_status(spark, sf_dir):
    both = ["l_returnflag", "l_linestatus"]
    q = stream("lineitem").grouping_sets([both, both[:1], both[1:], []], both).group_by(*both, "gid").agg(n=m.count())
    return run(spark, sf_dir, q, {"lineitem": "l_orderkey"}, gone={"lineitem": "l_linenumber = 2"})


@query("SELECT l_partkey AS k FROM (SELECT * FROM lineitem WHERE l_linenumber <> 1) EXCEPT ALL SELECT p_partkey FROM part")
def delete_except_all(spark, sf_dir):
    both = stream("lineitem").select(k="l_partkey", side="0").union(stream("part").select(k="p_partkey", side="1"))
    q = both.group_by("k").agg(a=m.count_if("side = 0"), b=m.count_if("side = 1")).flat_map(where="a > b", explode=("copy", "sequence(1L, a - b)"), k="k")
    return run(spark, sf_dir, q, {"lineitem": "l_orderkey", "part": "p_partkey"}, gone={"lineitem": "l_linenumber = 1"})


@query("SELECT user_id, COUNT(*) FILTER (value < 20) AS b0, COUNT(*) FILTER (value >= 20 AND value < 40) AS b1, COUNT(*) FILTER (value >= 40 AND value < 60) AS b2, COUNT(*) FILTER (value >= 60) AS b3 FROM events GROUP BY user_id")
def histogram_of_values(spark, sf_dir):
    q = stream("events").group_by("user_id").agg(h=m.histogram("value", 0, 80, 4)).select(user_id="user_id", b0="h[0]", b1="h[1]", b2="h[2]", b3="h[3]")
    return run(spark, sf_dir, q, {"events": "event_id"})


def _round_trip(spark, df: DataFrame, fmt: str, **options) -> DataFrame:
    folder = f"{checkpoint_folder(spark)}/{fmt}-{uuid.uuid4().hex}"
    df.write.format(fmt).options(**options).save(folder)
    return spark.read.format(fmt).options(**options).schema(df.schema).load(folder)


_ORDER_COLS = "SELECT o_orderkey, o_custkey, o_orderstatus FROM orders"
for _fmt, _options in {"parquet": {}, "orc": {}, "csv": {"header": True}, "json": {}, "xml": {"rowTag": "order"}}.items():

    def _sink(spark, sf_dir, fmt=_fmt, options=_options):
        return _round_trip(spark, table(spark, sf_dir, "orders").select("o_orderkey", "o_custkey", "o_orderstatus"), fmt, **options)

    _sink.__name__ = f"sink_roundtrip_{_fmt}"
    query(_ORDER_COLS)(_sink)

__all__ = ["ORACLE_SQL", "QUERIES", "cut"]
