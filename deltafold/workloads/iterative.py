"""Iterative and streaming workloads."""

from __future__ import annotations

import uuid

from pyspark.sql import functions as F

from deltafold.functions import monoids as m
from deltafold.functions.monoids import ADD, GREATEST, SUPPORT
from deltafold.operators.kmeans import IncrementalKMeans, kmeans, sums
from deltafold.operators.merge import co_group, diffuse, diminish, merge_states, near_join
from deltafold.operators.nmf import nmf, squared_error
from deltafold.operators.pagerank import IncrementalPageRank, pagerank, pagerank_fixed_point
from deltafold.operators.repeat import ExactRepeat, IncrementalRepeat
from deltafold.operators.time_joins import sliding_distinct
from deltafold.plans.algebra import stream
from deltafold.plans.incremental import IncrementalQuery
from deltafold.session import checkpoint_folder, cut
from deltafold.sources.generators import rmat_edges, square_points
from deltafold.sources.tables import arrive_by_key, table
from deltafold.streaming.runner import StreamRunner, as_files, deduplicated, dir_stream, keyed_average, native_aggregate

QUERIES: dict = {}
ORACLE_SQL: dict[str, str] = {}


def query(sql: str | None):
    def keep(f):
        QUERIES[f.__name__] = f
        if sql is not None:
            ORACLE_SQL[f.__name__] = sql
        return f

    return keep


INIT = [(10.0, 2.0), (10.0, 8.0), (40.0, 2.0), (40.0, 8.0)]
CENTRES = [(3.0, 3.0), (3.0, 7.0), (7.0, 3.0), (7.0, 7.0)]
NEAR = [(2.0, 2.0), (2.0, 8.0), (8.0, 2.0), (8.0, 8.0)]


def line_points(spark, sf_dir):
    return table(spark, sf_dir, "lineitem").select(F.col("l_orderkey").alias("id"), F.col("l_quantity").cast("long").alias("x"), F.round(F.col("l_discount") * 100).cast("long").alias("y"))


def _kmeans_sql(rounds: int) -> str:
    """Batch k-means unrolled: each round's centres are a common table expression."""
    start = ", ".join(f"({i}, {x}, {y})" for i, (x, y) in enumerate(INIT))
    parts = [f"p AS (SELECT CAST(l_quantity AS BIGINT) AS x, CAST(ROUND(l_discount * 100) AS BIGINT) AS y, COUNT(*) AS c FROM lineitem GROUP BY ALL), c0(i, cx, cy) AS (VALUES {start})"]
    for r in range(rounds):
        parts.append(f"a{r} AS (SELECT x, y, c, ARG_MIN(i, (CAST(x AS DOUBLE) - cx) * (CAST(x AS DOUBLE) - cx) + (CAST(y AS DOUBLE) - cy) * (CAST(y AS DOUBLE) - cy) + i * 1e-12) AS i FROM p, c{r} GROUP BY x, y, c)")
        parts.append(f"c{r + 1} AS (SELECT i, CAST(SUM(x * c) AS DOUBLE) / SUM(c) AS cx, CAST(SUM(y * c) AS DOUBLE) / SUM(c) AS cy FROM a{r} GROUP BY i)")
    return f"WITH {', '.join(parts)} SELECT CAST(i AS BIGINT) AS cid, CAST(SUM(c) AS BIGINT) AS points FROM a{rounds - 1} GROUP BY i"


@query(_kmeans_sql(4))
def kmeans_batch(spark, sf_dir):
    _, state = kmeans(line_points(spark, sf_dir), ["x", "y"], INIT, 4)
    return spark.createDataFrame([(i, v[-1]) for i, v in sorted(state.items())], "cid long, points long")


@query("SELECT COUNT(*) AS points FROM lineitem")
def kmeans_state_counts(spark, sf_dir):
    """After nine increments the state counts every point once."""
    q = IncrementalKMeans(spark, ["x", "y"], INIT, 3)
    for b in arrive_by_key(line_points(spark, sf_dir), "id", 10):
        q.step(b)
    return spark.createDataFrame([(q.points,)], "points long")


def kmeans_gaps(spark, initial: int = 1_000_000, increment: int = 40_000, increments: int = 9, rounds: int = 10) -> list[tuple[int, float, float]]:
    """Four squares, the reference's sizes: after the initial points and after each increment, (batch, largest
    distance in a coordinate of the incremental centres from batch ones on all points so far, from the known
    centres)."""
    whole = square_points(spark, initial + increments * increment).persist()
    gap = lambda a, b: max(abs(u - v) for p, r in zip(a, b, strict=True) for u, v in zip(p, r, strict=True))
    q, out, at = IncrementalKMeans(spark, ["x", "y"], NEAR, rounds), [], 0
    for n in range(increments + 1):
        upto = initial + n * increment
        q.step(whole.where((F.col("id") >= at) & (F.col("id") < upto)))
        full, _ = kmeans(whole.where(F.col("id") < upto), ["x", "y"], NEAR, rounds)
        out.append((n, gap(q.centres, full), gap(q.centres, CENTRES)))
        at = upto
    whole.unpersist()
    return out


@query(None)
def kmeans_incremental_gap(spark, sf_dir):
    """The gaps after the initial points and each of nine increments, at the reference's sizes."""
    return spark.createDataFrame(kmeans_gaps(spark), "batch int, from_batch double, from_truth double")


@query("SELECT i AS cid, CAST(340000 AS BIGINT) AS points FROM range(4) t(i)")
def kmeans_square_counts(spark, sf_dir):
    """The generator deals points to four squares in turn, and clusters are squares: each has a fourth of them."""
    q = IncrementalKMeans(spark, ["x", "y"], NEAR, 10)
    whole = square_points(spark, 1_360_000)
    for n in range(10):
        at, upto = (0, 1_000_000) if n == 0 else (1_000_000 + (n - 1) * 40_000, 1_000_000 + n * 40_000)
        q.step(whole.where((F.col("id") >= at) & (F.col("id") < upto)))
    return spark.createDataFrame([(i, v[-1]) for i, v in sorted(q.state.items())], "cid long, points long")


_T = "SELECT p_partkey AS t_id, CAST(p_partkey * 37 % 101 AS DOUBLE) AS x, CAST(p_size AS DOUBLE) AS y FROM part WHERE p_partkey <= 200"
_D = "SELECT s_suppkey AS d_id, CAST(s_suppkey * 53 % 101 AS DOUBLE) AS x, CAST(s_suppkey * 29 % 50 AS DOUBLE) AS y FROM supplier"


@query(f"""WITH n AS (SELECT d_id, t_id, sqrt((d.x - t.x) * (d.x - t.x) + (d.y - t.y) * (d.y - t.y)) AS far FROM ({_D}) d, ({_T}) t WHERE (d.x - t.x) * (d.x - t.x) + (d.y - t.y) * (d.y - t.y) <= 36),
  r AS (SELECT d_id, t_id, ROW_NUMBER() OVER (PARTITION BY d_id ORDER BY far, t_id) AS a, ROW_NUMBER() OVER (PARTITION BY t_id ORDER BY far, d_id) AS b FROM n) SELECT d_id, t_id FROM r WHERE a = 1 AND b = 1""")
def kmeans_near_join(spark, sf_dir):
    """Keys that are points, equal if they are each other's nearest within eps."""
    t = table(spark, sf_dir, "part").where("p_partkey <= 200").selectExpr("p_partkey AS t_id", "CAST(p_partkey * 37 % 101 AS DOUBLE) AS x", "CAST(p_size AS DOUBLE) AS y")
    d = table(spark, sf_dir, "supplier").selectExpr("s_suppkey AS d_id", "CAST(s_suppkey * 53 % 101 AS DOUBLE) AS x", "CAST(s_suppkey * 29 % 50 AS DOUBLE) AS y")
    return near_join(t, d, ["x", "y"], 6.0)


@query(None)
def kmeans_embeddings_purity(spark, sf_dir):
    """Clusters of vectors against their labels, beside the share of the most common label."""
    from deltafold.measures import purity
    from deltafold.operators.kmeans import nearest

    dims = [f"x{i}" for i in range(64)]
    df = cut(table(spark, sf_dir, "embeddings").select("label", *(F.col("embedding")[i].cast("double").alias(d) for i, d in enumerate(dims))))
    rows = df.groupBy("label").agg(*(F.first(d).alias(d) for d in dims)).orderBy("label").collect()  # one row a label
    centres, _ = kmeans(df, dims, [tuple(r[d] for d in dims) for r in rows], 3)
    found = purity(df.select(nearest(dims, centres).alias("cid"), "label"), "cid", "label")
    base = df.groupBy("label").count().agg(F.max("count") / F.sum("count")).first()[0]
    return spark.createDataFrame([(found, base)], "purity double, most_common double")


def part_supplier_edges(spark, sf_dir):
    li = table(spark, sf_dir, "lineitem").select(F.concat(F.lit("p"), F.col("l_partkey")).alias("src"), F.concat(F.lit("s"), F.col("l_suppkey")).alias("dst")).distinct()
    return li.unionByName(li.select(F.col("dst").alias("src"), F.col("src").alias("dst")))


def page_edges(spark, sf_dir):
    pages = table(spark, sf_dir, "pages").select(F.regexp_extract("url", "^https?://([^/]+)", 1).alias("src"), F.explode(F.regexp_extract_all("html", F.lit('href="([^"]*)"'), F.lit(1))).alias("dst"))
    return pages.distinct()


def _rank_sql(edges: str, rounds: int) -> str:
    parts = [f"e AS ({edges})", "d AS (SELECT src, COUNT(*) AS deg FROM e GROUP BY src)", "n AS (SELECT src AS node FROM e UNION SELECT dst FROM e)", "r0 AS (SELECT node, CAST(1000000000 AS BIGINT) AS rank FROM n)"]
    for r in range(rounds):
        parts.append(f"g{r} AS (SELECT e.dst, CAST(SUM(rank // deg) AS BIGINT) AS got FROM e JOIN d ON e.src = d.src JOIN r{r} ON e.src = r{r}.node GROUP BY e.dst)")
        parts.append(f"r{r + 1} AS (SELECT n.node, CAST(150000000 + (COALESCE(got, 0) * 85) // 100 AS BIGINT) AS rank FROM n LEFT JOIN g{r} ON n.node = g{r}.dst)")
    return f"WITH {', '.join(parts)} SELECT node, rank FROM r{rounds}"


_PS = "SELECT DISTINCT 'p' || l_partkey AS src, 's' || l_suppkey AS dst FROM lineitem"


@query(_rank_sql(f"{_PS} UNION ALL SELECT dst, src FROM ({_PS})", 3))
def pagerank_batch_fixed_point(spark, sf_dir):
    return pagerank_fixed_point(part_supplier_edges(spark, sf_dir), 3)


@query(_rank_sql("""SELECT DISTINCT regexp_extract(url, '^https?://([^/]+)', 1) AS src, UNNEST(regexp_extract_all(html, 'href="([^"]*)"', 1)) AS dst FROM pages""", 3))
def pagerank_pages(spark, sf_dir):
    return pagerank_fixed_point(page_edges(spark, sf_dir), 3)


def grown_graph(spark, edges: int, nodes: int, increments: list[tuple[int, int]]) -> list:
    """A recursive-matrix graph, then for each (new nodes, edges) edges between new nodes and the whole graph."""
    out = [cut(rmat_edges(spark, edges, nodes))]
    for n, (fresh, count) in enumerate(increments, 1):
        node = F.pmod("id", F.lit(fresh)) + nodes  # every new node has an edge; directions in turn
        back = F.pmod(F.floor(F.col("id") / fresh) + F.col("id"), F.lit(2)) == 1
        new = rmat_edges(spark, count, nodes + fresh, seed=6 + n, with_id=True)
        out.append(cut(new.select(F.when(back, F.col("src")).otherwise(node).alias("src"), F.when(back, node).otherwise(F.col("dst")).alias("dst"))))
        nodes += fresh
    return out


#: The reference's largest of four increment sizes (100, 200, 300 and 400 edges), nine times.
RANK_INCREMENTS = [(100, 400)] * 9


def pagerank_gaps(spark, edges: int = 50_000, nodes: int = 5_000, increments=RANK_INCREMENTS, rounds: int = 10) -> list[tuple[int, float, int]]:
    """After the initial graph and each increment: (batch, sum of rank differences from a batch run as a part of all
    rank, nodes that only one of them has)."""
    out, whole = [], None
    q = IncrementalPageRank(spark, rounds=rounds)
    for n, new in enumerate(grown_graph(spark, edges, nodes, list(increments))):
        whole = new if whole is None else whole.unionByName(new)
        ranks = q.step(new)
        full = pagerank(whole, rounds).withColumnRenamed("rank", "full")
        both = full.join(ranks, "node", "full_outer")
        r = both.agg(F.sum(F.abs(F.coalesce("full", F.lit(0.0)) - F.coalesce("rank", F.lit(0.0)))).alias("gap"), F.sum("full").alias("all"), F.count_if(F.col("full").isNull() | F.col("rank").isNull()).alias("lost")).first()
        out.append((n, r["gap"] / r["all"], r["lost"]))
    return out


@query(None)
def pagerank_incremental_gap(spark, sf_dir):
    """The gap of incremental ranks after the initial graph and each of nine increments."""
    return spark.createDataFrame(pagerank_gaps(spark), "batch int, gap double, lost long")


@query(None)
def nmf_events(spark, sf_dir):
    """Users by event types: the squared error after one and after four rounds."""
    entries = cut(table(spark, sf_dir, "events").groupBy(F.col("user_id").alias("i"), F.col("event_type").alias("j")).agg(F.count("*").cast("double").alias("v")))
    return spark.createDataFrame([(r, float(squared_error(entries, *nmf(entries, 2, r)))) for r in (1, 4)], "rounds int, error double")


@query("WITH a AS (SELECT l_orderkey AS x FROM lineitem), b AS (SELECT x * 2 + 1 AS x FROM a WHERE x % 7 <> 3), c AS (SELECT x * 2 + 1 AS x FROM b WHERE x % 7 <> 3), d AS (SELECT x * 2 + 1 AS x FROM c WHERE x % 7 <> 3) SELECT x, COUNT(*) AS n FROM d GROUP BY x")
def repeat_exact_increments(spark, sf_dir):
    """A repetition whose step merges: every batch runs its rounds alone and the results add up."""
    q = ExactRepeat(stream("x").flat_map(where="x % 7 <> 3", x="x * 2 + 1"), "x", 3)
    for b in arrive_by_key(table(spark, sf_dir, "lineitem").select(F.col("l_orderkey").alias("x")), "x", 10):
        q.step(b)
    return q.result.groupBy("x").agg(F.count("*").alias("n"))


@query("SELECT CAST(340000 AS BIGINT) AS points, i AS cid FROM range(4) t(i)")
def repeat_generic_near_keys(spark, sf_dir):
    """The generic loop with points as keys, matched within eps: the state counts every point once."""
    return loop_by_near_keys(spark, 1_000_000, 40_000, 9).select("points", "cid")


def loop_by_near_keys(spark, initial: int, increment: int, increments: int, rounds: int = 4):
    """K-means written for the generic loop: clusters are known by their centres."""
    dims = ["x", "y"]
    kinds = {"s_x": ADD, "s_y": ADD, "c": ADD}

    def partial(centres, batch):
        at = sums(batch, dims, [(x, y) for _, x, y in centres])
        names = F.array(*(F.lit(c) for c, _, _ in centres))
        return at.select(F.element_at(names, F.col("cid") + 1).alias("cid"), *kinds)

    def answer(state):
        return [(r["cid"], r["s_x"] / r["c"], r["s_y"] / r["c"]) for r in state.orderBy("cid").collect()]  # k rows

    place = lambda t: t.select("cid", (F.col("s_x") / F.col("c")).alias("x"), (F.col("s_y") / F.col("c")).alias("y"))
    q = IncrementalRepeat(spark, partial, answer, ["cid"], kinds, [(i, *c) for i, c in enumerate(NEAR)], rounds, start="init", near=(dims, 1.0), place=place)
    whole = square_points(spark, initial + increments * increment)
    for n in range(increments + 1):
        at, upto = (0, initial) if n == 0 else (initial + (n - 1) * increment, initial + n * increment)
        q.step(whole.where((F.col("id") >= at) & (F.col("id") < upto)))
    return q.state.select(F.col("cid").cast("long").alias("cid"), F.col("c").alias("points"))


def _two_states(spark, sf_dir):
    li = table(spark, sf_dir, "lineitem")
    one = lambda c: li.where(c).groupBy("l_suppkey").agg(F.sum(F.expr("CAST(l_quantity AS BIGINT)")).alias("s"), F.max("l_orderkey").alias("hi"), F.count("*").alias(SUPPORT))
    return one("l_orderkey % 3 = 0 AND l_suppkey % 2 = 0"), one("l_orderkey % 3 = 1 AND l_suppkey % 3 = 0")


_X = "SELECT l_suppkey, CAST(SUM(CAST(l_quantity AS BIGINT)) AS BIGINT) AS s, MAX(l_orderkey) AS hi, COUNT(*) AS n FROM lineitem WHERE l_orderkey % 3 = 0 AND l_suppkey % 2 = 0 GROUP BY l_suppkey"
_Y = _X.replace("% 3 = 0 AND l_suppkey % 2 = 0", "% 3 = 1 AND l_suppkey % 3 = 0")
_KINDS = {"s": ADD, "hi": GREATEST}


@query(f"SELECT l_suppkey, CAST(SUM(s) AS BIGINT) AS s, MAX(hi) AS hi FROM ({_X} UNION ALL {_Y}) GROUP BY l_suppkey")
def merge_rows(spark, sf_dir):
    return merge_states(*_two_states(spark, sf_dir), ["l_suppkey"], _KINDS, how="join")


@query(f"SELECT y.l_suppkey, y.s + COALESCE(x.s, 0) AS s, GREATEST(y.hi, COALESCE(x.hi, y.hi)) AS hi FROM ({_Y}) y LEFT JOIN ({_X}) x USING (l_suppkey)")
def diffusion_rows(spark, sf_dir):
    return diffuse(*_two_states(spark, sf_dir), ["l_suppkey"], _KINDS)


@query(f"SELECT l_suppkey, s, n AS support FROM ({_X})")
def diminish_rows(spark, sf_dir):
    """Merging a state in and diminishing by it again changes nothing."""
    x, y = _two_states(spark, sf_dir)
    kinds = {"s": ADD, SUPPORT: ADD}
    return diminish(merge_states(x, y, ["l_suppkey"], kinds), y, ["l_suppkey"], kinds).withColumnRenamed(SUPPORT, "support")


@query("SELECT COALESCE(o, l) AS k, COALESCE(no, 0) AS n_left, COALESCE(nl, 0) AS n_right FROM (SELECT o_orderkey AS o, COUNT(*) AS no FROM orders GROUP BY o) FULL JOIN (SELECT l_orderkey AS l, COUNT(*) AS nl FROM lineitem GROUP BY l) ON o = l")
def cogroup_sizes(spark, sf_dir):
    left = table(spark, sf_dir, "orders").select(F.col("o_orderkey").alias("k"), "o_custkey")
    right = table(spark, sf_dir, "lineitem").select(F.col("l_orderkey").alias("k"), "l_partkey")
    return co_group(left, right, ["k"]).select("k", F.size("left_bag").cast("long").alias("n_left"), F.size("right_bag").cast("long").alias("n_right"))


# ------------------------------------------------------------------ streams

_EVENT_COLUMNS = ["event_id", "user_id", "event_type", "cents"]
_AVG_EVENTS = "SELECT user_id, CAST(SUM(CAST(ROUND(value * 100) AS BIGINT)) AS DOUBLE) / COUNT(*) AS avg_cents, COUNT(*) AS n FROM events {} GROUP BY user_id"


def _events(spark, sf_dir):
    return table(spark, sf_dir, "events").withColumn("cents", F.round(F.col("value") * 100).cast("long")).select(*_EVENT_COLUMNS)


def _event_files(spark, sf_dir, n: int = 3):
    e = _events(spark, sf_dir)
    return as_files(spark, [e.where(F.pmod("event_id", F.lit(n)) == i) for i in range(n)], _EVENT_COLUMNS), e.schema


@query(_AVG_EVENTS.format(""))
def stream_dir_groupby(spark, sf_dir):
    """A directory as a stream; the incremental query runs in every micro-batch."""
    folder, schema = _event_files(spark, sf_dir)
    q = IncrementalQuery(spark, stream("events").group_by("user_id").agg(avg_cents=m.avg("cents"), n=m.count()), {"events": _EVENT_COLUMNS}, backend="layered")
    StreamRunner(q).run({"events": dir_stream(spark, folder, schema)}, f"{checkpoint_folder(spark)}/stream-{uuid.uuid4().hex}")
    return q.answer()


@query(_AVG_EVENTS.format("WHERE event_id % 10 <> 3"))
def stream_insert_delete_dirs(spark, sf_dir):
    """Two monitored directories, one of inserts and one of deletions."""
    folder, schema = _event_files(spark, sf_dir, 2)
    gone = as_files(spark, [_events(spark, sf_dir).where("event_id % 10 = 3")], _EVENT_COLUMNS)
    q = IncrementalQuery(spark, stream("events").group_by("user_id").agg(avg_cents=m.avg("cents"), n=m.count()), {"events": _EVENT_COLUMNS}, backend="layered", deletes=True)
    both = dir_stream(spark, folder, schema, sign=1).unionByName(dir_stream(spark, gone, schema, sign=-1))
    StreamRunner(q).run({"events": both}, f"{checkpoint_folder(spark)}/stream-{uuid.uuid4().hex}")
    return q.answer()


@query("SELECT event_type, COUNT(*) AS n, CAST(SUM(CAST(ROUND(value * 100) AS BIGINT)) AS BIGINT) AS cents FROM events GROUP BY event_type")
def native_streaming_baseline(spark, sf_dir):
    folder, schema = _event_files(spark, sf_dir)
    return native_aggregate(spark, dir_stream(spark, folder, schema), ["event_type"], [F.count("*").alias("n"), F.sum("cents").alias("cents")])


@query("SELECT DISTINCT user_id, event_type FROM events")
def stream_dedup_events(spark, sf_dir):
    folder, schema = _event_files(spark, sf_dir)
    return deduplicated(spark, dir_stream(spark, folder, schema).select("user_id", "event_type"), ["user_id", "event_type"])


@query("SELECT user_id AS key, CAST(SUM(CAST(ROUND(value * 100) AS BIGINT)) AS BIGINT) AS s, COUNT(*) AS n FROM events GROUP BY user_id")
def kv_state_user_avg(spark, sf_dir):
    folder, schema = _event_files(spark, sf_dir, 2)
    return keyed_average(spark, dir_stream(spark, folder, schema), "user_id", "cents")


@query("SELECT epoch_us(date_trunc('hour', ts)) AS start, COUNT(*) AS n FROM events GROUP BY start")
def late_events_merged(spark, sf_dir):
    """Hourly windows with events in any order: exact mode keeps all windows, so nothing is late."""
    e = table(spark, sf_dir, "events").select("event_id", F.unix_micros(F.date_trunc("hour", F.col("ts").cast("timestamp"))).alias("start"))
    q = IncrementalQuery(spark, stream("events").group_by("start").agg(n=m.count()), {"events": e.columns})
    for i in range(7):
        q.step({"events": e.where(F.pmod("event_id", F.lit(7)) == i)})
    out = cut(q.answer())
    q.close()
    return out


@query(_AVG_EVENTS.format(""))
def stream_restart_groupby(spark, sf_dir):
    """The stream stops after its first batches; a new process goes on with the same folders, and a batch that had
    been folded is delivered again."""
    folder, schema = _event_files(spark, sf_dir, 4)
    home = f"{checkpoint_folder(spark)}/restart-{uuid.uuid4().hex}"
    term = stream("events").group_by("user_id").agg(avg_cents=m.avg("cents"), n=m.count())
    make = lambda: IncrementalQuery(spark, term, {"events": _EVENT_COLUMNS}, folder=f"{home}/state")
    q = make()
    first = _events(spark, sf_dir).where(F.pmod("event_id", F.lit(4)) == 0)  # the first file
    q.step({"events": first}, version=0)  # folded, but the stream's own progress is lost with the process
    q = make()
    StreamRunner(q).run({"events": dir_stream(spark, folder, schema)}, f"{home}/offsets")
    return make().answer()


@query("SELECT o_custkey, CAST(SUM(CAST(l_quantity AS BIGINT)) AS BIGINT) AS qty, COUNT(*) AS n FROM orders JOIN lineitem ON o_orderkey = l_orderkey GROUP BY o_custkey")
def stream_restart_join(spark, sf_dir):
    """Two streams, two cells: the process ends after one cell has taken a batch and the other has not."""
    o = table(spark, sf_dir, "orders").select("o_orderkey", "o_custkey")
    li = table(spark, sf_dir, "lineitem").select("l_orderkey", F.expr("CAST(l_quantity AS BIGINT)").alias("qty"))
    term = stream("orders").join(stream("lineitem"), {"o_orderkey": "l_orderkey"}).group_by("o_custkey").agg(qty=m.sum_("qty"), n=m.count())
    home = f"{checkpoint_folder(spark)}/restart-{uuid.uuid4().hex}"
    make = lambda: IncrementalQuery(spark, term, {"orders": o.columns, "lineitem": li.columns}, folder=home)
    batches = list(zip(arrive_by_key(o, "o_custkey", 30), arrive_by_key(li, "l_orderkey", 30), strict=True))[:10]
    q = make()
    for version, (a, b) in enumerate(batches):
        if version == 3:  # the first cell folds, then the process dies
            tables = q._signed({"orders": a, "lineitem": b}, None)
            q.cells[0].step(q.plan.cells[0].partial(tables), version)
            q = make()
        q.step({"orders": a, "lineitem": b}, version=version)
        q.step({"orders": a, "lineitem": b}, version=version)  # delivered twice
    return make().answer()


@query(None)
def sliding_distinct_users(spark, sf_dir):
    """The approximate baseline beside exact counts of users in sliding days."""
    e = table(spark, sf_dir, "events").withColumn("ts", F.col("ts").cast("timestamp"))
    exact = e.groupBy(F.window("ts", "1 day", "6 hours")["start"].alias("start")).agg(F.count_distinct("user_id").alias("exact"))
    return sliding_distinct(e, "ts", "user_id", "1 day", "6 hours").join(exact, "start").select(F.unix_micros("start").alias("start"), "distinct", "exact")


@query(
    """WITH l AS (SELECT l_partkey AS k, l_linenumber % 2 AS odd, CASE WHEN r < 100 THEN 0 ELSE 1 + (r - 100) // 10 END AS n
        FROM (SELECT *, (l_orderkey % 190 + 190) % 190 AS r FROM lineitem)),
      a AS (SELECT k, n, COUNT(*) AS c FROM l WHERE odd = 0 GROUP BY k, n),
      b AS (SELECT k, n, COUNT(*) AS c FROM l WHERE odd <> 0 GROUP BY k, n)
    SELECT CAST(COALESCE(SUM(a.c * b.c) FILTER (a.n = b.n), 0) AS BIGINT) AS batchwise, CAST(COALESCE(SUM(a.c * b.c), 0) AS BIGINT) AS exact
    FROM a JOIN b ON a.k = b.k"""
)
def join_mn_random_pairs(spark, sf_dir):
    """A join with several partners on both sides, as the reference's of random pairs: lines of even and of odd number that
    have one part, arriving by order in an initial batch and nine of a tenth of it.  Pairs that merging batch by batch
    finds, beside all pairs."""
    from deltafold.workloads.experiments import count_pairs

    r = "pmod(l_orderkey, 190)"
    # a line without an order has no batch
    lines = table(spark, sf_dir, "lineitem").selectExpr("l_partkey AS k", f"CASE WHEN l_orderkey IS NOT NULL THEN IF({r} < 100, 0, 1 + ({r} - 100) div 10) END AS n", "l_linenumber % 2 AS odd")
    return count_pairs(lines.where("odd = 0"), lines.where("odd <> 0"))
