"""The reference's own experiments and methods on the given tables: state after a first batch and nine
increments must give what the plain query gives on all rows."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from deltafold.functions import monoids as m
from deltafold.plans.algebra import static, stream
from deltafold.plans.incremental import IncrementalQuery, run_in_batches, window_only
from deltafold.session import cut
from deltafold.sources.tables import arrive_by_key, arrive_by_time, table

QTY = "CAST(l_quantity AS BIGINT)"
CENTS = "CAST(ROUND(l_extendedprice * 100) AS BIGINT)"
HUNDREDTHS = "CAST(ROUND(value * 100) AS BIGINT)"


def _run(spark: SparkSession, query, batches: dict[str, list[DataFrame]], invariant: dict[str, DataFrame] | None = None, deletes: list[dict[str, DataFrame]] | None = None, **options) -> DataFrame:
    """Folds all batches (then all deletions) and returns the answer, written once."""
    schemas = {n: b[0].columns for n, b in batches.items()} | {n: d.columns for n, d in (invariant or {}).items()}
    q = IncrementalQuery(spark, query, schemas, invariant, deletes=bool(deletes), **options)
    for i in range(max(map(len, batches.values()))):
        q.step({n: b[i] for n, b in batches.items()})
    for gone in deletes or []:
        q.step({n: b[0].limit(0) for n, b in batches.items()}, gone)
    out = cut(q.answer())
    q.close()
    return out


def _lines(spark, sf_dir, key="l_orderkey", width=2):
    return {"lineitem": arrive_by_key(table(spark, sf_dir, "lineitem"), key, width)}


def _orders_lines(spark, sf_dir, late: bool = False, width: int = 20):
    o, li = table(spark, sf_dir, "orders"), table(spark, sf_dir, "lineitem")
    if late:
        return {"orders": arrive_by_time(o, "o_orderdate"), "lineitem": arrive_by_time(li, "l_shipdate")}
    return {"orders": arrive_by_key(o, "o_orderkey", width), "lineitem": arrive_by_key(li, "l_orderkey", width)}


AVG_BY_PART = stream("lineitem").group_by("l_partkey").agg(avg_qty=m.avg(QTY), n=m.count())


def incr_groupby_avg_part(spark, sf_dir):
    return _run(spark, AVG_BY_PART, _lines(spark, sf_dir))


def incr_groupby_avg_user(spark, sf_dir):
    q = stream("events").group_by("user_id").agg(avg_value=m.avg(HUNDREDTHS), n=m.count())
    return _run(spark, q, {"events": arrive_by_key(table(spark, sf_dir, "events"), "event_id")})


def incr_groupby_sum_count_min_max(spark, sf_dir):
    q = stream("lineitem").group_by("l_suppkey").agg(s=m.sum_(QTY), n=m.count(), lo=m.min_(CENTS), hi=m.max_(CENTS))
    return _run(spark, q, _lines(spark, sf_dir))


def _join_avg(mode=None):
    return stream("orders").join(stream("lineitem"), {"o_orderkey": "l_orderkey"}, mode=mode).group_by("o_custkey").agg(avg_cents=m.avg(CENTS), n=m.count())


def incr_join_groupby_coarrival(spark, sf_dir):
    return _run(spark, _join_avg("co_arrival"), _orders_lines(spark, sf_dir))


def incr_join_groupby_late(spark, sf_dir):
    return _run(spark, _join_avg(), _orders_lines(spark, sf_dir, late=True))


def incr_join_groupby_delta(spark, sf_dir):
    """Retained sides, and a third cell that each batch's three joins maintain."""
    from deltafold.operators.delta_join import DeltaJoin

    batches = _orders_lines(spark, sf_dir)
    left = lambda df: df.select(F.col("o_orderkey").alias("j"), F.col("o_custkey").alias("k"))
    right = lambda df: df.select(F.col("l_orderkey").alias("j"), F.expr(CENTS).alias("v"))
    q = DeltaJoin(spark)
    for o, li in zip(batches["orders"], batches["lineitem"], strict=True):
        q.step(left(o), right(li))
    out = cut(q.answer().select(F.col("k").alias("o_custkey"), (F.col("s").cast("double") / F.col("n")).alias("avg_cents"), "n"))
    q.close()
    return out


def incr_join_static_dim(spark, sf_dir):
    q = stream("lineitem").join(static("part"), {"l_partkey": "p_partkey"}).group_by("p_brand").agg(avg_qty=m.avg(QTY), n=m.count())
    return _run(spark, q, _lines(spark, sf_dir), {"part": table(spark, sf_dir, "part")})


def incr_join_mn(spark, sf_dir):
    """Many-to-many: pairs of a line in one stream and an order line of another with the same part."""
    lines = table(spark, sf_dir, "lineitem")
    a = lines.where("l_linenumber % 2 = 0").select(F.col("l_partkey").alias("a_part"), F.col("l_suppkey").alias("a_supp"), F.col("l_orderkey").alias("a_key"))
    b = lines.where("l_linenumber % 2 = 1").select(F.col("l_partkey").alias("b_part"), F.expr(QTY).alias("b_qty"), F.col("l_orderkey").alias("b_key"))
    q = stream("a").join(stream("b"), {"a_part": "b_part"}).group_by("a_supp").agg(pairs=m.count(), qty=m.sum_("b_qty"))
    return _run(spark, q, {"a": arrive_by_key(a, "a_key", 10), "b": arrive_by_key(b, "b_key", 10)})


def incr_join_lineage_state(spark, sf_dir):
    """The state itself: sums by group key and join key."""
    batches = _orders_lines(spark, sf_dir)
    q = run_in_batches(spark, _join_avg("co_arrival"), [dict(zip(batches, x, strict=True)) for x in zip(*batches.values(), strict=True)], {"orders": batches["orders"][0].columns, "lineitem": batches["lineitem"][0].columns})
    state = q.cells[0].backend.read()
    out = cut(state.select(F.col("__k0").alias("o_custkey"), F.col("__k1").alias("o_orderkey"), F.col("p0_s").alias("s"), F.col("p0_n").alias("n")))
    q.close()
    return out


def incr_join_minimal_lineage(spark, sf_dir):
    return _run(spark, _join_avg("co_arrival"), _orders_lines(spark, sf_dir), lineage="minimal")


def incr_global_reduce(spark, sf_dir):
    q = stream("lineitem").agg(cents=m.sum_(CENTS), n=m.count(), hi=m.max_(CENTS))
    return _run(spark, q, _lines(spark, sf_dir))


def incr_append_filter(spark, sf_dir):
    q = stream("orders").flat_map(where="o_orderstatus = 'F' AND o_totalprice > 100000", o_orderkey="o_orderkey", cents="CAST(ROUND(o_totalprice * 100) AS BIGINT)")
    return _run(spark, q, {"orders": arrive_by_key(table(spark, sf_dir, "orders"), "o_orderkey")})


def incr_count_distinct(spark, sf_dir):
    q = stream("lineitem").group_by("l_partkey").agg(suppliers=m.count_distinct("l_suppkey"))
    return _run(spark, q, _lines(spark, sf_dir))


def _nested(zero: bool):
    sums = stream("lineitem").group_by("l_orderkey").agg(total=m.sum_(CENTS))
    price = "CAST(ROUND(o_totalprice * 100) AS BIGINT)"
    condition = f"{price} > coalesce(total, 0)" if zero else f"{price} > total"
    return stream("orders").select(o_orderkey="o_orderkey", o_totalprice="o_totalprice").join(sums, {"o_orderkey": "l_orderkey"}, kind="left").flat_map(where=condition, o_orderkey="o_orderkey")


def incr_nested_correlated(spark, sf_dir):
    return _run(spark, _nested(True), _orders_lines(spark, sf_dir, late=True))


def incr_nested_correlated_relational(spark, sf_dir):
    """The baseline's form: group the inner side, outer join, filter with SQL's nulls."""
    return _run(spark, _nested(False), _orders_lines(spark, sf_dir, late=True))


def incr_two_level_group(spark, sf_dir):
    """Customers by their number of orders: the outer key changes as rows arrive, so it stays in the answer."""
    q = stream("orders").group_by("o_custkey").agg(n_orders=m.count()).group_by("n_orders").agg(customers=m.count())
    return _run(spark, q, {"orders": arrive_by_key(table(spark, sf_dir, "orders"), "o_orderkey")})


def incr_avg_of_sums(spark, sf_dir):
    sums = stream("orders").group_by("o_custkey").agg(spent=m.sum_("CAST(ROUND(o_totalprice * 100) AS BIGINT)"))
    q = sums.join(static("customer"), {"o_custkey": "c_custkey"}).group_by("c_mktsegment").agg(avg_spent=m.avg("spent"), n=m.count())
    return _run(spark, q, {"orders": arrive_by_key(table(spark, sf_dir, "orders"), "o_orderkey")}, {"customer": table(spark, sf_dir, "customer")})


def incr_order_by_topk(spark, sf_dir):
    q = stream("orders").group_by("o_custkey").agg(cents=m.sum_("CAST(ROUND(o_totalprice * 100) AS BIGINT)")).order_by("cents desc", "o_custkey", limit=20)
    return _run(spark, q, {"orders": arrive_by_key(table(spark, sf_dir, "orders"), "o_orderkey")})


def incr_three_way_join(spark, sf_dir):
    """Revenue by nation: two streams, and two invariant tables that are joined in the answer."""
    q = _join_avg().join(static("customer"), {"o_custkey": "c_custkey"}).join(static("nation"), {"c_nationkey": "n_nationkey"}).group_by("n_name").agg(customers=m.count(), line_count=m.sum_("n"))
    return _run(spark, q, _orders_lines(spark, sf_dir, late=True), {t: table(spark, sf_dir, t) for t in ("customer", "nation")})


def incr_outer_join(spark, sf_dir):
    lines = stream("lineitem").group_by("l_orderkey").agg(n=m.count())
    q = stream("orders").select(o_orderkey="o_orderkey", o_orderstatus="o_orderstatus").join(lines, {"o_orderkey": "l_orderkey"}, kind="left").group_by("o_orderstatus").agg(orders=m.count(), empty=m.count_if("n IS NULL"), line_count=m.sum_("n", empty_zero=True))
    return _run(spark, q, _orders_lines(spark, sf_dir, late=True))


def _gone(batches, rules: dict[str, str]) -> list[dict[str, DataFrame]]:
    whole = {}
    for n, condition in rules.items():
        out = batches[n][0]
        for b in batches[n][1:]:
            out = out.unionByName(b)
        whole[n] = out.where(condition)
    return [whole]


def delete_groupby_avg(spark, sf_dir):
    batches = _lines(spark, sf_dir)
    return _run(spark, AVG_BY_PART, batches, deletes=_gone(batches, {"lineitem": "l_orderkey % 10 = 3"}))


def delete_join_groupby(spark, sf_dir):
    batches = _orders_lines(spark, sf_dir)
    return _run(spark, _join_avg(), batches, deletes=_gone(batches, {"orders": "o_orderkey % 10 = 3", "lineitem": "l_orderkey % 10 = 3"}))


def delete_partial_lines(spark, sf_dir):
    """Only one side of matches goes."""
    batches = _orders_lines(spark, sf_dir)
    return _run(spark, _join_avg(), batches, deletes=_gone(batches, {"lineitem": "l_linenumber = 1"}))


def delete_min_max(spark, sf_dir):
    batches = _lines(spark, sf_dir)
    q = stream("lineitem").group_by("l_suppkey").agg(lo=m.min_(QTY), hi=m.max_(QTY))
    return _run(spark, q, batches, deletes=_gone(batches, {"lineitem": "l_orderkey % 10 = 3 OR l_quantity = 50 OR l_quantity = 1"}))


def delete_count_distinct(spark, sf_dir):
    batches = _lines(spark, sf_dir)
    q = stream("lineitem").group_by("l_partkey").agg(suppliers=m.count_distinct("l_suppkey"))
    return _run(spark, q, batches, deletes=_gone(batches, {"lineitem": "l_orderkey % 10 = 3"}))


def delete_all_is_empty(spark, sf_dir):
    batches = _lines(spark, sf_dir)
    return _run(spark, AVG_BY_PART, batches, deletes=_gone(batches, {"lineitem": "true"}))


def signed_stream_sum_zero(spark, sf_dir):
    """Sums that cancel are no reason to drop a group: its support counts rows, not values."""
    lines = table(spark, sf_dir, "lineitem").select("l_orderkey", "l_linenumber", F.expr(f"CASE WHEN l_linenumber % 2 = 0 THEN {QTY} ELSE -{QTY} END").alias("x"))
    both = lines.unionByName(lines.select("l_orderkey", "l_linenumber", (-F.col("x")).alias("x")))
    q = stream("signed").group_by("l_linenumber").agg(s=m.sum_("x"), n=m.count())
    return _run(spark, q, {"signed": arrive_by_key(both, "l_orderkey")})


def window_only_batches(spark, sf_dir):
    q = stream("lineitem").group_by("l_linestatus").agg(s=m.sum_(QTY), n=m.count())
    return window_only(q, [{"lineitem": b} for b in arrive_by_key(table(spark, sf_dir, "lineitem"), "l_orderkey")])


def retain_all_baseline(spark, sf_dir):
    return _run(spark, AVG_BY_PART, {"lineitem": [b.select("l_partkey", "l_quantity") for b in _lines(spark, sf_dir)["lineitem"]]}, split_policy="retain_all")


def batches_of_memory_size(spark, sf_dir):
    lines = table(spark, sf_dir, "lineitem")
    return _run(spark, AVG_BY_PART, {"lineitem": [lines.where(F.pmod("l_orderkey", F.lit(16)) == i) for i in range(16)]}, backend="layered")


def sorted_bucket_backend(spark, sf_dir):
    return _run(spark, AVG_BY_PART, {"lineitem": _lines(spark, sf_dir)["lineitem"][:10]}, backend="bucketed")


def full_outer_merge(spark, sf_dir):
    """The merge as a full outer join on lineage (an ablation of the default)."""
    return _run(spark, AVG_BY_PART, _lines(spark, sf_dir), how="join")


def aggregate_catalogue(spark, sf_dir):
    """Further aggregates, each with its own state, by order priority."""
    q = stream("orders").flat_map(p="o_orderpriority", x="CAST(ROUND(o_totalprice) AS BIGINT)", k="o_orderkey", c="o_custkey", st="o_orderstatus").group_by("p").agg(
        var=m.variance("x"), cov=m.covariance("x", "k", "covar_pop"), distinct_c=m.count_distinct("c"), sum_distinct_c=m.sum_distinct("c"), med=m.percentile("x", 0.5), mode_c=m.mode("c"),
        any_open=m.some("st = 'O'"), all_pos=m.every("x > 0"), xor_k=m.bit_xor("k"), or_k=m.bits("k", "or"), newest=m.by_order("c", "k"), ratio=m.Agg(m.sum_("x")) / m.Agg(m.count()))
    return _run(spark, q, {"orders": arrive_by_key(table(spark, sf_dir, "orders"), "o_orderkey")})


def _from_sql(spark, sf_dir, sql, streams, width=20):
    from deltafold.plans.sqlfront import from_sql

    tables = {n: table(spark, sf_dir, n) for n in ("orders", "lineitem", "customer", "part")}
    q = from_sql(spark, sql, list(streams), {n: t.columns for n, t in tables.items()})
    return _run(spark, q, {n: arrive_by_key(tables[n], key, width) for n, key in streams.items()}, {n: t for n, t in tables.items() if n not in streams})


SQL_AVG = "SELECT l_partkey, avg(CAST(l_quantity AS BIGINT)) AS avg_qty, count(*) AS n FROM lineitem WHERE l_quantity > 5 GROUP BY l_partkey"
SQL_JOIN = "SELECT o.o_custkey, sum(CAST(l.l_quantity AS BIGINT)) AS qty, count(*) AS n FROM orders o JOIN lineitem l ON o.o_orderkey = l.l_orderkey GROUP BY o.o_custkey"
SQL_NESTED = "SELECT c_mktsegment, count(*) AS customers, sum(n) AS order_count FROM (SELECT o_custkey, count(*) AS n FROM orders GROUP BY o_custkey) x JOIN customer c ON x.o_custkey = c.c_custkey GROUP BY c_mktsegment"


def sql_groupby_avg(spark, sf_dir):
    """The same text runs as a batch in DuckDB and incrementally here."""
    return _from_sql(spark, sf_dir, SQL_AVG, {"lineitem": "l_orderkey"})


def sql_join_groupby(spark, sf_dir):
    return _from_sql(spark, sf_dir, SQL_JOIN, {"orders": "o_orderkey", "lineitem": "l_partkey"})


def sql_derived_table(spark, sf_dir):
    return _from_sql(spark, sf_dir, SQL_NESTED, {"orders": "o_orderkey"})


_AVG_SQL = "SELECT l_partkey, CAST(SUM(CAST(l_quantity AS BIGINT)) AS DOUBLE) / COUNT(*) AS avg_qty, COUNT(*) AS n FROM lineitem {} GROUP BY l_partkey"
_CENTS_SQL = "CAST(ROUND(l_extendedprice * 100) AS BIGINT)"
_JOIN_SQL = f"SELECT o_custkey, CAST(SUM({_CENTS_SQL}) AS DOUBLE) / COUNT(*) AS avg_cents, COUNT(*) AS n FROM orders JOIN lineitem ON o_orderkey = l_orderkey {{}} GROUP BY o_custkey"
_PRICE_SQL = "CAST(ROUND(o_totalprice * 100) AS BIGINT)"

QUERIES = {f.__name__: f for f in (
    incr_groupby_avg_part, incr_groupby_avg_user, incr_groupby_sum_count_min_max, incr_join_groupby_coarrival, incr_join_groupby_late, incr_join_groupby_delta, incr_join_static_dim, incr_join_mn,
    incr_join_lineage_state, incr_join_minimal_lineage, incr_global_reduce, incr_append_filter, incr_count_distinct, incr_nested_correlated, incr_nested_correlated_relational, incr_two_level_group,
    incr_avg_of_sums, incr_order_by_topk, incr_three_way_join, incr_outer_join, delete_groupby_avg, delete_join_groupby, delete_partial_lines, delete_min_max, delete_count_distinct, delete_all_is_empty,
    signed_stream_sum_zero, window_only_batches, retain_all_baseline, batches_of_memory_size, sorted_bucket_backend, full_outer_merge, aggregate_catalogue, sql_groupby_avg, sql_join_groupby, sql_derived_table,
)}

ORACLE_SQL = {
    "sql_groupby_avg": SQL_AVG,
    "sql_join_groupby": SQL_JOIN.replace("sum(CAST(l.l_quantity AS BIGINT))", "CAST(sum(CAST(l.l_quantity AS BIGINT)) AS BIGINT)"),
    "sql_derived_table": SQL_NESTED.replace("sum(n)", "CAST(sum(n) AS BIGINT)"),
    "incr_groupby_avg_part": _AVG_SQL.format(""),
    "incr_groupby_avg_user": "SELECT user_id, CAST(SUM(CAST(ROUND(value * 100) AS BIGINT)) AS DOUBLE) / COUNT(*) AS avg_value, COUNT(*) AS n FROM events GROUP BY user_id",
    "incr_groupby_sum_count_min_max": f"SELECT l_suppkey, CAST(SUM(CAST(l_quantity AS BIGINT)) AS BIGINT) AS s, COUNT(*) AS n, MIN({_CENTS_SQL}) AS lo, MAX({_CENTS_SQL}) AS hi FROM lineitem GROUP BY l_suppkey",
    "incr_join_groupby_coarrival": _JOIN_SQL.format(""),
    "incr_join_groupby_late": _JOIN_SQL.format(""),
    "incr_join_groupby_delta": _JOIN_SQL.format(""),
    "incr_join_minimal_lineage": _JOIN_SQL.format(""),
    "incr_join_static_dim": "SELECT p_brand, CAST(SUM(CAST(l_quantity AS BIGINT)) AS DOUBLE) / COUNT(*) AS avg_qty, COUNT(*) AS n FROM lineitem JOIN part ON l_partkey = p_partkey GROUP BY p_brand",
    "incr_join_mn": "SELECT a.l_suppkey AS a_supp, COUNT(*) AS pairs, CAST(SUM(CAST(b.l_quantity AS BIGINT)) AS BIGINT) AS qty FROM lineitem a JOIN lineitem b ON a.l_partkey = b.l_partkey WHERE a.l_linenumber % 2 = 0 AND b.l_linenumber % 2 = 1 GROUP BY a.l_suppkey",
    "incr_join_lineage_state": f"SELECT o_custkey, o_orderkey, CAST(SUM({_CENTS_SQL}) AS BIGINT) AS s, COUNT(*) AS n FROM orders JOIN lineitem ON o_orderkey = l_orderkey GROUP BY ALL",
    "incr_global_reduce": f"SELECT CAST(SUM({_CENTS_SQL}) AS BIGINT) AS cents, COUNT(*) AS n, MAX({_CENTS_SQL}) AS hi FROM lineitem",
    "incr_append_filter": f"SELECT o_orderkey, {_PRICE_SQL} AS cents FROM orders WHERE o_orderstatus = 'F' AND o_totalprice > 100000",
    "incr_count_distinct": "SELECT l_partkey, COUNT(DISTINCT l_suppkey) AS suppliers FROM lineitem GROUP BY l_partkey",
    "incr_nested_correlated": f"SELECT o_orderkey FROM orders WHERE {_PRICE_SQL} > (SELECT COALESCE(SUM({_CENTS_SQL}), 0) FROM lineitem WHERE l_orderkey = o_orderkey)",
    "incr_nested_correlated_relational": f"SELECT o_orderkey FROM orders WHERE {_PRICE_SQL} > (SELECT SUM({_CENTS_SQL}) FROM lineitem WHERE l_orderkey = o_orderkey)",
    "incr_two_level_group": "SELECT n_orders, COUNT(*) AS customers FROM (SELECT o_custkey, COUNT(*) AS n_orders FROM orders GROUP BY o_custkey) GROUP BY n_orders",
    "incr_avg_of_sums": f"SELECT c_mktsegment, CAST(SUM(spent) AS DOUBLE) / COUNT(*) AS avg_spent, COUNT(*) AS n FROM (SELECT o_custkey, CAST(SUM({_PRICE_SQL}) AS BIGINT) AS spent FROM orders GROUP BY o_custkey) JOIN customer ON o_custkey = c_custkey GROUP BY c_mktsegment",
    "incr_order_by_topk": f"SELECT o_custkey, CAST(SUM({_PRICE_SQL}) AS BIGINT) AS cents FROM orders GROUP BY o_custkey ORDER BY cents DESC, o_custkey LIMIT 20",
    "incr_three_way_join": "SELECT n_name, COUNT(*) AS customers, CAST(SUM(n) AS BIGINT) AS line_count FROM (SELECT o_custkey, COUNT(*) AS n FROM orders JOIN lineitem ON o_orderkey = l_orderkey GROUP BY o_custkey) JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey GROUP BY n_name",
    "incr_outer_join": "SELECT o_orderstatus, COUNT(*) AS orders, COUNT(*) FILTER (n IS NULL) AS empty, CAST(SUM(COALESCE(n, 0)) AS BIGINT) AS line_count FROM orders LEFT JOIN (SELECT l_orderkey, COUNT(*) AS n FROM lineitem GROUP BY l_orderkey) ON o_orderkey = l_orderkey GROUP BY o_orderstatus",
    "delete_groupby_avg": _AVG_SQL.format("WHERE l_orderkey % 10 <> 3"),
    "delete_join_groupby": _JOIN_SQL.format("WHERE o_orderkey % 10 <> 3"),
    "delete_partial_lines": _JOIN_SQL.format("WHERE l_linenumber <> 1"),
    "delete_min_max": "SELECT l_suppkey, MIN(CAST(l_quantity AS BIGINT)) AS lo, MAX(CAST(l_quantity AS BIGINT)) AS hi FROM lineitem WHERE NOT (l_orderkey % 10 = 3 OR l_quantity = 50 OR l_quantity = 1) GROUP BY l_suppkey",
    "delete_count_distinct": "SELECT l_partkey, COUNT(DISTINCT l_suppkey) AS suppliers FROM lineitem WHERE l_orderkey % 10 <> 3 GROUP BY l_partkey",
    "delete_all_is_empty": _AVG_SQL.format("WHERE false"),
    "signed_stream_sum_zero": "SELECT l_linenumber, CAST(0 AS BIGINT) AS s, 2 * COUNT(*) AS n FROM lineitem GROUP BY l_linenumber",
    "window_only_batches": "SELECT l_linestatus, CAST(SUM(CAST(l_quantity AS BIGINT)) AS BIGINT) AS s, COUNT(*) AS n, CASE WHEN l_orderkey % 118 < 100 THEN CAST(0 AS BIGINT) ELSE CAST(1 + (l_orderkey % 118 - 100) // 2 AS BIGINT) END AS batch FROM lineitem GROUP BY ALL",
    "retain_all_baseline": _AVG_SQL.format(""),
    "batches_of_memory_size": _AVG_SQL.format(""),
    "sorted_bucket_backend": _AVG_SQL.format(""),
    "full_outer_merge": _AVG_SQL.format(""),
    "aggregate_catalogue": """WITH o AS (SELECT o_orderpriority AS p, CAST(ROUND(o_totalprice) AS BIGINT) AS x, o_orderkey AS k, o_custkey AS c, o_orderstatus AS st FROM orders),
      g AS (SELECT p, CAST(COUNT(*) AS DOUBLE) AS n, CAST(SUM(CAST(x AS HUGEINT)) AS DOUBLE) AS sx, CAST(SUM(CAST(x AS HUGEINT) * x) AS DOUBLE) AS sxx, CAST(SUM(CAST(k AS HUGEINT)) AS DOUBLE) AS sk, CAST(SUM(CAST(x AS HUGEINT) * k) AS DOUBLE) AS sxk FROM o GROUP BY p),
      mo AS (SELECT p, c FROM (SELECT p, c, ROW_NUMBER() OVER (PARTITION BY p ORDER BY COUNT(*) DESC, c) AS r FROM o GROUP BY p, c) WHERE r = 1)
      SELECT o.p, (ANY_VALUE(sxx) - ANY_VALUE(sx) * ANY_VALUE(sx) / ANY_VALUE(n)) / (ANY_VALUE(n) - 1) AS var, (ANY_VALUE(sxk) - ANY_VALUE(sx) * ANY_VALUE(sk) / ANY_VALUE(n)) / ANY_VALUE(n) AS cov,
        COUNT(DISTINCT o.c) AS distinct_c, CAST(SUM(DISTINCT o.c) AS BIGINT) AS sum_distinct_c, CAST(QUANTILE_DISC(x, 0.5) AS DOUBLE) AS med, ANY_VALUE(mo.c) AS mode_c,
        BOOL_OR(st = 'O') AS any_open, BOOL_AND(x > 0) AS all_pos, BIT_XOR(k) AS xor_k, BIT_OR(k) AS or_k, ARG_MAX(o.c, k) AS newest, CAST(SUM(x) AS DOUBLE) / COUNT(*) AS ratio
      FROM o JOIN g ON o.p = g.p JOIN mo ON o.p = mo.p GROUP BY o.p""",
}
