"""Queries of the engine on the given tables, with DuckDB's SQL for those that SQL can express."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from . import oracles as Q
from .functions import decompose as D
from .operators import accumulator as A
from .operators import baselines as B
from .operators import external as X
from .operators import joins as J
from .operators import mapreduce as M
from .operators import tree as T
from .operators import windows as Wi
from .plans import metrics as C
from .sources import io
from .sources import workloads as Wl
from .oracles import DIGITS
from .streaming import sums as S

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
ORACLES: dict[str, str] = {}

#: Bits below the point that make every value of a column whole (fixed values, from the columns' ranges).
SCALE = {"l_extendedprice": 43, "l_tax": 59, "l_discount": 59, "l_quantity": 52, "o_totalprice": 43, "c_acctbal": 60, "s_acctbal": 60, "p_retailprice": 43, "value": 59}


def exact_sql(x: str, k: int, extra: str = "") -> str:
    """Exact sum in DuckDB: whole numbers in HUGEINT, text, double, scaled back."""
    return f"(CAST(CAST(SUM(CAST(({x}) * pow(2, {k}) AS HUGEINT)){extra} AS VARCHAR) AS DOUBLE) / pow(2, {k}))"


def query(name: str, sql: str | None = None):
    def put(f):
        QUERIES[name] = f
        if sql:
            ORACLES[name] = sql
        return f

    return put


def simple(name: str, table: str, col: str, run) -> None:
    query(name, f"SELECT {exact_sql(col, SCALE[col])} AS value FROM {table}")(lambda s, d: run(io.load(s, d, table), col))


# the one-round sum on every numeric column
for _n, _t, _c in [("price", "lineitem", "l_extendedprice"), ("tax", "lineitem", "l_tax"), ("discount", "lineitem", "l_discount"), ("quantity", "lineitem", "l_quantity"), ("totalprice", "orders", "o_totalprice"), ("acctbal", "customer", "c_acctbal"), ("supplier_acctbal", "supplier", "s_acctbal"), ("retailprice", "part", "p_retailprice"), ("events", "events", "value")]:
    simple(f"q_sum_{_n}", _t, _c, M.exact_sum)

# its variants, on the column that drifts most
for _n, _kw in {"salt": {}, "hash": {"placement": "hash:l_orderkey"}, "range": {"placement": "range:idx"}, "partition": {"placement": "partition"}}.items():
    simple(f"q_sum_placement_{_n}", "lineitem", "l_discount", lambda df, c, kw=_kw: M.sum_mapreduce(df, c, **kw))
simple("q_sum_nocombine", "lineitem", "l_discount", lambda df, c: M.sum_mapreduce(df, c, combine=False))
simple("q_sum_dense", "lineitem", "l_discount", lambda df, c: M.sum_mapreduce(df, c, acc="dense"))
simple("q_sum_dense_columns", "lineitem", "l_discount", lambda df, c: M.sum_mapreduce(df, c, acc="dense_sql"))
simple("q_sum_external", "lineitem", "l_discount", lambda df, c: X.sum_external(df, c))
simple("q_sum_on_driver", "lineitem", "l_discount", lambda df, c: M.sum_mapreduce(df, c, finalize="driver"))
simple("q_sum_wide_headroom", "lineitem", "l_discount", lambda df, c: M.exact_sum(df, c, wide=True))
simple("q_scan", "lineitem", "l_discount", M.sum_scan)
simple("q_tree_sum", "lineitem", "l_discount", lambda df, c: T.sum_tree(df, c, fan_in=8, leaves=512))
simple("q_tree_binary", "customer", "c_acctbal", lambda df, c: T.sum_tree(df, c, fan_in=2, leaves=16))
simple("q_tree_pairwise", "lineitem", "l_tax", lambda df, c: T.sum_pairwise_tree(df, c, leaves=16))
simple("q_sorted", "lineitem", "l_discount", X.sum_sorted)
for _v in ("cut", "tree"):
    for _s in ("float", "exponent", "certified"):
        # the faithful tests may accept a neighbour; on this column all three give the nearest double
        simple(f"q_adaptive_{_v}_{_s}", "lineitem", "l_extendedprice", lambda df, c, v=_v, s=_s: T.sum_adaptive(df, c, variant=v, stop=s).select("value"))


query("q_adaptive_effort", "SELECT 4 AS r, 2 AS iterations, true AS certified, 'exact' AS accepted, false AS truncated")(lambda s, d: T.sum_adaptive(io.load(s, d, "lineitem"), "l_extendedprice").select("r", "iterations", "certified", "accepted", (F.col("truncations") > 0).alias("truncated")))
for _v in ("cut", "tree"):
    # 2000 binades: the value is certified although most limbs are cut
    query(f"q_adaptive_effort_wide_{_v}", "SELECT 4 AS r, 2 AS iterations, true AS certified, 'certified' AS accepted, true AS truncated")(lambda s, d, v=_v: T.sum_adaptive(Wl.make_workload(s, "positive", d, 2000), "x", variant=v).select("r", "iterations", "certified", "accepted", (F.col("truncations") > 0).alias("truncated")))
query("q_adaptive_by_key", f"SELECT l_returnflag, {exact_sql('l_tax', 59)} AS value FROM lineitem GROUP BY 1")(lambda s, d: T.sum_adaptive(io.load(s, d, "lineitem"), "l_tax", ["l_returnflag"], variant="tree").select("l_returnflag", "value"))


@query("q_sum_by_flag_status", f"""SELECT l_returnflag, l_linestatus, {exact_sql('l_quantity', 52)} AS sum_qty, {exact_sql('l_extendedprice', 43)} AS sum_price,
 {exact_sql('l_discount', 59)} AS sum_discount, {exact_sql('l_tax', 59)} AS sum_tax FROM lineitem GROUP BY ALL""")
def sum_by_flag_status(spark, d):
    return M.exact_agg(io.load(spark, d, "lineitem"), ["l_returnflag", "l_linestatus"], sum_qty="l_quantity", sum_price="l_extendedprice", sum_discount="l_discount", sum_tax="l_tax")


@query("q_sum_by_priority", f"SELECT o_orderpriority, {exact_sql('l_extendedprice', 43)} AS value FROM orders JOIN lineitem ON o_orderkey = l_orderkey GROUP BY 1")
def sum_by_priority(spark, d):
    o = io.load(spark, d, "orders").select(F.col("o_orderkey").alias("l_orderkey"), "o_orderpriority")
    return J.exact_sum_join(io.load(spark, d, "lineitem"), o, "l_orderkey", "l_extendedprice", ["o_orderpriority"], hint="shuffle_hash")


@query("q_sum_by_nation", f"SELECT n_name, {exact_sql('s_acctbal', 60)} AS value FROM supplier JOIN nation ON s_nationkey = n_nationkey GROUP BY 1")
def sum_by_nation(spark, d):
    n = io.load(spark, d, "nation").select(F.col("n_nationkey").alias("s_nationkey"), "n_name")
    return J.exact_sum_join(io.load(spark, d, "supplier"), n, "s_nationkey", "s_acctbal", ["n_name"])


@query("q_preagg_join", f"SELECT o_orderpriority, {exact_sql('l_tax', 59)} AS value FROM orders JOIN lineitem ON o_orderkey = l_orderkey GROUP BY 1")
def preagg(spark, d):
    return J.preagg_join(io.load(spark, d, "lineitem"), "l_tax", "l_orderkey", io.load(spark, d, "orders"), "o_orderkey", ["o_orderpriority"])


@query("q_revenue_by_nation", f"""SELECT n_name, {exact_sql('l_extendedprice', 43)} AS value FROM customer JOIN orders ON c_custkey = o_custkey
 JOIN lineitem ON l_orderkey = o_orderkey JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey WHERE r_name <> '' GROUP BY 1""")
def revenue_by_nation(spark, d):
    t = lambda n: io.load(spark, d, n)
    j = t("lineitem").join(t("orders"), F.col("l_orderkey") == F.col("o_orderkey")).join(t("customer"), F.col("o_custkey") == F.col("c_custkey"))
    j = j.join(t("nation"), F.col("c_nationkey") == F.col("n_nationkey")).join(t("region"), F.col("n_regionkey") == F.col("r_regionkey")).where("r_name <> ''")
    return M.exact_sum(j, "l_extendedprice", ["n_name"])


def digit_sums(df: DataFrame, col: str, keys=()) -> DataFrame:
    sums = A.limb_sums(A.limb_rows(df, keys, {"v": F.col(col)}), keys).where("top is not null")
    parts = F.array(*[F.struct((F.col("top") - i).alias("idx"), F.col(f"s{i}").alias("digit")) for i in range(3)])
    return sums.select(*keys, F.inline(parts)).groupBy(*keys, "idx").agg(F.sum("digit").alias("digit")).where("digit <> 0")


for _n, _t, _c in [("price", "lineitem", "l_extendedprice"), ("acctbal", "customer", "c_acctbal"), ("discount", "lineitem", "l_discount")]:
    query(f"q_limbs_{_n}", DIGITS.format(keys="", rows=f"SELECT {_c} AS x FROM {_t}"))(lambda s, d, t=_t, c=_c: digit_sums(io.load(s, d, t), c))
query("q_limbs_by_segment", DIGITS.format(keys="c_mktsegment,", rows="SELECT c_mktsegment, c_acctbal AS x FROM customer"))(lambda s, d: digit_sums(io.load(s, d, "customer"), "c_acctbal", ["c_mktsegment"]))


def workload_sql(kind: str, delta: int) -> str:
    x = f"""SELECT (((l_orderkey * 1103515245 + l_partkey * 12345 + l_suppkey * 2654435761 + l_linenumber::BIGINT * 97) % 4503599627370496 + 4503599627370496)::DOUBLE
 * pow(2, ((l_partkey * 7919 + l_orderkey * 31 + l_linenumber) % {delta} - {delta // 2} - 52))) AS x, (l_orderkey + l_linenumber + l_partkey) % 2 AS s FROM lineitem"""
    if kind == "mixed":
        return f"SELECT CASE WHEN s = 0 THEN x ELSE -x END AS x FROM ({x})"
    if kind == "centred":
        return f"SELECT x - mean AS x FROM ({x}), ({Q.exact_mean(f'SELECT x FROM ({x})')})"
    return f"SELECT x FROM ({x})"


for _d in Wl.DELTAS:
    for _k in ("positive", "mixed"):
        query(f"q_w_{_k}_{_d}", DIGITS.format(keys="", rows=workload_sql(_k, _d)))(lambda s, d, k=_k, w=_d: digit_sums(Wl.make_workload(s, k, d, w), "x"))
    query(f"q_w_zero_{_d}", "SELECT 0.0::DOUBLE AS value")(lambda s, d, w=_d: M.exact_sum(Wl.make_workload(s, "zero", d, w), "x"))
    query(f"q_w_near_zero_{_d}", f"SELECT pow(2, {-_d // 2})::DOUBLE AS value")(lambda s, d, w=_d: M.exact_sum(Wl.make_workload(s, "near_zero", d, w), "x"))
    query(f"q_w_centred_{_d}", Q.exact_any(workload_sql("centred", _d)))(lambda s, d, w=_d: M.exact_sum(Wl.make_workload(s, "centred", d, w), "x"))
for _k in ("positive", "mixed"):
    # the three algorithms of the experiments on one workload
    for _n, _run in {"sparse": M.exact_sum, "dense": lambda df, c: M.sum_mapreduce(df, c, acc="dense"), "distill": lambda df, c: B.sum_distill(df, c).select("value")}.items():
        query(f"q_w_{_k}_500_{_n}", Q.exact_any(workload_sql(_k, 500)))(lambda s, d, k=_k, run=_run: run(Wl.make_workload(s, k, d, 500), "x"))
query("q_w_adaptive_zero", "SELECT 0.0::DOUBLE AS value")(lambda s, d: T.sum_adaptive(Wl.make_workload(s, "zero", d, 500), "x").select("value"))


def balanced_total(spark, d):
    """The signed digits added up again, in units of 2^-60, and whether each lies in [-R/2, R/2)."""
    b = M.packed_sums(io.load(spark, d, "customer"), [], {"v": F.col("c_acctbal")}).select(A.acc_balanced(F.col("acc")).alias("b"))
    zero = F.lit(0).cast("decimal(38,0)")
    total = F.aggregate(F.transform(F.reverse("b.digits"), lambda x: x.cast("decimal(38,0)")), zero, lambda a, x: (a * F.lit(1 << 32) + x).cast("decimal(38,0)"))
    scaled = F.when(F.col("b.low") == -2, total / 16).when(F.col("b.low") == -1, total * F.lit(1 << 28)).otherwise(total * F.lit(1 << 60))
    return b.select(scaled.cast("decimal(38,0)").cast("string").alias("total"), F.forall("b.digits", lambda x: (x >= -(1 << 31)) & (x < 1 << 31)).alias("balanced"))


@query("q_acc_canonical", f"SELECT CAST(sum(CAST(c_acctbal * pow(2, 60) AS HUGEINT)) AS VARCHAR) AS total FROM customer")
def acc_canonical(spark, d):
    p = M.packed_sums(io.load(spark, d, "customer"), [], {"v": F.col("c_acctbal")})
    big = F.aggregate(F.transform(F.reverse("acc.digits"), lambda x: x.cast("decimal(38,0)")), F.lit(0).cast("decimal(38,0)"), lambda a, x: (a * F.lit(1 << 32) + x).cast("decimal(38,0)"))
    # limbs -2.. carry the value in units of 2^-64; the column has no bit below 2^-60
    scaled = F.when(F.col("acc.low") == -2, big / 16).when(F.col("acc.low") == -1, big * F.lit(1 << 28)).otherwise(big * F.lit(1 << 60))
    return p.select(F.when(F.col("acc.neg"), F.concat(F.lit("-"), scaled.cast("decimal(38,0)").cast("string"))).otherwise(scaled.cast("decimal(38,0)").cast("string")).alias("total"))


def tree_sql(final: str, leaves: int = 16) -> str:
    """CTEs l0..: digits of every node of a binary tree whose leaves are keys modulo `leaves`, with one local carry a level."""

    def carried(rows: str) -> str:
        c = "CASE WHEN p + 2147483648 < 0 THEN -((-(p + 2147483648) + 4294967295) // 4294967296) ELSE (p + 2147483648) // 4294967296 END"
        return f"""SELECT node, idx, digit FROM (SELECT node, unnest([idx, idx + 1]) AS idx, unnest([p - 4294967296 * ({c}), {c}]) AS digit FROM ({rows})) WHERE digit <> 0"""

    out, depth = [], leaves.bit_length() - 1
    leaf = DIGITS.format(keys="node,", rows=f"SELECT c_custkey % {leaves} AS node, c_acctbal AS x FROM customer")
    out.append(f"l0 AS MATERIALIZED ({carried(f'SELECT node, idx, digit::HUGEINT AS p FROM ({leaf})')})")
    for k in range(1, depth + 1):
        below = f"SELECT node // 2 AS node, idx, sum(digit)::HUGEINT AS p FROM l{k - 1} GROUP BY 1, 2"
        out.append(f"l{k} AS MATERIALIZED ({carried(below)})")
    every = " UNION ALL ".join(f"SELECT {k}::INTEGER AS level, node::BIGINT AS node, idx::INTEGER AS idx, sum(digit)::BIGINT AS digit FROM l{k} GROUP BY 1, 2, 3" for k in range(depth + 1))
    lists = " UNION ALL ".join(f"SELECT DISTINCT {k}::INTEGER AS level, (node // {2**k})::BIGINT AS node, idx::INTEGER AS idx FROM l0" for k in range(depth + 1))
    return f"WITH {', '.join(out)}, every AS ({every}), lists AS ({lists}) {final}"


_tree = {"fan_in": 2, "leaves": 16}
query("q_tree_levels", tree_sql("SELECT level, node, idx, digit FROM every"))(lambda s, d: T.sum_tree(io.load(s, d, "customer"), "c_acctbal", trace=True, leaf=F.col("c_custkey"), **_tree))
query("q_tree_exponents", tree_sql("SELECT level, node, list(idx ORDER BY idx) AS exponents FROM lists GROUP BY 1, 2"))(lambda s, d: T.tree_exponents(io.load(s, d, "customer"), "c_acctbal", leaf=F.col("c_custkey"), **_tree))
query(
    "q_tree_links",
    tree_sql(
        """, placed AS (SELECT *, (row_number() OVER w - 1)::INTEGER AS place, lag(idx) OVER w AS below FROM lists WINDOW w AS (PARTITION BY level, node ORDER BY idx))
SELECT c.level, c.node, c.idx, c.below, p.place AS parent FROM placed c LEFT JOIN placed p ON p.level = c.level + 1 AND p.node = c.node // 2 AND p.idx = c.idx"""
    ),
)(lambda s, d: T.tree_links(io.load(s, d, "customer"), "c_acctbal", leaf=F.col("c_custkey"), **_tree))
query("q_tree_cost", tree_sql("SELECT level, count(*) AS components, count(DISTINCT node) AS nodes FROM every GROUP BY 1"))(lambda s, d: C.trace_cost(T.sum_tree(io.load(s, d, "customer"), "c_acctbal", trace=True, leaf=F.col("c_custkey"), **_tree)))


def set_sql(a: str, b: str) -> str:
    return f"SELECT (SELECT count(*) FROM (({a}) EXCEPT ALL ({b}))) + (SELECT count(*) FROM (({b}) EXCEPT ALL ({a}))) = 0 AS equal"


for _n, (_a, _x, _b, _y, _sa, _sb) in {
    "same": ("lineitem", "l_suppkey", "lineitem", "l_suppkey", "SELECT l_suppkey AS v FROM lineitem", "SELECT l_suppkey AS v FROM lineitem"),
    "custkeys": ("orders", "o_custkey", "customer", "c_custkey", "SELECT o_custkey AS v FROM orders", "SELECT c_custkey AS v FROM customer"),
    "negative": ("customer", "c_custkey - 700", "customer", "c_custkey - 701", "SELECT c_custkey - 700 AS v FROM customer", "SELECT c_custkey - 701 AS v FROM customer"),
    "huge": ("orders", "o_orderkey * -600000000000", "orders", "o_orderkey * -600000000000", "SELECT o_orderkey * -600000000000 AS v FROM orders", "SELECT o_orderkey * -600000000000 AS v FROM orders"),
    "copies": ("lineitem", "-l_linenumber", "lineitem", "-l_linenumber - l_orderkey % 2", "SELECT -l_linenumber AS v FROM lineitem", "SELECT -l_linenumber - l_orderkey % 2 AS v FROM lineitem"),
    "nations": ("nation", "n_nationkey", "customer", "c_nationkey", "SELECT n_nationkey::BIGINT AS v FROM nation", "SELECT DISTINCT c_nationkey::BIGINT AS v FROM customer"),
}.items():
    query(f"q_set_equal_{_n}", set_sql(_sa, _sb))(lambda s, d, a=_a, x=_x, b=_b, y=_y, n=_n: X.multiset_equal(io.load(s, d, a).select(F.expr(x).alias("v")).repartition(5), "v", io.load(s, d, b).select(F.expr(y).alias("v")).distinct() if n == "nations" else io.load(s, d, b).select(F.expr(y).alias("v")), "v").select("equal"))


@query("q_cond_number", f"SELECT {exact_sql('abs(c_acctbal)', 60)} / abs({exact_sql('c_acctbal', 60)}) AS condition FROM customer")
def cond(spark, d):
    return C.condition_number(io.load(spark, d, "customer"), "c_acctbal")


query("q_cond_by_segment", f"SELECT c_mktsegment, {exact_sql('abs(c_acctbal)', 60)} / abs({exact_sql('c_acctbal', 60)}) AS condition FROM customer GROUP BY 1")(lambda s, d: C.condition_number(io.load(s, d, "customer"), "c_acctbal", ["c_mktsegment"]))
BITS = "CAST(floor(log2(CAST({x} AS DOUBLE))) + CASE WHEN {x} >= (1::HUGEINT << CAST(floor(log2(CAST({x} AS DOUBLE))) AS INTEGER)) THEN 0 ELSE -1 END AS INTEGER)"
query("q_log2_condition", f"SELECT {BITS.format(x='a')} - {BITS.format(x='s')} AS bits FROM (SELECT SUM(CAST(abs(c_acctbal) * pow(2, 60) AS HUGEINT)) AS a, abs(SUM(CAST(c_acctbal * pow(2, 60) AS HUGEINT))) AS s FROM customer)")(lambda s, d: C.log2_condition(io.load(s, d, "customer"), "c_acctbal"))
EXPONENT = "((CAST({x}::DOUBLE::BIT AS BIGINT) >> 52) & 2047)"
query("q_exponent_range", f"SELECT (max({EXPONENT.format(x='c_acctbal')}) - min({EXPONENT.format(x='c_acctbal')}))::INTEGER AS delta FROM customer WHERE c_acctbal <> 0")(lambda s, d: C.exponent_range(io.load(s, d, "customer"), "c_acctbal"))
query("q_sigma", f"SELECT count(DISTINCT idx) AS sigma FROM ({Q.TOUCHED.format(keys='', rows='SELECT l_discount AS x FROM lineitem')})")(lambda s, d: C.sigma(io.load(s, d, "lineitem"), "l_discount"))
query("q_ulp_naive")(lambda s, d: C.ulp_error(io.load(s, d, "lineitem").coalesce(1), "l_discount"))
query("q_reproducible", f"SELECT unnest([1, 2, 7, 64])::INTEGER AS partitions, {exact_sql('l_discount', 59)} AS value FROM lineitem")(lambda s, d: C.reproducibility(io.load(s, d, "lineitem"), "l_discount"))
query("q_drift_of_plain_sum")(lambda s, d: C.reproducibility(io.load(s, d, "lineitem"), "l_discount", exact=False))
query("q_balance")(lambda s, d: C.balance(io.load(s, d, "lineitem"), F.pmod(F.xxhash64(F.monotonically_increasing_id()), F.lit(8))))
query("q_balance_by_key", "SELECT max(n) AS most, avg(n) AS mean, count(*) AS reducers FROM (SELECT l_suppkey % 8, count(*) AS n FROM lineitem GROUP BY 1)")(lambda s, d: C.balance(io.load(s, d, "lineitem"), F.col("l_suppkey") % 8))
query(
    "q_carry_stats",
    f"""WITH RECURSIVE {Q.canonical("SELECT l_discount AS x FROM lineitem")}, e AS (SELECT min(idx) AS low, max(idx) AS high FROM c),
 ones AS (SELECT idx, idx - row_number() OVER (ORDER BY idx) AS g FROM c WHERE norm = 4294967295)
 SELECT (coalesce((SELECT max(n) FROM (SELECT count(*) AS n FROM ones GROUP BY g)), 0) + 1)::INTEGER AS longest_chain, (high - low + 1)::INTEGER AS limbs FROM e""",
)(lambda s, d: C.carry_stats(io.load(s, d, "lineitem"), "l_discount"))
query("q_faithful", "SELECT true AS correct, true AS faithful")(lambda s, d: M.exact_sum(io.load(s, d, "lineitem"), "l_tax", detail=True).select(C.is_correct(F.col("acc"), F.col("value")).alias("correct"), C.is_faithful(F.col("acc"), F.col("value")).alias("faithful")))

# baselines that are exact must agree with the engine
for _m in ("distill", "superacc_carry", "small_acc", "expansion", "fixed", "bucketed", "reference", "refine", "accurate"):
    simple(f"q_base_{_m}", "orders", "o_totalprice", lambda df, c, m=_m: B.sequential(df, c, m).select("value"))
for _m in ("distill", "expansion", "accurate"):
    simple(f"q_base_{_m}_discount", "lineitem", "l_discount", lambda df, c, m=_m: B.sequential(df, c, m).select("value"))
simple("q_base_refine_rounds", "lineitem", "l_discount", lambda df, c: B.sum_refine(df, c).select("value"))
simple("q_base_accurate_discount_passes", "lineitem", "l_discount", lambda df, c: B.sum_accurate_passes(df, c).select("value"))
for _m in ("naive", "pairwise", "huffman", "by_exponent", "compensated", "doubly_compensated"):
    query(f"q_base_{_m}")(lambda s, d, m=_m: B.sequential(io.load(s, d, "orders"), "o_totalprice", m))
simple("q_base_accurate_passes", "orders", "o_totalprice", lambda df, c: B.sum_accurate_passes(df, c).select("value"))
simple("q_base_parallel_carry", "orders", "o_totalprice", lambda df, c: B.sum_parallel_carry(df, c).select("value"))
query("q_base_decimal_cast", "SELECT CAST(SUM(CAST(l_discount AS DECIMAL(30,10))) AS DOUBLE) AS value FROM lineitem")(lambda s, d: B.sum_decimal_cast(io.load(s, d, "lineitem"), "l_discount"))
query("q_decimal_base", "SELECT l_returnflag, sum(CAST(l_extendedprice AS DECIMAL(18,2)))::DECIMAL(38,2)::VARCHAR AS value FROM lineitem GROUP BY 1")(lambda s, d: M.decimal_sum(io.load(s, d, "lineitem").withColumn("p", F.col("l_extendedprice").cast("decimal(18,2)")), "p", ["l_returnflag"]).withColumn("value", F.col("value").cast("string")))

# aggregation forms
for _k, _g in (("rollup", "ROLLUP"), ("cube", "CUBE")):
    query(f"q_{_k}_exact", f"SELECT l_returnflag, l_linestatus, grouping(l_returnflag, l_linestatus)::INTEGER AS gid, {exact_sql('l_tax', 59)} AS value FROM lineitem GROUP BY {_g}(l_returnflag, l_linestatus)")(lambda s, d, k=_k: M.exact_grouping_sets(io.load(s, d, "lineitem"), "l_tax", ["l_returnflag", "l_linestatus"], k))
query("q_distinct_exact", f"SELECT l_returnflag, {exact_sql('x', 59)} AS value FROM (SELECT DISTINCT l_returnflag, l_tax AS x FROM lineitem) GROUP BY 1")(lambda s, d: M.exact_sum_distinct(io.load(s, d, "lineitem"), "l_tax", ["l_returnflag"]))
query("q_filter_exact", f"SELECT l_linestatus, {exact_sql('l_extendedprice', 43, ' FILTER (WHERE l_discount >= 0.05)')} AS value FROM lineitem GROUP BY 1")(lambda s, d: M.exact_agg(io.load(s, d, "lineitem"), ["l_linestatus"], value=F.when(F.col("l_discount") >= 0.05, F.col("l_extendedprice"))))
query("q_pivot_exact", "SELECT user_id % 10 AS g, " + ", ".join(f"{exact_sql('value', 59, f' FILTER (WHERE event_type = {chr(39)}{t}{chr(39)})')} AS {t}" for t in ("click", "view", "purchase")) + " FROM events GROUP BY 1")(lambda s, d: M.exact_agg(io.load(s, d, "events").withColumn("g", F.col("user_id") % 10), ["g"], **{t: F.when(F.col("event_type") == t, F.col("value")) for t in ("click", "view", "purchase")}))
_S = "SUM(CAST({x} * pow(2, {k}) AS HUGEINT))"
query("q_exact_avg", f"SELECT l_returnflag, {Q.quotient(_S.format(x='l_discount', k=59), 'COUNT(l_discount)', 59)} AS value FROM lineitem GROUP BY 1")(lambda s, d: M.exact_avg(io.load(s, d, "lineitem"), "l_discount", ["l_returnflag"]))
_N, _X, _XX = "COUNT(l_quantity)::HUGEINT", "SUM(l_quantity::HUGEINT)", "SUM(l_quantity::HUGEINT * l_quantity::HUGEINT)"
query("q_exact_var", f"SELECT l_returnflag, {Q.quotient(f'({_N} * {_XX} - {_X} * {_X})', f'({_N} * ({_N} - 1))', 0, 60)} AS value FROM lineitem GROUP BY 1")(lambda s, d: M.exact_var(io.load(s, d, "lineitem"), "l_quantity", ["l_returnflag"]))
query("q_exact_std")(lambda s, d: M.exact_std(io.load(s, d, "lineitem"), "l_quantity", ["l_returnflag"]))
_L, _XL = "SUM(l_linenumber::HUGEINT)", "SUM(l_quantity::HUGEINT * l_linenumber::HUGEINT)"
query("q_exact_cov", f"SELECT l_returnflag, {Q.quotient(f'({_N} * {_XL} - {_X} * {_L})', f'({_N} * ({_N} - 1))', 0, 60)} AS value FROM lineitem GROUP BY 1")(lambda s, d: M.exact_cov(io.load(s, d, "lineitem"), "l_quantity", "l_linenumber", ["l_returnflag"]))
query("q_exact_corr")(lambda s, d: M.exact_corr(io.load(s, d, "lineitem"), "l_quantity", "l_linenumber", ["l_returnflag"]))
query("q_exact_weighted_avg", f"SELECT l_returnflag, {Q.quotient(_XL, _L, 0, 60)} AS value FROM lineitem GROUP BY 1")(lambda s, d: M.exact_weighted_avg(io.load(s, d, "lineitem"), "l_quantity", "l_linenumber", ["l_returnflag"]))
_A, _B = "CAST(l_extendedprice * pow(2, 43) AS HUGEINT)", "CAST(l_discount * pow(2, 59) AS HUGEINT)"
query(
    "q_exact_dot_columns",
    f"""SELECT l_returnflag, CAST(CAST((h + l // 1073741824) * 2 + CASE WHEN l % 1073741824 <> 0 THEN 1 ELSE 0 END AS VARCHAR) AS DOUBLE) / pow(2, 73) AS value
 FROM (SELECT l_returnflag, SUM(({_A} // 1073741824) * {_B}) AS h, SUM(({_A} % 1073741824) * {_B}) AS l FROM lineitem GROUP BY 1)""",
)(lambda s, d: M.exact_dot(io.load(s, d, "lineitem"), "l_extendedprice", "l_discount", ["l_returnflag"]))
_SPECIAL = "CASE WHEN l_orderkey % 50 = 0 THEN CAST('NaN' AS DOUBLE) WHEN l_orderkey % 50 = 1 THEN CAST('Infinity' AS DOUBLE) ELSE l_quantity END"
query("q_special_by_key", f"SELECT l_suppkey, SUM({_SPECIAL}) AS value FROM lineitem GROUP BY 1")(lambda s, d: M.exact_sum(io.load(s, d, "lineitem").withColumn("x", F.expr(_SPECIAL)), "x", ["l_suppkey"]))
query("q_array_special", f"SELECT l_suppkey, SUM({_SPECIAL}) AS value FROM lineitem GROUP BY 1")(lambda s, d: io.load(s, d, "lineitem").groupBy("l_suppkey").agg(F.collect_list(F.expr(_SPECIAL)).alias("v")).select("l_suppkey", M.array_exact_sum(F.col("v")).alias("value")))
query("q_running_special", f"SELECT l_orderkey, l_linenumber, l_partkey, SUM({_SPECIAL}) OVER (PARTITION BY l_suppkey ORDER BY l_orderkey, l_linenumber, l_partkey, l_shipdate, l_extendedprice ROWS UNBOUNDED PRECEDING) AS running FROM lineitem")(lambda s, d: Wi.exact_running_sum(io.load(s, d, "lineitem").withColumn("q", F.expr(_SPECIAL)), "q", ["l_suppkey"], [F.asc_nulls_last(c) for c in ("l_orderkey", "l_linenumber", "l_partkey", "l_shipdate", "l_extendedprice")], "running").select("l_orderkey", "l_linenumber", "l_partkey", "running"))
query("q_sum_by_month", f"SELECT date_trunc('month', o_orderdate)::DATE::VARCHAR AS month, {exact_sql('o_totalprice', 43)} AS value FROM orders GROUP BY 1")(lambda s, d: M.exact_sum(io.load(s, d, "orders").withColumn("month", F.trunc(F.col("o_orderdate").cast("date"), "month").cast("string")), "o_totalprice", ["month"]))
query("q_events_by_hour", f"SELECT event_type, extract(hour FROM ts)::INTEGER AS hour, {exact_sql('value', 59)} AS value FROM events GROUP BY 1, 2")(lambda s, d: M.exact_sum(io.load(s, d, "events").withColumn("hour", F.hour("ts")), "value", ["event_type", "hour"]))
query("q_mixed_aggs", f"SELECT e.*, s.value FROM (SELECT event_type, count(*) AS n, min(value) AS least, max(value) AS most, count(DISTINCT user_id) AS users FROM events GROUP BY 1) e JOIN (SELECT event_type, {exact_sql('value', 59)} AS value FROM events GROUP BY 1) s USING (event_type)".replace("SELECT e.*, s.value", "SELECT e.event_type, n, least, most, users, s.value"))(lambda s, d: io.load(s, d, "events").groupBy("event_type").agg(F.count("*").alias("n"), F.min("value").alias("least"), F.max("value").alias("most"), F.countDistinct("user_id").alias("users")).join(M.exact_sum(io.load(s, d, "events"), "value", ["event_type"]), "event_type"))
query("q_incremental", f"SELECT o_orderpriority, {exact_sql('o_totalprice', 43)} AS value FROM orders GROUP BY 1")(lambda s, d: io.merge_acc(M.packed_sums(io.load(s, d, "orders").where("o_orderkey % 2 = 0"), ["o_orderpriority"], {"v": F.col("o_totalprice")}).unionByName(M.packed_sums(io.load(s, d, "orders").where("o_orderkey % 2 = 1"), ["o_orderpriority"], {"v": F.col("o_totalprice")})), ["o_orderpriority"]).drop("acc"))

# windows
query("q_running_exact", f"SELECT event_id, {exact_sql('value', 59, ' OVER (PARTITION BY user_id ORDER BY ts, event_id)')} AS running FROM events")(lambda s, d: Wi.exact_running_sum(io.load(s, d, "events"), "value", ["user_id"], ["ts", "event_id"], "running").select("event_id", "running"))
query("q_sliding_exact", f"SELECT event_id, {exact_sql('value', 59, ' OVER (PARTITION BY event_type ORDER BY ts, event_id ROWS BETWEEN 99 PRECEDING AND CURRENT ROW)')} AS sliding FROM events")(lambda s, d: Wi.exact_sliding_sum(io.load(s, d, "events"), "value", ["event_type"], ["ts", "event_id"], 100, "sliding").select("event_id", "sliding"))
query("q_running_global", f"SELECT event_id, {exact_sql('value', 59, ' OVER (ORDER BY ts, event_id)')} AS running FROM events")(lambda s, d: Wi.exact_running_sum(io.load(s, d, "events"), "value", [], ["ts", "event_id"], "running", buckets=16).select("event_id", "running"))
query("q_running_levels", f"SELECT event_id, {exact_sql('value', 59, ' OVER (PARTITION BY event_type ORDER BY ts, event_id)')} AS running FROM events")(lambda s, d: Wi.exact_running_sum(io.load(s, d, "events"), "value", ["event_type"], ["ts", "event_id"], "running", buckets=16).select("event_id", "running"))
query("q_range_exact", f"SELECT event_id, {exact_sql('value', 59, ' OVER (PARTITION BY event_type ORDER BY user_id RANGE BETWEEN 3 PRECEDING AND CURRENT ROW)')} AS near FROM events")(lambda s, d: Wi.exact_range_sum(io.load(s, d, "events"), "value", ["event_type"], "user_id", 3, 0, "near").select("event_id", "near"))
query("q_rank_exact", f"SELECT c_nationkey, value, rank() OVER (ORDER BY value DESC)::INTEGER AS place, ntile(4) OVER (ORDER BY value DESC, c_nationkey)::INTEGER AS quarter FROM (SELECT c_nationkey, {exact_sql('c_acctbal', 60)} AS value FROM customer GROUP BY 1)")(lambda s, d: M.exact_sum(io.load(s, d, "customer"), "c_acctbal", ["c_nationkey"]).select("c_nationkey", "value", F.rank().over(W.orderBy(F.desc("value"))).alias("place"), F.ntile(4).over(W.orderBy(F.desc("value"), "c_nationkey")).alias("quarter")))
query(
    "q_lag_exact",
    """SELECT event_type, day, CAST(CAST(t - lag(t) OVER (PARTITION BY event_type ORDER BY day) AS VARCHAR) AS DOUBLE) / pow(2, 59) AS delta
 FROM (SELECT event_type, ts::DATE AS day, SUM(CAST(value * pow(2, 59) AS HUGEINT)) AS t FROM events GROUP BY 1, 2)""",
)(lambda s, d: J.delta(io.load(s, d, "events").withColumn("day", F.col("ts").cast("date")), "value", ["event_type"], "day"))

# joins and sets
query("q_topk_exact", f"SELECT l_suppkey, {exact_sql('l_extendedprice', 43)} AS value FROM lineitem GROUP BY 1 ORDER BY 2 DESC, 1 LIMIT 10")(lambda s, d: J.topk_exact(io.load(s, d, "lineitem"), "l_extendedprice", ["l_suppkey"], 10))
query("q_semi", f"SELECT lang, sum(n_chars)::DOUBLE AS value FROM documents WHERE doc_id IN (SELECT doc_id FROM labels WHERE toxic = 1) GROUP BY 1")(lambda s, d: M.exact_sum(io.load(s, d, "documents").join(io.load(s, d, "labels").where("toxic = 1"), "doc_id", "left_semi"), "n_chars", ["lang"]))
query("q_anti", f"SELECT {exact_sql('o_totalprice', 43)} AS value FROM orders WHERE NOT EXISTS (SELECT 1 FROM lineitem WHERE l_orderkey = o_orderkey)")(lambda s, d: M.exact_sum(io.load(s, d, "orders").join(io.load(s, d, "lineitem"), F.col("o_orderkey") == F.col("l_orderkey"), "left_anti"), "o_totalprice"))
query("q_outer_exact", f"SELECT c_custkey, {exact_sql('o_totalprice', 43)} AS value FROM customer LEFT JOIN orders ON c_custkey = o_custkey GROUP BY 1")(lambda s, d: J.exact_sum_join(io.load(s, d, "customer"), io.load(s, d, "orders").withColumn("c_custkey", F.col("o_custkey")), "c_custkey", "o_totalprice", ["c_custkey"], "left"))
for _h in ("right", "full"):
    query(f"q_outer_{_h}", f"SELECT c_custkey, {exact_sql('o_totalprice', 43)} AS value FROM (SELECT * FROM customer WHERE c_custkey % 3 = 0) {_h.upper()} JOIN (SELECT o_custkey AS c_custkey, o_totalprice FROM orders) USING (c_custkey) GROUP BY 1")(lambda s, d, h=_h: J.exact_sum_join(io.load(s, d, "customer").where("c_custkey % 3 = 0"), io.load(s, d, "orders").select(F.col("o_custkey").alias("c_custkey"), "o_totalprice"), "c_custkey", "o_totalprice", ["c_custkey"], h))
BANDS = [(0, 0.0, 1000.0), (1, 1000.0, 20000.0), (2, 20000.0, 60000.0), (3, 60000.0, 1e6)]


@query("q_range_join", f"SELECT band, {exact_sql('l_extendedprice', 43)} AS value FROM lineitem JOIN (VALUES {', '.join(map(str, BANDS))}) b(band, low, high) ON l_extendedprice >= low AND l_extendedprice < high GROUP BY 1")
def range_join(spark, d):
    bands = spark.createDataFrame(BANDS, "band int, low double, high double")
    return M.exact_sum(J.range_join(io.load(spark, d, "lineitem").select("l_extendedprice"), "l_extendedprice", bands, "low", "high", 10000.0), "l_extendedprice", ["band"])


@query("q_theta", f"SELECT band, {exact_sql('l_extendedprice', 43)} AS value FROM lineitem JOIN (VALUES {', '.join(map(str, BANDS))}) b(band, low, high) ON l_extendedprice >= low AND l_extendedprice < high GROUP BY 1")
def theta(spark, d):
    bands = F.broadcast(spark.createDataFrame(BANDS, "band int, low double, high double"))
    return M.exact_sum(io.load(spark, d, "lineitem").join(bands, (F.col("l_extendedprice") >= F.col("low")) & (F.col("l_extendedprice") < F.col("high"))), "l_extendedprice", ["band"])


@query("q_asof", """SELECT a.event_id, b.value AS viewed FROM (SELECT * FROM events WHERE event_type = 'purchase') a
 ASOF LEFT JOIN (SELECT user_id, ts, value FROM events WHERE event_type = 'view') b ON a.user_id = b.user_id AND a.ts >= b.ts""")
def asof(spark, d):
    e = io.load(spark, d, "events")
    return J.asof(e.where("event_type = 'purchase'"), e.where("event_type = 'view'"), "user_id", "ts", "ts", "value", "viewed").select("event_id", "viewed")


@query("q_interval", f"""SELECT a.user_id, {exact_sql('b.value', 59)} AS value FROM events a JOIN events b ON a.user_id = b.user_id
 AND epoch(a.ts)::BIGINT - epoch(b.ts)::BIGINT BETWEEN 0 AND 3599 WHERE a.event_type = 'purchase' AND b.event_type = 'view' GROUP BY 1""")
def interval(spark, d):
    # to the nearest second, halves to even, as the SQL's cast of epoch() does
    e = io.load(spark, d, "events").withColumn("ts", F.timestamp_seconds(F.rint(F.unix_micros(F.col("ts").cast("timestamp")) / 1e6)))
    j = J.interval_join(e.where("event_type = 'purchase'"), e.where("event_type = 'view'"), "user_id", "ts", "ts", 3600)
    return M.exact_sum(j, "r_value", ["user_id"])


query("q_salted_join", f"SELECT p_brand, {exact_sql('l_extendedprice', 43)} AS value FROM lineitem JOIN part ON l_partkey = p_partkey GROUP BY 1")(lambda s, d: M.exact_sum(J.salted(io.load(s, d, "lineitem").withColumn("p_partkey", F.col("l_partkey")), io.load(s, d, "part"), "p_partkey"), "l_extendedprice", ["p_brand"]))
query("q_union_zero", "SELECT 0.0::DOUBLE AS value")(lambda s, d: M.exact_sum(io.load(s, d, "orders").select(F.col("o_totalprice").alias("x")).unionAll(io.load(s, d, "orders").select((-F.col("o_totalprice")).alias("x"))), "x"))
query("q_intersect", f"SELECT {exact_sql('x', 59)} AS value FROM (SELECT l_tax AS x FROM lineitem INTERSECT SELECT l_discount FROM lineitem)")(lambda s, d: M.exact_sum(io.load(s, d, "lineitem").select(F.col("l_tax").alias("x")).intersect(io.load(s, d, "lineitem").select("l_discount")), "x"))
query("q_except", f"SELECT {exact_sql('x', 59)} AS value FROM (SELECT l_discount AS x FROM lineitem EXCEPT SELECT l_tax FROM lineitem)")(lambda s, d: M.exact_sum(io.load(s, d, "lineitem").select(F.col("l_discount").alias("x")).subtract(io.load(s, d, "lineitem").select("l_tax")), "x"))
query("q_except_all", f"SELECT {exact_sql('x', 59)} AS value FROM (SELECT l_discount AS x FROM lineitem EXCEPT ALL SELECT l_tax FROM lineitem)")(lambda s, d: M.exact_sum(io.load(s, d, "lineitem").select(F.col("l_discount").alias("x")).exceptAll(io.load(s, d, "lineitem").select("l_tax")), "x"))
query("q_intersect_all", f"SELECT {exact_sql('x', 59)} AS value FROM (SELECT l_discount AS x FROM lineitem INTERSECT ALL SELECT l_tax FROM lineitem)")(lambda s, d: M.exact_sum(io.load(s, d, "lineitem").select(F.col("l_discount").alias("x")).intersectAll(io.load(s, d, "lineitem").select("l_tax")), "x"))
query("q_magnitude_filter", f"SELECT {exact_sql('c_acctbal', 60)} AS value FROM customer WHERE abs(c_acctbal) >= 4096")(lambda s, d: M.exact_sum(io.load(s, d, "customer").where(D.magnitude_at_least(F.col("c_acctbal"), 12)), "c_acctbal"))
query("q_signed_filter", f"SELECT {exact_sql('c_acctbal', 60)} AS value FROM customer WHERE c_acctbal < 0")(lambda s, d: M.exact_sum(io.load(s, d, "customer").where(D.is_finite(F.col("c_acctbal")) & D.same_sign(F.col("c_acctbal"), negative=True)), "c_acctbal"))
query("q_percentiles", "SELECT event_type, quantile_disc(value, 0.5) AS middle, quantile_disc(value, 0.9) AS high FROM events GROUP BY 1")(lambda s, d: io.load(s, d, "events").groupBy("event_type").agg(F.expr("percentile_disc(0.5) WITHIN GROUP (ORDER BY value)").alias("middle"), F.expr("percentile_disc(0.9) WITHIN GROUP (ORDER BY value)").alias("high")))
query("q_condition_sample")(lambda s, d: C.condition_number(io.load(s, d, "customer").sample(0.2, seed=7), "c_acctbal"))

# scalars and arrays
query("q_project", "SELECT o_orderkey, CASE WHEN o_totalprice >= 250000 THEN 'high' ELSE 'low' END AS band, CAST(o_totalprice AS BIGINT) AS whole FROM orders WHERE o_orderstatus IN ('O', 'F') AND o_orderpriority LIKE '%URGENT%'")(lambda s, d: io.load(s, d, "orders").where("o_orderstatus IN ('O', 'F') AND o_orderpriority LIKE '%URGENT%'").select("o_orderkey", F.when(F.col("o_totalprice") >= 250000, "high").otherwise("low").alias("band"), F.rint("o_totalprice").cast("bigint").alias("whole")))
query("q_hexfloat", "SELECT c_custkey, c_acctbal AS back FROM customer")(lambda s, d: io.load(s, d, "customer").select("c_custkey", D.parse_hexfloat(D.hexfloat(F.col("c_acctbal"))).alias("back")))
query("q_ulp", f"SELECT c_custkey, pow(2, {EXPONENT.format(x='c_acctbal')} - 1075)::DOUBLE AS ulp FROM customer WHERE c_acctbal <> 0")(lambda s, d: io.load(s, d, "customer").where("c_acctbal <> 0").select("c_custkey", D.ulp(F.col("c_acctbal")).alias("ulp")))
query("q_float_parts", f"SELECT c_custkey, c_acctbal < 0 AS neg, (CAST(c_acctbal::DOUBLE::BIT AS BIGINT) & 4503599627370495) + 4503599627370496 AS mant, ({EXPONENT.format(x='c_acctbal')} - 1075)::INTEGER AS exp FROM customer WHERE c_acctbal <> 0")(lambda s, d: io.load(s, d, "customer").where("c_acctbal <> 0").select("c_custkey", D.float_parts(F.col("c_acctbal")).alias("p")).select("c_custkey", "p.*"))
query("q_two_sum", "SELECT l_orderkey, l_linenumber, l_extendedprice + l_tax AS s, (l_extendedprice - ((l_extendedprice + l_tax) - ((l_extendedprice + l_tax) - l_extendedprice))) + (l_tax - ((l_extendedprice + l_tax) - l_extendedprice)) AS e FROM lineitem")(lambda s, d: io.load(s, d, "lineitem").select("l_orderkey", "l_linenumber", D.two_sum(F.col("l_extendedprice"), F.col("l_tax")).alias("t")).select("l_orderkey", "l_linenumber", "t.*"))
query("q_exact_array_sum", "SELECT vec_id, CAST(CAST(sum(CAST(x::DOUBLE * pow(2, 60) AS HUGEINT)) AS VARCHAR) AS DOUBLE) / pow(2, 60) AS value FROM (SELECT vec_id, unnest(embedding) AS x FROM embeddings) GROUP BY 1")(lambda s, d: io.load(s, d, "embeddings").select("vec_id", M.array_exact_sum(F.col("embedding")).alias("value")))
query("q_exact_dot", "SELECT vec_id, CAST(CAST(sum(CAST(x::DOUBLE * x::DOUBLE * pow(2, 100) AS HUGEINT)) AS VARCHAR) AS DOUBLE) / pow(2, 100) AS value FROM (SELECT vec_id, unnest(embedding) AS x FROM embeddings) GROUP BY 1")(lambda s, d: io.load(s, d, "embeddings").select("vec_id", M.array_exact_dot(F.col("embedding"), F.col("embedding")).alias("value")))
query("q_exact_norm", "SELECT vec_id, sqrt(CAST(CAST(sum(CAST(x::DOUBLE * x::DOUBLE * pow(2, 100) AS HUGEINT)) AS VARCHAR) AS DOUBLE) / pow(2, 100)) AS value FROM (SELECT vec_id, unnest(embedding) AS x FROM embeddings) GROUP BY 1")(lambda s, d: io.load(s, d, "embeddings").select("vec_id", M.array_exact_norm(F.col("embedding")).alias("value")))
query("q_exact_centroid", "SELECT label, i, CAST(CAST(sum(CAST(embedding[i]::DOUBLE * pow(2, 60) AS HUGEINT)) AS VARCHAR) AS DOUBLE) / pow(2, 60) AS value FROM (SELECT label, embedding, unnest(range(1, 65))::INTEGER AS i FROM embeddings) GROUP BY 1, 2")(lambda s, d: M.exact_sum(io.load(s, d, "embeddings").select("label", F.posexplode("embedding").alias("i", "x")).withColumn("i", F.col("i") + 1), "x", ["label", "i"]))
query("q_acc_map", f"WITH RECURSIVE {Q.canonical('SELECT c_acctbal AS x FROM customer')} SELECT idx::INTEGER AS idx, (sgn * norm)::BIGINT AS digit FROM c")(lambda s, d: M.packed_sums(io.load(s, d, "customer"), [], {"v": F.col("c_acctbal")}).select(F.explode(A.acc_map(F.col("acc"))).alias("idx", "digit")))
query("q_to_fixed", "SELECT c_custkey, CAST(c_acctbal * pow(2, 60) AS HUGEINT)::VARCHAR AS fixed FROM customer")(lambda s, d: io.load(s, d, "customer").select("c_custkey", D.to_fixed(F.col("c_acctbal"), -60).cast("string").alias("fixed")))
query("q_balanced", "SELECT CAST(sum(CAST(c_acctbal * pow(2, 60) AS HUGEINT)) AS VARCHAR) AS total, true AS balanced FROM customer")(balanced_total)
query("q_decimal_text", r"SELECT c_mktsegment, regexp_replace(CAST((sum(CAST(floor(c_acctbal * 16) AS HUGEINT))::DECIMAL(30,0) * 0.0625)::DECIMAL(38,4) AS VARCHAR), '\.?0+$', '') AS total FROM customer GROUP BY 1")(lambda s, d: M.packed_sums(io.load(s, d, "customer").withColumn("x", F.floor(F.col("c_acctbal") * 16) / 16), ["c_mktsegment"], {"v": F.col("x")}).select("c_mktsegment", A.acc_decimal(F.col("acc")).alias("total")))
query("q_acc_json", f"SELECT c_mktsegment, {exact_sql('c_acctbal', 60)} AS value FROM customer GROUP BY 1")(lambda s, d: M.packed_sums(io.load(s, d, "customer"), ["c_mktsegment"], {"v": F.col("c_acctbal")}).select("c_mktsegment", A.acc_round(A.acc_from_json(A.acc_to_json(F.col("acc")))).alias("value")))
query("q_json_weighted", f"SELECT event_type, {exact_sql('value * CAST(json_extract(props, chr(36) || chr(46) || chr(107)) AS BIGINT)', 70)} AS value FROM events GROUP BY 1")(lambda s, d: M.exact_dot(io.load(s, d, "events").withColumn("k", F.get_json_object("props", "$.k").cast("double")), "value", "k", ["event_type"]))


def truncated_sql(gamma: int) -> str:
    return f"(SELECT any_value(sgn) * CAST(CAST(sum(norm * (1::HUGEINT << (32 * (idx - t.low)))) AS VARCHAR) AS DOUBLE) * pow(2, any_value(32 * t.low)) FROM k, (SELECT min(idx) AS low FROM k WHERE place <= {gamma}) t WHERE place <= {gamma}) AS gamma_{gamma}"


@query("q_truncated", f"WITH RECURSIVE {Q.canonical('SELECT l_discount AS x FROM lineitem')}, k AS (SELECT *, row_number() OVER (ORDER BY idx DESC) AS place FROM c) SELECT {', '.join(truncated_sql(g) for g in (1, 2, 3))}")
def truncated(spark, d):
    p = M.packed_sums(io.load(spark, d, "lineitem"), [], {"v": F.col("l_discount")})
    return p.select(*[A.acc_round(A.acc_truncate(F.col("acc"), g)).alias(f"gamma_{g}") for g in (1, 2, 3)])


COUNTS = """WITH RECURSIVE n AS (SELECT count(*) AS n FROM lineitem),
h(k, part, rest) AS (SELECT 0, 0::BIGINT, n FROM n UNION ALL SELECT k + 1, p, rest - p FROM (SELECT k, rest, (rest >> d) << d AS p FROM (SELECT k, rest, greatest(0, floor(log2(rest))::INTEGER + 1 - 11) AS d FROM h WHERE rest > 0)))
SELECT n, list(part::DOUBLE ORDER BY k) FILTER (k > 0) AS halves, [n::DOUBLE] AS singles FROM n, h GROUP BY n"""


@query("q_count_as_floats", COUNTS)
def count_as_floats(spark, d):
    n = io.load(spark, d, "lineitem").count()
    return spark.createDataFrame([(n, X.count_as_floats(n, "half"), X.count_as_floats(n, "single"))], "n bigint, halves array<double>, singles array<double>")


@query("q_udf_exact_sum", f"SELECT c_mktsegment, {exact_sql('c_acctbal', 60)} AS value FROM customer GROUP BY 1")
def udf_exact_sum(spark, d):
    from .functions.sql import register_sql

    register_sql(spark)
    io.load(spark, d, "customer").createOrReplaceTempView("exact_customer")
    return spark.sql("SELECT c_mktsegment, exact_sum(c_acctbal) AS value FROM exact_customer GROUP BY c_mktsegment")


@query("q_udtf_limbs", DIGITS.format(keys="", rows="SELECT s_acctbal AS x FROM supplier"))
def udtf_limbs(spark, d):
    from .functions.sql import register_sql

    register_sql(spark)
    io.load(spark, d, "supplier").createOrReplaceTempView("exact_supplier")
    return spark.sql("SELECT idx, sum(digit) AS digit FROM exact_supplier, LATERAL limbs_of(s_acctbal) GROUP BY idx HAVING sum(digit) <> 0")


@query("q_sql_template", DIGITS.format(keys="", rows="SELECT l_tax AS x FROM lineitem"))
def sql_template(spark, d):
    from .functions.sql import exact_sql as template

    io.load(spark, d, "lineitem").createOrReplaceTempView("exact_lineitem")
    sums = spark.sql(template("exact_lineitem", "l_tax"))
    parts = F.array(*[F.struct((F.col("top") - i).alias("idx"), F.col(f"s{i}").alias("digit")) for i in range(3)])
    return sums.select(F.inline(parts)).groupBy("idx").agg(F.sum("digit").alias("digit")).where("digit <> 0")


# streams
def _stream(spark: SparkSession, d: str) -> DataFrame:
    schema = io.load(spark, d, "events").schema
    return spark.readStream.schema(schema).option("pathGlobFilter", "events.parquet*").parquet(d)


def _streamed(name: str, mode: str = "complete", **kw):
    def run(spark, d):
        import uuid

        return S.run_once(S.stream_exact_sum(_stream(spark, d), "value", "ts", ["event_type"], **kw), spark, f"{name}_{uuid.uuid4().hex[:8]}", mode).select("event_type", F.col("start").cast("string").alias("start"), "n", "value")

    return run


query("q_stream_tumbling", f"SELECT event_type, strftime(time_bucket(INTERVAL 1 DAY, ts), '%Y-%m-%d %H:%M:%S') AS start, count(*) AS n, {exact_sql('value', 59)} AS value FROM events GROUP BY 1, 2")(_streamed("tumbling"))
query("q_stream_sliding", f"SELECT event_type, strftime(w, '%Y-%m-%d %H:%M:%S') AS start, count(*) AS n, {exact_sql('value', 59)} AS value FROM (SELECT *, unnest([time_bucket(INTERVAL 12 HOUR, ts), time_bucket(INTERVAL 12 HOUR, ts) - INTERVAL 12 HOUR]) AS w FROM events) GROUP BY 1, 2")(_streamed("sliding", window="1 day", slide="12 hours"))
query(
    "q_stream_session",
    f"""SELECT event_type, min(ts)::VARCHAR AS start, count(*) AS n, {exact_sql('value', 59)} AS value
 FROM (SELECT *, sum(new) OVER (PARTITION BY event_type ORDER BY ts, event_id ROWS UNBOUNDED PRECEDING) AS g
       FROM (SELECT *, CASE WHEN ts - lag(ts) OVER (PARTITION BY event_type ORDER BY ts, event_id) < INTERVAL 30 MINUTE THEN 0 ELSE 1 END AS new FROM events))
 GROUP BY event_type, g""",
)(_streamed("session", session_gap="30 minutes"))


@query("q_stream_deduplicated", f"SELECT event_type, {exact_sql('value', 59)} AS value FROM (SELECT DISTINCT * FROM (SELECT user_id, event_type, max(value) AS value FROM events GROUP BY 1, 2)) GROUP BY 1")
def stream_deduplicated(spark, d):
    """Every event arrives twice as a stream; ids seen before are dropped, then the greatest value of a user counts."""
    import uuid

    name = f"deduplicated_{uuid.uuid4().hex[:8]}"
    e = _stream(spark, d).select("event_id", "ts", "user_id", "event_type", "value")
    twice = S.stream_deduplicated(e.unionAll(e), ["event_id"], "ts", "3650 days").select("user_id", "event_type", "value")
    once = S.run_to_files(twice, spark, name)
    most = once.groupBy("user_id", "event_type").agg(F.max("value").alias("value"))
    return M.exact_sum(most, "value", ["event_type"])


@query("q_stream_state", f"SELECT event_type AS key, count(*) AS n, {exact_sql('value', 59)} AS value FROM events GROUP BY 1")
def stream_state(spark, d):
    import uuid

    out = S.run_once(S.stream_running_sum(_stream(spark, d), "value", "event_type"), spark, f"state_{uuid.uuid4().hex[:8]}", "update")
    return out.groupBy("key").agg(F.max_by(F.struct("n", "value"), "n").alias("s")).select("key", "s.*")
