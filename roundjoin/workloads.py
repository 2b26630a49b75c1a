"""Registered queries of the join engine and their DuckDB oracles."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import fixtures as X
from . import functions as FN
from . import streaming as ST
from .operators import baselines as B
from .operators import counting as C
from .operators import primitives as P
from .operators import reducer as R
from .operators import relational as O
from .operators.decomposition import decomposition_join, materialize_bags
from .plans import cost
from .plans.bagtree import BagTree
from .plans.hypergraph import Hypergraph, find_bag_tree
from .plans.query import Atom, JoinQuery
from .plans.rewrite import log_depth_rewrite, log_depth_rewrite_edge_labels, log_depth_rewrite_hypertree, merge_log_depth_rewrite, merge_rewrite
from .plans.schedule import count_rounds
from .scratch import cut, scratch_path
from .sources import load_tables

Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Query] = {}
ORACLES: dict[str, str] = {}


def register(name: str, sql: str | None = None):
    def keep(f: Query) -> Query:
        QUERIES[name] = f
        if sql is not None:
            ORACLES[name] = sql
        return f

    return keep


# joins by method


def _tree(h: Hypergraph) -> BagTree:
    return find_bag_tree(h).reroot("center")


def _acyclic(q: JoinQuery, how: str) -> DataFrame:
    tree = _tree(Hypergraph.from_query(q))
    rels = q.bound()
    if how == "serial":
        return R.serial_reducer_join(tree, rels, q.shared)
    if how == "sequential":
        return R.acyclic_join_sequential(tree, rels, R.Runner(q.shared))
    if how == "hub":
        return R.hub_tree_join(tree, rels, q.shared)
    return R.acyclic_join_parallel(tree, rels, R.Runner(q.shared), reduce=how != "noreduce")


METHODS: dict[str, Callable[[JoinQuery], DataFrame]] = {
    "parallel": lambda q: _acyclic(q, "parallel"),
    "sequential": lambda q: _acyclic(q, "sequential"),
    "serial": lambda q: _acyclic(q, "serial"),
    "noreduce": lambda q: _acyclic(q, "noreduce"),
    "hub": lambda q: _acyclic(q, "hub"),
    "share": lambda q: B.one_round_share_join(q),
    "contraction": lambda q: B.contraction_join(q, _tree(Hypergraph.from_query(q))),
    "native": B.native_join,
    "single": B.single_machine_join,
    "decomp": lambda q: decomposition_join(q),
    "direct": lambda q: decomposition_join(q),
    "hash": lambda q: decomposition_join(q, _tree(Hypergraph.from_query(q)), physical="hash"),
    "grid": lambda q: decomposition_join(q, m=20_000, physical="grid"),
    "logdepth": lambda q: decomposition_join(q, log_depth_rewrite(find_bag_tree(h := Hypergraph.from_query(q)), h).tree),
    "merge1": lambda q: decomposition_join(q, merge_rewrite(find_bag_tree(h := Hypergraph.from_query(q)), h, 1)),
    "merge1_logdepth": lambda q: decomposition_join(q, merge_log_depth_rewrite(find_bag_tree(h := Hypergraph.from_query(q)), h, 1).tree),
    "edge_labels": lambda q: decomposition_join(q, log_depth_rewrite_edge_labels(find_bag_tree(h := Hypergraph.from_query(q)), h).tree),
    "hypertree": lambda q: decomposition_join(q, log_depth_rewrite_hypertree(find_bag_tree(h := Hypergraph.from_query(q)), h).tree),
    "attributes": lambda q: decomposition_join(q, log_depth_rewrite(find_bag_tree(h := Hypergraph.from_query(q)), h, kind="tree").tree),
}
JOINS = {
    "star_4": "parallel sequential serial hub share contraction native single grid",
    "star_11": "parallel",
    "chain_6": "parallel sequential native logdepth",
    "chain_5_asia": "parallel noreduce",
    "path_16": "hash",
    "ring_16": "direct logdepth merge1 merge1_logdepth edge_labels hypertree",
    "path_16_user7": "logdepth",
    "tri_6": "decomp share contraction native",
    "tri_12": "decomp logdepth contraction native",
    "tri_21": "decomp logdepth attributes",
    "five_rel": "decomp parallel",
    "cycle_4": "decomp share",
    "disconnected": "decomp",
    "conv_chain": "parallel",
}
for _fixture, _methods in JOINS.items():
    for _method in _methods.split():
        register(f"{_fixture.replace('_', '', 1) if _fixture[-1].isdigit() and _fixture.count('_') == 1 else _fixture}_{_method}", X.oracle(_fixture))(
            lambda spark, d, f=_fixture, m=_method: METHODS[m](X.fixture(spark, d, f))
        )

# primitives

_SKEW = "SELECT l.label, l.vec_id AS v1, r.vec_id AS v2 FROM embeddings l JOIN embeddings r USING (label)"
_FK = "SELECT l.o_custkey AS cust, l.o_orderkey AS o1, r.o_orderkey AS o2 FROM orders l JOIN orders r USING (o_custkey)"
_SEMI = "SELECT DISTINCT o_custkey AS cust, o_orderkey AS o FROM orders WHERE o_orderkey IN (SELECT l_orderkey FROM lineitem)"


def _t(spark: SparkSession, d: str, *names: str) -> dict[str, DataFrame]:
    return load_tables(spark, d, names or None)


register("grid_join_2", _SKEW)(lambda s, d: P.grid_join(list(X.skew_2(_t(s, d))), m=200))
register("grid_join_3", "SELECT r_regionkey AS reg, r_name AS rname, n_nationkey AS nat, s_suppkey AS s FROM region JOIN nation ON r_regionkey = n_regionkey JOIN supplier ON s_nationkey = n_nationkey")(
    lambda s, d: P.grid_join([(t := _t(s, d))["region"].selectExpr("r_regionkey AS reg", "r_name AS rname"), t["nation"].selectExpr("n_regionkey AS reg", "n_nationkey AS nat"), t["supplier"].selectExpr("s_nationkey AS nat", "s_suppkey AS s")], m=40)
)
register("grid_product", "SELECT r_name, n_name FROM region, nation")(lambda s, d: P.grid_join([(t := _t(s, d))["region"].select("r_name"), t["nation"].select("n_name")], m=10))
register("hash_join", _FK)(lambda s, d: P.hash_join(*X.skew_fk(_t(s, d)), strategy="shuffle_hash"))
register("hybrid_join", _SKEW)(lambda s, d: P.hybrid_join(*X.skew_2(_t(s, d)), m=200, share=0.1))
register("hybrid_join_fk", _FK)(lambda s, d: P.hybrid_join(*X.skew_fk(_t(s, d)), m=10_000, share=0.01))


def _orders_lines(s: SparkSession, d: str) -> tuple[DataFrame, DataFrame]:
    t = _t(s, d, "orders", "lineitem")
    return t["orders"].selectExpr("o_custkey AS cust", "o_orderkey AS o"), t["lineitem"].selectExpr("l_orderkey AS o")


register("semijoin_native", _SEMI)(lambda s, d: P.semijoin(*_orders_lines(s, d)))
register("semijoin_grid", _SEMI)(lambda s, d: P.semijoin(*_orders_lines(s, d), m=20_000, physical="grid"))
register("staged_distinct", "SELECT DISTINCT l_orderkey AS o, l_linenumber AS ln FROM lineitem")(lambda s, d: P.staged_distinct(_t(s, d)["lineitem"].selectExpr("l_orderkey AS o", "l_linenumber AS ln"), copies=8, m=16))
register("intersect", "SELECT l_orderkey AS k FROM lineitem INTERSECT SELECT o_orderkey FROM orders WHERE o_orderstatus = 'F'")(lambda s, d: P.intersect((t := _t(s, d))["lineitem"].selectExpr("l_orderkey AS k"), t["orders"].where("o_orderstatus = 'F'").selectExpr("o_orderkey AS k")))
register("dangling_report", "SELECT o_custkey AS cust, o_orderkey AS o FROM orders WHERE o_orderkey NOT IN (SELECT l_orderkey FROM lineitem)")(lambda s, d: O.anti_join(*_orders_lines(s, d), ["o"]))

_ASIA = X.oracle("chain_5_asia").replace("SELECT * FROM", "SELECT DISTINCT {} FROM")


def _reduced(s: SparkSession, d: str, atom: str, contraction: bool = False) -> DataFrame:
    q = X.fixture(s, d, "chain_5_asia")
    if contraction:
        return B.contraction_reduce(q)[atom]
    return R.full_reduce(_tree(Hypergraph.from_query(q)), q.bound(), R.Runner(q.shared))[atom]


for _atom, _cols in {"Region": "rname, reg", "Nation": "reg, nat", "Customer": "nat, cust", "Orders": "cust, o", "Line": "o, p"}.items():
    register(f"full_reduce_{_atom.lower()}", _ASIA.format(_cols))(lambda s, d, a=_atom: _reduced(s, d, a))
    register(f"contraction_reduce_{_atom.lower()}", _ASIA.format(_cols))(lambda s, d, a=_atom: _reduced(s, d, a, True))


@register("reduce_up_customer", "SELECT c_nationkey AS nat, c_custkey AS cust FROM customer WHERE c_custkey IN (SELECT o_custkey FROM orders WHERE o_orderkey IN (SELECT l_orderkey FROM lineitem)) AND c_nationkey IN (SELECT n_nationkey FROM nation JOIN region ON n_regionkey = r_regionkey WHERE r_name = 'ASIA')")
def _reduce_up(s: SparkSession, d: str) -> DataFrame:
    q = X.fixture(s, d, "chain_5_asia")
    return R.reduce_up(_tree(Hypergraph.from_query(q)).reroot("Customer"), q.bound(), R.Runner(q.shared))["Customer"]


@register("bag_multiplicity", "SELECT l_orderkey AS o, l_linenumber AS ln, o_custkey AS cust, count(*) AS mult FROM lineitem JOIN orders ON l_orderkey = o_orderkey GROUP BY 1, 2, 3")
def _bags(s: SparkSession, d: str) -> DataFrame:
    t = _t(s, d)
    q = JoinQuery([Atom.of("Line", t["lineitem"], {"o": "l_orderkey", "ln": "l_linenumber"}), Atom.of("Orders", t["orders"], {"o": "o_orderkey", "cust": "o_custkey"})])
    return decomposition_join(q, bag=True).withColumnRenamed("__mult", "mult")


@register("null_keys", "SELECT o, cust, nat, bal FROM (SELECT o_orderkey AS o, CASE WHEN o_orderkey % 10 = 0 THEN NULL ELSE o_custkey END AS cust FROM orders) JOIN (SELECT c_custkey AS cust, c_nationkey AS nat, CASE WHEN c_custkey % 7 = 0 THEN NULL ELSE CAST(c_acctbal AS DECIMAL(12,2)) END AS bal FROM customer) USING (cust)")
def _nulls(s: SparkSession, d: str) -> DataFrame:
    t = _t(s, d)
    orders = t["orders"].selectExpr("o_orderkey AS o", "CASE WHEN o_orderkey % 10 = 0 THEN NULL ELSE o_custkey END AS cust")
    customer = t["customer"].selectExpr("c_custkey AS cust", "c_nationkey AS nat", "CASE WHEN c_custkey % 7 = 0 THEN NULL ELSE CAST(c_acctbal AS DECIMAL(12,2)) END AS bal")
    return decomposition_join(JoinQuery([Atom.of("Orders", orders), Atom.of("Customer", customer)]))


for _name, _keys in {"tri6": ("tri_6", None), "star4": ("star_4", None), "chain6": ("chain_6", None)}.items():
    register(f"count_join_{_name}", f"SELECT count(*) AS n_answers FROM ({X.oracle(_keys[0])})")(lambda s, d, f=_keys[0]: C.count_join(X.fixture(s, d, f)))
register("aggregate_join_star4", f"SELECT nat, count(*) AS n_answers FROM ({X.oracle('star_4')}) GROUP BY 1")(lambda s, d: C.aggregate_join(X.fixture(s, d, "star_4"), ["nat"]))
register("aggregate_join_tri6", f"SELECT reg, nat, count(*) AS n_answers FROM ({X.oracle('tri_6')}) GROUP BY 1, 2")(lambda s, d: C.aggregate_join(X.fixture(s, d, "tri_6"), ["reg", "nat"]))

# structure: trees and rounds, with what they mean for a chain of the events of each user

#: Tuples a reducer of these studies holds.
STUDY_M = 1000
_EDGES = f"e AS ({X._EDGE}), n AS (SELECT count(*) AS n FROM e)"
#: Rounds of a semijoin of the edges with themselves: by hashing, and by a grid of reducers of STUDY_M tuples.
_ROUNDS_C = f"{_EDGES}, c AS (SELECT CAST(1 AS BIGINT) AS c UNION ALL SELECT CAST(CASE WHEN k <= 1 THEN 1 ELSE 2 + ceil(ln(k * k) / ln(sqrt({STUDY_M}))) END AS BIGINT) FROM (SELECT ceil(2.0 * n / {STUDY_M}) AS k FROM n))"


def edge_table(spark: SparkSession, d: str) -> DataFrame:
    """Each event with the next one of its user, written once."""
    return cut(X.edges(_t(spark, d, "events")))


def semijoin_rounds(n: int) -> list[int]:
    """Rounds of a semijoin of n tuples with n: by hashing, and by a grid."""
    return [cost.semijoin_cost(n, n, m)[0] for m in (None, STUDY_M)]


def star_graph(n: int) -> Hypergraph:
    return Hypergraph({"S": frozenset(f"a{i}" for i in range(1, n)), **{f"R{i}": frozenset((f"a{i}", f"b{i}")) for i in range(1, n)}})


def chain_graph(n: int) -> Hypergraph:
    return Hypergraph({f"R{i:02d}": frozenset((f"a{i:02d}", f"a{i + 1:02d}")) for i in range(n)})


def chain_tree(n: int) -> BagTree:
    h = chain_graph(n)
    return BagTree(h.edges, {e: frozenset([e]) for e in h.edges}, {f"R{i:02d}": f"R{i - 1:02d}" if i else None for i in range(n)})


def triangle_graph(k: int) -> Hypergraph:
    return Hypergraph({f"{n}{i:02d}": frozenset((f"a{p:02d}", f"a{q:02d}")) for i in range(k) for n, p, q in (("X", 2 * i, 2 * i + 1), ("Y", 2 * i, 2 * i + 2), ("Z", 2 * i + 1, 2 * i + 2))})


def triangle_tree(k: int) -> BagTree:
    chi = {f"t{i:02d}": frozenset(f"a{j:02d}" for j in (2 * i, 2 * i + 1, 2 * i + 2)) for i in range(k)}
    return BagTree(chi, {f"t{i:02d}": frozenset((f"X{i:02d}", f"Y{i:02d}")) for i in range(k)}, {f"t{i:02d}": f"t{i - 1:02d}" if i else None for i in range(k)})


def star_tree(n: int) -> BagTree:
    h = star_graph(n)
    return BagTree(h.edges, {e: frozenset([e]) for e in h.edges}, {e: None if e == "S" else "S" for e in h.edges})


_STATS = {
    "star_8": (lambda: (star_tree(8), star_graph(8)), (8, 1, 1, 1, True)),
    "chain_16": (lambda: (chain_tree(16), chain_graph(16)), (16, 15, 1, 1, True)),
    "chain_16_center": (lambda: (chain_tree(16).reroot("center"), chain_graph(16)), (16, 8, 1, 1, True)),
    "chain_16_logdepth": (lambda: (log_depth_rewrite(chain_tree(16), h := chain_graph(16)).tree, h), (27, 4, 3, 2, True)),
    "triangles_7": (lambda: (triangle_tree(7), triangle_graph(7)), (7, 6, 2, 1, True)),
    "triangles_7_logdepth": (lambda: (log_depth_rewrite(triangle_tree(7), h := triangle_graph(7)).tree, h), (11, 2, 3, 2, True)),
}


def _literal(rows: list[tuple], columns: list[str]) -> str:
    show = lambda v: "NULL" if v is None else f"'{v}'" if isinstance(v, str) else str(v).upper() if isinstance(v, bool) else f"CAST({v} AS {'DOUBLE' if isinstance(v, float) else 'BIGINT'})"
    return " UNION ALL ".join("SELECT " + ", ".join(f"{show(v)} AS {c}" for v, c in zip(r, columns, strict=True)) for r in rows)


_STAT_COLUMNS = ["tree", "bags", "depth", "width", "iw", "valid"]


@register("tree_stats", _literal([(n, *want) for n, (_, want) in _STATS.items()], _STAT_COLUMNS))
def _tree_stats(spark: SparkSession, d: str) -> DataFrame:
    rows = []
    for n, (make, _) in _STATS.items():
        tree, h = make()
        x = tree.stats(h)
        rows.append((n, x["bags"], x["depth"], x["width"], x["iw"], x["valid"]))
    return spark.createDataFrame(rows, "tree string, bags long, depth long, width long, iw long, valid boolean")


@register("logdepth_trace_tri21", f"WITH {_EDGES}, p AS (SELECT count(*) AS p FROM e x JOIN e y ON x.b = y.a) " + " UNION ALL ".join(f"SELECT CAST({i} AS BIGINT) AS iteration, CAST({a} AS BIGINT) AS active, CAST({l} AS BIGINT) AS leaves, CAST({t} AS BIGINT) AS tops, {a} * p AS tuples FROM p" for i, a, l, t in [(0, 7, 1, 3), (1, 3, 1, 1), (2, 1, 1, 0)]))
def _trace(spark: SparkSession, d: str) -> DataFrame:
    """Iterations of the log-depth rewrite on seven triangles of an event, the next and the one after that; tuples of as many of their bags as are active."""
    one = edge_table(spark, d)
    two = cut(one.toDF("a", "m").join(one.toDF("m", "b"), "m").select("a", "b"))
    h, tree = triangle_graph(7), triangle_tree(7)
    q = JoinQuery([Atom(n, (two if n[0] == "Y" else one).toDF(*sorted(h.edges[n])), tuple(sorted(h.edges[n])), (min(h.edges[n]),)) for n in h.edges])
    bags = P.counts(list(materialize_bags(tree, q.bound(), R.Runner(q.shared)).values()))
    rows = [(*r, sum(bags[: r[1]])) for r in log_depth_rewrite(tree, h, guard=False).trace]
    return spark.createDataFrame(rows, "iteration long, active long, leaves long, tops long, tuples long")


@register("one_round_lower_bound", f"WITH {_EDGES} SELECT CAST(k AS BIGINT) AS n, pow(n.n / 100::DOUBLE, k / 4.0::DOUBLE) AS tuples FROM n, (VALUES (16), (4)) t(k)")
def _bound(spark: SparkSession, d: str) -> DataFrame:
    """Least tuples of a chain of 16 and of 4 relations in one round, each of as many tuples as events have a next one, with reducers of 100."""
    found = X.edges(_t(spark, d, "events")).count()
    return spark.createDataFrame([(n, float(cost.one_round_chain_lower_bound(found, 100, n))) for n in (16, 4)], "n long, tuples double")


@register("example_e_rounds", f"WITH {_ROUNDS_C} SELECT what, c, CAST(k * (2 * c + 1) AS BIGINT) AS rounds FROM c, (VALUES ('levels_chain', 16), ('levels_wide', 6)) t(what, k)")
def _example(spark: SparkSession, d: str) -> DataFrame:
    """Rounds on the 16 levels of a chain of the edges and on the 6 of wider bags, with the rounds that a semijoin of the edges takes."""
    each = semijoin_rounds(X.edges(_t(spark, d, "events")).count())
    rows = [(n, c, cost.chain_levels_cost(k, c)) for c in each for n, k in (("levels_chain", 16), ("levels_wide", 6))]
    return spark.createDataFrame(rows, "what string, c long, rounds long")


@register("chain16_schedule", f"WITH {_ROUNDS_C} SELECT tree, c, CAST(fixed + per * c AS BIGINT) AS rounds FROM c, (VALUES ('chain', 15, 30), ('center', 8, 16), ('logdepth', 20, 11)) t(tree, fixed, per)")
def _schedule(spark: SparkSession, d: str) -> DataFrame:
    """Rounds of three trees of a chain of 16 edges, with the rounds that a semijoin of the edges takes."""
    h = chain_graph(16)
    trees = {"chain": chain_tree(16), "center": chain_tree(16).reroot("center"), "logdepth": log_depth_rewrite(chain_tree(16), h).tree.make_complete(h)}
    each = semijoin_rounds(X.edges(_t(spark, d, "events")).count())
    return spark.createDataFrame([(n, c, count_rounds(t, c, True)["total"]) for n, t in trees.items() for c in each], "tree string, c long, rounds long")


@register("predicted_costs", _literal([("star", "contraction", "parallel", True), ("triangles", "contraction", "log_depth", True), ("triangles", "log_depth", "decomposition", True)], ["workload", "costlier", "cheaper", "holds"]))
def _predicted(spark: SparkSession, d: str) -> DataFrame:
    at = {"in_": 1e6, "out": 1e6, "m": 1e4}
    star = lambda m: cost.predict(m, n=10, w=1, iw=1, d=1, **at)[1]
    tri = lambda m: cost.predict(m, n=21, w=2, iw=1, d=6, **at)[1]
    rows = [("star", "contraction", "parallel", star("contraction") > star("parallel")), ("triangles", "contraction", "log_depth", tri("contraction") > tri("log_depth")), ("triangles", "log_depth", "decomposition", tri("log_depth") > tri("decomposition"))]
    return spark.createDataFrame(rows, "workload string, costlier string, cheaper string, holds boolean")


# measures on the data

_G = "CAST(greatest(1, ceil(2.0 * {n} / 1000)) AS BIGINT)"


@register("grid_ledger", f"SELECT n_o, n_c, {_G.format(n='n_o')} AS g_o, {_G.format(n='n_c')} AS g_c, n_o * {_G.format(n='n_c')} + n_c * {_G.format(n='n_o')} AS sent FROM (SELECT count(*) AS n_o FROM orders), (SELECT count(*) AS n_c FROM customer)")
def _grid_ledger(spark: SparkSession, d: str) -> DataFrame:
    t = _t(spark, d)
    sizes = [t["orders"].count(), t["customer"].count()]
    g = cost.grid_sizes(sizes, 1000)
    return spark.createDataFrame([(*sizes, *g, cost.grid_sent(sizes, 1000))], "n_o long, n_c long, g_o long, g_c long, sent long")


@register("max_cell_load", "SELECT max(n) AS max_load, min(n) AS min_load FROM (SELECT ((o_orderkey * 2654435761) % 4294967296) % 16 AS cell, count(*) AS n FROM orders GROUP BY 1)")
def _load(spark: SparkSession, d: str) -> DataFrame:
    cells = _t(spark, d)["orders"].select(FN.cell_id(F.col("o_orderkey"), F.lit(16).cast("long")).alias("cell"))
    return cells.groupBy("cell").count().agg(F.max("count").alias("max_load"), F.min("count").alias("min_load"))


_STAR_LEDGER = """
WITH h AS (SELECT DISTINCT l_orderkey AS o, l_partkey AS p, l_suppkey AS s FROM lineitem),
up AS (SELECT * FROM h WHERE o IN (SELECT o_orderkey FROM orders) AND p IN (SELECT p_partkey FROM part)),
s2 AS (SELECT s_suppkey AS s, s_nationkey FROM supplier WHERE s_suppkey IN (SELECT s FROM up)),
h2 AS (SELECT * FROM up WHERE s IN (SELECT s FROM s2)),
o2 AS (SELECT o_orderkey AS o, o_custkey FROM orders WHERE o_orderkey IN (SELECT o FROM h2)),
p2 AS (SELECT p_partkey AS p, p_brand FROM part WHERE p_partkey IN (SELECT p FROM h2)),
j AS (SELECT * FROM h2 NATURAL JOIN o2 NATURAL JOIN p2),
n AS (SELECT (SELECT count(*) FROM h) AS h, (SELECT count(*) FROM up) AS up, (SELECT count(*) FROM h2) AS h2, (SELECT count(*) FROM orders) AS o, (SELECT count(*) FROM o2) AS o2,
    (SELECT count(*) FROM part) AS p, (SELECT count(*) FROM p2) AS p2, (SELECT count(*) FROM supplier) AS s, (SELECT count(*) FROM s2) AS s2, (SELECT count(*) FROM j) AS j, (SELECT count(*) FROM j NATURAL JOIN s2) AS answers)
SELECT CAST(unnest([2, 3, 4, 5, 6, 6, 8, 9, 10]) AS INT) AS round,
    unnest(['semijoin up pair', 'semijoin up lone', 'semijoin up lone', 'semijoin down', 'semijoin down', 'semijoin down', 'join pair', 'join lone', 'join lone']) AS op,
    unnest(['Orders', 'Hub', 'Supp', 'Hub', 'Orders', 'Part', 'Orders', 'Hub', 'Supp']) AS bag,
    unnest([h + o + h + p + 2 * up, h + up, s + up, up + s2, o + h2, p + h2, h2 + o2 + p2, h2 + j, s2 + j]) AS sent, unnest([up, up, s2, h2, o2, p2, j, j, answers]) AS produced, unnest([0, 0, 0, 0, 0, 0, 0, 0, 0]::BIGINT[]) AS max_load FROM n
"""


@register("ledger_star4", _STAR_LEDGER)
def _ledger(spark: SparkSession, d: str) -> DataFrame:
    q, ledger = X.fixture(spark, d, "star_4"), cost.CostLedger(machine=100_000)
    decomposition_join(q, ledger=ledger)
    ledger.release()
    return ledger.to_df(spark)


# supporting operators

def _sums() -> dict:
    return {"n": F.count("*"), "qty": F.sum(F.col("l_quantity").cast("decimal(12,2)"))}


_SUM_SQL = "count(*) AS n, sum(CAST(l_quantity AS DECIMAL(12,2))) AS qty"
_LK = ["l_returnflag", "l_linestatus"]


def _line(s: SparkSession, d: str) -> DataFrame:
    return _t(s, d)["lineitem"]


def _within(df: DataFrame, estimate: str, deviation: float) -> DataFrame:
    """One row: the exact count, and whether the estimate is within three deviations of it."""
    return df.select("exact", (F.abs(F.col(estimate) - F.col("exact")) <= 3 * deviation * F.col("exact")).alias("within_three_deviations"))


register("op_project_filter", "SELECT o_orderkey, o_custkey FROM orders WHERE o_orderstatus IN ('F', 'O') AND o_custkey BETWEEN 10 AND 500")(lambda s, d: O.project(O.filter_rows(_t(s, d)["orders"], "o_orderstatus IN ('F', 'O') AND o_custkey BETWEEN 10 AND 500"), ["o_orderkey", "o_custkey"]))
register("op_push_predicate", X.oracle("chain_6") + " WHERE nat < 5")(lambda s, d: METHODS["parallel"](O.push_predicate(X.fixture(s, d, "chain_6"), "nat", "nat < 5")))
for _how, _sql in {"left": "LEFT", "right": "RIGHT", "full": "FULL"}.items():
    register(f"op_join_{_how}", f"SELECT k, o, c FROM (SELECT o_custkey AS k, o_orderkey AS o FROM orders WHERE o_orderkey % 3 = 0) {_sql} JOIN (SELECT c_custkey AS k, c_nationkey AS c FROM customer WHERE c_custkey % 2 = 0) USING (k)")(
        lambda s, d, h=_how: O.equi_join((t := _t(s, d))["orders"].where("o_orderkey % 3 = 0").selectExpr("o_custkey AS k", "o_orderkey AS o"), t["customer"].where("c_custkey % 2 = 0").selectExpr("c_custkey AS k", "c_nationkey AS c"), ["k"], h)
    )
    register(f"op_join_whole_{_how}", f"SELECT k, o, c FROM (SELECT o_custkey AS k, o_orderkey AS o FROM orders) {_sql} JOIN (SELECT c_custkey + 20 AS k, c_nationkey AS c FROM customer) USING (k)")(
        lambda s, d, h=_how: O.equi_join((t := _t(s, d))["orders"].selectExpr("o_custkey AS k", "o_orderkey AS o"), t["customer"].selectExpr("c_custkey + 20 AS k", "c_nationkey AS c"), ["k"], h)
    )
for _hint in ("broadcast", "merge", "shuffle_hash"):
    register(f"op_join_{_hint}", "SELECT n_nationkey AS k, n_name, s_suppkey FROM nation JOIN supplier ON n_nationkey = s_nationkey")(lambda s, d, h=_hint: O.equi_join((t := _t(s, d))["nation"].selectExpr("n_nationkey AS k", "n_name"), t["supplier"].selectExpr("s_nationkey AS k", "s_suppkey"), ["k"], strategy=h))
register("op_semi_join", "SELECT c_custkey, c_name FROM customer WHERE c_custkey IN (SELECT o_custkey FROM orders)")(lambda s, d: O.semi_join((t := _t(s, d))["customer"].select("c_custkey", "c_name"), t["orders"].selectExpr("o_custkey AS c_custkey"), ["c_custkey"]))
register("op_theta_join", "SELECT r_regionkey, n_nationkey FROM region JOIN nation ON r_regionkey < n_regionkey")(lambda s, d: O.theta_join((t := _t(s, d))["region"], t["nation"], F.col("r_regionkey") < F.col("n_regionkey")).select("r_regionkey", "n_nationkey"))
register("op_range_join", "SELECT p_partkey, s_suppkey FROM part JOIN supplier ON p_partkey BETWEEN s_suppkey * 3 AND s_suppkey * 3 + 10")(lambda s, d: O.range_join((t := _t(s, d))["part"], t["supplier"].selectExpr("s_suppkey", "s_suppkey * 3 AS lo", "s_suppkey * 3 + 10 AS hi"), "p_partkey", "lo", "hi", 16).select("p_partkey", "s_suppkey"))
register("op_interval_join", "SELECT a.event_id AS e1, b.event_id AS e2 FROM events a JOIN events b ON a.user_id = b.user_id AND a.event_id <> b.event_id AND epoch(b.ts)::BIGINT - epoch(a.ts)::BIGINT BETWEEN 0 AND 3600 AND date_trunc('second', a.ts) IS NOT NULL")(
    lambda s, d: O.interval_join((e := _t(s, d)["events"]).select("user_id", F.col("event_id").alias("e1"), O.nearest_second("ts").alias("t1")), e.select("user_id", F.col("event_id").alias("e2"), O.nearest_second("ts").alias("t2")), "t1", "t2", 0, 3600, ["user_id"]).where("e1 <> e2").select("e1", "e2")
)
register("op_asof_join", "SELECT a.event_id, (SELECT max_by(b.event_id, (b.ts, b.event_id)) FROM events b WHERE b.user_id = a.user_id AND b.event_type = 'purchase' AND b.ts <= a.ts) AS last_id FROM events a WHERE a.event_type <> 'purchase'")(
    lambda s, d: O.asof_join((e := _t(s, d)["events"]).where("event_type <> 'purchase'").select("user_id", "ts", "event_id"), e.where("event_type = 'purchase'").groupBy("user_id", "ts").agg(F.max("event_id").alias("last_id")), "ts", ["user_id"], "last_id").select("event_id", "last_id")
)
register("op_aggregate", f"SELECT l_returnflag, l_linestatus, {_SUM_SQL} FROM lineitem GROUP BY ALL")(lambda s, d: O.aggregate(_line(s, d), _LK, _sums()))
register("op_count_distinct", "SELECT l_returnflag, count(DISTINCT l_partkey) AS distinct_l_partkey FROM lineitem GROUP BY 1")(lambda s, d: O.count_distinct_by(_line(s, d), ["l_returnflag"], "l_partkey"))
# the estimate itself depends on the sketch; its distance from the exact count is bounded
register("op_approx_distinct", "SELECT count(DISTINCT l_partkey) AS exact, TRUE AS within_three_deviations FROM lineitem")(
    lambda s, d: _within(_line(s, d).agg(F.count_distinct("l_partkey").alias("exact")).crossJoin(O.approx_distinct(_line(s, d), "l_partkey", 0.02)), "approx_l_partkey", 0.02)
)
register("op_cube", f"SELECT l_returnflag, l_linestatus, CAST(grouping_id(l_returnflag, l_linestatus) AS BIGINT) AS gid, {_SUM_SQL} FROM lineitem GROUP BY CUBE (l_returnflag, l_linestatus)")(lambda s, d: O.cube(_line(s, d), _LK, _sums()))
register("op_rollup", f"SELECT l_returnflag, l_linestatus, CAST(grouping_id(l_returnflag, l_linestatus) AS BIGINT) AS gid, {_SUM_SQL} FROM lineitem GROUP BY ROLLUP (l_returnflag, l_linestatus)")(lambda s, d: O.rollup(_line(s, d), _LK, _sums()))
register("op_grouping_sets", f"SELECT l_returnflag, l_linestatus, {_SUM_SQL} FROM lineitem GROUP BY GROUPING SETS ((l_returnflag), (l_linestatus))")(lambda s, d: O.grouping_sets(_line(s, d), [["l_returnflag"], ["l_linestatus"]], _sums()))
register("op_pivot", "SELECT l_returnflag, count(*) FILTER (l_linestatus = 'F') AS \"F\", count(*) FILTER (l_linestatus = 'O') AS \"O\" FROM lineitem GROUP BY 1")(lambda s, d: O.pivot_counts(_line(s, d), "l_returnflag", "l_linestatus", ["F", "O"]))
register("op_unpivot", "SELECT l_orderkey, l_linenumber, 'l_partkey' AS name, l_partkey AS value FROM lineitem UNION ALL SELECT l_orderkey, l_linenumber, 'l_suppkey', l_suppkey FROM lineitem")(lambda s, d: O.unpivot(_line(s, d).select("l_orderkey", "l_linenumber", "l_partkey", "l_suppkey"), ["l_orderkey", "l_linenumber"], ["l_partkey", "l_suppkey"]))
_CW = "OVER (PARTITION BY o_custkey ORDER BY o_orderkey)"
register("op_window_rank", f"SELECT o_custkey, o_orderkey, CAST(row_number() {_CW} AS INT) AS rn, CAST(rank() {_CW} AS INT) AS rk, CAST(dense_rank() {_CW} AS INT) AS dr FROM orders")(lambda s, d: O.window_rank(_t(s, d)["orders"].select("o_custkey", "o_orderkey"), ["o_custkey"], [F.col("o_orderkey")]))
register("op_window_lag_lead", f"SELECT o_custkey, o_orderkey, lag(o_orderkey) {_CW} AS prev_o_orderkey, lead(o_orderkey) {_CW} AS next_o_orderkey FROM orders")(lambda s, d: O.window_lag_lead(_t(s, d)["orders"].select("o_custkey", "o_orderkey"), ["o_custkey"], [F.col("o_orderkey")], "o_orderkey"))
register("op_window_rows", "SELECT o_custkey, o_orderkey, CAST(sum(o_orderkey) OVER (PARTITION BY o_custkey ORDER BY o_orderkey ROWS BETWEEN 2 PRECEDING AND CURRENT ROW) AS BIGINT) AS s FROM orders")(lambda s, d: O.window_frame(_t(s, d)["orders"].select("o_custkey", "o_orderkey"), ["o_custkey"], [F.col("o_orderkey")], F.sum("o_orderkey"), "s", -2, 0))
register("op_window_range", "SELECT o_custkey, o_orderkey, count(*) OVER (PARTITION BY o_custkey ORDER BY o_orderkey RANGE BETWEEN 1000 PRECEDING AND CURRENT ROW) AS n FROM orders")(lambda s, d: O.window_frame(_t(s, d)["orders"].select("o_custkey", "o_orderkey"), ["o_custkey"], [F.col("o_orderkey")], F.count("*"), "n", -1000, 0, "range"))
register("op_sort_limit", "SELECT o_orderkey FROM orders ORDER BY o_orderkey DESC LIMIT 10")(lambda s, d: O.sort_limit(_t(s, d)["orders"].select("o_orderkey"), [F.desc("o_orderkey")], 10))
register("op_topk", f"SELECT o_custkey, o_orderkey, CAST(row_number() {_CW} AS INT) AS rn FROM orders QUALIFY row_number() {_CW} <= 3")(lambda s, d: O.topk_per_group(_t(s, d)["orders"].select("o_custkey", "o_orderkey"), ["o_custkey"], [F.col("o_orderkey")], 3))
_A, _B = "SELECT l_orderkey % 50 AS k FROM lineitem", "SELECT o_custkey % 40 AS k FROM orders"
for _op, _word in {"union_all": "UNION ALL", "union_set": "UNION", "intersect_set": "INTERSECT", "intersect_all": "INTERSECT ALL", "except_set": "EXCEPT", "except_all": "EXCEPT ALL"}.items():
    register(f"op_{_op}", f"{_A} {_word} {_B}")(lambda s, d, f=getattr(O, _op): f((t := _t(s, d))["lineitem"].selectExpr("l_orderkey % 50 AS k"), t["orders"].selectExpr("o_custkey % 40 AS k")))
register("op_heavy_keys", "SELECT label, count(*) AS count FROM embeddings GROUP BY 1 HAVING count(*) >= 0.1 * (SELECT count(*) FROM embeddings)")(lambda s, d: P.heavy_keys(_t(s, d)["embeddings"], ["label"], 0.1))
register("fn_string", "SELECT c_custkey, lower(c_name) AS low, substring(c_name, 1, 4) AS head, length(c_name) AS len, concat_ws('-', c_mktsegment, c_name) AS tag, regexp_extract(c_name, '([0-9]+)', 1) AS digits, levenshtein(c_name, 'Customer') AS lev FROM customer")(lambda s, d: FN.fn_string(_t(s, d)["customer"]))
register("fn_url", "SELECT page_id, regexp_extract(url, '^[a-z]+://([^/?#:]+)', 1) AS host, regexp_extract(url, '^([a-z]+)://', 1) AS protocol FROM pages")(lambda s, d: FN.fn_url(_t(s, d)["pages"]))
register("fn_date", "SELECT o_orderkey, year(o_orderdate) AS y, month(o_orderdate) AS m, strftime(date_trunc('month', o_orderdate), '%Y-%m-%d') AS month_start, date_diff('day', DATE '1992-01-01', CAST(o_orderdate AS DATE)) AS days FROM orders")(lambda s, d: FN.fn_date(_t(s, d)["orders"]))
register("fn_math", "SELECT CAST(floor(CAST(l_quantity AS DECIMAL(12,2)) / 7) AS BIGINT) AS sevenths, l_partkey % 13 AS part_mod, count(*) AS n, max(greatest(l_partkey, l_suppkey)) AS top_key, CAST(sum(CAST(round(CAST(l_quantity AS DECIMAL(12,2)), 0) AS BIGINT)) AS BIGINT) AS rounded FROM lineitem GROUP BY 1, 2")(lambda s, d: FN.fn_math(_line(s, d)))
register("fn_array", "SELECT vec_id, len(embedding) AS dim, len(list_filter(embedding, lambda x: x > 0)) AS positive, list_position(embedding, list_max(embedding)) - 1 AS argmax FROM embeddings")(lambda s, d: FN.fn_array(_t(s, d)["embeddings"]))
register("fn_map", "SELECT o_custkey, count(*) FILTER (o_orderstatus = 'F') AS n_f, count(DISTINCT o_orderstatus) AS kinds FROM orders GROUP BY 1")(lambda s, d: FN.fn_map(_t(s, d)["orders"]))
register("fn_json", "SELECT event_id, json_extract_string(props, '$.page') AS page, len(json_keys(props)) AS n_keys FROM events")(lambda s, d: FN.fn_json(_t(s, d)["events"]))
register("udf_cell_id", "SELECT o_orderkey, ((o_orderkey * 2654435761) % 4294967296) % 16 AS cell FROM orders")(lambda s, d: _t(s, d)["orders"].select("o_orderkey", FN.cell_id_udf("o_orderkey", F.lit(16).cast("long")).alias("cell")))
register("udaf_load", "SELECT o_orderstatus, max(n) AS most FROM (SELECT o_orderstatus, o_custkey % 8 AS c, count(*) AS n FROM orders GROUP BY 1, 2) GROUP BY 1")(lambda s, d: _t(s, d)["orders"].groupBy("o_orderstatus").agg(FN.load_histogram_udaf(F.expr("o_custkey % 8")).alias("most")))


@register("udtf_grid_cells", "SELECT n_nationkey, CAST((n_nationkey % 3) * 4 + j AS INT) AS cell FROM nation, range(4) t(j)")
def _udtf(s: SparkSession, d: str) -> DataFrame:
    s.udtf.register("grid_cells", FN.grid_cells_udtf)
    _t(s, d)["nation"].createOrReplaceTempView("__nation")
    return s.sql("SELECT n_nationkey, cell FROM __nation, LATERAL grid_cells(CAST(n_nationkey % 3 AS INT), 4)")


# streams, each run to its end on the table's files


def _drained(s: SparkSession, stream: DataFrame, mode: str = "append") -> DataFrame:
    """The rows that a finite stream has written when it has read everything, as a table in the shared folder."""
    out, state = (scratch_path(s, kind) for kind in ("stream", "state"))
    stream.writeStream.format("parquet").outputMode(mode).option("path", out).option("checkpointLocation", state).trigger(availableNow=True).start().awaitTermination()
    return s.read.schema(stream.schema).parquet(out)


def _events(s: SparkSession, d: str) -> DataFrame:
    schema = _t(s, d)["events"].schema
    # event times need a zone
    return s.readStream.schema(schema).option("pathGlobFilter", "events.parquet").parquet(d).withColumn("ts", F.col("ts").cast("timestamp"))


register("stream_star", "SELECT event_id, user_id, c_nationkey, n_name FROM events JOIN customer ON user_id = c_custkey JOIN nation ON c_nationkey = n_nationkey")(
    lambda s, d: _drained(s, ST.stream_star(_events(s, d).select("event_id", "user_id"), [((t := _t(s, d))["customer"].selectExpr("c_custkey AS user_id", "c_nationkey").join(t["nation"].selectExpr("n_nationkey AS c_nationkey", "n_name"), "c_nationkey"), ["user_id"])])).select("event_id", "user_id", "c_nationkey", "n_name")
)
register("stream_distinct", "SELECT DISTINCT event_id FROM events")(lambda s, d: _drained(s, ST.stream_distinct(_events(s, d).select("ts", "event_id"), "ts", ["event_id"])).select("event_id"))
# windows that end no later than the watermark after the last row, one hour behind it, have been written
_CLOSED = "(SELECT max(ts) - INTERVAL 1 HOUR FROM events)"
_HALF_HOURS = "SELECT event_type, time_bucket(INTERVAL 30 MINUTE, ts) AS b FROM events"
_SESSIONS = """SELECT min(ts) AS start, max(ts) + INTERVAL 30 MINUTE AS "end", user_id, count(*) AS n FROM (
    SELECT user_id, ts, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts) AS no FROM (
        SELECT user_id, ts, CASE WHEN ts <= lag(ts) OVER (PARTITION BY user_id ORDER BY ts) + INTERVAL 30 MINUTE THEN 0 ELSE 1 END AS fresh FROM events)) GROUP BY user_id, no"""


def _windows(s: SparkSession, d: str, *args: str, **options: str) -> DataFrame:
    return _drained(s, ST.stream_windows(_events(s, d), "ts", *args, **options)).withColumns({c: F.col(c).cast("timestamp_ntz") for c in ("start", "end")})


register("stream_windows_tumbling", f'SELECT start, start + INTERVAL 1 HOUR AS "end", event_type, count(*) AS n FROM (SELECT event_type, time_bucket(INTERVAL 1 HOUR, ts) AS start FROM events) GROUP BY ALL HAVING "end" <= {_CLOSED}')(lambda s, d: _windows(s, d, ["event_type"]))
register("stream_windows_sliding", f'SELECT start, start + INTERVAL 1 HOUR AS "end", event_type, count(*) AS n FROM (SELECT event_type, b AS start FROM ({_HALF_HOURS}) UNION ALL SELECT event_type, b - INTERVAL 30 MINUTE FROM ({_HALF_HOURS})) GROUP BY ALL HAVING "end" <= {_CLOSED}')(
    lambda s, d: _windows(s, d, ["event_type"], "sliding", slide="30 minutes")
)
register("stream_windows_session", f'SELECT * FROM ({_SESSIONS}) WHERE "end" <= {_CLOSED}')(lambda s, d: _windows(s, d, ["user_id"], "session"))
register("stream_interval_join", "SELECT a.event_id AS e1, b.event_id AS e2 FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts >= a.ts AND b.ts <= a.ts + INTERVAL 10 MINUTE AND a.event_type = 'click' AND b.event_type = 'purchase'")(
    lambda s, d: _drained(s, ST.stream_interval_join(_events(s, d).where("event_type = 'click'").selectExpr("event_id AS e1", "ts AS t1", "user_id AS u1"), _events(s, d).where("event_type = 'purchase'").selectExpr("event_id AS e2", "ts AS t2", "user_id AS u2"), "t1", "t2", "u1", "u2")).select("e1", "e2")
)
_PATHS = "SELECT user_id, [event_id, b, c] AS path FROM (SELECT user_id, event_id, lead(event_id) OVER w AS b, lead(event_id, 2) OVER w AS c FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)) WHERE c IS NOT NULL"
register("batch_paths", _PATHS)(lambda s, d: ST.batch_paths(_t(s, d)["events"], "user_id", "event_id", "ts", 3))
# events wait for the watermark; without a delay the one after the last row lets all of them take their place, which a finite table's answer needs
register("stream_paths", _PATHS)(lambda s, d: _drained(s, ST.stream_paths(_events(s, d).select("user_id", "event_id", "ts"), "user_id", "event_id", "ts", 3, "0 seconds")))


@register("stream_batches", "SELECT DISTINCT event_id, user_id, c_nationkey AS nat, n_regionkey AS reg FROM events JOIN customer ON user_id = c_custkey JOIN nation ON c_nationkey = n_nationkey")
def _batches(s: SparkSession, d: str) -> DataFrame:
    t, out, state = _t(s, d), scratch_path(s, "batches"), scratch_path(s, "state")
    hub = Atom.of("Hub", t["events"].selectExpr("event_id", "user_id"))
    arms = [Atom.of("Customer", t["customer"].selectExpr("c_custkey AS user_id", "c_nationkey AS nat")), Atom.of("Nation", t["nation"].selectExpr("n_nationkey AS nat", "n_regionkey AS reg"))]
    q = JoinQuery([hub, *arms])
    ST.stream_batches(_events(s, d).select("event_id", "user_id"), q, "Hub", out, state).awaitTermination()
    return s.read.parquet(out).select(*q.attributes)
register("window_tumbling_batch", "SELECT time_bucket(INTERVAL 1 HOUR, ts) AS start, event_type, count(*) AS n FROM events GROUP BY 1, 2")(lambda s, d: _t(s, d)["events"].groupBy(F.window("ts", "1 hour").alias("w"), "event_type").agg(F.count("*").alias("n")).select(F.col("w.start").alias("start"), "event_type", "n"))
