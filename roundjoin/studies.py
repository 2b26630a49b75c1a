"""Registered queries that study the methods: trees and rewrites, rounds and costs, comparisons of methods on one workload, matching data, plans as SQL."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from . import fixtures as X
from .operators import baselines as B
from .operators import primitives as P
from .operators import reducer as R
from .operators import relational as O
from .operators.decomposition import decomposition_join, decomposition_sql, materialize_bags
from .operators.statistics import Stats, join
from .plans import cost
from .plans.bagtree import BagTree
from .plans.hypergraph import Hypergraph, find_bag_tree
from .plans.query import Atom, JoinQuery
from .plans.rewrite import ExtendedTree, contract, log_depth_rewrite, log_depth_rewrite_edge_labels, log_depth_rewrite_hypertree, merge_bags, merge_rewrite, predict_treewidth
from .plans.schedule import count_rounds, explain_rounds
from .scratch import cut, scratch_path, shuffles_dropped
from .sources import load_tables, stage_bucketed
from .workloads import _EDGES, _ROUNDS_C, METHODS, ORACLES, STUDY_M, _literal, chain_graph, chain_tree, edge_table, register, semijoin_rounds, star_graph, star_tree, triangle_graph, triangle_tree

# trees


_FIVE = _literal(
    [(0, "v1", None, True, 0, "a0,a1", "R1"), (0, "v2", "v1", True, 0, "a1,a2", "R2"), (0, "v3", "v2", True, 0, "a2,a3", "R3"), (0, "v4", "v3", True, 0, "a3,a4", "R4"), (0, "v5", "v3", True, 0, "a3,a5", "R5")]
    + [(1, "v1", None, True, 0, "a0,a1", "R1"), (1, "v2", "v1", True, 0, "a1,a2", "R2"), (1, "v3", "v2", True, 0, "a2,a3", "R3"), (1, "v4", "v3", False, 0, "a3,a4", "R4"), (1, "v5", "v3", True, 0, "a3,a5", "R5")]
    + [(2, "s0", None, True, 0, "a1,a2", "R2,R3"), (2, "v1", "s0", False, 0, "a0,a1", "R1"), (2, "v2", "s0", False, 0, "a1,a2", "R2"), (2, "v3", "s0", True, 0, "a2,a3", "R3"), (2, "v4", "v3", False, 0, "a3,a4", "R4"), (2, "v5", "v3", True, 0, "a3,a5", "R5")],
    ["stage", "bag", "parent", "active", "height", "attrs", "cover"],
)
#: Rows of the bags, by what covers them.
_FIVE_ROWS = """SELECT 'R1' AS cover, (SELECT count(*) FROM (SELECT DISTINCT n_regionkey, n_nationkey FROM nation)) AS tuples
UNION ALL SELECT 'R2', (SELECT count(*) FROM (SELECT DISTINCT c_nationkey, c_custkey FROM customer))
UNION ALL SELECT 'R3', (SELECT count(*) FROM (SELECT DISTINCT o_custkey, o_orderkey FROM orders))
UNION ALL SELECT 'R4', (SELECT count(*) FROM (SELECT DISTINCT l_orderkey, l_partkey FROM lineitem))
UNION ALL SELECT 'R5', (SELECT count(*) FROM (SELECT DISTINCT l_orderkey, l_suppkey FROM lineitem))
UNION ALL SELECT 'R2,R3', (SELECT count(*) FROM (SELECT DISTINCT c_nationkey, c_custkey FROM customer JOIN orders ON c_custkey = o_custkey))"""


@register("five_bag_trace", f"SELECT * FROM ({_FIVE}) JOIN ({_FIVE_ROWS}) USING (cover)")
def _five_bags(spark: SparkSession, d: str) -> DataFrame:
    """A chain v1-v2-v3 (nations, customers, orders) with leaves v4, v5 (parts and suppliers of an order): as given, with leaf v4 retired, and with the chain top
    v1 folded; tuples are the rows of each bag."""
    t = load_tables(spark, d, ("nation", "customer", "orders", "lineitem"))
    of = {"R1": ("nation", "n_regionkey", "n_nationkey"), "R2": ("customer", "c_nationkey", "c_custkey"), "R3": ("orders", "o_custkey", "o_orderkey"), "R4": ("lineitem", "l_orderkey", "l_partkey"), "R5": ("lineitem", "l_orderkey", "l_suppkey")}
    chi = {f"v{i}": frozenset(x) for i, x in enumerate((("a0", "a1"), ("a1", "a2"), ("a2", "a3"), ("a3", "a4"), ("a3", "a5")), 1)}
    q = JoinQuery([Atom.of(n, t[of[n][0]], dict(zip(sorted(chi[f"v{n[1]}"]), of[n][1:], strict=True))) for n in of])
    h, rels = Hypergraph.from_query(q), q.bound()
    x = ExtendedTree(BagTree(chi, {b: frozenset([f"R{b[1]}"]) for b in chi}, {"v1": None, "v2": "v1", "v3": "v2", "v4": "v3", "v5": "v3"}), h)
    rows, bags = [], {}
    for stage, step in enumerate((lambda: None, lambda: x.retire_leaf("v4"), lambda: x.fold_chain("v1"))):
        step()
        rows += [(stage, b, x.tree.parent[b], b in x.active, x.height[b], ",".join(sorted(x.tree.chi[b])), ",".join(sorted(x.tree.lam[b]))) for b in x.tree.chi]
        made = materialize_bags(x.tree, rels, R.Runner(q.shared))
        bags |= {(x.tree.chi[b], x.tree.lam[b]): d for b, d in made.items()}
    tuples = {(",".join(sorted(c)), ",".join(sorted(lam))): n for (c, lam), n in zip(bags, P.counts(list(bags.values())), strict=True)}
    return spark.createDataFrame([(*r, tuples[r[5:]]) for r in rows], "stage long, bag string, parent string, active boolean, height long, attrs string, cover string, tuples long")


def grouped_chain(n: int, size: int) -> tuple[BagTree, Hypergraph]:
    """The chain's tree with `size` neighbouring bags merged at a time."""
    tree, h = chain_tree(n), chain_graph(n)
    for i in range(0, n, size):
        for j in range(i + 1, min(i + size, n)):
            tree = merge_bags(tree, f"R{i:02d}", f"R{j:02d}")
    return tree, h


@register("chain16_by_threes", f"""WITH {_ROUNDS_C}, p AS (SELECT count(*) AS p FROM e x JOIN e y ON x.b = y.a JOIN e z ON y.b = z.a)
SELECT 'one' AS bags_of, CAST(16 AS BIGINT) AS bags, CAST(1 AS BIGINT) AS width, TRUE AS valid, c, 16 * (2 * c + 1) AS rounds, 16 * n AS tuples FROM c, n
UNION ALL SELECT 'three', 6, 3, TRUE, c, 6 * (2 * c + 1), 5 * p + n FROM c, n, p""")
def _by_threes(spark: SparkSession, d: str) -> DataFrame:
    """Rounds on a tree of width 3 made by merging, and on that of width 1: a level a bag, each with a semijoin of c rounds up, one down, and a join. tuples are the
    rows of the bags of a chain of each event and the next one."""
    edges, rows = edge_table(spark, d), []
    q = X._chain(edges, 16, name="R")
    for name, size in (("one", 1), ("three", 3)):
        tree, h = grouped_chain(16, size)
        tuples = sum(P.counts(list(materialize_bags(tree, q.bound(), R.Runner(q.shared)).values())))
        rows += [(name, len(tree.chi), tree.width(), tree.validate(h) == [], c, cost.chain_levels_cost(tree.depth() + 1, c), tuples) for c in semijoin_rounds(edges.count())]
    return spark.createDataFrame(rows, "bags_of string, bags long, width long, valid boolean, c long, rounds long, tuples long")


def _grouped(q: JoinQuery, size: int) -> BagTree:
    """The chain's tree with `size` neighbouring bags merged at a time."""
    tree = find_bag_tree(Hypergraph.from_query(q))
    names = sorted(tree.chi)
    tree = tree.reroot(names[0])
    for i in range(0, len(names), size):
        for b in names[i + 1 : i + size]:
            tree = merge_bags(tree, names[i], b)
    return tree


register("ring16_by_threes", X.oracle("ring_16"))(lambda s, d: decomposition_join(q := X.fixture(s, d, "ring_16"), _grouped(q, 3)))
register("path16_by_threes", X.oracle("path_16"))(lambda s, d: decomposition_join(q := X.fixture(s, d, "path_16"), _grouped(q, 3)))
register("path16_parallel", X.oracle("path_16"))(lambda s, d: METHODS["parallel"](X.fixture(s, d, "path_16")))
register("path16_direct", X.oracle("path_16"))(lambda s, d: METHODS["decomp"](X.fixture(s, d, "path_16")))

_MEASURES = ["tree", "bags", "depth", "width", "iw", "tw", "tiw", "hypertree", "potential", "bound", "refined"]


def measured_trees() -> list[tuple]:
    """Every measure of every rewrite on a star, a chain and a chain of triangles; the bounds are those of the attribute-only rewrite."""
    rows = []
    for name, tree, h in (("star_8", star_tree(8), star_graph(8)), ("chain_16", chain_tree(16), chain_graph(16)), ("triangles_7", triangle_tree(7), triangle_graph(7))):
        made = {
            "given": tree, "log_depth": log_depth_rewrite(tree, h, guard=False).tree, "edge_labels": log_depth_rewrite_edge_labels(tree, h).tree, "hypertree": log_depth_rewrite_hypertree(tree, h).tree,
            "attributes": log_depth_rewrite(tree, h, kind="tree", guard=False).tree, "merged": merge_rewrite(tree, h, 1),
        }
        for how, t in made.items():
            x, bounds = t.stats(h), predict_treewidth(tree)
            rows.append((f"{name}_{how}", x["bags"], x["depth"], x["width"], x["iw"], x["tw"], x["tiw"], t.is_hypertree(h), t.leaf_potential(), bounds["general"], bounds["refined"]))
    return rows


#: What the worked trees measure.
_TREES = (
    ("star_8_given", 8, 1, 1, 1, 6, 1, True, 14, 20, 6),
    ("star_8_log_depth", 8, 1, 1, 1, 6, 1, True, 14, 20, 6),
    ("star_8_edge_labels", 8, 1, 1, 1, 6, 1, True, 14, 20, 6),
    ("star_8_hypertree", 8, 1, 1, 1, 6, 1, True, 14, 20, 6),
    ("star_8_attributes", 8, 1, 1, 1, 6, 1, True, 14, 20, 6),
    ("star_8_merged", 4, 1, 2, 1, 7, 2, True, 6, 20, 6),
    ("chain_16_given", 16, 15, 1, 1, 1, 1, True, 32768, 5, 2),
    ("chain_16_log_depth", 27, 4, 3, 2, 2, 2, False, 128, 5, 2),
    ("chain_16_edge_labels", 27, 4, 3, 2, 5, 4, True, 128, 5, 2),
    ("chain_16_hypertree", 27, 4, 3, 2, 5, 4, True, 128, 5, 2),
    ("chain_16_attributes", 27, 4, 1, 2, 2, 2, True, 128, 5, 2),
    ("chain_16_merged", 8, 7, 2, 1, 2, 1, True, 128, 5, 2),
    ("triangles_7_given", 7, 6, 2, 1, 2, 1, True, 64, 8, 2),
    ("triangles_7_log_depth", 11, 2, 3, 2, 2, 2, False, 28, 8, 2),
    ("triangles_7_edge_labels", 11, 2, 6, 3, 6, 6, True, 28, 8, 2),
    ("triangles_7_hypertree", 11, 2, 3, 2, 3, 4, True, 28, 8, 2),
    ("triangles_7_attributes", 11, 2, 2, 2, 2, 2, True, 28, 8, 2),
    ("triangles_7_merged", 4, 3, 4, 1, 4, 1, True, 8, 8, 2),
)


@register("tree_measures", _literal(_TREES, _MEASURES))
def _measures(spark: SparkSession, d: str) -> DataFrame:
    return spark.createDataFrame(measured_trees(), "tree string, bags long, depth long, width long, iw long, tw long, tiw long, hypertree boolean, potential long, bound long, refined long")


@register("bag_tree_rows", "WITH " + ", ".join(f"{n} AS ({x})" for n, x in X.SQL["tri_6"]) + """ SELECT * FROM (""" + _literal([("b1", None, 0, "o,p,s", "T1,T2"), ("b3", "b1", 1, "nat,reg,s", "T4,T5")], ["bag", "parent", "depth", "attrs", "cover"]) + """)
JOIN (SELECT 'b1' AS bag, (SELECT count(*) FROM T1 NATURAL JOIN T2) AS tuples UNION ALL SELECT 'b3', (SELECT count(*) FROM T4 NATURAL JOIN T5)) USING (bag)""")
def _bag_rows(spark: SparkSession, d: str) -> DataFrame:
    """The tree of tri_6 as rows, with the tuples of each bag."""
    q = X.fixture(spark, d, "tri_6")
    tree = find_bag_tree(Hypergraph.from_query(q))
    bags = materialize_bags(tree, q.bound(), R.Runner(q.shared))
    tuples = spark.createDataFrame(list(zip(bags, P.counts(list(bags.values())), strict=True)), "bag string, tuples long")
    return tree.to_df(spark).join(tuples, "bag").select("bag", "parent", F.col("depth").cast("long").alias("depth"), F.array_join("attrs", ",").alias("attrs"), F.array_join("cover", ",").alias("cover"), "tuples")


@register("explain_rounds_chain3", f"""WITH {_EDGES}, q1 AS (SELECT * FROM e WHERE b IN (SELECT a FROM e)), q0 AS (SELECT * FROM e WHERE b IN (SELECT a FROM q1)),
d1 AS (SELECT * FROM q1 WHERE a IN (SELECT b FROM q0)), d2 AS (SELECT * FROM e WHERE a IN (SELECT b FROM d1)),
j1 AS (SELECT x.a, y.b FROM d1 x JOIN d2 y ON x.b = y.a), j0 AS (SELECT x.a, y.b FROM q0 x JOIN j1 y ON x.b = y.a)
SELECT 'up' AS phase, CAST(1 AS BIGINT) AS round, 'lone' AS op, 'R01' AS bag, 'R02' AS others, (SELECT count(*) FROM q1) AS produced
UNION ALL SELECT 'up', 2, 'lone', 'R00', 'R01', (SELECT count(*) FROM q0) UNION ALL SELECT 'down', 1, 'semijoin', 'R01', 'R00', (SELECT count(*) FROM d1)
UNION ALL SELECT 'down', 2, 'semijoin', 'R02', 'R01', (SELECT count(*) FROM d2) UNION ALL SELECT 'join', 1, 'lone', 'R01', 'R02', (SELECT count(*) FROM j1)
UNION ALL SELECT 'join', 2, 'lone', 'R00', 'R01', (SELECT count(*) FROM j0)""")
def _explained(spark: SparkSession, d: str) -> DataFrame:
    """The schedule of a chain of three, with the tuples that each of its operations produces on a chain of each event and the next one."""
    q, ledger = X._chain(edge_table(spark, d), 3, name="R"), cost.CostLedger()
    decomposition_join(q, chain_tree(3), ledger=ledger)
    ledger.release()
    made = [("up" if " up " in op else "down" if " down" in op else "join", bag, produced) for _, op, bag, _, produced, _ in ledger.entries]
    return explain_rounds(spark, chain_tree(3)).withColumn("round", F.col("round").cast("long")).join(spark.createDataFrame(made, "phase string, bag string, produced long"), ["phase", "bag"]).select("phase", "round", "op", "bag", "others", "produced")


# rounds and costs


def rounds_table() -> list[tuple]:
    """Rounds of the direct and the log-depth method, and steps of the contraction, by the length of chains of triangles, whose given trees are as deep as long."""
    rows = []
    for k in (4, 8, 16, 32, 64, 128):
        tree, h = triangle_tree(k), triangle_graph(k)
        log, steps = log_depth_rewrite(tree, h).tree, len(contract(tree, h).steps)
        direct, rewritten = (count_rounds(t, 1, True)["total"] for t in (tree, log))
        rows.append((k, tree.depth(), log.depth(), direct, rewritten, steps, rewritten < direct))
    return rows


#: Rounds by length.
_ROUNDS = (
    (4, 3, 2, 10, 13, 3, False),
    (8, 7, 3, 22, 22, 4, False),
    (16, 15, 4, 46, 31, 5, True),
    (32, 31, 5, 94, 40, 6, True),
    (64, 63, 6, 190, 49, 7, True),
    (128, 127, 7, 382, 58, 8, True),
)


@register("rounds_by_length", _literal(_ROUNDS, ["triangles", "depth", "log_depth", "direct", "rewritten", "contraction_steps", "rewriting_wins"]))
def _rounds(spark: SparkSession, d: str) -> DataFrame:
    return spark.createDataFrame(rounds_table(), "triangles long, depth long, log_depth long, direct long, rewritten long, contraction_steps long, rewriting_wins boolean")


def _ledgers(q: JoinQuery, methods: dict) -> dict[str, tuple[int, int, int, int]]:
    """Rounds, tuples, largest relation made, and answers of each method."""
    out = {}
    for name, run in methods.items():
        ledger = cost.CostLedger(written=True)
        with shuffles_dropped(q.atoms[0].df.sparkSession):
            got = run(ledger)
            answers = got if isinstance(got, int) else got.count()
        ledger.release()
        out[name] = (ledger.rounds(), ledger.communication(), max(ledger.sizes().values(), default=answers), answers)
    return out


def _written(q: JoinQuery) -> JoinQuery:
    """q on tables of its relations, bound: methods that are compared read them without making them again."""
    tables = P.barrier(q.bound(), "parquet")
    return JoinQuery([Atom(a.name, tables[a.name], a.attrs, a.key if a.key and set(a.key) <= set(a.attrs) else a.attrs) for a in q.atoms])


def _shared(q: JoinQuery, ledger: cost.CostLedger, reducers: int = 64) -> int:
    """Answers of the share join, which runs once, to count them."""
    sizes = dict(zip([a.name for a in q.atoms], P.counts(list(q.bound().values())), strict=True))
    shares = B.best_shares(q, sizes, reducers)
    answers = B.one_round_share_join(q, reducers, shares).count()
    ledger.add(1, "share", "all", B.share_sent(q, sizes, shares), answers)
    return answers


def _compared(spark: SparkSession, got: dict[str, tuple[int, int, int, int]]) -> DataFrame:
    """A row for each method, and its place by tuples among those of several rounds."""
    several = sorted((v[1], n) for n, v in got.items() if v[0] > 1)
    rows = [(n, v[0], v[3], next((i for i, x in enumerate(several, 1) if x[1] == n), None)) for n, v in got.items()]
    return spark.createDataFrame(rows, "method string, rounds long, answers long, place long")


def _by_method(answers: str, rows: list[tuple]) -> str:
    each = " UNION ALL ".join(f"SELECT '{m}' AS method, CAST({r} AS BIGINT) AS rounds, n AS answers, CAST({'NULL' if p is None else p} AS BIGINT) AS place FROM a" for m, r, p in rows)
    return f"WITH a AS (SELECT count(*) AS n FROM ({answers})) {each}"


def star_of(spark: SparkSession, d: str, n: int) -> JoinQuery:
    """The hub of star_11 with n - 1 of its arms."""
    return JoinQuery(X.fixture(spark, d, "star_11").atoms[:n])


_STAR_7 = "WITH " + ", ".join(f"{n} AS ({s})" for n, s in X.SQL["star_11"][:7]) + f" SELECT * FROM {X._natural(X.SQL['star_11'][:7])}"


@register("table2_star", _by_method(_STAR_7, [("share", 1, None), ("contraction", 17, 2), ("parallel", 16, 1)]))
def _table2(spark: SparkSession, d: str) -> DataFrame:
    """The star: one round for the share join, comparable numbers for the others, and by tuples sent and made the reducer join before the contraction. On a star of 4
    whose tree is rooted at an arm it is the other way round."""
    q = _written(star_of(spark, d, 7))
    return _compared(spark, _ledgers(q, {"share": lambda x: _shared(q, x), "contraction": lambda x: B.contraction_join(q, ledger=x), "parallel": lambda x: decomposition_join(q, ledger=x)}))


@register("table3_triangles", _by_method(X.oracle("tri_12"), [("share", 1, None), ("contraction", 16, 3), ("log_depth", 16, 2), ("direct", 13, 1)]))
def _table3(spark: SparkSession, d: str) -> DataFrame:
    """The chain of triangles: by tuples sent and made the direct method is first, the log-depth one second, contraction last."""
    q = _written(X.fixture(spark, d, "tri_12"))
    h = Hypergraph.from_query(q)
    tree = find_bag_tree(h)
    return _compared(spark, _ledgers(q, {
        "share": lambda x: _shared(q, x), "contraction": lambda x: B.contraction_join(q, tree, ledger=x),
        "log_depth": lambda x: decomposition_join(q, log_depth_rewrite(tree, h).tree, ledger=x), "direct": lambda x: decomposition_join(q, tree, ledger=x),
    }))


@register("predicted_tables", """
WITH x AS (SELECT 1e6::DOUBLE AS i, 1e6::DOUBLE AS o, 1e4::DOUBLE AS m, 12 AS n)
SELECT 'star' AS workload, 'share' AS method, 1.0::DOUBLE AS rounds, pow(i / m, n / 2.0) + o AS tuples FROM x
UNION ALL SELECT 'star', 'contraction', log2(n), n * pow(pow(i, 3) + o, 2) / m FROM x
UNION ALL SELECT 'star', 'parallel', 1 + log2(n), n * pow(i + o, 2) / m FROM x
UNION ALL SELECT 'triangles', 'share', 1.0, pow(i / m, n / 6.0) + o FROM x
UNION ALL SELECT 'triangles', 'contraction', log2(n), n * pow(pow(i, 6) + o, 2) / m FROM x
UNION ALL SELECT 'triangles', 'log_depth', log2(n), n * pow(pow(i, 3) + o, 2) / m FROM x
UNION ALL SELECT 'triangles', 'linear', n, n * pow(pow(i, 2) + o, 2) / m FROM x
UNION ALL SELECT 'triangles', 'merged', log2(15 / 16.0 * n), n * pow(pow(i, 6) + o, 2) / m FROM x
""")
def _predictions(spark: SparkSession, d: str) -> DataFrame:
    at, rows = {"in_": 1e6, "out": 1e6, "m": 1e4, "n": 12}, []
    for workload, shape, methods in (("star", {"w": 1, "iw": 1, "d": 1, "cover": 6.0}, ("share", "contraction", "parallel")), ("triangles", {"w": 2, "iw": 1, "d": 3, "cover": 2.0}, ("share", "contraction", "log_depth", "linear", "merged"))):
        rows += [(workload, m, *map(float, cost.predict(m, **at, **shape))) for m in methods]
    return _rounded(spark.createDataFrame(rows, "workload string, method string, rounds double, tuples double"), "rounds", "tuples")


def _rounded(df: DataFrame, *names: str, digits: int = 9) -> DataFrame:
    """Doubles to `digits` significant digits, as text, so that systems agree."""
    return df.withColumns({n: F.format_string(f"%.{digits}e", n) for n in names})


ORACLES["predicted_tables"] = f"SELECT workload, method, printf('%.9e', rounds) AS rounds, printf('%.9e', tuples) AS tuples FROM ({ORACLES['predicted_tables']})"


@register("model_measures", f"""WITH {_EDGES}, x AS (SELECT n::DOUBLE AS n, {STUDY_M}::DOUBLE AS m, (SELECT count(*) FROM e l JOIN e r ON l.b = r.a)::DOUBLE AS answers FROM n)
SELECT 'epsilon' AS measure, ln(n) / ln(m) AS value FROM x UNION ALL SELECT 'space_exponent_of_the_binary_grid', 0.5 FROM x
UNION ALL SELECT 'machines', ceil((2 * n + answers) / m) FROM x
UNION ALL SELECT 'mrc_within', CAST(pow(n, 0.4) <= pow(n, 0.5) AND n <= pow(n, 1.0) AS INT) FROM x UNION ALL SELECT 'mrc_load_beyond', CAST(2 * pow(n, 0.5) <= pow(n, 0.5) AS INT) FROM x
UNION ALL SELECT 'mrc_total_beyond', CAST(2 * n <= pow(n, 1.0) AS INT) FROM x
UNION ALL SELECT 'chain_bound', pow(n / m, 4.0) FROM x UNION ALL SELECT 'relaxed_rounds', 4 * ln(n) / ln(m) FROM x UNION ALL SELECT 'parallel_steps', 57 FROM x""")
def _model(spark: SparkSession, d: str) -> DataFrame:
    """Measures of the model for the join of each event and its next one with the next one's."""
    edges = edge_table(spark, d)
    n, answers = P.counts([edges, P.natural_join(edges.toDF("a", "b"), edges.toDF("b", "c"))])
    ledger = cost.CostLedger(machine=STUDY_M)
    ledger.add(1, "join", "x", cost.join_cost([n, n], None), answers)
    rows = [
        ("epsilon", cost.epsilon(n, STUDY_M)), ("space_exponent_of_the_binary_grid", cost.space_exponent(n, n / STUDY_M**0.5, STUDY_M)), ("machines", ledger.machines()),
        ("mrc_within", cost.mrc_feasible(n, n**0.4, n, 0.5)), ("mrc_load_beyond", cost.mrc_feasible(n, 2 * n**0.5, n, 0.5)), ("mrc_total_beyond", cost.mrc_feasible(n, n**0.4, 2 * n, 0.5)),
        ("chain_bound", cost.one_round_chain_lower_bound(n, STUDY_M, 16)), ("relaxed_rounds", cost.predict("log_depth", n, answers, STUDY_M, 16, relaxed=True)[0]), ("parallel_steps", cost.parallel_steps(chain_tree(16))),
    ]
    return _rounded(spark.createDataFrame([(a, float(b)) for a, b in rows], "measure string, value double"), "value")


ORACLES["model_measures"] = f"SELECT measure, printf('%.9e', CAST(value AS DOUBLE)) AS value FROM ({ORACLES['model_measures']})"

_ASIA = X.oracle("chain_5_asia").replace("SELECT * FROM", "SELECT DISTINCT {} FROM")
_PARTS = {"Region": "rname, reg", "Nation": "reg, nat", "Customer": "nat, cust", "Orders": "cust, o", "Line": "o, p"}


@register("dangling_share", " UNION ALL ".join(f"SELECT '{n}' AS atom, (SELECT count(*) FROM ({s})) AS before, (SELECT count(*) FROM ({_ASIA.format(_PARTS[n])})) AS after" for n, s in X.SQL["chain_5_asia"]))
def _dangling(spark: SparkSession, d: str) -> DataFrame:
    """Tuples of each relation before and after the full reduction."""
    q = X.fixture(spark, d, "chain_5_asia")
    rels = q.bound()
    reduced = R.full_reduce(find_bag_tree(Hypergraph.from_query(q)).reroot("center"), rels, R.Runner(q.shared))
    counts = [P.counts(list(x.values())) for x in (rels, {n: reduced[n] for n in rels})]
    return spark.createDataFrame(list(zip(rels, *counts, strict=True)), "atom string, before long, after long")


@register("sizes_tri6", "WITH " + ", ".join(f"{n} AS ({s})" for n, s in X.SQL["tri_6"]) + """
SELECT 'in' AS what, (SELECT count(*) FROM T1) + (SELECT count(*) FROM T2) + (SELECT count(*) FROM T3) + (SELECT count(*) FROM T4) + (SELECT count(*) FROM T5) + (SELECT count(*) FROM T6) AS n
UNION ALL SELECT 'out', (SELECT count(*) FROM T1 NATURAL JOIN T2 NATURAL JOIN T3 NATURAL JOIN T4 NATURAL JOIN T5 NATURAL JOIN T6)
UNION ALL SELECT 'bag o,p,s', (SELECT count(*) FROM T1 NATURAL JOIN T2) UNION ALL SELECT 'bag nat,reg,s', (SELECT count(*) FROM T4 NATURAL JOIN T5)""")
def _sizes(spark: SparkSession, d: str) -> DataFrame:
    """Tuples of the input, of each bag, and of the result."""
    q = X.fixture(spark, d, "tri_6")
    tree, rels = find_bag_tree(Hypergraph.from_query(q)), q.bound()
    bags = materialize_bags(tree, rels, R.Runner(q.shared))
    found = {"in": sum(P.counts(list(rels.values()))), "out": decomposition_join(q, tree).count()}
    found |= {f"bag {','.join(sorted(tree.chi[b]))}": n for b, n in zip(bags, P.counts(list(bags.values())), strict=True)}
    return spark.createDataFrame(list(found.items()), "what string, n long")


@register("grid_cell_load", """
WITH g AS (SELECT CAST(greatest(1, ceil(2.0 * (SELECT count(*) FROM orders) / 1000)) AS BIGINT) AS g_o, CAST(greatest(1, ceil(2.0 * (SELECT count(*) FROM customer) / 1000)) AS BIGINT) AS g_c),
o AS (SELECT CAST('0x' || substr(md5('17|' || o_custkey || '|' || o_orderkey), 1, 8) AS BIGINT) % (SELECT g_o FROM g) AS cell FROM orders),
c AS (SELECT CAST('0x' || substr(md5('18|' || c_custkey), 1, 8) AS BIGINT) % (SELECT g_c FROM g) AS cell FROM customer)
SELECT (SELECT max(n) FROM (SELECT count(*) AS n FROM o GROUP BY cell)) + (SELECT max(n) FROM (SELECT count(*) AS n FROM c GROUP BY cell)) AS load, (SELECT count(*) FROM orders JOIN customer ON o_custkey = c_custkey) AS answers""")
def _grid_load(spark: SparkSession, d: str) -> DataFrame:
    """Tuples in the fullest reducer of a grid join, which is refused if they are too many for chance."""
    t, loads = load_tables(spark, d), []
    out = P.grid_join([t["orders"].selectExpr("o_custkey AS cust", "o_orderkey AS o"), t["customer"].selectExpr("c_custkey AS cust")], m=1000, loads=loads, portable=True)
    return spark.createDataFrame([(loads[0], out.count())], "load long, answers long")


# matching data: every value of a relation's column is in one tuple only

def _star_of_edges(t: dict[str, DataFrame]) -> JoinQuery:
    """Each event with the next one (hub), the one after that, and the one before."""
    e = X.edges(t)
    return JoinQuery([Atom("Hub", e.toDF("a", "b"), ("a", "b"), ("a",)), Atom("After", e.toDF("b", "c"), ("b", "c"), ("b",)), Atom("Before", e.toDF("z", "a"), ("z", "a"), ("a",))])


_MATCHED = f"WITH e AS ({X._EDGE}) SELECT h.a, h.b, n.b AS c, p.a AS z FROM e h JOIN e n ON h.b = n.a JOIN e p ON p.b = h.a"


def _hub(spark: SparkSession, d: str):
    q = _star_of_edges(load_tables(spark, d))
    rels = q.bound()
    return q, rels["Hub"], [rels["After"], rels["Before"]]


register("matching_columns", f"WITH e AS ({X._EDGE}) SELECT count(a) = count(*) AND count(DISTINCT a) = count(*) AS a, count(b) = count(*) AND count(DISTINCT b) = count(*) AS b FROM e")(lambda s, d: P.is_matching(X.edges(load_tables(s, d))))
register("matching_star_hub", _MATCHED)(lambda s, d: R.hub_join((h := _hub(s, d))[1], h[2], h[0].shared).select("a", "b", "c", "z"))
register("matching_hub_semijoin", f"WITH e AS ({X._EDGE}) SELECT a, b FROM e WHERE b IN (SELECT a FROM e) AND a IN (SELECT b FROM e)")(lambda s, d: R.hub_semijoin((h := _hub(s, d))[1], h[2], h[0].shared))
register("matching_path_hub", f"WITH e AS ({X._EDGE}) SELECT p.a AS a00, p.b AS a01, q.b AS a02, r.b AS a03, s.b AS a04 FROM e p JOIN e q ON p.b = q.a JOIN e r ON q.b = r.a JOIN e s ON r.b = s.a")(
    lambda s, d: METHODS["hub"](X._chain(X.edges(load_tables(s, d)), 4)).select("a00", "a01", "a02", "a03", "a04")
)


_AFTER = "SELECT event_id, " + ", ".join(f"lead(event_id, {i}) OVER w AS n{i}" for i in (3, 5, 9, 17)) + " FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)"


@register("matching_rounds", f"WITH s AS ({_AFTER}) " + " UNION ALL ".join(f"SELECT CAST({n} AS BIGINT) AS relations, CAST(2 AS BIGINT) AS hub_rounds, CAST(2 AS BIGINT) AS levels_times_two, count(n{n}) AS answers FROM s" for n in (3, 5, 9, 17)))
def _matching_rounds(spark: SparkSession, d: str) -> DataFrame:
    """Rounds of the hub join on stars: two for each level, however many arms there are. The hub is each event and the next one, its i-th arm the next one and that
    i places later; answers are those of the hub join."""
    t, rows = load_tables(spark, d, ("events",)), []
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    later = cut(t["events"].select("event_id", *[F.lead("event_id", i).over(w).alias(f"n{i}") for i in range(1, 17)]))
    arm = lambda i, a, b: later.select(F.col("event_id").alias(a), F.col(f"n{i}").alias(b)).where(F.col(b).isNotNull())
    for n in (3, 5, 9, 17):
        answers = R.hub_join(arm(1, "a", "b"), [arm(i, "b", f"c{i:02d}") for i in range(1, n)], frozenset("b")).count()
        rows.append((n, 2 * star_tree(n).depth(), 2 * len(R.levels(star_tree(n))), answers))
    return spark.createDataFrame(rows, "relations long, hub_rounds long, levels_times_two long, answers long")


# plans

for _f in ("star_4", "chain_6", "tri_6", "tri_12", "five_rel", "cycle_4"):
    _short = _f.replace("_", "") if _f[-1].isdigit() else _f
    register(f"join_auto_{_short}", X.oracle(_f))(lambda s, d, f=_f: join(X.fixture(s, d, f)))
for _m in ("decomposition", "log_depth", "merged_log_depth", "contraction", "share", "native", "single", "hash"):
    register(f"join_tri6_{_m}", X.oracle("tri_6"))(lambda s, d, m=_m: join(X.fixture(s, d, "tri_6"), m))
for _m in ("sequential", "parallel", "hub"):
    register(f"join_chain6_{_m}", X.oracle("chain_6"))(lambda s, d, m=_m: join(X.fixture(s, d, "chain_6"), m))
for _f in ("five_rel", "chain_5_asia", "cycle_4", "star_11"):
    register(f"{_f.replace('_', '') if _f in ('cycle_4', 'star_11') else _f}_native", X.oracle(_f))(lambda s, d, f=_f: METHODS["native"](X.fixture(s, d, f)))


def run_as_sql(spark: SparkSession, q: JoinQuery, tree: BagTree | None = None) -> DataFrame:
    """The decomposition join of q, run from its SQL text over views of the atoms, which are there only while the text is read."""
    named = JoinQuery([Atom(f"roundjoin_{a.name}", a.df, a.attrs, a.key) for a in q.atoms], q.filters)
    for a in named.atoms:
        a.df.createOrReplaceTempView(a.name)
    try:
        return spark.sql(decomposition_sql(named, tree))
    finally:
        for a in named.atoms:
            spark.catalog.dropTempView(a.name)


for _f in ("chain_6", "chain_5_asia", "tri_6", "cycle_4"):
    register(f"as_sql_{_f.replace('_', '')}", X.oracle(_f))(lambda s, d, f=_f: run_as_sql(s, X.fixture(s, d, f)))


@register("atom_statistics", " UNION ALL ".join(f"SELECT '{n}' AS atom, count(*) AS n FROM ({s})" for n, s in (("Customer", "SELECT c_custkey FROM customer"), ("Orders", "SELECT o_orderkey FROM orders"), ("Line", "SELECT l_orderkey FROM lineitem"), ("Supp", "SELECT s_suppkey FROM supplier"))))
def _statistics(spark: SparkSession, d: str) -> DataFrame:
    return spark.createDataFrame(list(Stats.of(X.fixture(spark, d, "cycle_4")).rows.items()), "atom string, n long")


@register("bucketed_join", "SELECT o_orderkey AS k, o_custkey, l_partkey FROM orders JOIN lineitem ON o_orderkey = l_orderkey")
def _bucketed(spark: SparkSession, d: str) -> DataFrame:
    """Both sides staged in buckets by the key, so that their join needs no exchange."""
    t = load_tables(spark, d)
    left = stage_bucketed(t["orders"].selectExpr("o_orderkey AS k", "o_custkey"), "staged_orders", ["k"], 8, scratch_path(spark, "buckets"))
    right = stage_bucketed(t["lineitem"].selectExpr("l_orderkey AS k", "l_partkey"), "staged_lines", ["k"], 8, scratch_path(spark, "buckets"))
    return left.hint("merge").join(right, "k")


# supporting operators

_BY = "OVER (PARTITION BY o_custkey ORDER BY o_orderkey)"
_ALL = "OVER (PARTITION BY o_custkey ORDER BY o_orderkey ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING)"


def _orders(s: SparkSession, d: str) -> DataFrame:
    return load_tables(s, d, ("orders",))["orders"].select("o_custkey", "o_orderkey")


register("op_window_shares", f"SELECT o_custkey, o_orderkey, CAST(ntile(4) {_BY} AS INT) AS tile, percent_rank() {_BY} AS relative, cume_dist() {_BY} AS share FROM orders")(lambda s, d: O.window_shares(_orders(s, d), ["o_custkey"], [F.col("o_orderkey")]))
register("op_window_ends", f"SELECT o_custkey, o_orderkey, first_value(o_orderkey) {_ALL} AS first_value, last_value(o_orderkey) {_ALL} AS last_value, nth_value(o_orderkey, 2) {_ALL} AS nth_value FROM orders")(lambda s, d: O.window_ends(_orders(s, d), ["o_custkey"], [F.col("o_orderkey")], "o_orderkey"))
register("op_lateral_join", "SELECT c_custkey, (SELECT count(*) FROM orders WHERE o_custkey = c_custkey) AS n_orders FROM customer")(
    lambda s, d: O.lateral_join((t := load_tables(s, d))["customer"].select("c_custkey"), lambda outer: t["orders"].where(F.col("o_custkey") == outer("c_custkey")).select(F.count("*").alias("n_orders")))
)
register("op_exists", "SELECT c_custkey FROM customer WHERE EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey AND o_orderstatus = 'F')")(
    lambda s, d: O.exists_in((t := load_tables(s, d))["customer"].select("c_custkey"), t["orders"].where("o_orderstatus = 'F'"), "c_custkey", "o_custkey")
)
register("op_scalar_subquery", "SELECT o_custkey, o_orderkey FROM orders WHERE o_orderkey > (SELECT avg(o_orderkey) FROM orders)")(lambda s, d: O.above_scalar(_orders(s, d), "o_orderkey", F.avg("o_orderkey")))
register("op_sketch_distinct", "SELECT count(DISTINCT l_partkey) AS exact, TRUE AS within_three_deviations FROM lineitem")(
    lambda s, d: (line := load_tables(s, d, ("lineitem",))["lineitem"]).agg(F.count_distinct("l_partkey").alias("exact")).crossJoin(O.merge_sketches(O.sketch_distinct(line, ["l_returnflag"], "l_partkey"))).select("exact", (F.abs(F.col("estimate") - F.col("exact")) <= 3 * 0.0163 * F.col("exact")).alias("within_three_deviations"))
)
register("op_heavy_keys_sketched", ORACLES["op_heavy_keys"])(lambda s, d: P.heavy_keys_sketched(load_tables(s, d, ("embeddings",))["embeddings"], ["label"], 0.1))
