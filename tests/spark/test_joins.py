"""Joins, primitives and operators on the small tables, held against DuckDB and against each other."""

import decimal

import duckdb
import pytest

from roundjoin import fixtures, workloads
from roundjoin.operators import primitives as P
from roundjoin.operators import reducer as R
from roundjoin.operators.decomposition import BagTooLarge, decomposition_join, expand_multiset
from roundjoin.plans.cost import CostLedger
from roundjoin.plans.hypergraph import Hypergraph, find_bag_tree
from roundjoin.plans.query import Atom, JoinQuery
from roundjoin.plans.rewrite import log_depth_rewrite
from roundjoin.sources import TABLES, read_source, write_sink

CHECKED = "stream_paths stream_batches stream_windows_tumbling stream_windows_sliding stream_windows_session star4_parallel star4_serial star4_hub star4_share tri6_decomp cycle4_decomp five_rel_decomp conv_chain_parallel disconnected_decomp bag_multiplicity null_keys semijoin_grid staged_distinct hybrid_join grid_join_3 count_join_tri6 aggregate_join_star4 op_cube op_asof_join op_range_join op_topk tree_stats logdepth_trace_tri21".split()


def norm(v):
    if isinstance(v, decimal.Decimal):
        return str(v.normalize())
    return str(list(v)) if isinstance(v, (list, tuple)) else str(v)


def rows(df):
    cols = sorted(df.columns)
    return sorted(tuple(norm(r[c]) for c in cols) for r in df.collect())


@pytest.fixture(scope="module")
def con():
    c = duckdb.connect()
    for t in TABLES:
        c.execute(f"CREATE VIEW {t} AS SELECT * FROM '/root/testdata/sf0.001/{t}.parquet'")
    return c


@pytest.mark.parametrize("name", CHECKED)
def test_against_duckdb(spark, small, con, name):
    df = workloads.QUERIES[name](spark, small)
    c = con.execute(workloads.ORACLES[name])
    names = [x[0] for x in c.description]
    order = [names.index(k) for k in sorted(names)]
    assert sorted(df.columns) == sorted(names)
    assert rows(df) == sorted(tuple(norm(r[i]) for i in order) for r in c.fetchall())


@pytest.mark.parametrize("how", ("left", "right", "full"))
def test_outer_joins_of_whole_tables(spark, small, con, how):
    test_against_duckdb(spark, small, con, f"op_join_whole_{how}")
    got = workloads.QUERIES[f"op_join_whole_{how}"](spark, small).collect()
    orders, customers = (con.execute(f"SELECT count(*) FROM {t}").fetchone()[0] for t in ("orders", "customer"))
    unmatched_orders, unmatched_customers = sum(r.c is None for r in got), sum(r.o is None for r in got)
    assert how == "right" or len(got) - unmatched_customers == orders and unmatched_orders > 0
    assert how == "left" or len({r.k for r in got if r.c is not None}) == customers and unmatched_customers > 0


def pair(spark, data, cols):
    return spark.createDataFrame(data, cols)


def test_edge_cases(spark):
    r, s = pair(spark, [(1, 10), (2, 20), (None, 30)], "a int, b long"), pair(spark, [(1, 7), (1, 8), (3, 9)], "a long, c int")
    q = JoinQuery([Atom.of("R", r), Atom.of("S", s)])
    assert rows(decomposition_join(q)) == [("1", "10", "7"), ("1", "10", "8")]
    empty = JoinQuery([Atom.of("R", r.where("false")), Atom.of("S", s)])
    assert rows(decomposition_join(empty)) == []
    single = JoinQuery([Atom.of("R", r)])
    assert len(rows(decomposition_join(single))) == 3
    twice = JoinQuery([Atom.of("R", r.union(r)), Atom.of("S", s)])
    bag = decomposition_join(twice, bag=True)
    assert sorted(x["__mult"] for x in bag.collect()) == [2, 2] and expand_multiset(bag).count() == 4


def test_all_methods_agree(spark):
    ring = [(i, (i + 1) % 6) for i in range(6)]
    base = pair(spark, ring, "a long, b long")
    q = fixtures._chain(base, 5)
    h = Hypergraph.from_query(q)
    tree = find_bag_tree(h)
    want = rows(workloads.METHODS["native"](q))
    assert len(want) == 6
    for t in (tree, tree.reroot("center"), log_depth_rewrite(tree, h, guard=False).tree):
        assert rows(decomposition_join(q, t)) == want
    assert rows(decomposition_join(q, tree, m=4, physical="grid")) == want


def test_grid_and_capacity(spark):
    r, s = pair(spark, [(1, i) for i in range(30)], "k int, x int"), pair(spark, [(1, i) for i in range(20)], "k int, y int")
    for m in (1000, 20, 8):
        assert P.grid_join([r, s], m).count() == 600
    with pytest.raises(P.ReducerOverflow):
        P.grid_join([r, s], m=10, groups=[1, 1], check=True)


def test_full_reduction_bounds_intermediates(spark):
    r, s, t = pair(spark, [(i, i % 3) for i in range(30)], "a long, b long"), pair(spark, [(i, i) for i in range(9)], "b long, c long"), pair(spark, [(2, 5)], "c long, d long")
    q = JoinQuery([Atom.of("R", r), Atom.of("S", s), Atom.of("T", t)])
    ledger = CostLedger(machine=10)
    out = decomposition_join(q, ledger=ledger)
    n = out.count()
    assert n == 10 and max(e[4] for e in ledger.entries if e[1].startswith("join")) <= n
    assert ledger.rounds() > 0 and ledger.machines() >= 1
    reduced = R.full_reduce(find_bag_tree(Hypergraph.from_query(q)), q.bound(), R.Runner(q.shared))
    assert {k: d.count() for k, d in reduced.items()} == {"R": 10, "S": 1, "T": 1}


def test_guards(spark):
    x, y = pair(spark, [(i, i) for i in range(5)], "a long, b long"), pair(spark, [(i, i) for i in range(5)], "c long, d long")
    q = JoinQuery([Atom.of("X", x), Atom.of("Y", y)])
    assert decomposition_join(q).count() == 25
    with pytest.raises(ValueError):
        JoinQuery([Atom.of("X", x.selectExpr("CAST(a AS DOUBLE) AS k")), Atom.of("Y", y.selectExpr("CAST(c AS DOUBLE) AS k"))]).bound()
    assert issubclass(BagTooLarge, RuntimeError)


def test_sources_round_trip(spark, small, tmp_path):
    nation = spark.read.parquet(f"{small}/nation.parquet")
    for fmt in ("parquet", "json", "orc", "csv"):
        path = write_sink(nation, str(tmp_path / fmt), fmt)
        assert rows(read_source(spark, path, fmt, nation.schema)) == rows(nation)
