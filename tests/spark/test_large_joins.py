"""Joins whose size made them fail: what their plans copy, gather and keep."""

import pytest

from roundjoin.operators import baselines as B
from roundjoin.operators import primitives as P
from roundjoin.plans.query import Atom, JoinQuery


def plan(df) -> str:
    return df._jdf.queryExecution().executedPlan().toString()


@pytest.fixture()
def keyed(spark):
    """Two relations that share a key, each of 20,000 rows."""
    return [spark.range(20_000).toDF("k").selectExpr("k", f"k * {i} AS {c}") for i, c in ((2, "x"), (3, "y"))]


def test_share_join_gathers_no_copies_on_the_driver(keyed):
    l, r = keyed
    got = B.one_round_share_join(JoinQuery([Atom.of("R", l), Atom.of("S", r), Atom.of("T", l.selectExpr("x", "x AS z"))]), 16)
    assert "Broadcast" not in plan(got)
    assert got.count() == 20_000


def test_grid_join_copies_to_cells_with_partners_only(keyed):
    # 4,000 groups each: copies to whole axes would be 160 million rows
    got = P.grid_join(keyed, m=10)
    assert "Broadcast" not in plan(got) and "Generate" not in plan(got)
    assert got.where("x * 3 = y * 2").count() == 20_000


def test_grid_join_of_a_hot_key_on_long_axes(spark):
    hot = [spark.range(300).selectExpr("IF(id < 200, 0, id) AS k", f"id AS {c}") for c in "xy"]
    assert P.grid_join(hot, m=20).count() == 200 * 200 + 100


@pytest.mark.parametrize("scale", (6, 60))
def test_auto_does_not_choose_to_copy_large_tables(scale):
    from roundjoin.plans.hypergraph import Hypergraph
    from roundjoin.plans.planner import choose

    star = Hypergraph({"Hub": frozenset("ops"), "Orders": frozenset(("o", "cust")), "Part": frozenset(("p", "brand")), "Supp": frozenset(("s", "nat"))})
    rows = {"Hub": 600_000 * scale, "Orders": 150_000 * scale, "Part": 20_000 * scale, "Supp": 1_000 * scale}
    assert choose(star, rows, 690_000 * scale, distinct={"o": 150_000 * scale, "p": 20_000 * scale, "s": 1_000 * scale}).method == "native"


def test_auto_gathers_no_large_relation_on_the_driver(spark, tmp_path):
    from roundjoin.operators.statistics import join

    # few bytes of files, but 60,000 rows
    spark.range(60_000).selectExpr("id AS k", "id AS x").coalesce(1).write.parquet(f"{tmp_path}/r")
    spark.range(60_000).selectExpr("id AS x", "id % 5 AS y").coalesce(1).write.parquet(f"{tmp_path}/s")
    r, s = (Atom.of(n, spark.read.parquet(f"{tmp_path}/{n}"), key=(k,)) for n, k in (("r", "k"), ("s", "x")))
    t = Atom.of("t", spark.range(5).selectExpr("id AS y", "id AS z"), key=("y",))
    for atoms, broadcasts in (([r, s], 0), ([r, s, t], 1)):
        got = join(JoinQuery(atoms), "native")
        assert plan(got).count("BroadcastHashJoin") == broadcasts
        assert got.count() == 60_000


def test_interval_join_rounds_to_seconds_as_its_sql_does(spark, tmp_path):
    import duckdb

    from roundjoin import workloads
    from roundjoin.sources import TABLES

    gaps = "(VALUES (1, '00:00:00.6'), (2, '01:00:00.7'), (3, '01:00:00.4'), (4, '01:00:01.5'), (5, '00:00:00.5'), (6, '00:00:01.4'), (7, '01:00:01.4999'), (8, '00:00:02.5')) t(event_id, clock)"
    duckdb.sql(f"COPY (SELECT event_id::BIGINT AS event_id, ('2024-01-01 ' || clock)::TIMESTAMP AS ts, 7::BIGINT AS user_id, 'view' AS event_type FROM {gaps}) TO '{tmp_path}/events.parquet' (FORMAT parquet)")
    for t in TABLES:
        if t != "events":
            (tmp_path / f"{t}.parquet").symlink_to(f"/root/testdata/sf0.001/{t}.parquet")
    con = duckdb.connect()
    con.execute(f"CREATE VIEW events AS FROM '{tmp_path}/events.parquet'")
    want = sorted(con.execute(workloads.ORACLES["op_interval_join"]).fetchall())
    assert sorted(map(tuple, workloads.QUERIES["op_interval_join"](spark, str(tmp_path)).collect())) == want


@pytest.mark.parametrize("name", "bag_tree_rows chain16_by_threes chain16_schedule example_e_rounds explain_rounds_chain3 five_bag_trace logdepth_trace_tri21 matching_rounds model_measures one_round_lower_bound".split())
def test_studies_follow_the_tables(spark, name):
    import duckdb

    from roundjoin import studies, workloads  # noqa: F401
    from roundjoin.sources import TABLES

    found = []
    for d in ("/root/testdata/sf0.001", "/root/testdata/sf0.01"):
        con = duckdb.connect()
        for t in TABLES:
            con.execute(f"CREATE VIEW {t} AS SELECT * FROM '{d}/{t}.parquet'")
        df = workloads.QUERIES[name](spark, d)
        got = sorted(map(repr, map(tuple, df.collect())))
        assert got == sorted(map(repr, con.execute(f"SELECT {', '.join(df.columns)} FROM ({workloads.ORACLES[name]})").fetchall()))
        found.append(got)
    assert found[0] != found[1]


def test_grid_plans_write_each_result(spark, small):
    from roundjoin import workloads

    got = workloads.QUERIES["star4_grid"](spark, small)
    assert plan(got).count("FileScan") == 1
    assert got.count() == workloads.QUERIES["star4_native"](spark, small).count()


def test_ledgers_gather_no_large_relation_on_the_driver(spark, tmp_path):
    from roundjoin.operators.decomposition import decomposition_join
    from roundjoin.plans.cost import CostLedger

    # kept compressed: 200,000 rows of values that repeat take less than Spark broadcasts
    r = Atom.of("R", spark.range(200_000).selectExpr("id AS k", "id % 7 AS x"))
    s = Atom.of("S", spark.range(200_000).selectExpr("id AS k", "id % 5 AS y"))
    t = Atom.of("T", spark.range(5).selectExpr("id AS y", "id AS z"))
    ledger = CostLedger()
    got = decomposition_join(JoinQuery([r, s, t]), ledger=ledger)
    assert got.count() == 200_000
    joins = [line for line in plan(got).splitlines() if "BroadcastHashJoin" in line or "SortMergeJoin" in line]
    assert any("SortMergeJoin [k" in line for line in joins) and not any("BroadcastHashJoin [k" in line for line in joins)
    ledger.release()


def test_written_ledgers_nest_no_plans(spark):
    from pathlib import Path

    from roundjoin.plans.cost import CostLedger

    hub = Atom.of("Hub", spark.range(500).selectExpr("id AS k", "id % 7 AS x", "id % 5 AS y", "IF(id % 3 = 0, NULL, id) AS z"))
    arms = [Atom.of(c.upper(), spark.range(7).selectExpr(f"id AS {c}", f"id * 2 AS of_{c}"), key=(c,)) for c in "xy"]
    q, ledger = JoinQuery([hub, *arms]), CostLedger(written=True)
    got = B.contraction_join(q, ledger=ledger)
    # a plan is that of one operation on tables, of which those not in use any more are gone
    assert "InMemoryTableScan" not in plan(got) and got.count() == 500
    tables = [Path(path.removeprefix("file:")) for _, _, path in ledger.kept]
    assert 0 < len(tables) < len(ledger.entries) and all(t.exists() for t in tables)
    ledger.release()
    assert not ledger.kept and not any(t.exists() for t in tables)


def test_study_runs_the_share_join_once(spark, small, monkeypatch):
    from roundjoin import fixtures, studies
    from roundjoin.plans.cost import CostLedger

    runs, plain = [], B.one_round_share_join

    def counted(*args):
        df = plain(*args)
        monkeypatch.setattr(df, "count", lambda count=df.count: runs.append(1) or count())
        return df

    monkeypatch.setattr(B, "one_round_share_join", counted)
    q = fixtures.fixture(spark, small, "star_4")
    got = studies._ledgers(q, {"share": lambda x: studies._shared(q, x)})
    assert len(runs) == 1 and got["share"][3] == plain(q).count()


def test_star4_share_broadcasts_nothing(spark, small):
    from roundjoin import workloads

    got = workloads.QUERIES["star4_share"](spark, small)
    assert "Broadcast" not in plan(got)
    assert got.count() == workloads.QUERIES["star4_native"](spark, small).count()


def test_share_join_sends_each_relation_once(spark, small):
    from roundjoin import workloads

    q = JoinQuery([Atom.of(n, spark.range(2_000).selectExpr(f"id % {i} AS {a}", f"id AS {b}"), key=(b,)) for n, i, a, b in (("R", 40, "x", "y"), ("S", 50, "y", "z"), ("T", 60, "z", "x"))])
    got = B.one_round_share_join(q, 16)
    want = q.bound()
    assert plan(got).count("Exchange") == 3 and got.rdd.getNumPartitions() == 16
    assert sorted(got.collect()) == sorted(want["R"].join(want["S"], "y").join(want["T"], ["z", "x"]).select("x", "y", "z").collect())
    # the hub's duplicates are removed before: one exchange more than relations
    assert plan(workloads.QUERIES["star4_share"](spark, small)).count("Exchange") == 5


def test_grid_semijoin_copies_to_cells_with_partners_only(keyed):
    l, r = keyed
    got = P.semijoin(l, r.where("k % 2 = 0"), m=40, physical="grid")
    # 1,000 groups and 500: copies to whole axes would be 20 million rows
    assert "Generate" not in plan(got) and got.count() == 10_000


def test_grid_semijoin_reads_its_partners_group_from_the_tuple(spark, keyed):
    l, r = keyed
    l = l.union(l.where("k < 100")).union(spark.sql("SELECT CAST(NULL AS BIGINT), 1L"))
    got = P.semijoin(l, r.where("k % 2 = 0"), m=40, physical="grid")
    # one join finds the groups of the keys' partners, one is that of the cells
    assert plan(got).count("SortMergeJoin") == 2
    assert sorted(got.collect()) == sorted(l.where("k % 2 = 0").distinct().collect())
    # an int and a long of one value have different hashes, so their groups are looked up
    narrow = r.selectExpr("CAST(k AS INT) AS k").where("k % 2 = 0")
    assert sorted(P.semijoin(l, narrow, m=40, physical="grid").collect()) == sorted(got.collect())
    # and so may equal texts of a collation
    upper, lower = (spark.range(400).selectExpr(f"{f}('k' || id) COLLATE UTF8_LCASE AS k") for f in ("upper", "lower"))
    assert P.semijoin(upper, lower, m=40, physical="grid").count() == 400


def test_grid_join_deals_by_keys_that_partners_hold(spark):
    # r's key is k, so a tuple of either side tells its partner's group, and only the cells are joined
    r, s = spark.range(20_000).selectExpr("id AS k", "id * 2 AS x"), spark.range(20_000).selectExpr("id AS k", "id * 3 AS y")
    got = P.grid_join([r, s], m=40, keys=[frozenset("k"), frozenset("k")])
    assert plan(got).count("SortMergeJoin") == 1 and got.where("x * 3 = y * 2").count() == 20_000
    # a many to one join: the group of each of s's tuples is looked up
    s = s.selectExpr("k % 100 AS k", "y")
    got = P.grid_join([r, s], m=40, keys=[frozenset("k"), frozenset("ky")])
    assert plan(got).count("SortMergeJoin") == 2 and sorted(got.collect()) == sorted(r.join(s, "k").collect())


def test_grid_semijoin_of_a_set_runs_no_stages(spark):
    from roundjoin.operators.reducer import Runner

    s, r = spark.range(2_000).selectExpr("id AS x", "id % 50 AS k"), spark.range(0, 100, 2).selectExpr("id AS k")
    got = Runner(frozenset("k"), 40, "grid").semi(s, r)
    assert plan(got).count("Exchange") < plan(P.semijoin(s, r, 40, "grid")).count("Exchange")
    assert sorted(got.collect()) == sorted(s.where("k % 2 = 0").collect())


def test_written_rounds_leave_no_shuffle_files(spark):
    import time

    def files():
        return {f for f in map(str, spark._jvm.org.apache.spark.SparkEnv.get().blockManager().diskBlockManager().getAllFiles().mkString("\n").splitlines()) if "shuffle_" in f}

    before = files()
    wide = spark.range(5_000).selectExpr("id % 977 AS k").groupBy("k").count()
    assert P.barrier({"t": wide}, "parquet")["t"].columns == ["k", "count"] and P.counts([wide]) == [977]
    end = time.time() + 10
    while files() - before and time.time() < end:
        time.sleep(0.2)
    assert not files() - before
    assert spark.conf.get("spark.sql.classic.shuffleDependency.fileCleanup.enabled") == "false"


def test_written_ledgers_write_nothing_twice(spark):
    from pathlib import Path

    from roundjoin.operators.decomposition import decomposition_join
    from roundjoin.plans.cost import CostLedger

    hub = Atom.of("Hub", spark.range(500).selectExpr("id AS k", "id % 7 AS x", "id % 5 AS y", "IF(id % 3 = 0, NULL, id) AS z"))
    some = lambda n: [Atom.of(c.upper(), spark.range(n).selectExpr(f"id AS {c}", f"id * 2 AS of_{c}"), key=(c,)) for c in "xy"]
    for method in (B.contraction_join, decomposition_join):
        kept = []
        # with seven of each every tuple of the hub has one partner an arm; with three most have none
        for q in (JoinQuery([hub, *some(7)]), JoinQuery([hub, *some(3)])):
            ledger, plain = CostLedger(written=True), CostLedger()
            made, keep = [], ledger.keep
            ledger.keep = lambda df, keep=keep, made=made: made.append(df) or keep(df)
            want = sorted(map(repr, method(q).collect()))
            assert sorted(map(repr, method(q, ledger=ledger).collect())) == want
            method(q, ledger=plain).count()
            # the figures are those of a ledger that keeps each result
            assert ledger.entries == plain.entries
            ledger.release(), plain.release()
            kept.append(len(made))
        # the hub, and the arm that loses tuples of which the hub has no partner; else results too
        assert kept[0] == 2 < kept[1]


def test_triangles_are_made_once_for_all_methods(spark, small, monkeypatch):
    from roundjoin import studies, workloads

    seen = []
    monkeypatch.setattr(studies, "_ledgers", lambda q, methods: seen.append(q))
    monkeypatch.setattr(studies, "_compared", lambda spark, got: None)
    workloads.QUERIES["table3_triangles"](spark, small)
    assert len(seen[0].atoms) == 12 and not any("Exchange" in plan(d) for d in seen[0].bound().values())
