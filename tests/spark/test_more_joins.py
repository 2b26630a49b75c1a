"""Plans, guards, streams of several batches and studies, on small tables."""

import itertools
import random

import pytest
from test_joins import con, pair, rows, test_against_duckdb  # noqa: F401

from pyspark.sql import functions as F

from roundjoin import fixtures, scratch, studies, workloads
from roundjoin import streaming as ST
from roundjoin.operators import baselines as B
from roundjoin.operators import primitives as P
from roundjoin.operators import reducer as R
from roundjoin.operators import relational as O
from roundjoin.operators import statistics as S
from roundjoin.operators.decomposition import BagTooLarge, decomposition_join, materialize_bags
from roundjoin.plans.bagtree import BagTree
from roundjoin.plans.cost import CostLedger
from roundjoin.plans.hypergraph import Hypergraph, find_bag_tree
from roundjoin.plans.query import Atom, JoinQuery

NEW = (
    "ledger_star4 max_cell_load op_approx_distinct five_bag_trace chain16_by_threes tree_measures bag_tree_rows explain_rounds_chain3 rounds_by_length table2_star predicted_tables model_measures "
    "dangling_share sizes_tri6 grid_cell_load matching_columns matching_star_hub matching_hub_semijoin matching_path_hub matching_rounds join_auto_cycle4 join_auto_five_rel join_tri6_contraction join_chain6_hub "
    "as_sql_tri6 as_sql_chain6 atom_statistics bucketed_join op_window_shares op_window_ends op_lateral_join op_exists op_scalar_subquery op_sketch_distinct op_heavy_keys_sketched tri12_decomp tri12_logdepth tri12_contraction"
).split()


@pytest.mark.parametrize("name", NEW)
def test_new_queries_against_duckdb(spark, small, con, name):  # noqa: F811
    test_against_duckdb(spark, small, con, name)


def test_every_query_but_a_few_has_an_oracle():
    assert set(workloads.QUERIES) == set(workloads.ORACLES)


def test_random_acyclic_and_cyclic_joins(spark):
    rng = random.Random(31)
    shapes = ("R(a,b), S(b,c), T(b,d), U(d,e)", "R(a,b), S(b,c), T(c,a)", "R(a,b,c), S(b,d), T(c,e), U(e,f), V(e,g)", "R(a,b), S(b,c), T(c,d), U(d,a), V(d,e)", "R(a), S(a,b), T(b)")
    for shape in shapes:
        text = JoinQuery.parse(shape)
        data = {a.name: pair(spark, [tuple(rng.choice((None, 1, 2, 3, 4)) for _ in a.attrs) for _ in range(14)], ", ".join(f"{c} int" for c in a.attrs)) for a in text.atoms}
        q = JoinQuery.parse(shape, data)
        want = rows(B.native_join(q))
        tree = find_bag_tree(h := Hypergraph.from_query(q)).make_complete(h)
        assert rows(decomposition_join(q)) == rows(decomposition_join(q, ledger=CostLedger())) == want
        assert rows(B.contraction_join(q)) == rows(S.join(q)) == rows(S.join(q, "log_depth")) == want
        assert rows(studies.run_as_sql(spark, q)) == want
        full, whole = R.full_reduce(tree, materialize_bags(tree, q.bound(), R.Runner(q.shared)), R.Runner(q.shared)), decomposition_join(q)
        for b, d in full.items():
            assert rows(d.distinct()) == rows(whole.select(*d.columns).distinct())
        reduced = B.contraction_reduce(q)
        for a in q.atoms:
            assert rows(reduced[a.name]) == rows(whole.select(*a.attrs).distinct())


def test_product_bags_are_bounded(spark):
    x, y = pair(spark, [(i, i) for i in range(40)], "a long, b long"), pair(spark, [(i, i) for i in range(40)], "c long, d long")
    q = JoinQuery([Atom.of("X", x), Atom.of("Y", y), Atom.of("Z", x.toDF("b", "c"))])
    tree = BagTree({"p": frozenset("abcd")}, {"p": frozenset("XY")}, {"p": None}).make_complete(Hypergraph.from_query(q))
    assert decomposition_join(q, tree).count() == 40
    with pytest.raises(BagTooLarge):
        decomposition_join(q, tree, max_bag_rows=1000)


def test_grid_joins_refuse_what_chance_does_not_explain(spark):
    same, other = pair(spark, [(1, 2)] * 500, "k int, x int"), pair(spark, [(1, i) for i in range(100)], "k int, y int")
    with pytest.raises(P.ReducerOverflow):
        P.grid_join([same, other], m=50)
    loads = []
    assert P.grid_join([other, other.toDF("k", "z")], m=50, loads=loads).count() == 10_000 and 0 < loads[0] <= P.overflow_bound(50, [4, 4])
    ledger = CostLedger()
    q = JoinQuery([Atom.of("R", other), Atom.of("S", other.toDF("k", "z"))])
    assert decomposition_join(q, m=50, physical="grid", ledger=ledger).count() == 10_000 and ledger.max_load() > 0


def test_statistics(spark, small):
    q = fixtures.fixture(spark, small, "cycle_4")
    stats = S.Stats.of(q)
    assert stats.rows["Orders"] == 1500 and abs(stats.values["Customer"]["nat"] - 25) <= 3
    assert stats.join_rows(["Orders"]) == 1500 and stats.join_rows(["Customer", "Orders"]) == pytest.approx(1500, rel=0.2)
    with pytest.raises(ValueError):
        S.join(q, "no such")


def test_paths_in_event_time(spark, tmp_path):
    minute = lambda m: f"2024-01-01 {10 + m // 60:02d}:{m % 60:02d}:00"
    batches = [[(1, 1, minute(0)), (1, 3, minute(20)), (2, 50, minute(5))], [(1, 2, minute(10)), (1, 4, minute(200))], [(1, 99, minute(-500)), (1, 5, minute(210)), (2, 51, minute(200))], [(1, 6, minute(400)), (2, 52, minute(401))], [(3, 7, minute(600))]]
    for i, b in enumerate(batches):
        spark.createDataFrame(b, "k long, e long, ts string").selectExpr("k", "e", "CAST(ts AS TIMESTAMP) AS ts").coalesce(1).write.parquet(str(tmp_path / f"in/{i}"))
    stream = spark.readStream.schema("k long, e long, ts timestamp").option("maxFilesPerTrigger", 1).option("recursiveFileLookup", True).parquet(str(tmp_path / "in"))
    query = ST.stream_paths(stream, "k", "e", "ts", 3, "1 hour").writeStream.format("parquet").option("path", str(tmp_path / "out")).option("checkpointLocation", str(tmp_path / "state")).trigger(availableNow=True).start()
    query.awaitTermination()
    got = rows(spark.read.parquet(str(tmp_path / "out")))
    # event 2 comes a batch late but in time, event 99 beyond the watermark; 6 and 52 wait for a watermark that 7 brings
    assert got == sorted([("1", str(list(p))) for p in ((1, 2, 3), (2, 3, 4), (3, 4, 5), (4, 5, 6))] + [("2", str([50, 51, 52]))])
    assert sum(s["numRowsDroppedByWatermark"] for p in query.recentProgress for s in p["stateOperators"]) == 1


def test_asof_join_in_buckets(spark):
    rng = random.Random(3)
    left = pair(spark, [(rng.randint(0, 2), rng.randint(0, 400), i) for i in range(120)], "k int, t int, id int")
    right = pair(spark, [(k, t, 1000 * k + t) for k, t in {(rng.randint(0, 2), rng.randint(0, 400)) for _ in range(50)}], "k int, t int, v int")
    want = rows(O.asof_join(left, right, "t", ["k"], "v"))
    for width in (1, 7, 1000):
        assert rows(O.asof_join(left, right, "t", ["k"], "v", width)) == want


def test_scratch_tables_go(spark):
    df = scratch.cut(spark.range(5))
    assert df.count() == 5 and scratch.clean(spark) > 0
    with pytest.raises(Exception, match="PATH_NOT_FOUND|does not exist|FileNotFound|not found"):
        spark.read.parquet(scratch.shared_dir(spark) + "/roundjoin-gone").count()


def test_shares_by_exchange():
    q = JoinQuery.parse(", ".join(f"R{i}(a{i},a{i + 1})" for i in range(14)))
    sizes = {a.name: 10 ** (3 + i % 3) for i, a in enumerate(q.atoms)}
    shares = B.best_shares(q, sizes, 64)
    total = 1
    for s in shares.values():
        total *= s
    assert total == 64 and set(shares) == q.shared
    few = JoinQuery.parse("R(a,b), S(b,c), T(c,a)")
    best = B.best_shares(few, {"R": 100, "S": 100, "T": 100}, 64)
    assert best == {"a": 4, "b": 4, "c": 4}
    for split in itertools.product((1, 2, 4, 8, 16), repeat=3):
        if split[0] * split[1] * split[2] == 64:
            assert B.share_sent(few, {"R": 100, "S": 100, "T": 100}, best) <= B.share_sent(few, {"R": 100, "S": 100, "T": 100}, dict(zip("abc", split, strict=True)))


def batches_of(spark, path, batches, schema="k long, e long, ts string"):
    """A stream that reads each of the given lists of rows in a micro-batch of its own."""
    for i, b in enumerate(batches):
        spark.createDataFrame(b, schema).withColumn("ts", F.col("ts").cast("timestamp")).coalesce(1).write.parquet(f"{path}/{i}")
    return spark.readStream.schema(schema.replace("ts string", "ts timestamp")).option("maxFilesPerTrigger", 1).option("recursiveFileLookup", True).parquet(str(path))


def drained(spark, stream, path):
    query = stream.writeStream.format("parquet").option("path", f"{path}/out").option("checkpointLocation", f"{path}/state").trigger(availableNow=True).start()
    query.awaitTermination()
    dropped = sum(s["numRowsDroppedByWatermark"] for p in query.recentProgress for s in p["stateOperators"])
    return spark.read.schema(stream.schema).parquet(f"{path}/out"), dropped


def at(minutes):
    return f"2024-01-{1 + minutes // 1440:02d} {minutes // 60 % 24:02d}:{minutes % 60:02d}:00"


LATE = [[(1, 1, at(600)), (1, 2, at(610)), (2, 3, at(615))], [(1, 1, at(605)), (1, 4, at(650)), (2, 5, at(800))], [(1, 6, at(100)), (2, 7, at(790)), (1, 8, at(1200))], [(3, 9, at(1500))]]


def test_windows_over_several_batches(spark, tmp_path):
    for kind, size in (("tumbling", 60), ("session", None)):
        stream = batches_of(spark, tmp_path / kind / "in", LATE)
        out, dropped = drained(spark, ST.stream_windows(stream, "ts", ["k"], kind), tmp_path / kind)
        got = sorted((r.start.strftime("%H:%M"), r.k, r.n) for r in out.collect())
        if kind == "tumbling":  # row 6 is a whole batch behind the watermark, row 1 again and row 7 are late but in time; the window of row 9 stays open
            assert got == [("10:00", 1, 4), ("10:00", 2, 1), ("13:00", 2, 2), ("20:00", 1, 1)] and dropped == 1
        else:
            assert ("10:00", 1, 3) in got and ("10:50", 1, 1) in got and ("13:10", 2, 2) in got and dropped == 1


def test_distinct_and_interval_join_over_several_batches(spark, tmp_path):
    out, _ = drained(spark, ST.stream_distinct(batches_of(spark, tmp_path / "d/in", LATE), "ts", ["e"]), tmp_path / "d")
    found = [r.e for r in out.collect()]
    assert sorted(found) == sorted(set(found)) and set(found) == {1, 2, 3, 4, 5, 7, 8, 9}
    a = batches_of(spark, tmp_path / "a", [[(1, 1, at(600))], [(1, 2, at(700)), (2, 3, at(705))]]).selectExpr("k AS k1", "e AS e1", "ts AS t1")
    b = batches_of(spark, tmp_path / "b", [[(1, 10, at(605))], [(1, 11, at(609)), (1, 12, at(711)), (2, 13, at(705))]]).selectExpr("k AS k2", "e AS e2", "ts AS t2")
    out, _ = drained(spark, ST.stream_interval_join(a, b, "t1", "t2", "k1", "k2"), tmp_path / "j")
    assert sorted((r.e1, r.e2) for r in out.collect()) == [(1, 10), (1, 11), (3, 13)]


def test_batches_join_one_by_one(spark, tmp_path):
    stream = batches_of(spark, tmp_path / "in", LATE).select("k", "e")
    q = JoinQuery([Atom.of("Hub", spark.createDataFrame([], "k long, e long")), Atom.of("Arm", pair(spark, [(1, "x"), (2, "y")], "k long, v string"))])
    ST.stream_batches(stream, q, "Hub", str(tmp_path / "out"), str(tmp_path / "state")).awaitTermination()
    got = rows(spark.read.parquet(str(tmp_path / "out")).select("e", "k", "v"))
    assert got == sorted((str(e), str(k), "x" if k == 1 else "y") for b in LATE for k, e, _ in b if k < 3)
