"""The workloads' queries on the given tables, as joins and as DuckDB text."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .plans.query import Atom, JoinQuery
from .sources import load_tables

#: name -> [(atom, SELECT of it), ...]: the DuckDB side of each fixture.
SQL: dict[str, list[tuple[str, str]]] = {}


def _line(t) -> DataFrame:
    return t["lineitem"]


_RING = "SELECT n_nationkey AS a, coalesce(lead(n_nationkey) OVER w, first_value(n_nationkey) OVER w) AS b FROM nation WINDOW w AS (PARTITION BY n_regionkey ORDER BY n_nationkey)"
_EDGE = "SELECT a, b FROM (SELECT event_id AS a, lead(event_id) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS b, user_id FROM events) WHERE b IS NOT NULL"
_EDGE7 = _EDGE + " AND user_id = 7"


def ring(t: dict[str, DataFrame]) -> DataFrame:
    """Next nation of the same region, the last one's next being the first."""
    w = Window.partitionBy("n_regionkey").orderBy("n_nationkey")
    first = F.first("n_nationkey").over(w.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing))
    return t["nation"].select(F.col("n_nationkey").alias("a"), F.coalesce(F.lead("n_nationkey").over(w), first).alias("b"))


def edges(t: dict[str, DataFrame], user: int | None = None) -> DataFrame:
    """Each event with the next one of its user."""
    e = t["events"] if user is None else t["events"].where(F.col("user_id") == user)
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    return e.select(F.col("event_id").alias("a"), F.lead("event_id").over(w).alias("b")).where("b IS NOT NULL")


def _q(*atoms: tuple[str, DataFrame, dict[str, str]], keys: dict[str, tuple[str, ...]] | None = None) -> JoinQuery:
    return JoinQuery([Atom.of(n, df, cols, (keys or {}).get(n)) for n, df, cols in atoms])


def star_4(t) -> JoinQuery:
    return _q(("Hub", _line(t), {"o": "l_orderkey", "p": "l_partkey", "s": "l_suppkey"}), ("Orders", t["orders"], {"o": "o_orderkey", "cust": "o_custkey"}), ("Part", t["part"], {"p": "p_partkey", "brand": "p_brand"}), ("Supp", t["supplier"], {"s": "s_suppkey", "nat": "s_nationkey"}), keys={"Orders": ("o",), "Part": ("p",), "Supp": ("s",)})


SQL["star_4"] = [("Hub", "SELECT DISTINCT l_orderkey AS o, l_partkey AS p, l_suppkey AS s FROM lineitem"), ("Orders", "SELECT o_orderkey AS o, o_custkey AS cust FROM orders"), ("Part", "SELECT p_partkey AS p, p_brand AS brand FROM part"), ("Supp", "SELECT s_suppkey AS s, s_nationkey AS nat FROM supplier")]
_S11 = {"ln": "l_linenumber", "qty": "CAST(l_quantity AS INT)", "rf": "l_returnflag", "ls": "l_linestatus", "disc": "CAST(l_discount AS DECIMAL(4,2))", "tax": "CAST(l_tax AS DECIMAL(4,2))", "mon": "CAST(month(l_shipdate) AS INT)"}


def star_11(t) -> JoinQuery:
    hub = _line(t).selectExpr("l_orderkey AS o", "l_partkey AS p", "l_suppkey AS s", *[f"{e} AS {a}" for a, e in _S11.items()])
    arms = [(f"Arm_{a}", hub.groupBy(a).agg(F.count("*").alias(f"n_{a}")), {a: a, f"n_{a}": f"n_{a}"}) for a in _S11]
    base = star_4(t).atoms[1:]
    return JoinQuery([Atom.of("Hub", hub), *base, *[Atom.of(n, d, c, (next(iter(c)),)) for n, d, c in arms]])


_H11 = "SELECT l_orderkey AS o, l_partkey AS p, l_suppkey AS s, " + ", ".join(f"{e} AS {a}" for a, e in _S11.items()) + " FROM lineitem"
SQL["star_11"] = [("Hub", _H11.replace("SELECT", "SELECT DISTINCT", 1)), *SQL["star_4"][1:], *[(f"Arm_{a}", f"SELECT {e} AS {a}, count(*) AS n_{a} FROM lineitem GROUP BY 1") for a, e in _S11.items()]]


def chain_6(t) -> JoinQuery:
    return _q(("Region", t["region"], {"rname": "r_name", "reg": "r_regionkey"}), ("Nation", t["nation"], {"reg": "n_regionkey", "nat": "n_nationkey"}), ("Customer", t["customer"], {"nat": "c_nationkey", "cust": "c_custkey"}), ("Orders", t["orders"], {"cust": "o_custkey", "o": "o_orderkey"}), ("Line", _line(t), {"o": "l_orderkey", "p": "l_partkey"}), ("Part", t["part"], {"p": "p_partkey", "brand": "p_brand"}), keys={"Region": ("reg",), "Nation": ("nat",), "Customer": ("cust",), "Orders": ("o",), "Part": ("p",)})


SQL["chain_6"] = [("Region", "SELECT r_name AS rname, r_regionkey AS reg FROM region"), ("Nation", "SELECT n_regionkey AS reg, n_nationkey AS nat FROM nation"), ("Customer", "SELECT c_nationkey AS nat, c_custkey AS cust FROM customer"), ("Orders", "SELECT o_custkey AS cust, o_orderkey AS o FROM orders"), ("Line", "SELECT DISTINCT l_orderkey AS o, l_partkey AS p FROM lineitem"), ("Part", "SELECT p_partkey AS p, p_brand AS brand FROM part")]


def chain_5_asia(t) -> JoinQuery:
    return JoinQuery(chain_6(t).atoms[:5]).filtered("rname", "rname = 'ASIA'")


SQL["chain_5_asia"] = [("Region", SQL["chain_6"][0][1] + " WHERE r_name = 'ASIA'"), *SQL["chain_6"][1:5]]


def _chain(df: DataFrame, n: int, prefix: str = "a", name: str = "E") -> JoinQuery:
    return JoinQuery([Atom(f"{name}{i:02d}", df.select(F.col("a").alias(f"{prefix}{i:02d}"), F.col("b").alias(f"{prefix}{i + 1:02d}")), (f"{prefix}{i:02d}", f"{prefix}{i + 1:02d}"), (f"{prefix}{i:02d}",)) for i in range(n)])


def _chain_sql(base: str, n: int) -> list[tuple[str, str]]:
    return [(f"E{i:02d}", f"SELECT a AS a{i:02d}, b AS a{i + 1:02d} FROM ({base})") for i in range(n)]


def path_16(t) -> JoinQuery:
    return _chain(edges(t), 16)


def path_16_user7(t) -> JoinQuery:
    return _chain(edges(t, 7), 16)


def ring_16(t) -> JoinQuery:
    return _chain(ring(t), 16)


SQL["path_16"], SQL["path_16_user7"], SQL["ring_16"] = _chain_sql(_EDGE, 16), _chain_sql(_EDGE7, 16), _chain_sql(_RING, 16)


def tri_6(t) -> JoinQuery:
    line, supp = _line(t), t["supplier"]
    sreg = supp.join(t["nation"], F.col("s_nationkey") == F.col("n_nationkey")).select("s_suppkey", "n_regionkey")
    return _q(("T1", line, {"o": "l_orderkey", "p": "l_partkey"}), ("T2", line, {"o": "l_orderkey", "s": "l_suppkey"}), ("T3", line, {"p": "l_partkey", "s": "l_suppkey"}), ("T4", supp, {"s": "s_suppkey", "nat": "s_nationkey"}), ("T5", sreg, {"s": "s_suppkey", "reg": "n_regionkey"}), ("T6", t["nation"], {"nat": "n_nationkey", "reg": "n_regionkey"}), keys={"T4": ("s",), "T5": ("s",), "T6": ("nat",)})


SQL["tri_6"] = [("T1", "SELECT DISTINCT l_orderkey AS o, l_partkey AS p FROM lineitem"), ("T2", "SELECT DISTINCT l_orderkey AS o, l_suppkey AS s FROM lineitem"), ("T3", "SELECT DISTINCT l_partkey AS p, l_suppkey AS s FROM lineitem"), ("T4", "SELECT s_suppkey AS s, s_nationkey AS nat FROM supplier"), ("T5", "SELECT s_suppkey AS s, n_regionkey AS reg FROM supplier JOIN nation ON s_nationkey = n_nationkey"), ("T6", "SELECT n_nationkey AS nat, n_regionkey AS reg FROM nation")]


def tri_12(t) -> JoinQuery:
    c, o = t["customer"], t["orders"]
    first = _q(("C1", c, {"c": "c_custkey", "cn": "c_nationkey"}), ("C2", c, {"c": "c_custkey", "g": "c_mktsegment"}), ("C3", c, {"cn": "c_nationkey", "g": "c_mktsegment"}), ("O1", o, {"c": "o_custkey", "o": "o_orderkey"}), ("O2", o, {"c": "o_custkey", "t": "o_orderstatus"}), ("O3", o, {"o": "o_orderkey", "t": "o_orderstatus"}))
    return JoinQuery([*first.atoms, *tri_6(t).atoms])


SQL["tri_12"] = [("C1", "SELECT c_custkey AS c, c_nationkey AS cn FROM customer"), ("C2", "SELECT c_custkey AS c, c_mktsegment AS g FROM customer"), ("C3", "SELECT DISTINCT c_nationkey AS cn, c_mktsegment AS g FROM customer"), ("O1", "SELECT o_custkey AS c, o_orderkey AS o FROM orders"), ("O2", "SELECT DISTINCT o_custkey AS c, o_orderstatus AS t FROM orders"), ("O3", "SELECT o_orderkey AS o, o_orderstatus AS t FROM orders"), *SQL["tri_6"]]


def tri_21(t) -> JoinQuery:
    one = ring(t)
    two = one.select("a", F.col("b").alias("m")).join(one.select(F.col("a").alias("m"), "b"), "m").select("a", "b")
    name = lambda i: f"a{i:02d}"
    atoms = []
    for k in range(7):
        x, y, z = 2 * k, 2 * k + 1, 2 * k + 2
        for n, (df, p, r) in {f"X{k}": (one, x, y), f"Y{k}": (two, x, z), f"Z{k}": (one, y, z)}.items():
            atoms.append(Atom(n, df.select(F.col("a").alias(name(p)), F.col("b").alias(name(r))), (name(p), name(r))))
    return JoinQuery(atoms)


_RING2 = f"SELECT x.a AS a, y.b AS b FROM ({_RING}) x JOIN ({_RING}) y ON x.b = y.a"
SQL["tri_21"] = [(f"{n}{k}", f"SELECT DISTINCT a AS a{p:02d}, b AS a{r:02d} FROM ({base})") for k in range(7) for n, base, p, r in (("X", _RING, 2 * k, 2 * k + 1), ("Y", _RING2, 2 * k, 2 * k + 2), ("Z", _RING, 2 * k + 1, 2 * k + 2))]


def five_rel(t) -> JoinQuery:
    o = t["orders"]
    r1 = _line(t).join(o, F.col("l_orderkey") == F.col("o_orderkey")).select("l_linenumber", "o_custkey", "o_orderkey")
    r5 = o.groupBy("o_orderstatus", "o_orderpriority").agg(F.count("*").alias("cnt"))
    return _q(("R1", r1, {"line": "l_linenumber", "cust": "o_custkey", "o": "o_orderkey"}), ("R2", t["customer"], {"cust": "c_custkey", "nat": "c_nationkey"}), ("R3", o, {"cust": "o_custkey", "o": "o_orderkey", "st": "o_orderstatus"}), ("R4", o, {"o": "o_orderkey", "st": "o_orderstatus", "pri": "o_orderpriority"}), ("R5", r5, {"st": "o_orderstatus", "pri": "o_orderpriority", "cnt": "cnt"}))


SQL["five_rel"] = [("R1", "SELECT DISTINCT l_linenumber AS line, o_custkey AS cust, o_orderkey AS o FROM lineitem JOIN orders ON l_orderkey = o_orderkey"), ("R2", "SELECT c_custkey AS cust, c_nationkey AS nat FROM customer"), ("R3", "SELECT o_custkey AS cust, o_orderkey AS o, o_orderstatus AS st FROM orders"), ("R4", "SELECT o_orderkey AS o, o_orderstatus AS st, o_orderpriority AS pri FROM orders"), ("R5", "SELECT o_orderstatus AS st, o_orderpriority AS pri, count(*) AS cnt FROM orders GROUP BY 1, 2")]


def cycle_4(t) -> JoinQuery:
    return _q(("Customer", t["customer"], {"nat": "c_nationkey", "cust": "c_custkey"}), ("Orders", t["orders"], {"cust": "o_custkey", "o": "o_orderkey"}), ("Line", _line(t), {"o": "l_orderkey", "s": "l_suppkey"}), ("Supp", t["supplier"], {"s": "s_suppkey", "nat": "s_nationkey"}))


SQL["cycle_4"] = [("Customer", "SELECT c_nationkey AS nat, c_custkey AS cust FROM customer"), ("Orders", "SELECT o_custkey AS cust, o_orderkey AS o FROM orders"), ("Line", "SELECT DISTINCT l_orderkey AS o, l_suppkey AS s FROM lineitem"), ("Supp", "SELECT s_suppkey AS s, s_nationkey AS nat FROM supplier")]


def disconnected(t) -> JoinQuery:
    return _q(("Doc", t["documents"], {"doc": "doc_id", "lang": "lang"}), ("Label", t["labels"], {"doc": "doc_id", "quality": "quality"}), ("Region", t["region"], {"reg": "r_regionkey", "rname": "r_name"}), ("Nation", t["nation"], {"reg": "n_regionkey", "nat": "n_nationkey"}))


SQL["disconnected"] = [("Doc", "SELECT DISTINCT doc_id AS doc, lang FROM documents"), ("Label", "SELECT DISTINCT doc_id AS doc, quality FROM labels"), ("Region", "SELECT r_regionkey AS reg, r_name AS rname FROM region"), ("Nation", "SELECT n_regionkey AS reg, n_nationkey AS nat FROM nation")]


def conv_chain(t) -> JoinQuery:
    c = t["conversations"]
    step = lambda i: c.select(F.col("conv_id").alias("conv"), F.col("turn").alias(f"t{i}"), (F.col("turn") + 1).alias(f"t{i + 1}"))
    return JoinQuery([Atom(f"S{i}", step(i), ("conv", f"t{i}", f"t{i + 1}")) for i in range(3)])


SQL["conv_chain"] = [(f"S{i}", f"SELECT DISTINCT conv_id AS conv, turn AS t{i}, turn + 1 AS t{i + 1} FROM conversations") for i in range(3)]


def skew_2(t) -> tuple[DataFrame, DataFrame]:
    e = t["embeddings"]
    return e.select("label", F.col("vec_id").alias("v1")), e.select("label", F.col("vec_id").alias("v2"))


def skew_fk(t) -> tuple[DataFrame, DataFrame]:
    o = t["orders"]
    return o.select(F.col("o_custkey").alias("cust"), F.col("o_orderkey").alias("o1")), o.select(F.col("o_custkey").alias("cust"), F.col("o_orderkey").alias("o2"))


FIXTURES = {f.__name__: f for f in (star_4, star_11, chain_6, chain_5_asia, path_16, path_16_user7, ring_16, tri_6, tri_12, tri_21, five_rel, cycle_4, disconnected, conv_chain)}


def fixture(spark: SparkSession, sf_dir: str, name: str) -> JoinQuery:
    return FIXTURES[name](load_tables(spark, sf_dir))


def oracle(name: str) -> str:
    """DuckDB text of a fixture's join."""
    atoms = SQL[name]
    joined = f"(SELECT * FROM {_natural(atoms[:2])}) CROSS JOIN (SELECT * FROM {_natural(atoms[2:])})" if name == "disconnected" else _natural(atoms)
    return "WITH " + ", ".join(f"{n} AS ({s})" for n, s in atoms) + " SELECT * FROM " + joined


def _natural(atoms: list[tuple[str, str]]) -> str:
    out = atoms[0][0]
    for n, _ in atoms[1:]:
        out += f" NATURAL JOIN {n}"
    return out
