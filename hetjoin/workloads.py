"""Queries over the given tables, with the SQL that each is held against."""

from __future__ import annotations

import math
from collections.abc import Callable, Sequence

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .functions import coords, measure, profile
from .operators import baselines
from .operators.execute import Totals, evaluate, plan
from .plans import bounds, lp, pack, sides
from .plans.cost import CostFunction, Linear, Power, Tabulated
from .plans.query import FullCQ, bind, null_keys, parse_cq
from .sources import datagen
from .sources.tables import stored, table

# The machine weights of the worked example.
EXAMPLE = [4.0, 4.0, 3.0, 2.0, 2.0, 2.0] + [1.0] * 11
LINEAR: list[CostFunction] = [Linear(w) for w in EXAMPLE]

CARTESIAN = parse_cq("q(x, y) :- R(x), S(y)")
JOIN = parse_cq("q(x, y, z) :- R(x, z), S(y, z)")
TRIANGLE = parse_cq("q(x, y, z) :- R(x, y), S(y, z), T(z, x)")

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
ORACLES: dict[str, str] = {}


def workload(sql: str | Callable[[], str]):
    def add(f):
        QUERIES[f.__name__] = f
        ORACLES[f.__name__] = sql if isinstance(sql, str) else sql()
        return f

    return add


def queries() -> dict:
    return dict(QUERIES)


def oracle_sql() -> dict[str, str]:
    return dict(ORACLES)


def keys(spark, d, name: str, column: str, var: str) -> DataFrame:
    return bind(table(spark, d, name), {column: var})


def summed(answers: DataFrame, by: str, over: str) -> DataFrame:
    return answers.groupBy(by).agg(F.count("*").alias("n"), F.sum(over).alias("total"))


def orders_keys(spark, d) -> tuple[DataFrame, int]:
    o = keys(spark, d, "orders", "o_orderkey", "i")
    return o, o.count()


# --- Cartesian products -------------------------------------------------------------------


def example_inputs(spark, d) -> dict[str, DataFrame]:
    c, p = keys(spark, d, "customer", "c_custkey", "x"), keys(spark, d, "part", "p_partkey", "y")
    n = min(c.count(), p.count()) * 2 // 3
    return {"R": c.where(F.col("x") < n), "S": p.where(F.col("y") < n)}


LIMIT = "(SELECT least((SELECT count(*) FROM customer), (SELECT count(*) FROM part)) * 2 // 3)"


# A product of n keys on both sides has n * n answers: every machine counts and sums those of its box without making them.
BY_X100 = Totals("x100", "x % 100", "x", "y")


@workload(f"SELECT c_custkey % 100 AS x100, count(*) AS n, sum(p_partkey)::BIGINT AS total FROM customer, part WHERE c_custkey < {LIMIT} AND p_partkey < {LIMIT} GROUP BY 1")
def cartesian_equal(spark, d):
    return evaluate(CARTESIAN, example_inputs(spark, d), LINEAR, mode="uniform", totals=BY_X100).answers


WHOLE = "(SELECT least((SELECT count(*) FROM customer), (SELECT count(*) FROM part)))"


@workload(f"SELECT c_custkey % 100 AS x100, count(*) AS n, sum(p_partkey)::BIGINT AS total FROM customer, part WHERE c_custkey < {WHOLE} AND p_partkey < {WHOLE} GROUP BY 1")
def cartesian_equal_whole(spark, d):
    """All keys that both sides have; every box is cut into two tasks."""
    c, p = keys(spark, d, "customer", "c_custkey", "x"), keys(spark, d, "part", "p_partkey", "y")
    n = min(c.count(), p.count())
    return evaluate(CARTESIAN, {"R": c.where(F.col("x") < n), "S": p.where(F.col("y") < n)}, LINEAR, mode="uniform", sub=2, classify=True, totals=BY_X100).answers


def part_supplier(spark, d):
    return {"R": keys(spark, d, "part", "p_partkey", "x"), "S": keys(spark, d, "supplier", "s_suppkey", "y")}


@workload("SELECT s_suppkey AS y, count(*) AS n, sum(p_partkey)::BIGINT AS total FROM part, supplier GROUP BY 1")
def cartesian_unequal(spark, d):
    return summed(evaluate(CARTESIAN, part_supplier(spark, d), LINEAR).answers, "y", "x")


@workload("SELECT s_suppkey AS y, count(*) AS n, sum(p_partkey)::BIGINT AS total FROM part, supplier GROUP BY 1")
def cartesian_sub(spark, d):
    """Every machine's box in four tasks."""
    return summed(evaluate(CARTESIAN, part_supplier(spark, d), LINEAR, sub=4).answers, "y", "x")


@workload("SELECT r_regionkey::BIGINT AS x, n_nationkey::BIGINT AS y FROM region, nation")
def cartesian_small(spark, d):
    rel = {"R": keys(spark, d, "region", "r_regionkey", "x"), "S": keys(spark, d, "nation", "n_nationkey", "y")}
    return evaluate(CARTESIAN, rel, LINEAR).answers.select("x", "y")


@workload("SELECT s_suppkey AS y, count(*) AS n, sum(p_partkey)::BIGINT AS total FROM part, supplier WHERE p_partkey % 3 = 0 AND s_suppkey % 3 = 0 GROUP BY 1")
def cartesian_sparse(spark, d):
    rel = {k: v.where(f"{c} % 3 = 0") for (k, v), c in zip(part_supplier(spark, d).items(), "xy")}
    return summed(evaluate(CARTESIAN, rel, LINEAR).answers, "y", "x")


# --- Binary joins --------------------------------------------------------------------------


def orders_customer(spark, d):
    return {"R": bind(table(spark, d, "orders"), {"o_orderkey": "x", "o_custkey": "z"}), "S": bind(table(spark, d, "customer"), {"c_nationkey": "y", "c_custkey": "z"})}


ORDERS_CUSTOMER = "SELECT o_orderkey AS x, c_nationkey::BIGINT AS y, o_custkey AS z FROM orders JOIN customer ON o_custkey = c_custkey"


@workload(ORDERS_CUSTOMER)
def join_orders_customer(spark, d):
    return evaluate(JOIN, orders_customer(spark, d), LINEAR).answers.select("x", "y", "z")


@workload("SELECT l_orderkey AS z, l_linenumber::BIGINT AS x, o_custkey AS y FROM lineitem JOIN orders ON l_orderkey = o_orderkey")
def join_lineitem_orders(spark, d):
    rel = {"R": bind(table(spark, d, "lineitem"), {"l_linenumber": "x", "l_orderkey": "z"}), "S": bind(table(spark, d, "orders"), {"o_custkey": "y", "o_orderkey": "z"})}
    return evaluate(JOIN, rel, LINEAR, sub=2).answers.select("x", "y", "z")


NORDERS = "(SELECT count(*) FROM orders)"
I = "SELECT o_orderkey AS i FROM orders"  # noqa: E741
PA, PB, PD = (f"(i * {r[0]} + {r[1]}) % {NORDERS}" for r in (datagen.A, datagen.B, datagen.D))


def join_matching_inputs(spark, d):
    o, n = orders_keys(spark, d)
    return {"R": datagen.matching(o, "i", n, {"x": None, "z": datagen.A}), "S": datagen.matching(o.where("i % 2 = 0"), "i", n, {"y": None, "z": datagen.B})}


JOIN_MATCHING = f"WITH o AS ({I}), r AS (SELECT i AS x, {PA} AS z FROM o), s AS (SELECT i AS y, {PB} AS z FROM o WHERE i % 2 = 0) SELECT x, y, z FROM r JOIN s USING (z)"


@workload(JOIN_MATCHING)
def join_matching(spark, d):
    return evaluate(JOIN, join_matching_inputs(spark, d), LINEAR).answers.select("x", "y", "z")


@workload(
    "WITH r AS (SELECT s_suppkey AS x, n_nationkey::BIGINT AS z FROM supplier, nation WHERE (s_suppkey * 7919 + n_nationkey * 104729) % 100 < 50),"
    " s AS (SELECT c_custkey AS y, n_nationkey::BIGINT AS z FROM customer, nation WHERE c_custkey < 100 AND (c_custkey * 104729 + n_nationkey * 7919) % 100 < 20) SELECT x, y, z FROM r JOIN s USING (z)"
)
def join_dense(spark, d):
    nation = keys(spark, d, "nation", "n_nationkey", "z")
    rel = {"R": datagen.dense(keys(spark, d, "supplier", "s_suppkey", "x"), nation, "x", "z", (7919, 104729, 0), 0.5), "S": datagen.dense(keys(spark, d, "customer", "c_custkey", "y").where("y < 100"), nation, "y", "z", (104729, 7919, 0), 0.2)}
    return evaluate(JOIN, rel, LINEAR).answers.select("x", "y", "z")


@workload(
    "WITH r AS (SELECT s_suppkey AS x, n_nationkey::BIGINT AS z FROM supplier, nation WHERE (s_suppkey * 7919 + n_nationkey * 104729) % 100 < 50),"
    " s AS (SELECT c_custkey AS y, n_nationkey::BIGINT AS z FROM customer, nation WHERE (c_custkey * 104729 + n_nationkey * 7919) % 100 < 20) SELECT z, count(*) AS n, sum(x + y)::BIGINT AS total FROM r JOIN s USING (z) GROUP BY 1"
)
def join_dense_whole(spark, d):
    """All customers; heavy nations are split by the keys that go with them."""
    nation = keys(spark, d, "nation", "n_nationkey", "z")
    rel = {"R": datagen.dense(keys(spark, d, "supplier", "s_suppkey", "x"), nation, "x", "z", (7919, 104729, 0), 0.5), "S": datagen.dense(keys(spark, d, "customer", "c_custkey", "y"), nation, "y", "z", (104729, 7919, 0), 0.2)}
    return evaluate(JOIN, rel, LINEAR, sub=4, sub_by=("x", "y")).answers.groupBy("z").agg(F.count("*").alias("n"), F.sum(F.col("x") + F.col("y")).alias("total"))


@workload("SELECT d.doc_id AS x, l.quality::BIGINT AS y, d.lang AS z FROM labels l JOIN documents d USING (doc_id)")
def labels_documents(spark, d):
    cq = parse_cq("q(x, y, z) :- R(x, y), S(x, z)")
    rel = {"R": bind(table(spark, d, "labels"), {"doc_id": "x", "quality": "y"}), "S": bind(table(spark, d, "documents"), {"doc_id": "x", "lang": "z"})}
    return evaluate(cq, rel, LINEAR).answers.select("x", "y", "z")


# --- Stars ---------------------------------------------------------------------------------

STAR = parse_cq("q(a, b, c, z) :- R(a, z), S(b, z), T(c, z)")


def arm(spark, d, name, own, key, var):
    return bind(table(spark, d, name), {own: var, key: "z"})


@workload("SELECT n_nationkey::BIGINT AS z, count(*) AS n, sum(c_custkey + s_suppkey)::BIGINT AS total FROM customer JOIN supplier ON c_nationkey = s_nationkey JOIN nation ON n_nationkey = c_nationkey GROUP BY 1")
def star_nation(spark, d):
    rel = {"R": arm(spark, d, "customer", "c_custkey", "c_nationkey", "a"), "S": arm(spark, d, "supplier", "s_suppkey", "s_nationkey", "b"), "T": arm(spark, d, "nation", "n_regionkey", "n_nationkey", "c")}
    return evaluate(STAR, rel, LINEAR).answers.groupBy("z").agg(F.count("*").alias("n"), F.sum(F.col("a") + F.col("b")).alias("total"))


@workload("SELECT c_custkey AS z, count(*) AS n, sum(o_orderkey + event_id)::BIGINT AS total FROM customer JOIN orders ON o_custkey = c_custkey JOIN events ON user_id = c_custkey GROUP BY 1")
def star_customer(spark, d):
    rel = {"R": arm(spark, d, "customer", "c_nationkey", "c_custkey", "a"), "S": arm(spark, d, "orders", "o_orderkey", "o_custkey", "b"), "T": arm(spark, d, "events", "event_id", "user_id", "c")}
    return evaluate(STAR, rel, LINEAR, sub=4, sub_by=("b", "c")).answers.groupBy("z").agg(F.count("*").alias("n"), F.sum(F.col("b") + F.col("c")).alias("total"))


@workload(f"WITH o AS ({I}), r AS (SELECT i AS a, {PA} AS z FROM o), s AS (SELECT i AS b, {PB} AS z FROM o WHERE i < {NORDERS} // 2), t AS (SELECT i AS c, {PD} AS z FROM o WHERE i < {NORDERS} // 4) SELECT a, b, c, z FROM r JOIN s USING (z) JOIN t USING (z)")
def star_matching(spark, d):
    o, n = orders_keys(spark, d)
    rel = {"R": datagen.matching(o, "i", n, {"a": None, "z": datagen.A}), "S": datagen.matching(o.where(F.col("i") < n // 2), "i", n, {"b": None, "z": datagen.B}), "T": datagen.matching(o.where(F.col("i") < n // 4), "i", n, {"c": None, "z": datagen.D})}
    return evaluate(STAR, rel, LINEAR).answers.select("a", "b", "c", "z")


# --- Triangles -----------------------------------------------------------------------------


@workload(
    "WITH r AS (SELECT DISTINCT o_custkey AS x, l_suppkey AS y FROM orders JOIN lineitem ON l_orderkey = o_orderkey)"
    " SELECT x, y, s_nationkey::BIGINT AS z FROM r JOIN supplier ON y = s_suppkey JOIN customer ON x = c_custkey AND c_nationkey = s_nationkey"
)
def triangle_nation(spark, d):
    r = stored(table(spark, d, "orders").join(table(spark, d, "lineitem"), F.col("o_orderkey") == F.col("l_orderkey")).select("o_custkey", "l_suppkey").distinct())
    rel = {"R": bind(r, {"o_custkey": "x", "l_suppkey": "y"}), "S": bind(table(spark, d, "supplier"), {"s_suppkey": "y", "s_nationkey": "z"}), "T": bind(table(spark, d, "customer"), {"c_nationkey": "z", "c_custkey": "x"})}
    return evaluate(TRIANGLE, rel, LINEAR).answers.select("x", "y", "z")


def planted(part: str) -> str:
    turned = f"CASE WHEN i % 2 = 0 THEN i ELSE (i + 2) % ({part}) END"
    return (
        f"WITH o AS ({I}), r AS (SELECT i AS x, {PA} AS y FROM o), s AS (SELECT {PA} AS y, (({turned}) * {datagen.B[0]} + {datagen.B[1]}) % {NORDERS} AS z FROM o WHERE i < {part}),"
        f" t AS (SELECT {PB} AS z, i AS x FROM o WHERE i < {part}) SELECT x, y, z FROM r JOIN s USING (y) JOIN t USING (z, x)"
    )


TRIANGLE_MATCHING = planted(NORDERS)


def triangle_inputs(spark, d, parts: int = 1):
    o, n = orders_keys(spark, d)
    return datagen.triangles(o, "i", n, n // parts)


@workload(TRIANGLE_MATCHING)
def triangle_matching(spark, d):
    return evaluate(TRIANGLE, triangle_inputs(spark, d), LINEAR, mode="uniform").answers.select("x", "y", "z")


@workload(TRIANGLE_MATCHING)
def triangle_sub(spark, d):
    """Every machine's box in four tasks, still one exchange for each atom."""
    return evaluate(TRIANGLE, triangle_inputs(spark, d), LINEAR, mode="uniform", sub=4).answers.select("x", "y", "z")


@workload(planted(f"{NORDERS} // 5"))
def triangle_mixed(spark, d):
    return evaluate(TRIANGLE, triangle_inputs(spark, d, 5), LINEAR, mode="triangle").answers.select("x", "y", "z")


DENSE = [(7919, 104729, 0), (104729, 7919, 31), (1299709, 15485863, 7)]


def _dense_sql(name, a, b, rule):
    return f"{name} AS (SELECT p.n_nationkey::BIGINT AS {a}, q.n_nationkey::BIGINT AS {b} FROM nation p, nation q WHERE (p.n_nationkey::BIGINT * {rule[0]} + q.n_nationkey::BIGINT * {rule[1]} + {rule[2]}) % 100 < 50)"


TRIANGLE_DENSE = "WITH " + ", ".join(_dense_sql(n, a, b, r) for n, a, b, r in zip("rst", "xyz", "yzx", DENSE)) + " SELECT x, y, z FROM r JOIN s USING (y) JOIN t USING (z, x)"


def triangle_dense_inputs(spark, d):
    n = lambda v: keys(spark, d, "nation", "n_nationkey", v)
    return {k: datagen.dense(n(a), n(b), a, b, r, 0.5) for k, a, b, r in zip("RST", "xyz", "yzx", DENSE)}


@workload(TRIANGLE_DENSE)
def triangle_dense(spark, d):
    return evaluate(TRIANGLE, triangle_dense_inputs(spark, d), LINEAR, mode="triangle").answers.select("x", "y", "z")


@workload(TRIANGLE_DENSE)
def triangle_generic(spark, d):
    """Local evaluation variable by variable."""
    return evaluate(TRIANGLE, triangle_dense_inputs(spark, d), LINEAR, local="generic").answers.select("x", "y", "z")


# --- Paths, chains, higher arity -----------------------------------------------------------


def path_inputs(spark, d):
    return {"nation": bind(table(spark, d, "nation"), {"n_nationkey": "n", "n_regionkey": "r"}), "customer": bind(table(spark, d, "customer"), {"c_custkey": "c", "c_nationkey": "n"}), "orders": bind(table(spark, d, "orders"), {"o_orderkey": "o", "o_custkey": "c"})}


PATH_SQL = "SELECT n_nationkey::BIGINT AS n, n_regionkey::BIGINT AS r, c_custkey AS c, o_orderkey AS o FROM nation JOIN customer ON c_nationkey = n_nationkey JOIN orders ON o_custkey = c_custkey"


@workload(PATH_SQL)
def path3(spark, d):
    cq = parse_cq("q(n, r, c, o) :- nation(n, r), customer(c, n), orders(o, c)")
    return evaluate(cq, path_inputs(spark, d), LINEAR, mode="dual").answers.select("n", "r", "c", "o")


@workload(PATH_SQL.replace("FROM nation", "FROM region JOIN nation ON n_regionkey = r_regionkey"))
def chain4(spark, d):
    cq = parse_cq("q(r, n, c, o) :- region(r), nation(n, r), customer(c, n), orders(o, c)")
    return evaluate(cq, {"region": keys(spark, d, "region", "r_regionkey", "r"), **path_inputs(spark, d)}, LINEAR, mode="padded").answers.select("n", "r", "c", "o")


@workload(f"WITH o AS ({I}), r AS (SELECT i AS x, {PA} AS y, {PB} AS z FROM o), s AS (SELECT {PA} AS y, ((CASE WHEN i % 2 = 0 THEN i ELSE (i + 2) % {NORDERS} END) * {datagen.B[0]} + {datagen.B[1]}) % {NORDERS} AS z, {PD} AS t FROM o) SELECT x, y, z, t FROM r JOIN s USING (y, z)")
def arity3(spark, d):
    o, n = orders_keys(spark, d)
    turned = F.when(F.col("i") % 2 == 0, F.col("i")).otherwise(F.pmod(F.col("i") + 2, F.lit(n)))
    s = o.select(datagen.line(F.col("i"), datagen.A, n).alias("y"), datagen.line(turned, datagen.B, n).alias("z"), datagen.line(F.col("i"), datagen.D, n).alias("t"))
    rel = {"R": datagen.matching(o, "i", n, {"x": None, "y": datagen.A, "z": datagen.B}), "S": s}
    return evaluate(parse_cq("q(x, y, z, t) :- R(x, y, z), S(y, z, t)"), rel, LINEAR, mode="uniform").answers.select("x", "y", "z", "t")


# --- General costs and baselines -----------------------------------------------------------


@workload(JOIN_MATCHING)
def power_cost_join(spark, d):
    return evaluate(JOIN, join_matching_inputs(spark, d), [Power(w, 2.0) for w in EXAMPLE]).answers.select("x", "y", "z")


@workload(TRIANGLE_MATCHING)
def power_cost_triangle(spark, d):
    return evaluate(TRIANGLE, triangle_inputs(spark, d), [Power(w, 0.5) if i % 2 else Linear(w) for i, w in enumerate(EXAMPLE)]).answers.select("x", "y", "z")


@workload("SELECT a, s_suppkey AS y, count(*) AS n, sum(p_partkey)::BIGINT AS total FROM part, supplier, (VALUES (0.5::DOUBLE), (1.0::DOUBLE), (2.0::DOUBLE), (3.0::DOUBLE)) AS t(a) GROUP BY 1, 2")
def power_cost_cartesian(spark, d):
    """Costs x^a / w for four exponents: other boxes, the same answers."""
    rel, out = part_supplier(spark, d), None
    for a in (0.5, 1.0, 2.0, 3.0):
        one = summed(evaluate(CARTESIAN, rel, [Power(w, a) for w in EXAMPLE]).answers, "y", "x").select(F.lit(a).alias("a"), "y", "n", "total")
        out = one if out is None else out.unionAll(one)
    return out


@workload(JOIN_MATCHING)
def tabulated_cost_join(spark, d):
    """Measured costs: past a size that goes with its weight, a machine gets ten times as slow."""
    costs = [Tabulated(((1000 * w, 1000.0), (2000 * w, 11000.0))) for w in EXAMPLE]
    return evaluate(JOIN, join_matching_inputs(spark, d), costs).answers.select("x", "y", "z")


@workload(TRIANGLE_MATCHING)
def hypercube_lp_triangle(spark, d):
    """Shares from the cover instead of a search."""
    rel = triangle_inputs(spark, d)
    m = counted(rel)
    return baselines.hypercube(TRIANGLE, rel, 17, m, baselines.shares(TRIANGLE, m, 17, "lp"))[0].select("x", "y", "z")


def counted(rel) -> dict[str, int]:
    return {k: v.count() for k, v in rel.items()}


@workload(TRIANGLE_MATCHING)
def hypercube_triangle(spark, d):
    rel = triangle_inputs(spark, d)
    return baselines.hypercube(TRIANGLE, rel, 17, counted(rel))[0].select("x", "y", "z")


@workload(TRIANGLE_MATCHING)
def hypercube_fastest_triangle(spark, d):
    rel = triangle_inputs(spark, d)
    return baselines.hypercube_fastest(TRIANGLE, rel, EXAMPLE, counted(rel))[0].select("x", "y", "z")


@workload(TRIANGLE_MATCHING)
def virtual_hypercube_triangle(spark, d):
    rel = triangle_inputs(spark, d)
    return baselines.virtual_hypercube(TRIANGLE, rel, [int(w) for w in EXAMPLE], counted(rel))[0].select("x", "y", "z")


@workload(TRIANGLE_MATCHING)
def equal_weights_triangle(spark, d):
    return evaluate(TRIANGLE, triangle_inputs(spark, d), [Linear(1.0)] * 17).answers.select("x", "y", "z")


@workload(TRIANGLE_MATCHING)
def pairwise_triangle(spark, d):
    rel = triangle_inputs(spark, d)
    return baselines.pairwise(TRIANGLE, rel, counted(rel)).select("x", "y", "z")


@workload(ORDERS_CUSTOMER)
def single_machine_join(spark, d):
    rel = orders_customer(spark, d)
    return baselines.single_machine(JOIN, rel, counted(rel)).select("x", "y", "z")


# --- Measures ------------------------------------------------------------------------------

BITS = 10


def fixed_boxes(cq: FullCQ) -> pack.Packing:
    return pack.pack(cq, sides.uniform(cq, EXAMPLE), grid_bits=BITS)


def example_boxes(n: int) -> pack.Packing:
    """The worked example's boxes for n keys on each side that are their own coordinates."""
    return pack.pack(CARTESIAN, sides.uniform(CARTESIAN, EXAMPLE), {"x": n, "y": n}, grid_bits=BITS)


def box_values(p: pack.Packing) -> str:
    rows = ", ".join("(" + ", ".join(map(str, (c, *[v for x in p.vars for v in p.boxes[c][x]]))) + ")" for c in p.used())
    return f"(VALUES {rows}) AS b(machine, " + ", ".join(f"{x}_lo, {x}_hi" for x in p.vars) + ")"


def digest_sql(var: str, expr: str) -> str:
    return f"(('0x' || substr(md5('7:{var}:' || ({expr})::VARCHAR), 1, 8))::BIGINT >> {32 - BITS})"


def inside_sql(vars: Sequence[str], exprs: Sequence[str]) -> str:
    return " AND ".join(f"{digest_sql(x, e)} >= {x}_lo AND {digest_sql(x, e)} < {x}_hi" for x, e in zip(vars, exprs))


def _route_fixed(cq, rel, strategy="auto"):
    from .operators.route import route

    p, c = fixed_boxes(cq), {x: coords.md5(7, BITS) for x in cq.vars}
    return {a.name: route(rel[a.name], a, p, c, strategy) for a in cq.atoms}


def received_cartesian_sql() -> str:
    b = box_values(fixed_boxes(CARTESIAN))
    return " UNION ALL ".join(f"SELECT machine, '{a}' AS atom, count(*) AS tuples FROM {t} JOIN {b} ON {inside_sql([x], [k])} GROUP BY 1" for a, t, x, k in (("R", "part", "x", "p_partkey"), ("S", "supplier", "y", "s_suppkey")))


@workload(received_cartesian_sql)
def received_cartesian(spark, d):
    return measure.received(_route_fixed(CARTESIAN, part_supplier(spark, d), "tree"))


def triangle_parts_sql() -> str:
    head = TRIANGLE_MATCHING.split(" SELECT x, y, z FROM r JOIN")[0]
    b = box_values(fixed_boxes(TRIANGLE))
    return head + " " + " UNION ALL ".join(f"SELECT machine, '{a}' AS atom, count(*) AS tuples FROM {a.lower()} JOIN {b} ON {inside_sql(v, v)} GROUP BY 1" for a, v in (("R", "xy"), ("S", "yz"), ("T", "zx")))


@workload(triangle_parts_sql)
def received_matching(spark, d):
    return measure.received(_route_fixed(TRIANGLE, triangle_inputs(spark, d), "cells"))


def weights_sql() -> str:
    return "(VALUES " + ", ".join(f"({i}, {w}::DOUBLE)" for i, w in enumerate(EXAMPLE)) + ") AS w(machine, weight)"


@workload(lambda: f"SELECT round(max(tuples / weight), 6) AS load FROM (SELECT machine, sum(tuples) AS tuples FROM ({received_cartesian_sql()}) GROUP BY 1) JOIN {weights_sql()} USING (machine)")
def load_cartesian(spark, d):
    return measure.load(measure.received(_route_fixed(CARTESIAN, part_supplier(spark, d), "nested")), LINEAR).select(F.round("load", 6).alias("load"))


@workload(lambda: f"SELECT sum(tuples)::BIGINT AS sent, round(sum(tuples) / (3.0 * {NORDERS}), 6)::DOUBLE AS replication FROM ({triangle_parts_sql()})")
def replication_matching(spark, d):
    rel = triangle_inputs(spark, d)
    return measure.replication(measure.received(_route_fixed(TRIANGLE, rel)), counted(rel)).select("sent", F.round("replication", 6).alias("replication"))


@workload(lambda: f"SELECT machine, atom, sum(tuples)::BIGINT AS tuples FROM ({received_cartesian_sql()}) GROUP BY ROLLUP (machine, atom)")
def received_rollup(spark, d):
    return measure.rollup(measure.received(_route_fixed(CARTESIAN, part_supplier(spark, d))))


@workload(lambda: f"SELECT machine, atom, sum(tuples)::BIGINT AS tuples FROM ({received_cartesian_sql()}) GROUP BY CUBE (machine, atom)")
def received_cube(spark, d):
    return measure.cube(measure.received(_route_fixed(CARTESIAN, part_supplier(spark, d))))


@workload(lambda: f"SELECT machine, atom, sum(tuples)::BIGINT AS tuples FROM ({received_cartesian_sql()}) GROUP BY GROUPING SETS ((machine), (atom))")
def received_sets(spark, d):
    return measure.grouping_sets(measure.received(_route_fixed(CARTESIAN, part_supplier(spark, d))), [["machine"], ["atom"]])


@workload(lambda: f"SELECT machine, atom, tuples, tuples * 10.0::DOUBLE AS bits FROM ({received_cartesian_sql()})")
def bits_cartesian(spark, d):
    """Bits received, ten for each tuple of a domain of 1,024."""
    return measure.bits(measure.received(_route_fixed(CARTESIAN, part_supplier(spark, d))), CARTESIAN, 1 << BITS).select("machine", "atom", "tuples", "bits")


@workload(lambda: f"SELECT machine::INT AS machine, v AS var, round(((hi * {LIMIT} >> {BITS}) - (lo * {LIMIT} >> {BITS})) / {LIMIT}::DOUBLE / (weight / 8), 6)::DOUBLE AS inflation FROM (SELECT machine, 'x' AS v, x_lo AS lo, x_hi AS hi FROM {box_values(fixed_boxes(CARTESIAN))} UNION ALL SELECT machine, 'y', y_lo, y_hi FROM {box_values(fixed_boxes(CARTESIAN))}) JOIN {weights_sql()} USING (machine)")
def inflation_example(spark, d):
    """Final over planned side of each box of the worked example over the keys of customer and part; its weights have the norm 8."""
    n = example_inputs(spark, d)["R"].count()
    of = {"R": "x", "S": "y"}
    return spark.createDataFrame([(c, of[a], round(f, 6)) for (c, a), f in example_boxes(n).inflation(CARTESIAN).items()], "machine int, var string, inflation double")


# --- Measured loads ------------------------------------------------------------------------

STAR_SIZES, MIXED_SIZES = {"R": 4, "S": 2, "T": 1}, {"R": 5, "S": 1, "T": 1}


def planned_boxes(cq: FullCQ, sizes: dict[str, int] | None = None, weights: Sequence[float] = EXAMPLE) -> pack.Packing:
    """Boxes for relations whose sizes have these ratios, on a small grid that SQL can hash to."""
    m = {a: n * 100_000 for a, n in (sizes or {a.name: 1 for a in cq.atoms}).items()}
    return plan(cq, m, [Linear(w) for w in weights], coordinates={x: coords.md5(7, BITS) for x in cq.vars}, grid_bits=BITS).packing


def parts_sql(head: str, atoms: dict[str, str], p: pack.Packing) -> str:
    """(machine, atom, tuples) of the relations that ``head`` defines, each with its variables."""
    return head + " " + " UNION ALL ".join(f"SELECT machine, '{a}' AS atom, count(*) AS tuples FROM {a.lower()} JOIN {box_values(p)} ON {inside_sql(v, v)} GROUP BY 1" for a, v in atoms.items())


def grid_sql(head: str, cq: FullCQ, grid: dict[str, int], owner: Sequence[int]) -> str:
    """The same for a share grid whose point i belongs to machine ``owner[i]``."""
    selects = []
    for a in cq.atoms:
        number = "0"
        for x in cq.vars:
            number = f"({number}) * {grid[x]} + " + (f"({digest_sql(x, x)} * {grid[x]} >> {BITS})" if x in a.vars else f"g_{x}")
        free = "".join(f", (SELECT unnest(range({grid[x]})) AS g_{x}) AS f_{x}" for x in cq.vars if x not in a.vars)
        selects.append(f"SELECT [{', '.join(map(str, owner))}][point + 1] AS machine, '{a.name}' AS atom, count(*) AS tuples FROM (SELECT {number} AS point FROM {a.name.lower()}{free}) GROUP BY 1")
    return head + " " + " UNION ALL ".join(selects)


def load_sql(name: str, parts: str, weights: str | None = None) -> str:
    return f"SELECT '{name}' AS workload, round(max(tuples / weight), 6)::DOUBLE AS load, sum(tuples)::BIGINT AS sent FROM (SELECT machine, sum(tuples) AS tuples FROM ({parts}) GROUP BY 1) JOIN {weights or weights_sql()} USING (machine)"


def load_row(name: str, routed, costs=None) -> DataFrame:
    """workload, load (the worst machine's tuples by weight) and rows sent; routing alone decides both."""
    loads = measure.cost(measure.received(routed), costs or LINEAR)
    return loads.agg(F.round(F.max("cost"), 6).alias("load"), F.sum("amount").cast("long").alias("sent")).select(F.lit(name).alias("workload"), "load", "sent")


def route_planned(cq, rel, p):
    from .operators.route import route

    return {a.name: route(rel[a.name], a, p, {x: coords.md5(7, BITS) for x in cq.vars}) for a in cq.atoms}


def stacked(rows: list[DataFrame]) -> DataFrame:
    out = rows[0]
    for r in rows[1:]:
        out = out.unionAll(r)
    return out


def example_load_sql() -> str:
    p = fixed_boxes(CARTESIAN)
    sides_ = [("R", "customer", "c_custkey", "x"), ("S", "part", "p_partkey", "y")]
    parts = " UNION ALL ".join(f"SELECT machine, '{a}' AS atom, count(*) AS tuples FROM {t} JOIN {box_values(p)} ON {k} < {LIMIT} AND {k} >= ({x}_lo * {LIMIT} >> {BITS}) AND {k} < ({x}_hi * {LIMIT} >> {BITS}) GROUP BY 1" for a, t, k, x in sides_)
    return load_sql("example", parts)


@workload(example_load_sql)
def load_example(spark, d):
    """The worked example with keys as their own coordinates."""
    from .operators.route import route

    rel = example_inputs(spark, d)
    n = rel["R"].count()
    return load_row("example", {a.name: route(rel[a.name], a, example_boxes(n), {v: coords.identity(0, n) for v in "xy"}) for a in CARTESIAN.atoms})


JOIN_HEAD = JOIN_MATCHING.split(" SELECT x, y, z FROM r JOIN")[0]
STAR_HEAD = ORACLES["star_matching"].split(" SELECT a, b, c, z FROM r JOIN")[0]
TRIANGLE_HEAD = TRIANGLE_MATCHING.split(" SELECT x, y, z FROM r JOIN")[0]
MIXED_HEAD = ORACLES["triangle_mixed"].split(" SELECT x, y, z FROM r JOIN")[0]
TRIANGLE_VARS = {"R": "xy", "S": "yz", "T": "zx"}


def star_inputs(spark, d):
    o, n = orders_keys(spark, d)
    return {"R": datagen.matching(o, "i", n, {"a": None, "z": datagen.A}), "S": datagen.matching(o.where(F.col("i") < n // 2), "i", n, {"b": None, "z": datagen.B}), "T": datagen.matching(o.where(F.col("i") < n // 4), "i", n, {"c": None, "z": datagen.D})}


@workload(
    lambda: " UNION ALL ".join(
        f"({load_sql(n, parts_sql(h, v, planned_boxes(q, m)))})"
        for n, h, v, q, m in (("join", JOIN_HEAD, {"R": "xz", "S": "yz"}, JOIN, {"R": 2, "S": 1}), ("star", STAR_HEAD, {"R": "az", "S": "bz", "T": "cz"}, STAR, STAR_SIZES), ("triangle", TRIANGLE_HEAD, TRIANGLE_VARS, TRIANGLE, None), ("triangle_mixed", MIXED_HEAD, TRIANGLE_VARS, TRIANGLE, MIXED_SIZES))
    )
)
def loads_boxes(spark, d):
    """Measured loads of the planned boxes on matching inputs, equal and unequal."""
    made = [("join", JOIN, join_matching_inputs(spark, d), {"R": 2, "S": 1}), ("star", STAR, star_inputs(spark, d), STAR_SIZES), ("triangle", TRIANGLE, triangle_inputs(spark, d), None), ("triangle_mixed", TRIANGLE, triangle_inputs(spark, d, 5), MIXED_SIZES)]
    return stacked([load_row(n, route_planned(q, rel, planned_boxes(q, m))) for n, q, rel, m in made])


@workload(lambda: f"SELECT machine, round(CASE WHEN count(*) = 3 THEN exp(sum(ln(tuples / {NORDERS}::DOUBLE) * 0.5)) ELSE 0 END, 6)::DOUBLE AS known FROM ({parts_sql(TRIANGLE_HEAD, TRIANGLE_VARS, planned_boxes(TRIANGLE))}) GROUP BY 1")
def known_matching(spark, d):
    """The most of the expected triangles that each machine can know from the fractions that it received."""
    rel = triangle_inputs(spark, d)
    known = measure.known(measure.received(route_planned(TRIANGLE, rel, planned_boxes(TRIANGLE))), counted(rel), lp.max_edge_packing(TRIANGLE))
    return known.select("machine", F.round("known", 6).alias("known"))


def triangle_grids() -> list[tuple[str, dict[str, int], list[int]]]:
    """The share grids that ignore weights, and that take the fastest machines only: name, grid, owners of the points."""
    m = {a.name: 1 for a in TRIANGLE.atoms}
    blind, (fast, _) = baselines.shares(TRIANGLE, m, 17), baselines.fastest_grid(TRIANGLE, m, EXAMPLE)
    return [("grid", blind, list(range(17))), ("grid_fastest", fast, sorted(range(17), key=lambda c: -EXAMPLE[c]))]


def baseline_loads_sql() -> str:
    made = [load_sql(n, grid_sql(TRIANGLE_HEAD, TRIANGLE, g, owner)) for n, g, owner in triangle_grids()]
    made.append(load_sql("equal_weights", parts_sql(TRIANGLE_HEAD, TRIANGLE_VARS, planned_boxes(TRIANGLE, None, [1.0] * 17))))
    made.append(f"SELECT 'single' AS workload, round(3 * {NORDERS} / 4.0, 6)::DOUBLE AS load, 3 * {NORDERS} AS sent")
    return " UNION ALL ".join(f"({x})" for x in made)


@workload(baseline_loads_sql)
def loads_baselines(spark, d):
    """Measured loads of the baselines on the triangle of equal matchings: what ignoring weights costs."""
    rel, rows = triangle_inputs(spark, d), []
    at = {x: coords.md5(7, BITS) for x in "xyz"}
    for name, grid, owner in triangle_grids():
        owners = F.array(*[F.lit(c) for c in owner])
        rows.append(load_row(name, {a.name: baselines.grid_route(rel[a.name], TRIANGLE, a.name, grid, coordinates=at).withColumn("machine", F.element_at(owners, F.col("machine") + 1)) for a in TRIANGLE.atoms}))
    rows.append(load_row("equal_weights", route_planned(TRIANGLE, rel, planned_boxes(TRIANGLE, None, [1.0] * 17))))
    rows.append(load_row("single", {k: v.withColumn("machine", F.lit(0)) for k, v in rel.items()}))
    return stacked(rows)


SEEDS, DELTA = 100, 0.25


def seeded_sql(head: str, atoms: dict[str, str], p: pack.Packing) -> str:
    digest = lambda x: f"(('0x' || substr(md5(seed || ':{x}:' || {x}::VARCHAR), 1, 8))::BIGINT >> {32 - BITS})"
    inside = lambda v: " AND ".join(f"h_{x} >= {x}_lo AND h_{x} < {x}_hi" for x in v)
    return head + " " + " UNION ALL ".join(f"SELECT seed, machine, '{a}' AS atom, count(*) AS tuples FROM (SELECT seed, " + ", ".join(f"{digest(x)} AS h_{x}" for x in v) + f" FROM {a.lower()}, range({SEEDS}) AS s(seed)) JOIN {box_values(p)} ON {inside(v)} GROUP BY 1, 2" for a, v in atoms.items())


def expected_shares(cq: FullCQ, p: pack.Packing) -> list[tuple[int, str, float]]:
    return [(c, a.name, p.share(c, a.vars)) for c in p.used() for a in cq.atoms]


def seed_sweep_sql() -> str:
    p = planned_boxes(TRIANGLE)
    shares = "(VALUES " + ", ".join(f"({c}, '{a}', {s!r}::DOUBLE)" for c, a, s in expected_shares(TRIANGLE, p)) + ") AS e(machine, atom, share)"
    return f"SELECT seed, count(*) FILTER (WHERE tuples > {1 + DELTA} * share * {NORDERS}) AS exceeded, round(max(tuples / (share * {NORDERS})), 6)::DOUBLE AS worst FROM ({seeded_sql(TRIANGLE_HEAD, TRIANGLE_VARS, p)}) JOIN {shares} USING (machine, atom) GROUP BY 1"


@workload(seed_sweep_sql)
def seed_sweep(spark, d):
    """For a hundred hash seeds: how many machines and atoms got over 1 + DELTA times their share, and the worst ratio."""
    rel, p = triangle_inputs(spark, d), planned_boxes(TRIANGLE)
    n = rel["R"].count()
    parts = [measure.received_by_seed(rel[a.name], a, p, SEEDS, BITS).withColumn("atom", F.lit(a.name)) for a in TRIANGLE.atoms]
    shares = spark.createDataFrame(expected_shares(TRIANGLE, p), "machine int, atom string, share double")
    expected = F.col("share") * n
    return stacked(parts).join(F.broadcast(shares), ["machine", "atom"]).groupBy("seed").agg(F.count_if(F.col("tuples") > (1 + DELTA) * expected).alias("exceeded"), F.round(F.max(F.col("tuples") / expected), 6).alias("worst"))


# --- Profiles ------------------------------------------------------------------------------


@workload("SELECT count(*) AS rows, count(*) - count(lang) AS dropped FROM documents")
def null_join_keys(spark, d):
    """Documents that cannot join on their language."""
    return null_keys(table(spark, d, "documents"), {"lang": "z"})


def class_sql(name: str, rows: str, vars: Sequence[str]) -> str:
    """Class of the relation ``rows``: degrees, and how much of its range of keys it fills."""
    degree = f"greatest({', '.join(f'(SELECT max(n) FROM (SELECT count(*) AS n FROM t GROUP BY {v}))' for v in vars)}, 0)"
    space = " * ".join(f"(SELECT max({v}) - min({v}) + 1 FROM t)" for v in vars)
    sparse = "TRUE" if len(vars) > 1 else f"(SELECT count(*) FROM t) <= 0.5 * {space}"
    return f"(WITH t AS ({rows}) SELECT '{name}' AS name, (SELECT count(*) FROM t) AS rows, CASE WHEN {degree} = 1 AND {sparse} THEN 'matching' WHEN (SELECT count(*) FROM t) >= {profile.DENSE} * {space} THEN 'dense' ELSE 'other' END AS kind)"


@workload(
    lambda: " UNION ALL ".join(
        [
            class_sql("part", "SELECT p_partkey AS x FROM part", "x"),
            class_sql("third", "SELECT p_partkey AS x FROM part WHERE p_partkey % 3 = 0", "x"),
            class_sql("orders", "SELECT o_orderkey AS x, o_custkey AS y FROM orders", "xy"),
            class_sql("permutation", f"SELECT i AS x, {PA} AS y FROM ({I})", "xy"),
            class_sql("grid", "WITH " + _dense_sql("r", "x", "y", DENSE[0]) + " SELECT x, y FROM r", "xy"),
        ]
    )
)
def input_classes(spark, d):
    one, two = parse_cq("q(x) :- R(x)"), parse_cq("q(x, y) :- R(x, y)")
    part = keys(spark, d, "part", "p_partkey", "x")
    made = [("part", one, part), ("third", one, part.where("x % 3 = 0")), ("orders", two, bind(table(spark, d, "orders"), {"o_orderkey": "x", "o_custkey": "y"})), ("permutation", two, triangle_inputs(spark, d)["R"]), ("grid", two, triangle_dense_inputs(spark, d)["R"])]
    found = [(n, profile.classify(q, {"R": df})["R"]) for n, q, df in made]
    return spark.createDataFrame([(n, c.rows, c.kind) for n, c in found], "name string, rows long, kind string")


@workload(
    " UNION ALL ".join(
        f"SELECT '{t}' AS atom, '{a}' AS attribute, sum(n)::BIGINT AS rows, count(*) AS \"distinct\", max(n) AS max_degree, min(v) AS lo, max(v) AS hi FROM (SELECT {a}::BIGINT AS v, count(*) AS n FROM {t} GROUP BY 1)"
        for t, a in (("orders", "o_custkey"), ("lineitem", "l_orderkey"), ("lineitem", "l_suppkey"), ("events", "user_id"))
    )
)
def degree_profile(spark, d):
    out = None
    for t, attrs in (("orders", ["o_custkey"]), ("lineitem", ["l_orderkey", "l_suppkey"]), ("events", ["user_id"])):
        one = profile.profile(table(spark, d, t), t, attrs)
        out = one if out is None else out.unionAll(one)
    return out


@workload("WITH " + _dense_sql("r", "x", "y", DENSE[0]) + " SELECT count(*) AS rows, round(count(*) / 625.0, 6)::DOUBLE AS density FROM r")
def density_profile(spark, d):
    return profile.density(triangle_dense_inputs(spark, d)["R"], [25, 25]).select("rows", F.round("density", 6).alias("density"))


@workload(lambda: f"SELECT machine::INT AS machine, dim, (lo * {LIMIT} >> {BITS})::BIGINT AS lo, (hi * {LIMIT} >> {BITS})::BIGINT AS hi FROM (VALUES " + ", ".join(f"({c}, '{x}', {lo}, {hi})" for c, x, lo, hi in [(c, x, *fixed_boxes(CARTESIAN).boxes[c][x]) for c in fixed_boxes(CARTESIAN).used() for x in "xy"]) + ") AS t(machine, dim, lo, hi)")
def boxes_example(spark, d):
    """The worked example's boxes over the keys of customer and part. The SQL lists the same planner's boxes on a grid, so it
    tests the table and the sizes, not the plan; tests hold the plan against the worked example."""
    from .operators.route import boxes_frame

    return boxes_frame(spark, example_boxes(example_inputs(spark, d)["R"].count()))


def numbers(spark, rows) -> DataFrame:
    return spark.createDataFrame([(k, round(float(v), 4)) for k, v in rows], "name string, value double")


@workload(lambda: " UNION ALL ".join(f"SELECT '{n}' AS name, round({NORDERS} / pow(sum(pow(weight, {u}::DOUBLE)), 1 / {u}::DOUBLE), 4) AS value FROM {weights_sql()}" for n, u in (("cartesian", 2), ("triangle", 1.5), ("join", 1))))
def bounds_uniform(spark, d):
    """Relations all as large as orders."""
    m = orders_keys(spark, d)[1]
    return numbers(spark, [(n, bounds.lower_uniform(m, EXAMPLE, float(sum(lp.max_edge_packing(q).values())))) for n, q in (("cartesian", CARTESIAN), ("triangle", TRIANGLE), ("join", JOIN))])


@workload(lambda: " UNION ALL ".join(f"SELECT 'a={a}' AS name, round(pow({NORDERS}, {a}::DOUBLE) / pow(sum(pow(weight, 2 / {a}::DOUBLE)), {a}::DOUBLE / 2), 4) AS value FROM {weights_sql()}" for a in (0.5, 1.0, 2.0)))
def bounds_power(spark, d):
    """Products of two relations as large as orders, for costs x^a / w."""
    n = orders_keys(spark, d)[1]
    return numbers(spark, [(f"a={a}", bounds.lower_power(n, EXAMPLE, a, 2)) for a in (0.5, 1.0, 2.0)])


@workload(lambda: f"SELECT 'low' AS name, round({NORDERS} / sum(weight), 4) AS value FROM {weights_sql()} UNION ALL SELECT 'high', round({NORDERS} / max(weight), 4) FROM {weights_sql()} UNION ALL SELECT 'join', round({NORDERS} / sum(weight), 4) FROM {weights_sql()}")
def bounds_mixed(spark, d):
    """The bracket, and the bound of orders with customers, which is the bracket's low end."""
    m = {"R": table(spark, d, "orders").count(), "S": table(spark, d, "customer").count()}
    low, high = bounds.mixed_bracket(m, EXAMPLE)
    return numbers(spark, [("low", low), ("high", high), ("join", bounds.lower_mixed(JOIN, m, EXAMPLE)[0])])


def halved(setup: str, enough: str, by: str, steps: int = 90) -> str:
    """SQL that halves the bracket of each row of ``setup`` (by, lo, hi, ...) until ``enough``, an aggregate over the weights at ``mid``, turns true."""
    return (
        f"(WITH RECURSIVE w AS (SELECT * FROM {weights_sql()}), b AS (SELECT *, 0 AS step FROM ({setup}) UNION ALL"
        f" SELECT * EXCLUDE (mid, ok) REPLACE (CASE WHEN ok THEN lo ELSE mid END AS lo, CASE WHEN ok THEN mid ELSE hi END AS hi, step + 1 AS step) FROM (SELECT m.*, (SELECT {enough} FROM w) AS ok FROM (SELECT *, (lo + hi) / 2 AS mid FROM b WHERE step < {steps}) m)) SELECT {by}, hi FROM b WHERE step = {steps})"
    )


# A machine of weight w pays x^a / w; amounts are whole.
GENERAL = [(0.5, 2.0), (1.0, 1.5), (2.0, 1.5), (3.0, 2.0)]


@workload(
    lambda: "SELECT 'a=' || a || ',u=' || u AS name, round(ln(hi), 6) AS log_bound FROM "
    + halved(f"SELECT a, u, m, 0.0::DOUBLE AS lo, pow(m, a) / 4 AS hi FROM (SELECT {NORDERS}::DOUBLE AS m), (VALUES " + ", ".join(f"({a}::DOUBLE, {u}::DOUBLE)" for a, u in GENERAL) + ") AS t(a, u)", "sum(pow(least(floor(pow(mid * weight, 1 / a) * (1 + 1e-12)), m) / m, u)) >= 1 - 1e-12", "a, u")
)
def bounds_general(spark, d):
    """Least load at which all machines can afford enough, for power costs and two packings of relations as large as orders."""
    n = orders_keys(spark, d)[1]
    rows = [(f"a={a},u={u}", round(math.log(bounds.lower_general(n, [Power(w, a) for w in EXAMPLE], u)), 6)) for a, u in GENERAL]
    return spark.createDataFrame(rows, "name string, log_bound double")


def shapes_sql() -> str:
    sizes = {
        "cartesian": "(SELECT count(*) FROM part)::DOUBLE AS m1, (SELECT count(*) FROM supplier)::DOUBLE AS m2, 1.0::DOUBLE AS m3",
        "triangle": f"{NORDERS}::DOUBLE AS m1, ({NORDERS} // 5)::DOUBLE AS m2, ({NORDERS} // 5)::DOUBLE AS m3",
        "join": f"{NORDERS}::DOUBLE AS m1, (SELECT count(*) FROM customer)::DOUBLE AS m2, 1.0::DOUBLE AS m3",
    }
    setup = " UNION ALL ".join(f"SELECT name, m1, m2, m3, greatest(m1, m2, m3) / (SELECT sum(weight) FROM {weights_sql()}) AS lo, greatest(m1, m2, m3) / 4 AS hi FROM (SELECT '{n}' AS name, {m})" for n, m in sizes.items())
    # What a machine can know: the least product over the vertices of the packings of each shape.
    term = "CASE name WHEN 'cartesian' THEN least(1, {L} * weight / m1) * least(1, {L} * weight / m2) WHEN 'join' THEN least(1, {L} * weight / m1, {L} * weight / m2) ELSE least(1, {L} * weight / m1, {L} * weight / m2, {L} * weight / m3, sqrt(pow({L} * weight, 3) / (m1 * m2 * m3))) END"
    exact = halved(f"SELECT *, lo AS low FROM ({setup})", f"sum({term.format(L='mid')}) >= 1 - 1e-12", "name, low")
    doubled = (
        f"(WITH RECURSIVE w AS (SELECT * FROM {weights_sql()}), s AS (SELECT *, lo AS load, 0 AS steps FROM ({setup}) UNION ALL"
        f" SELECT * REPLACE (least(load * 2, hi) AS load, steps + 1 AS steps) FROM s WHERE load < hi AND (SELECT sum({term.format(L='load')}) FROM w) < 1 - 1e-12) SELECT name, arg_max(load, steps) AS doubled, max(steps) AS steps FROM s GROUP BY 1)"
    )
    return f"SELECT name, round(low, 4) AS low, round(hi, 4) AS bound, round(doubled, 4) AS doubled, steps::BIGINT AS steps FROM {exact} JOIN {doubled} USING (name)"


@workload(shapes_sql)
def bounds_shapes(spark, d):
    """Bounds for unequal sizes: bracket, exact by halving, within two by doubling."""
    n = {t: table(spark, d, t).count() for t in ("part", "supplier", "orders", "customer")}
    rows = []
    for name, q, m in (("cartesian", CARTESIAN, {"R": n["part"], "S": n["supplier"]}), ("triangle", TRIANGLE, {"R": n["orders"], "S": n["orders"] // 5, "T": n["orders"] // 5}), ("join", JOIN, {"R": n["orders"], "S": n["customer"]})):
        doubled, steps = bounds.lower_mixed(q, m, EXAMPLE, "double")
        rows.append((name, *[round(x, 4) for x in (bounds.mixed_bracket(m, EXAMPLE)[0], bounds.lower_mixed(q, m, EXAMPLE, tol=1e-13)[0], doubled)], steps))
    return spark.createDataFrame(rows, "name string, low double, bound double, doubled double, steps long")


@workload(
    lambda: f"SELECT 'expected_matching' AS name, round(pow({NORDERS}::DOUBLE, 3) * pow({NORDERS}::DOUBLE / pow({NORDERS}::DOUBLE, 2), 3), 4) AS value UNION ALL SELECT 'expected_dense', round(pow(0.5, 3) * pow(25, 3), 4)"
    f" UNION ALL SELECT 'tail', round(least(1, sum(exp(-0.0625 * {NORDERS} * weight / (3 * (SELECT sum(weight) FROM {weights_sql()}))))), 4) FROM {weights_sql()} UNION ALL SELECT 'known', round(pow(0.25, 0.5) * pow(0.5, 0.5) * pow(1.0, 0.5), 4)"
)
def bounds_knowledge(spark, d):
    """Expected answers, the tail of the load, and what fractions of the atoms let a machine know."""
    n = table(spark, d, "orders").count()
    m = {k: n for k in "RST"}
    return numbers(spark, [("expected_matching", bounds.expected_output(TRIANGLE, m, n)), ("expected_dense", bounds.expected_output(TRIANGLE, m, 25, 0.5)), ("tail", bounds.tail(n, EXAMPLE, 1, 0.25)), ("known", bounds.known_fraction({"R": 0.25, "S": 0.5, "T": 1.0}, lp.max_edge_packing(TRIANGLE)))])


SCALES = [(p, kind) for p in (16, 256, 10_000) for kind in ("uniform", "cycle", "geometric")]
WEIGHT_OF = {"uniform": lambda i: 1.0, "cycle": lambda i: float(1 + i % 7), "geometric": lambda i: float(2 ** (i % 6))}


def planner_scale_sql() -> str:
    weight = "CASE kind WHEN 'uniform' THEN 1 WHEN 'cycle' THEN 1 + i % 7 ELSE pow(2, i % 6) END"
    sets = ", ".join(f"({p}, '{k}')" for p, k in SCALES)
    shapes = ", ".join(f"('{s}', {u}::DOUBLE, {l})" for s, u, l in (("cartesian", 2, 2), ("join", 1, 2), ("triangle", 1.5, 3)))
    return f"SELECT p::BIGINT AS p, kind, shape, round({NORDERS} / pow(sum(pow({weight}, u)), 1 / u), 6)::DOUBLE AS bound, round({NORDERS} * l / max({weight}), 6)::DOUBLE AS single, TRUE AS covers, TRUE AS within FROM (VALUES {sets}) AS s(p, kind), (VALUES {shapes}) AS t(shape, u, l), range(10000) AS r(i) WHERE i < p GROUP BY p, kind, shape, u, l"


@workload(planner_scale_sql)
def planner_scale(spark, d):
    """Plans for up to 10,000 machines and relations as large as orders: bound, all on one machine, whether the boxes cover the space once, and whether
    the packing keeps its constants (block, last shapes, stretch, inflation)."""
    rows, n = [], orders_keys(spark, d)[1]
    for p, kind in SCALES:
        w = [WEIGHT_OF[kind](i) for i in range(p)]
        for shape, q in (("cartesian", CARTESIAN), ("join", JOIN), ("triangle", TRIANGLE)):
            m, made = {a.name: n for a in q.atoms}, pack.pack(q, sides.uniform(q, w))
            k, got = len(q.vars), made.stats()
            within = got["block_share"] > 0.5 and got["last_shapes_share"] > 1 and got["stretch"] <= 2 ** (k + 1) and all(f <= 2 ** (k + 1 + len(q.atom(a).vars)) for (_, a), f in made.inflation(q).items())
            rows.append((p, kind, shape, bounds.lower_uniform(n, w, float(sum(lp.max_edge_packing(q).values()))), baselines.single_machine_load(m, [Linear(x) for x in w]), pack.covers(made), within))
    made = spark.createDataFrame(rows, "p long, kind string, shape string, bound double, single double, covers boolean, within boolean")
    # Halves go up, as in SQL: a size over a power of two can lie in the middle.
    return made.withColumns({c: F.round(c, 6) for c in ("bound", "single")})


def profiles() -> dict[str, list[float]]:
    """Machine sets for planning sweeps."""
    import random

    r = random.Random(64)
    return {"paper17": EXAMPLE, "uniform16": [1.0] * 16, "uniform64": [1.0] * 64, "geometric48": [float(2 ** (i % 6)) for i in range(48)], "giant64": [50.0] + [1.0] * 63, "random64": [float(r.randint(1, 20)) for _ in range(64)]}


def planner_sweep(spark, d) -> DataFrame:
    """Planned load over the bound, for every machine set, shape and variant, of relations as large as orders."""
    rows, n = [], orders_keys(spark, d)[1]
    for name, w in profiles().items():
        for shape, q in (("cartesian", CARTESIAN), ("join", JOIN), ("triangle", TRIANGLE)):
            m = {a.name: n for a in q.atoms}
            bound = bounds.lower_uniform(n, w, float(sum(lp.max_edge_packing(q).values())))
            costs = [Linear(x) for x in w]
            up, best = (plan(q, m, costs, "uniform", rounding=r).packing.planned_load(q, m, w) for r in ("up", "search"))
            rows.append((name, shape, *[round(x / bound, 4) for x in (up, best, baselines.grid_load(q, m, baselines.shares(q, m, len(w)), w), baselines.fastest_grid(q, m, w)[1], baselines.single_machine_load(m, costs))]))
    return spark.createDataFrame(rows, "profile string, shape string, round_up double, search double, grid double, grid_fastest double, single double")


QUERIES["planner_sweep"] = planner_sweep
