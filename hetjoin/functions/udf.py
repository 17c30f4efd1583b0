"""Functions for SQL users."""

from __future__ import annotations

from pyspark.sql import Column, SparkSession
from pyspark.sql import functions as F

from ..plans import pack, sides
from ..plans.cost import Linear, Power, Tabulated
from ..plans.query import parse_cq


def cost(kind: str, params: dict, amount: Column) -> Column:
    """Native expression of a cost."""
    if kind == "linear":
        return Linear(params["w"]).column(amount)
    if kind == "power":
        return Power(params["w"], params["a"]).column(amount)
    return Tabulated(tuple(sorted((float(k), v) for k, v in params.items()))).column(amount)


def box_rows(weights: str, query: str) -> list[tuple[int, str, int, int]]:
    cq, w = parse_cq(query), [float(x) for x in weights.split(",")]
    p = pack.pack(cq, sides.uniform(cq, w))
    return [(c, x, *p.boxes[c][x]) for c in p.used() for x in p.vars]


def register(spark: SparkSession) -> None:
    """``SELECT * FROM boxes('4,2,1,1', 'q(x,y) :- R(x), S(y)')`` lists a packing."""

    class Boxes:
        def eval(self, weights: str, query: str):
            yield from box_rows(weights, query)

    spark.udtf.register("boxes", F.udtf(Boxes, returnType="machine int, dim string, lo long, hi long"))
