"""Full conjunctive queries: natural joins without projection, selection or self-join."""

from __future__ import annotations

import re
from collections.abc import Mapping, Sequence
from dataclasses import dataclass
from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T


@dataclass(frozen=True)
class Atom:
    name: str
    vars: tuple[str, ...]


@dataclass(frozen=True)
class FullCQ:
    atoms: tuple[Atom, ...]

    def __post_init__(self):
        if not self.atoms:
            raise ValueError("a query needs an atom")
        names = [a.name for a in self.atoms]
        if len(set(names)) < len(names):
            raise ValueError("a relation may appear once only; use parse_cq(..., allow_copies=True) for aliased copies")
        for a in self.atoms:
            if not a.vars or len(set(a.vars)) < len(a.vars):
                raise ValueError(f"atom {a.name} needs variables, each once")

    @property
    def vars(self) -> tuple[str, ...]:
        return tuple(dict.fromkeys(v for a in self.atoms for v in a.vars))

    def atom(self, name: str) -> Atom:
        return next(a for a in self.atoms if a.name == name)

    def having(self, var: str) -> list[Atom]:
        return [a for a in self.atoms if var in a.vars]


def parse_cq(text: str, allow_copies: bool = False) -> FullCQ:
    """``q(x, y) :- R(x), S(y)``. The head has to list exactly the variables of the body."""
    m = re.fullmatch(r"\s*\w+\s*\(([^)]*)\)\s*(?::-|=|<-)\s*(.+?)\s*\.?\s*", text, re.S)
    if not m:
        raise ValueError(f"no query: {text!r}")
    head = [v.strip() for v in m[1].split(",") if v.strip()]
    atoms, seen = [], {}
    for name, inside in re.findall(r"(\w+)\s*\(([^)]*)\)", m[2]):
        seen[name] = seen.get(name, 0) + 1
        if seen[name] > 1 and allow_copies:
            name = f"{name}__{seen[name]}"
        atoms.append(Atom(name, tuple(v.strip() for v in inside.split(","))))
    cq = FullCQ(tuple(atoms))
    if sorted(head) != sorted(cq.vars):
        raise ValueError(f"head {head} is not the body's variables {list(cq.vars)}: projections are not full queries")
    return cq


def _as_key(df: DataFrame, column: str):
    kind, c = df.schema[column].dataType, F.col(column)
    if isinstance(kind, T.IntegralType):
        return c.cast("long")
    if isinstance(kind, T.BooleanType):
        return c.cast("int").cast("long")
    if isinstance(kind, T.StringType):
        return c
    if isinstance(kind, (T.DateType, T.TimestampType)):
        return F.unix_micros(c.cast("timestamp"))
    if isinstance(kind, T.DecimalType):
        return (c * F.lit(10**kind.scale).cast("decimal(38,0)")).cast("long")
    if isinstance(kind, T.StructType):
        # A key with a part missing is no key.
        return F.when(reduce(lambda a, b: a & b, [c[f.name].isNotNull() for f in kind.fields], c.isNotNull()), c)
    raise TypeError(f"{column}: {kind.simpleString()} cannot be a join variable")


def bind(df: DataFrame, columns: Mapping[str, str], payload: Sequence[str] = ()) -> DataFrame:
    """Columns as variables of one common key type; rows with a null key never join and go."""
    keys = [_as_key(df, c).alias(v) for c, v in columns.items()]
    return df.select(*keys, *payload).dropna(subset=list(columns.values()))


def null_keys(df: DataFrame, columns: Mapping[str, str]) -> DataFrame:
    """rows, dropped: how many there are, and how many :func:`bind` drops for a null key."""
    missing = reduce(lambda a, b: a | b, [_as_key(df, c).isNull() for c in columns])
    return df.agg(F.count("*").alias("rows"), F.coalesce(F.sum(missing.cast("long")), F.lit(0)).alias("dropped"))


def restrict(df: DataFrame, predicate) -> DataFrame:
    """A selection; it belongs before statistics and planning, outside the query."""
    return df.filter(predicate)
