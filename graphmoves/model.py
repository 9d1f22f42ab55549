"""Schemas and records. A graph's edges hold both directions of every edge; loops stand in `nodes`, once."""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark.sql import DataFrame
from pyspark.sql import types as T

EDGE_COLUMNS, NODE_COLUMNS, LABEL_COLUMNS = ("src", "dst", "w"), ("id", "loop", "deg", "mass"), ("id", "c")
RUNS = T.StructType([T.StructField(n, t) for n, t in (
    ("graph", T.StringType()), ("algo", T.StringType()), ("objective", T.StringType()), ("seed", T.IntegerType()),
    ("params", T.MapType(T.StringType(), T.StringType())), ("seconds", T.DoubleType()), ("modularity", T.DoubleType()),
    ("map_equation", T.DoubleType()), ("clusters", T.LongType()), ("ari_truth", T.DoubleType()))])
TRACE = "level int, round int, sub_round int, moved long, clusters long, score double"


def require(df: DataFrame, columns: tuple[str, ...]) -> DataFrame:
    if missing := [c for c in columns if c not in df.columns]:
        raise ValueError(f"columns {missing} are missing")
    return df.select(*columns)


@dataclass(frozen=True)
class WeightedGraph:
    edges: DataFrame
    nodes: DataFrame  # mass: how many nodes of the first level a node stands for
    total: int | float  # sum of degrees
    buckets: int = 0  # of edges by src and nodes by id, the same number; 0: neither is bucketed

    @property
    def exact(self) -> bool:
        """Products of two weights fit 64 bits; otherwise gains are decimals."""
        return self.total < 3_000_000_000


@dataclass(frozen=True)
class Config:
    sub_rounds: int = 4
    max_rounds: int = 8
    max_levels: int = 50
    seed: int = 0
    hash_kind: str = "fast"  # "portable": the same in any SQL engine
    strategy: str = "edge_join"  # or "broadcast_labels", "cluster_local"
    stats: str = "per_sub_round"  # "per_round": cluster measures grow stale within a round
    broadcast_bytes: int = 32 << 20  # what labels may take at most to be broadcast; beyond, edges are joined
    trace: str = "rounds"  # "sub_rounds": a row for each of these too
    scores: bool = False  # the trace holds scores, at the price of a pass over the edges for each row
    min_gain_digits: int = 12


@dataclass
class Result:
    labels: DataFrame
    levels: int
    trace: list[tuple] = field(default_factory=list)
    members: list[DataFrame] = field(default_factory=list)
