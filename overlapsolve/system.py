"""The data model: a sparse system as DataFrames, its overlapping decomposition, and schema checks."""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark.sql import DataFrame
from pyspark.sql import types as T

ENTRIES = T.StructType([T.StructField("i", T.LongType()), T.StructField("j", T.LongType()), T.StructField("a", T.DoubleType())])
VEC = T.StructType([T.StructField("i", T.LongType()), T.StructField("x", T.DoubleType())])
OWNER = T.StructType([T.StructField("i", T.LongType()), T.StructField("p", T.IntegerType())])
MEMBER = T.StructType([T.StructField("p", T.IntegerType()), T.StructField("i", T.LongType()), T.StructField("slot", T.IntegerType()), T.StructField("layer", T.IntegerType()), T.StructField("owned", T.BooleanType()), T.StructField("surface", T.BooleanType())])


def require_schema(df: DataFrame, schema: T.StructType) -> DataFrame:
    """The columns of the schema, in its order; a missing or differently typed one raises ValueError."""
    have = dict(df.dtypes)
    wrong = [f"{f.name}: {have.get(f.name)} is not {f.dataType.simpleString()}" for f in schema if have.get(f.name) != f.dataType.simpleString()]
    if wrong:
        raise ValueError("; ".join(wrong))
    return df.select(*schema.fieldNames())


@dataclass
class Sys:
    """A u = f in parts. `name` keys what workers keep between supersteps."""

    entries: DataFrame
    rhs: DataFrame
    owner: DataFrame
    parts: int
    member: DataFrame | None = None
    interp: DataFrame | None = None
    name: str = ""
    extra: dict = field(default_factory=dict)

    def __post_init__(self) -> None:
        self.entries, self.rhs, self.owner = require_schema(self.entries, ENTRIES), require_schema(self.rhs, VEC), require_schema(self.owner, OWNER)


@dataclass(frozen=True)
class Config:
    """How to run: overlap layers, local solver, weights of local and coarse correction, stop rule, local solves per exchange."""

    delta: int = 1
    solver: str = "direct"
    weights: tuple[float, float] = (0.5, 0.5)
    tol: float = 1e-8
    max_iter: int = 200
    sweeps: int = 1
    checkpoint_every: int = 4
    coarse_limit: int = 200_000
    seed: int = 42
    timeout_s: float = 60.0
    rtol: float = 0.1
    coarse: str = "direct"  # or vcycle (aggregation), multigrid (geometric, on Sys.extra["coarse_shape"]), decomposed (a system of its own)
    coarse_parts: int = 4
    transfer: str = "p2p"  # or tree: shares of the coarse right-hand side are added up on the executors first
