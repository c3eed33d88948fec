"""Problem sizes and the schemas that the public functions exchange."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import types as T

#: usable bits of a word: words stay non-negative, so signed order is numeric order
BITS = 63


@dataclass(frozen=True)
class ProblemSpec:
    """``m`` orbitals, ``n`` of them occupied."""

    m: int
    n: int

    def __post_init__(self) -> None:
        if not 0 <= self.n <= self.m:
            raise ValueError(f"need 0 <= n <= m, got m={self.m} n={self.n}")

    @property
    def words(self) -> int:
        return max(1, -(-self.m // BITS))

    @property
    def names(self) -> list[str]:
        return [f"w{k}" for k in range(self.words)]

    @property
    def source_names(self) -> list[str]:
        return [f"s{w}" for w in self.names]

    @property
    def order(self) -> list[str]:
        """Columns by which configurations are compared: highest word first."""
        return self.names[::-1]


def _longs(*names: str) -> list[T.StructField]:
    return [T.StructField(n, T.LongType()) for n in names]


def space_schema(spec: ProblemSpec) -> T.StructType:
    return T.StructType(_longs(*spec.names))


def edge_schema(spec: ProblemSpec, value: T.DataType) -> T.StructType:
    return T.StructType([*_longs(*spec.source_names, *spec.names), T.StructField("h", value), T.StructField("kind", T.IntegerType())])


HISTORY = T.StructType([T.StructField("iter", T.IntegerType()), *(T.StructField(n, T.DoubleType()) for n in ("energy", "variance")), *_longs("n_space", "n_generated", "n_unique"), T.StructField("seconds", T.MapType(T.StringType(), T.DoubleType()))])
PARAMS = T.StructType([T.StructField("iter", T.IntegerType()), T.StructField("name", T.StringType()), T.StructField("shape", T.ArrayType(T.IntegerType())), T.StructField("data", T.ArrayType(T.DoubleType()))])


def require(frame: DataFrame, names: list[str]) -> DataFrame:
    """``frame`` if it has the columns, else an error that names the missing ones."""
    missing = [n for n in names if n not in frame.columns]
    if missing:
        raise ValueError(f"missing columns {missing}; there are {frame.columns}")
    return frame
