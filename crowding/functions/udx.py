"""Functions for SQL and DataFrames: Erdős–Gallai checks, minimum lift cost, enumeration as a table function."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.functions import pandas_udf, udtf

from crowding.core.feasibility import eg_test
from crowding.core.lifting import enumerate_lifts, min_cost


@pandas_udf(T.BooleanType())
def eg_ok(demands: pd.Series) -> pd.Series:
    """Whether arrays of demands are realizable; null for null."""
    return demands.map(lambda d: None if d is None else eg_test(d))


def eg_ok_native(demands: str) -> Column:
    """The same as an expression over an array<int> column."""
    d = F.reverse(F.array_sort(F.filter(demands, lambda x: x > 0)))
    total = lambda a: F.aggregate(a, F.lit(0).cast("long"), lambda s, x: s + x)
    row = lambda r: total(F.slice(d, F.lit(1), r)) <= r * (r - 1) + total(F.transform(F.slice(d, r + 1, F.greatest(F.size(d) - r, F.lit(0))), lambda x: F.least(x, r)))
    return F.when(F.size(d) == 0, F.lit(True)).otherwise((total(d) % 2 == 0) & F.forall(F.sequence(F.lit(1), F.greatest(F.size(d), F.lit(1))), row))


@pandas_udf(T.LongType())
def min_lift_cost_2(degree: pd.Series) -> int:
    """Grouped aggregate: minimum lift cost of a group's degrees for k = 2."""
    return min_cost(degree.value_counts().reindex(range(int(degree.max()) + 1), fill_value=0).to_numpy(), 2)


def min_lift_cost(k: int):
    """The same for any k."""

    @pandas_udf(T.LongType())
    def cost(degree: pd.Series) -> int:
        return min_cost(degree.value_counts().reindex(range(int(degree.max()) + 1), fill_value=0).to_numpy(), k)

    return cost


@udtf(returnType=T.StructType([*[T.StructField(c, T.IntegerType()) for c in ("lift_id", "degree", "x")], T.StructField("b_after", T.LongType())]))
class Lifts:
    """lifts(blocks, k, cost): every lift of a cost, a row a degree."""

    def eval(self, blocks: list, k: int, cost: int):
        for i, lift in enumerate(enumerate_lifts(blocks, k, cost)):
            for d, (x, b) in enumerate(zip(lift.x, lift.blocks(blocks))):
                yield i, d, int(x), int(b)


def conflicts_by_arrow(edges: DataFrame, demanders: list[int]) -> DataFrame:
    """Edges among a small list of vertices, filtered in Arrow batches."""
    wanted = pa.array(sorted(set(demanders)), pa.int64())

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        import pyarrow.compute as pc

        for b in batches:
            yield b.filter(pc.and_(pc.is_in(b.column("u"), value_set=wanted), pc.is_in(b.column("v"), value_set=wanted)))

    return edges.select("u", "v").mapInArrow(run, "u long, v long")


def register(spark: SparkSession) -> None:
    """Names for SQL: eg_ok(array), min_lift_cost_2(degree), lifts(array, k, cost), crowd_level as min(size)."""
    spark.udf.register("eg_ok", eg_ok)
    spark.udf.register("min_lift_cost_2", min_lift_cost_2)
    spark.udtf.register("lifts", Lifts)


def register_views(edges: DataFrame) -> None:
    """Views edges, degrees, blocks for SQL."""
    from crowding.operators import graph as g

    deg = g.degrees(edges)
    for name, df in (("edges", edges), ("degrees", deg), ("blocks", g.block_sequence(deg))):
        df.createOrReplaceTempView(name)
