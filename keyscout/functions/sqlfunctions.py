"""SQL surface: a table function for hitting sets and an aggregate that minimises masks."""

from __future__ import annotations

from pyspark.sql import SparkSession
from pyspark.sql import functions as F


def register(spark: SparkSession) -> None:
    """minimal_hitting_sets(edges array<bigint>, m int) -> (key_mask), and minimize_agg(mask) -> array<bigint>."""

    @F.udtf(returnType="key_mask: bigint")
    class HittingSets:
        def eval(self, edges: list, m: int):
            from keyscout.plans.hitting import minimal_hitting_sets

            for mask in minimal_hitting_sets([int(e) for e in edges], int(m)):
                yield (mask,)

    spark.udtf.register("minimal_hitting_sets", HittingSets)
    spark.udf.register("minimize_agg", minimize_agg())


def minimize_agg():
    """Grouped aggregate: the masks of a group that contain no other one, sorted."""
    from pyspark.sql.functions import PandasUDFType

    def smallest(mask):
        from keyscout.functions.masks import minimal_masks

        return sorted(minimal_masks(int(v) for v in mask))

    return F.pandas_udf(smallest, "array<bigint>", PandasUDFType.GROUPED_AGG)
