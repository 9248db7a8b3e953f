"""SQL surface: functions, views, and a table function for the path of a bucket."""

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql.functions import PandasUDFType, pandas_udf, udtf


def register(spark: SparkSession, edges: DataFrame | None = None, assign: DataFrame | None = None) -> None:
    """Temporary functions pf_term(cnt, p) and bucket_hash(vid, seed, k), inlined by the optimiser, table function expand_path, and views edge and assign."""
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION pf_term(cnt BIGINT, p DOUBLE) RETURNS DOUBLE RETURN 1.0D - pow(1.0D - p, cnt)")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION bucket_hash(vid BIGINT, seed INT, k INT) RETURNS INT RETURN CAST(CAST(conv(substring(md5(concat_ws('#', CAST(vid AS STRING), CAST(seed AS STRING))), 1, 8), 16, 10) AS BIGINT) % k AS INT)")
    spark.udtf.register("expand_path", expand_path)
    if edges is not None:
        edges.createOrReplaceTempView("edge")
    if assign is not None:
        assign.createOrReplaceTempView("assign")


@udtf(returnType="level int, code int")
class expand_path:
    """The codes of a bucket's ancestors under halving, from the root's children down."""

    def eval(self, code: int, levels: int):
        for level in range(1, levels + 1):
            yield level, code >> (levels - level)


def pfanout_agg(p: float):
    """A grouped Arrow aggregate of counts, for reference: the built-in expression is faster."""

    def agg(cnt: pd.Series) -> float:
        return float((1 - (1 - p) ** cnt).sum())

    return pandas_udf(agg, "double", PandasUDFType.GROUPED_AGG)
