"""SQL-registered functions and table functions."""

from __future__ import annotations

from pyspark.sql import SparkSession
from pyspark.sql import types as T
from pyspark.sql.functions import udtf


@udtf(returnType=T.StructType([T.StructField("name", T.StringType()), T.StructField("args", T.ArrayType(T.StringType())), T.StructField("types", T.ArrayType(T.StringType()))]))
class ScanSqlCalls:
    """One row for each function call of a statement, in visit order."""

    def eval(self, sql: str):
        from querygrade.functions.sqlscan import scan

        for c in scan(sql)["calls"]:
            yield c["name"], c["args"], c["types"]


@udtf(returnType=T.StructType([T.StructField("path", T.IntegerType()), *(T.StructField(n, T.DoubleType()) for n in "xyz")]))
class DumpPoints:
    """One row for each vertex of a geometry text."""

    def eval(self, text: str):
        from querygrade.functions.geometry import Invalid, dump_points, parse_text

        try:
            shape = parse_text(text)
        except Invalid:
            return
        for k, p in enumerate(dump_points(shape), 1):
            yield k, float(p[0]), float(p[1]), float(p[2]) if len(p) > 2 else None


def register(spark: SparkSession) -> None:
    from querygrade.functions import geometry_udfs

    spark.udtf.register("scan_sql_calls", ScanSqlCalls)
    spark.udtf.register("dump_points", DumpPoints)
    geometry_udfs.register(spark)
