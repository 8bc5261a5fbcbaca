"""User functions for SQL: normal tail, Kendall aggregate, ball of a small graph; built-in expressions are the faster way in DataFrames."""

from __future__ import annotations

import math

import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql.functions import pandas_udf, udtf
from pyspark.sql.types import DoubleType, IntegerType, LongType, StructField, StructType

from ..sources.graphs import ship


@pandas_udf(DoubleType())
def normal_sf(z: pd.Series) -> pd.Series:
    """Chance of a standard normal above z; null for null."""
    return z.map(lambda x: None if pd.isna(x) else math.erfc(x / math.sqrt(2)) / 2)


@pandas_udf(LongType())
def kendall_s(a: pd.Series, b: pd.Series) -> int:
    """Vote sum of a group of bounded size (one task holds it); rows with a null are left out."""
    from vicicorr.operators.kendall import block_sum

    ok = a.notna() & b.notna()
    return block_sum(a[ok].to_numpy(), b[ok].to_numpy())


@udtf(returnType=StructType([StructField("node", LongType()), StructField("dist", IntegerType())]))
class BallOf:
    """Nodes within ``h`` hops of ``root`` in a graph given as an array of structs (u, v), both directions."""

    def eval(self, root: int, h: int, arcs: list):
        near: dict[int, list[int]] = {}
        for arc in arcs or ():
            near.setdefault(arc[0], []).append(arc[1])
        seen, front = {root}, [root]
        yield root, 0
        for d in range(1, h + 1):
            front = sorted({v for u in front for v in near.get(u, ())} - seen)
            seen.update(front)
            for v in front:
                yield v, d


#: The test over a view dens(size, cnt_a, cnt_b) in plain SQL; {dens} names the view.
TEST_SQL = """
WITH r AS (SELECT cnt_a / size AS da, cnt_b / size AS db FROM {dens}),
c AS (SELECT da, db, count(*) AS w FROM r GROUP BY da, db),
s AS (SELECT coalesce(sum(sign(x.da - y.da) * sign(x.db - y.db) * x.w * y.w), 0) AS s FROM c x JOIN c y ON x.da < y.da),
n AS (SELECT cast(count(*) AS double) AS n FROM r),
ta AS (SELECT sum(u * (u - 1)) AS t2, sum(u * (u - 1) * (u - 2)) AS t3, sum(u * (u - 1) * (2 * u + 5)) AS t5 FROM (SELECT cast(sum(w) AS double) AS u FROM c GROUP BY da) q),
tb AS (SELECT sum(u * (u - 1)) AS t2, sum(u * (u - 1) * (u - 2)) AS t3, sum(u * (u - 1) * (2 * u + 5)) AS t5 FROM (SELECT cast(sum(w) AS double) AS u FROM c GROUP BY db) q),
v AS (SELECT (n * (n - 1) * (2 * n + 5) - ta.t5 - tb.t5) / 18 + ta.t3 * tb.t3 / (9 * n * (n - 1) * (n - 2)) + ta.t2 * tb.t2 / (2 * n * (n - 1)) AS var_s FROM n, ta, tb)
SELECT cast(n AS bigint) AS n, cast(s AS bigint) AS s, s / sqrt(var_s) AS z FROM n, s, v
"""


def register(spark: SparkSession) -> None:
    """Names for SQL: normal_sf(z), kendall_s(a, b), ball_of(root, h, arcs)."""
    ship(spark)
    spark.udf.register("normal_sf", normal_sf)
    spark.udf.register("kendall_s", kendall_s)
    spark.udtf.register("ball_of", BallOf)


def sql_test(spark: SparkSession, dens):
    """The test on a DataFrame of densities, by SQL text alone."""
    return spark.sql(TEST_SQL, dens=dens.select("size", "cnt_a", "cnt_b"))


__all__ = ["BallOf", "kendall_s", "normal_sf", "register", "sql_test"]
