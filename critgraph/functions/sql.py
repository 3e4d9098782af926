"""Functions for SQL and DataFrames: lane arithmetic, means, and a table function for critical paths."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import Column, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.functions import pandas_udf, udtf


def lane_max(a: Column, b: Column) -> Column:
    """Lane-wise maximum of weight vectors; an absent (null) element gives way."""
    return F.zip_with(a, b, lambda x, y: F.greatest(x, y))


def lane_add(a: Column, b: Column) -> Column:
    """Lane-wise sum; an absent element makes the sum absent."""
    return F.zip_with(a, b, lambda x, y: x + y)


def lane_total(terms: Column) -> Column:
    """Sum of array<struct<term, w array>> by lane."""
    return F.aggregate(F.slice(terms, 2, F.size(terms)), F.element_at(terms, 1)["w"], lambda acc, t: F.zip_with(acc, t["w"], lambda x, y: x + y))


@pandas_udf("double")
def geo_mean(v: pd.Series) -> float:
    """Geometric mean with a floor for zeros (a grouped aggregate)."""
    import numpy as np

    return float(np.exp(np.log(v.clip(lower=1e-6)).mean())) if len(v) else float("nan")


@udtf(returnType="program_id int, src_seq bigint, src_stage string, dst_seq bigint, dst_stage string, kind string, w int, cp bigint")
class CriticalPath:
    """The longest path of a partition's edges: TABLE(edges) PARTITION BY program_id ORDER BY dst_seq."""

    def __init__(self):
        self.rows, self.program = [], None

    def eval(self, row):
        self.program = row["program_id"]
        self.rows.append((row["src_seq"], row["src_stage"], row["dst_seq"], row["dst_stage"], row["kind"], row["w"]))

    def terminate(self):
        out, degree = {}, {}
        for r in self.rows:
            out.setdefault(r[:2], []).append(r)
            degree[r[2:4]] = degree.get(r[2:4], 0) + 1
            degree.setdefault(r[:2], 0)
        at, via = dict.fromkeys(degree, 0), {}
        ready = [v for v, d in degree.items() if not d]
        while ready:
            v = ready.pop()
            for r in out.get(v, ()):
                u, length = r[2:4], at[v] + r[5]
                if length > at[u] or (length == at[u] and (u not in via or (r[0], r[1], r[4]) > (via[u][0], via[u][1], via[u][4]))):
                    at[u], via[u] = length, r
                degree[u] -= 1
                if not degree[u]:
                    ready.append(u)
        if not at:
            return
        v = max(at, key=lambda x: (at[x], x))
        path = []
        while v in via:
            path.append((*via[v], at[v]))
            v = via[v][:2]
        for r in reversed(path):
            yield self.program, *r


def register(spark: SparkSession) -> None:
    """Make the functions available in SQL: geo_mean, critical_path, seeded_choice, lane_max, lane_add."""
    spark.udf.register("geo_mean", geo_mean)
    spark.udtf.register("critical_path", CriticalPath)
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION seeded_choice(seq BIGINT, pc BIGINT, permille INT) RETURNS BOOLEAN RETURN (seq * 7919 + pc * 104729 + 42 * 1299709) % 1000 < permille")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION lane_max(a ARRAY<INT>, b ARRAY<INT>) RETURNS ARRAY<INT> RETURN zip_with(a, b, (x, y) -> greatest(x, y))")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION lane_add(a ARRAY<INT>, b ARRAY<INT>) RETURNS ARRAY<INT> RETURN zip_with(a, b, (x, y) -> x + y)")
