"""User-defined functions: a table function that solves a simulation, a cosine, combinations."""

from __future__ import annotations

from itertools import combinations

import numpy as np
import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import types as T
from pyspark.sql.functions import pandas_udf, udtf


@udtf(returnType=T.StructType().add("sim", T.IntegerType()).add("id", T.LongType()).add("label", T.LongType()))
class ComponentLabels:
    """component_labels(TABLE(sampled) PARTITION BY sim): the memo rows of each simulation."""

    def __init__(self):
        self.sim, self.src, self.dst = None, [], []

    def eval(self, row):
        self.sim = row["sim"]
        self.src.append(row["src"])
        self.dst.append(row["dst"])

    def terminate(self):
        from spreadmax.operators.components import label_components

        if self.src:
            ids, labels = label_components(np.array(self.src, np.int64), np.array(self.dst, np.int64))
            for i, label in zip(ids.tolist(), labels.tolist(), strict=True):
                yield self.sim, i, label


@udtf(returnType=T.StructType().add("ids", T.ArrayType(T.LongType())))
class Combinations:
    """combinations(array, k): all k-subsets in order."""

    def eval(self, ids, k: int):
        for c in combinations(sorted(ids), k):
            yield (list(c),)


@pandas_udf(T.DoubleType())
def cosine(a: pd.Series, b: pd.Series) -> pd.Series:
    x, y = np.stack(a.to_list()).astype(float), np.stack(b.to_list()).astype(float)
    return pd.Series((x * y).sum(axis=1) / np.sqrt((x * x).sum(axis=1) * (y * y).sum(axis=1)))


@pandas_udf(T.ArrayType(T.LongType()))
def lane_min(lanes: pd.Series) -> list:
    """Lane-wise minimum of label arrays: the form without lane columns, for comparison."""
    return np.stack(lanes.to_list()).min(axis=0).tolist()


def register(spark: SparkSession) -> None:
    spark.udtf.register("component_labels", ComponentLabels)
    spark.udtf.register("combinations", Combinations)
    spark.udf.register("cosine", cosine)
    spark.udf.register("lane_min", lane_min)
