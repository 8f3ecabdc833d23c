"""SQL names: views of the graphs and their matchings, and functions."""

from __future__ import annotations

from collections.abc import Callable

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession, functions as F
from pyspark.sql.types import ArrayType, LongType

from ..catalog import make_importable
from ..operators.localmax import local_max
from .kernels import local_max_phases, path_optimum


def register_views(spark: SparkSession, sf_dir: str, graphs: dict[str, Callable[[SparkSession, str], DataFrame]]) -> list[str]:
    """``edges_<name>`` and ``matching_<name>`` as temporary views."""
    names = []
    for name, build in graphs.items():
        edges = build(spark, sf_dir)
        edges.createOrReplaceTempView(f"edges_{name}")
        local_max(edges).matching.createOrReplaceTempView(f"matching_{name}")
        names += [f"edges_{name}", f"matching_{name}"]
    return names


def register_functions(spark: SparkSession) -> None:
    """``path_optimum(array<double>, boolean)``: positions that the best choice takes, and the
    table function ``local_match(TABLE(edges) PARTITION BY grp)`` for many small graphs."""
    make_importable(spark)

    @F.pandas_udf(ArrayType(LongType()))
    def optimum(w: pd.Series, cycle: pd.Series) -> pd.Series:
        return pd.Series([sorted(path_optimum(list(x), bool(c))) if x is not None and len(x) else [] for x, c in zip(w, cycle)])

    spark.udf.register("path_optimum", optimum)

    @F.udtf(returnType="grp string, u long, v long, phase int")
    class LocalMatch:
        def __init__(self):
            self.rows = []

        def eval(self, row):
            self.rows.append((str(row["grp"]), row["u"], row["v"], row["w"]))

        def terminate(self):
            self.rows.sort(key=lambda r: (-r[3], r[1], r[2]))
            u, v = (np.array([r[k] for r in self.rows], np.int64) for k in (1, 2))
            matched, _ = local_max_phases(u, v)
            for r, phase in zip(self.rows, matched.tolist()):
                if phase:
                    yield r[0], r[1], r[2], phase

    spark.udtf.register("local_match", LocalMatch)
