"""Table functions and a grouped aggregate for small graphs."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import functions as F


def register_table_functions(spark: SparkSession) -> None:
    """small_graph_cluster(TABLE(edges) PARTITION BY g): clusters every partition's edges (src, dst, w); modularity_part(src, dst, w, c_src, c_dst)."""

    @F.udtf(returnType="id bigint, cid bigint")
    class SmallGraphCluster:
        def __init__(self):
            self.rows = []

        def eval(self, row):
            self.rows.append((row["src"], row["dst"], row["w"]))

        def terminate(self):
            import numpy as np

            from lattica.operators import kernel
            from lattica.operators.options import Options

            if not self.rows:
                return
            e = np.array(self.rows, np.int64)
            ids, where = np.unique(e[:, :2], return_inverse=True)
            where = where.reshape(-1, 2)
            g = kernel.Graph(ids, np.bincount(where[:, 0], e[:, 2]).astype(np.int64), where[:, 0], where[:, 1], e[:, 2], 1, int(e[:, 2].sum()))
            for v, c in zip(ids.tolist(), ids[kernel.two_way(g, Options())].tolist(), strict=True):
                yield v, c

    spark.udtf.register("small_graph_cluster", SmallGraphCluster)

    @F.pandas_udf("double")
    def modularity_part(src: pd.Series, dst: pd.Series, w: pd.Series, c_src: pd.Series, c_dst: pd.Series) -> float:
        total = float(w.sum())
        if not total:
            return 0.0
        degree = w.groupby(c_src).sum()
        return float(w[c_src == c_dst].sum()) / total - float(((degree / total) ** 2).sum())

    spark.udf.register("modularity_part", modularity_part)
