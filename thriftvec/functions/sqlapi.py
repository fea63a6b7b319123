"""SQL surface: registered functions, and a table function that searches a saved vector table."""

from __future__ import annotations

from pyspark.sql import SparkSession
from pyspark.sql import functions as F


def register(spark: SparkSession) -> None:
    """l2sq, dot_product, vec_mean (aggregate) and vec_knn (table function) for SQL."""
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION l2sq(a ARRAY<FLOAT>, b ARRAY<FLOAT>) RETURNS DOUBLE RETURN aggregate(zip_with(a, b, (x, y) -> (double(x) - double(y)) * (double(x) - double(y))), 0D, (s, v) -> s + v)")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION dot_product(a ARRAY<FLOAT>, b ARRAY<FLOAT>) RETURNS DOUBLE RETURN aggregate(zip_with(a, b, (x, y) -> double(x) * double(y)), 0D, (s, v) -> s + v)")

    def mean(v):
        import numpy as np

        return np.mean(np.array(v.tolist(), float), axis=0).tolist()

    spark.udf.register("vec_mean", F.pandas_udf(mean, "array<double>", F.PandasUDFType.GROUPED_AGG))

    @F.udtf(returnType="query_id: bigint, rank: int, node_id: bigint, dist: double")
    class VecKnn:
        """vec_knn(TABLE(queries) or scalars, path, k): nearest rows of a vector file set (node_id, v), read once per task."""

        def __init__(self):
            self.path = None

        def eval(self, query_id: int, qv: list, path: str, k: int):
            import numpy as np

            if self.path != path:
                import pyarrow.dataset as ds

                t = ds.dataset(path.removeprefix("file:"), format="parquet").to_table(columns=["node_id", "v"])
                self.ids = t.column("node_id").to_numpy()
                self.x = np.array(t.column("v").to_pylist(), np.float64)
                self.path = path
            q = np.asarray(qv, np.float64)
            d = ((self.x - q) ** 2).sum(1)
            for r, i in enumerate(np.lexsort((self.ids, d))[:k]):
                yield query_id, r + 1, int(self.ids[i]), float(d[i])

    spark.udtf.register("vec_knn", VecKnn)
