"""Python and SQL functions for users of the methods."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T


@F.udf(T.StringType(), useArrow=True)
def priority_text(text):
    import hashlib

    return hashlib.md5(text.encode()).hexdigest()


@F.pandas_udf(T.DoubleType())
def vector_norm(v: pd.Series) -> pd.Series:
    return pd.Series(np.linalg.norm(np.stack(v).astype(np.float64), axis=1)) if len(v) else pd.Series([], dtype=float)


@F.pandas_udf(T.ArrayType(T.DoubleType()))
def vector_sum(v: pd.Series) -> list[float]:
    return np.sum(np.stack(v).astype(np.float64), axis=0).tolist()


@F.udtf(returnType=T.StructType([T.StructField("node_id", T.LongType()), T.StructField("dist", T.IntegerType())]))
class KhopExpand:
    """Neighbour arrays unpacked: eval(nbrs, dist) gives a row for each neighbour."""

    def eval(self, nbrs, dist: int):
        for n in nbrs or []:
            yield n, dist


def score_candidates(vectors: DataFrame, queries: np.ndarray) -> DataFrame:
    """(vec_id, query, score): a model (the query matrix) is loaded once a task, vectors stream through in Arrow batches."""
    names = np.arange(len(queries))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        model = queries.T
        for batch in batches:
            v = np.stack(batch.column("v").to_numpy(zero_copy_only=False)) if batch.num_rows else np.empty((0, model.shape[0]))
            ids = batch.column("vec_id").to_numpy()
            yield pa.RecordBatch.from_arrays([pa.array(np.repeat(ids, len(names))), pa.array(np.tile(names, len(ids)).astype(np.int32)), pa.array((v @ model).ravel())], names=["vec_id", "query", "score"])

    return vectors.select("vec_id", "v").mapInArrow(run, "vec_id bigint, query int, score double")


def apply_sparse_updates(nodes: DataFrame, grads: DataFrame, rate: float) -> DataFrame:
    """(node_id, h): vectors (node_id, h) less rate times the sum of their gradients (node_id, g); the others stay as they are."""

    def run(old: pd.DataFrame, new: pd.DataFrame) -> pd.DataFrame:
        if not len(old):
            return pd.DataFrame({"node_id": pd.Series([], dtype="int64"), "h": pd.Series([], dtype=object)})
        h = np.stack(old["h"]).astype(np.float64)
        if len(new):
            place = pd.Series(np.arange(len(old)), index=old["node_id"].to_numpy())
            at = place.reindex(new["node_id"]).to_numpy()
            known = ~np.isnan(at)
            np.add.at(h, at[known].astype(int), -rate * np.stack(new["g"])[known])
        return pd.DataFrame({"node_id": old["node_id"], "h": list(h)})

    slot = F.pmod(F.xxhash64("node_id"), F.lit(256)).cast("int").alias("slot")
    return nodes.select("node_id", "h", slot).groupBy("slot").cogroup(grads.select("node_id", "g", slot).groupBy("slot")).applyInPandas(run, "node_id bigint, h array<double>")


def register_sql(spark: SparkSession) -> None:
    """Temporary SQL functions dh_priority, dh_dot and dh_distmult."""
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION dh_priority(seed BIGINT, node BIGINT, nbr BIGINT) RETURNS STRING RETURN md5(concat_ws(':', seed, node, nbr))")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION dh_dot(a ARRAY<DOUBLE>, b ARRAY<DOUBLE>) RETURNS DOUBLE RETURN aggregate(zip_with(a, b, (x, y) -> x * y), 0D, (s, x) -> s + x)")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION dh_distmult(s ARRAY<DOUBLE>, r ARRAY<DOUBLE>, t ARRAY<DOUBLE>) RETURNS DOUBLE RETURN aggregate(zip_with(zip_with(s, r, (x, y) -> x * y), t, (x, y) -> x * y), 0D, (s, x) -> s + x)")
