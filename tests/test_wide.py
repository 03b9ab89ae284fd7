"""The index over blocks of channels against brute force, and the blocks of the given tables."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from mts_search.baselines import methods as B
from mts_search.operators import fixtures as X
from mts_search.operators import index as I
from mts_search.operators.series import CHANNEL_BLOCK, query_points, to_chunks
from mts_search.plans import workloads as W

KEYS = ("query_id", "rank", "series_id", "start")
Q = 16


def rows(df):
    return sorted(tuple(r[k] for k in KEYS) for r in df.collect())


@pytest.fixture(scope="module")
def data(spark):
    p = X.walks(spark, 4, 130, 90).withColumn("v", F.round(F.col("v") * 10).cast("bigint")).persist()
    whole = to_chunks(p, Q, 50).persist()
    parts = F.explode(F.array(*[F.struct(F.lit(b).cast("bigint").alias("block_id"), F.slice("vals", b * CHANNEL_BLOCK + 1, CHANNEL_BLOCK).alias("vals")) for b in range(3)])).alias("p")
    return p, whole, whole.select("series_id", "chunk_id", "base_t", "n_core", parts).select("series_id", "chunk_id", "base_t", "n_core", "p.*").persist()


@pytest.mark.parametrize("options", [{}, {"normalized": True, "n_pivots": 0}, {"layout": "kd", "leaf_pct": 5.0}, {"bins": "energy", "boxes": "float32", "compress": False}], ids=str)
def test_blocks_equal_brute(data, options):
    p, whole, blocks = data
    index = I.build_index(blocks, Q, **options)
    for channels in (None, [1, 70, 129]):
        qs = I.collect_queries(query_points(p, Q, 2, 3, channels))
        assert rows(I.knn_index(index, qs, 4)) == rows(B.knn_brute(whole, qs, 4, options.get("normalized", False)))


def test_options_of_a_search_over_blocks(data):
    p, whole, blocks = data
    index = I.build_index(blocks, Q)
    qs = I.cut_queries(blocks, Q, 2, 3, [0, 64, 65])
    for got, want in zip(qs, I.cut_queries(whole, Q, 2, 3, [0, 64, 65]), strict=True):
        assert got.channels == want.channels and np.array_equal(got.values, want.values)
    truth = rows(B.knn_brute(whole, qs, 3))
    for o in ({"browsing": False}, {"correction": "none"}):
        assert rows(I.knn_index(index, qs, 3, **o)) == truth
    with pytest.raises(I.LengthMismatch):
        I.knn_index(index, [I.Query(0, [0], np.zeros((1, 8)))], 1)


def test_no_row_holds_all_channels_of_the_given_tables(spark, tmp_path):
    d = str(tmp_path)
    few = spark.read.parquet("/root/testdata/sf0.01/lineitem.parquet").withColumn("l_suppkey", F.col("l_suppkey") * 2)
    few.write.parquet(f"{d}/lineitem.parquet")
    index = W.index_of(spark, d, "many_channels_blocks")
    assert index.chunks.agg(F.max(F.size("vals"))).first()[0] <= CHANNEL_BLOCK
    whole = X.FIXTURES["many_channels"].chunks(spark, d, 52)
    got = index.chunks.select("series_id", "block_id", F.posexplode("vals").alias("i", "l")).select("series_id", (F.col("block_id") * CHANNEL_BLOCK + F.col("i")).alias("c"), "l")
    want = whole.select("series_id", F.posexplode("vals").alias("c", "l"))
    assert got.exceptAll(want).isEmpty() and want.exceptAll(got).isEmpty()
    found, sql = W.by_index("many_channels_blocks", 1), W.by_index("many_channels", 1)
    assert found[1] == sql[1] and rows(found[0](spark, d)) == rows(sql[0](spark, d))
