"""Batches of queries: runs of a measurement, search in passes for many queries, scans without a join."""

import pytest
from pyspark.sql import functions as F

from mts_search.baselines import methods as B
from mts_search.operators import chunk_pass as P
from mts_search.operators import index as I
from mts_search.operators.fixtures import walks
from mts_search.operators.series import query_points, to_chunks
from mts_search.plans import experiments as E

KEYS = ("query_id", "rank", "series_id", "start")


def rows(df):
    return sorted(tuple(r[k] for k in KEYS) for r in df.collect())


def test_a_batch_is_measured_in_ten_runs(spark, monkeypatch):
    of, sizes = E._workload, []
    monkeypatch.setattr(E, "_workload", lambda s, d, n: sizes.append(n) or of(s, d, 2))
    got = E._bench_queries(spark, "/root/testdata/sf0.001")
    assert sizes == [100]
    assert {r["method"]: r["runs"] for r in got} == {"index": 10, "scan": 10, "brute": 10}


@pytest.fixture(scope="module")
def data(spark):
    p = walks(spark, 6, 3, 120).withColumn("v", F.round(F.col("v") * 10).cast("bigint")).persist()
    return to_chunks(p, 16, 50).persist(), I.collect_queries(query_points(p, 16, 9, 3))


def test_many_queries_are_searched_in_passes(data, monkeypatch):
    chunks, qs = data
    index, seen, traces = I.build_index(chunks, 16), [], []
    for name in ("nearest_runs", "windows_within"):
        monkeypatch.setattr(P, name, lambda *a, f=getattr(P, name), name=name, **k: seen.append(name) or f(*a, **k))
    for most in (8, 10):
        monkeypatch.setattr(I, "MANY_QUERIES", most)
        trace = I.Trace([])
        assert rows(I.knn_index(index, qs, 4, trace=trace)) == rows(B.knn_brute(chunks, qs, 4))
        traces.append(trace.rows)
    assert seen == ["nearest_runs", "windows_within"]
    assert traces[0] == traces[1]
    # runs that compacting has moved stand in other leaves than the router's
    monkeypatch.setattr(I, "MANY_QUERIES", 1)
    assert rows(I.knn_index(I.compact(index), qs, 4)) == rows(B.knn_brute(chunks, qs, 4))
    assert len(seen) == 2


@pytest.mark.parametrize("normalized", [False, True])
def test_scans_join_nothing(data, normalized):
    chunks, qs = data
    for scan in (B.knn_scan, B.knn_brute):
        found = scan(chunks, qs, 3, normalized)
        assert "Join" not in found._jdf.queryExecution().sparkPlan().toString()
        ids, starts = (found.select(c).distinct().count() for c in ("query_id", "start"))
        assert ids == len(qs) and starts > 1
    assert rows(B.knn_scan(chunks, qs, 3, normalized)) == rows(B.knn_brute(chunks, qs, 3, normalized))


def test_a_traced_search_passes_over_the_chunks_twice(data, monkeypatch):
    chunks, qs = data
    index, seen = I.build_index(chunks, 16), []
    monkeypatch.setattr(P, "windows_within", lambda *a, f=P.windows_within, **k: seen.append(1) or f(*a, **k))
    trace = I.Trace([])
    assert rows(I.knn_index(index, qs, 4, trace=trace)) == rows(B.knn_brute(chunks, qs, 4))
    assert len(seen) == 1 and [r["query_id"] for r in trace.rows] == list(range(len(qs)))
