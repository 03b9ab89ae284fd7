"""Index search against brute force, with every option; wrapper, append, storage, edges, plans."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from mts_search.baselines import methods as B
from mts_search.operators import chunk_pass as P
from mts_search.operators import index as I
from mts_search.operators.fixtures import walks
from mts_search.operators.series import build_series, mts_distance, query_points, to_chunks, windows

Q = 16
KEYS = ("query_id", "rank", "series_id", "start")


@pytest.fixture(scope="module")
def data(spark):
    p = walks(spark, 6, 3, 120).withColumn("v", F.round(F.col("v") * 10).cast("bigint")).persist()
    return p, to_chunks(p, Q, 50).persist(), I.collect_queries(query_points(p, Q, 2, 3))


def rows(df):
    return sorted(tuple(r[k] for k in KEYS) for r in df.collect())


@pytest.mark.parametrize("options", [{}, {"normalized": True}, {"n_pivots": 0}, {"n_pivots": 3}, {"layout": "kd", "leaf_pct": 1.0}, {"bins": "first", "f": 2}, {"bins": "energy", "boxes": "float32"}, {"compress": False, "weighting": "share"}], ids=str)
def test_index_equals_brute(data, options):
    _, chunks, qs = data
    index = I.build_index(chunks, Q, **options)
    truth = rows(B.knn_brute(chunks, qs, 4, options.get("normalized", False)))
    assert rows(I.knn_index(index, qs, 4)) == truth
    assert index.entries.agg(F.sum("n_windows")).first()[0] == index.spec.n_windows == windows(chunks, Q).count() == 6 * (120 - Q + 1)


def test_search_options_and_nodes(data):
    _, chunks, qs = data
    index = I.build_index(chunks, Q, n_pivots=2)
    truth = rows(B.knn_brute(chunks, qs, 3))
    for o in ({"browsing": False}, {"correction": "none"}, {"correction": "max"}):
        assert rows(I.knn_index(index, qs, 3, **o)) == truth
    index.nodes = I.build_levels(index.entries, 4)
    assert rows(I.knn_index(index, qs, 3)) == truth
    assert index.nodes.orderBy(F.desc("level")).first()["n_windows"] == index.spec.n_windows
    sub = [I.Query(q.query_id, [0, 2], q.values[[0, 2]]) for q in qs]
    assert rows(I.knn_index(index, sub, 3)) == rows(B.knn_brute(chunks, sub, 3))
    trace = I.Trace([])
    I.knn_index(index, qs, 1, trace=trace).collect()
    assert all(r["windows"] < index.spec.n_windows for r in trace.rows)


@pytest.mark.parametrize("kind", ["trail", "meanlookup", "segtree", "envelope"])
@pytest.mark.parametrize("normalized", [False, True])
def test_wrapper_equals_brute(data, kind, normalized):
    _, chunks, qs = data
    built = B.build_channel_index(chunks, Q, kind, normalized=normalized)
    truth = rows(B.knn_brute(chunks, qs, 3, normalized))
    assert rows(B.knn_per_channel(built, qs, 3)) == truth
    if kind == "envelope":
        assert rows(B.knn_envelope(built, qs, 3)) == truth


def test_scan_range_sql_and_dispatch(data):
    p, chunks, qs = data
    truth = B.knn_brute(chunks, qs, 5).collect()
    assert rows(B.knn_scan(chunks, qs, 5)) == sorted(tuple(r[k] for k in KEYS) for r in truth)
    assert rows(B.knn_brute_sql(p, query_points(p, Q, 2, 3), Q, 5)) == sorted(tuple(r[k] for k in KEYS) for r in truth)
    third = [r for r in truth if r["rank"] == 3 and r["query_id"] == 0][0]["d2"] ** 0.5
    got = I.range_query(I.build_index(chunks, Q), qs[:1], third).collect()
    assert len(got) == 2 and all(r["d2"] < third**2 for r in got)
    assert rows(B.knn(chunks, qs, 5, "auto")) == rows(B.knn(chunks, qs, 5, "scan"))


def test_append_and_storage(data, spark, tmp_path):
    p, _, qs = data
    old, new = to_chunks(p.where("series_id < 4"), Q, 50), to_chunks(p.where("series_id >= 4"), Q, 50)
    index = I.append(I.build_index(old, Q), new)
    whole = B.knn_brute(to_chunks(p, Q, 50), qs, 4)
    assert rows(I.knn_index(index, qs, 4)) == rows(whole)
    I.save_index(index, str(tmp_path / "ix"))
    assert rows(I.knn_index(I.load_index(spark, str(tmp_path / "ix")), qs, 4)) == rows(whole)


def test_edges(spark, data):
    _, chunks, qs = data
    index = I.build_index(chunks, Q)
    assert I.knn_index(index, qs, 0).count() == 0
    assert I.knn_index(index, qs[:1], 10_000).count() == index.spec.n_windows
    with pytest.raises(I.LengthMismatch):
        I.knn_index(index, [I.Query(0, [0], qs[0].values[:1, :8])], 1)
    short = spark.createDataFrame([(1, 0, 0, 5)], "series_id bigint, channel int, t bigint, v bigint")
    assert to_chunks(short, Q).count() == 0
    flat = spark.range(40).select(F.lit(1).cast("bigint").alias("series_id"), F.lit(0).alias("channel"), F.col("id").alias("t"), F.lit(7).alias("v")).union(spark.range(40).select(F.lit(2).cast("bigint"), F.lit(0), F.col("id"), F.lit(7)))
    c = to_chunks(flat, Q)
    q = I.collect_queries(query_points(flat, Q, 1, 0))
    got = I.knn_index(I.build_index(c, Q, normalized=True), q, 3).orderBy("rank").collect()
    assert [(r["series_id"], r["start"]) for r in got] == [(1, 0), (1, 1), (1, 2)]


def test_series_fill_and_distance(spark):
    df = spark.createDataFrame([(1, 0, 4), (1, 3, 10), (1, 3, 2)], "e bigint, t bigint, x bigint")
    one = lambda fill: [r["v"] for r in build_series(df, F.col("e"), F.col("t"), [F.sum("x")], 5, fill).orderBy("t").collect()]
    assert one("zero") == [4, 0, 0, 12, 0] and one("locf") == [4, 4, 4, 12, 12] and one("none") == [4, 12]
    assert [round(x, 3) for x in one("linear")] == [4, 6.667, 9.333, 12, 12]
    d = spark.range(1).select(mts_distance(F.array(F.array(F.lit(0.0), F.lit(0.0))), F.array(F.array(F.lit(3.0), F.lit(4.0), F.lit(9.0)), F.array(F.lit(1.0)))))
    assert d.first()[0] == 5.0


def test_plans(spark, data):
    from mts_search.plans.explain_checks import explain_checks

    _, chunks, qs = data
    flags = explain_checks(I.knn_index(I.build_index(chunks, Q), qs, 3))
    assert flags["broadcast_join"] and not flags["cartesian"] and not flags["row_python"]


def test_sources_and_sql(spark, tmp_path):
    from mts_search.operators import sqlapi
    from mts_search.sources import readers

    readers.register(spark)
    w = spark.read.format("walks").option("n", 3).option("channels", 2).option("m", 10).load()
    assert w.count() == 60
    for kind in ("csv", "json", "orc"):
        w.write.format(kind).save(str(tmp_path / kind))
        assert readers.read_points(spark, str(tmp_path / kind), kind).count() == 60
    sqlapi.register(spark)
    got = spark.sql("select * from knn_subsequences(array(0D, 1D, 5D, 1D, 0D), array(1D, 5D), 1)").first()
    assert (got["start"], got["distance"]) == (1, 0.0)
    assert spark.sql("select * from windows_of(array(1D, 2D, 3D), 2)").count() == 2


def test_discords_of_all_starts(spark, monkeypatch):
    import numpy as np

    from mts_search.plans import workloads as W

    g = np.random.default_rng(8)
    x = {i: g.integers(0, 9, 75) for i in (2, 4, 9)}
    x[9][:] = np.roll(x[2], 20)  # a close match at another, farther start
    x[4][5:57] = np.roll(x[4], 7)[5:57] * 40
    df = spark.createDataFrame([(i, 0, t, int(v)) for i, a in x.items() for t, v in enumerate(a)], "series_id bigint, channel int, t bigint, v bigint")
    monkeypatch.setattr(W, "points_of", lambda *_: df)
    cut = {i: [a[s : s + 52] for s in range(24)] for i, a in x.items()}
    d = sorted((-min(int(((w - u) ** 2).sum()) for o in cut if o != i for u in cut[o]), i, s) for i in cut for s, w in enumerate(cut[i]))
    assert [(-r["nearest_d2"], r["series_id"], r["start"]) for r in W.discords(spark, "").collect()] == d[:3]


def test_nodes_come_before_runs(spark, tmp_path, monkeypatch):
    from mts_search.plans.explain_checks import explain_checks, plan_text

    p = walks(spark, 24, 3, 200).withColumn("v", F.round(F.col("v") * 10).cast("bigint")).persist()
    chunks, qs = to_chunks(p, Q, 100).persist(), I.collect_queries(query_points(p, Q, 2, 3))
    index = I.build_index(chunks, Q, leaf_pct=0.2)
    truth = rows(B.knn_brute(chunks, qs, 3))
    trace = I.Trace([])
    assert rows(I.knn_index(index, qs, 3, trace=trace)) == truth
    n = index.entries.count()
    assert all(r["run_bounds"] < 0.3 * n and r["runs"] <= r["run_bounds"] for r in trace.rows)
    # the way down by joins, level by level, reaches the same leaves as the one on the driver
    held = {(r["query_id"], r["leaf_id"]) for r in I.descend(index, None, qs, {q.query_id: 900.0 for q in qs}).collect()}
    monkeypatch.setattr(I, "HELD_VALUES", 0)
    monkeypatch.setattr(I, "BROADCAST_ROWS", 8)
    joined = I.Index(index.spec, index.chunks, index.entries, I.build_levels(index.entries, 4))
    frame = F.broadcast(I.query_frame(spark, joined, qs))
    assert {(r["query_id"], r["leaf_id"]) for r in I.descend(joined, frame, qs, {q.query_id: 900.0 for q in qs}).collect()} == held
    assert rows(I.knn_index(joined, qs, 3)) == truth
    monkeypatch.undo()
    # a saved index reads the slabs reached and lets statistics skip row groups
    monkeypatch.setattr(I, "SLAB", 4)
    I.save_index(index, str(tmp_path / "ix"))
    saved = I.load_index(spark, str(tmp_path / "ix"))
    assert rows(I.knn_index(saved, qs, 3)) == truth
    reach = {q.query_id: 900.0 for q in qs}
    frame = F.broadcast(I.query_frame(spark, saved, qs))
    found = I.bounded_runs(saved, frame, I.descend(saved, frame, qs, reach), len(qs), "nearest", I.flat_filters(saved, qs, reach, 1e-9))
    flags = explain_checks(found)
    assert flags["partition_filters"] and flags["pushed_filters"] and "lo_0" in plan_text(found)


def test_compact_splits_overfull_leaves(data):
    p, _, qs = data
    old, new = to_chunks(p.where("series_id < 1"), Q, 50), to_chunks(p.where("series_id >= 1"), Q, 50)
    grown = I.append(I.build_index(old, Q, leaf_pct=10.0), new)
    tidy = I.compact(grown)
    most = lambda x: x.entries.groupBy("leaf_id").agg(F.sum("n_windows").alias("n"), F.count(F.lit(1)).alias("c")).where("c > 1").agg(F.max("n")).first()[0]
    assert most(grown) > 2 * grown.spec.leaf >= most(tidy)
    assert tidy.entries.agg(F.sum("n_windows")).first()[0] == grown.entries.agg(F.sum("n_windows")).first()[0]
    assert rows(I.knn_index(tidy, qs, 4)) == rows(B.knn_brute(to_chunks(p, Q, 50), qs, 4))


def test_windows_apart(data):
    _, chunks, qs = data
    every = sorted(((r["d2"], r["series_id"], r["start"]) for r in B.knn_brute(chunks, qs[:1], 10_000).collect()))
    want = []
    for _, s, t in every:
        if len(want) < 5 and all(s != a or abs(t - b) > 8 for a, b in want):
            want.append((s, t))
    got = I.knn_index(I.build_index(chunks, Q), qs[:1], 5, exclusion=8).orderBy("rank").collect()
    assert [(r["series_id"], r["start"]) for r in got] == want


def test_sinks_and_entry_source(data, spark, tmp_path):
    from mts_search.sources import readers

    p, chunks, qs = data
    readers.register(spark)
    spark.conf.set("spark.sql.python.filterPushdown.enabled", "true")
    index = I.build_index(chunks, Q)
    I.save_index(index, str(tmp_path / "ix"))
    got = spark.read.format("mts_entries").option("path", str(tmp_path / "ix" / "entries")).load()
    assert got.count() == index.entries.count()
    assert got.where("lo_0 <= 5 and hi_0 >= 5").count() == index.entries.where("lo[0] <= 5 and hi[0] >= 5").count()
    found = I.knn_index(index, qs, 3)
    for _ in range(2):
        readers.write_results(found, str(tmp_path / "out"), "overwrite", by="query_id")
    assert rows(spark.read.parquet(str(tmp_path / "out"))) == rows(found)
    readers.write_bucketed(p, "points_by_series", 4)
    joined = spark.table("points_by_series").groupBy("series_id").count()
    assert joined.count() == 6 and "Exchange" not in joined._jdf.queryExecution().sparkPlan().toString()
    spark.sql("drop table points_by_series")


def test_large_boxes_are_not_kept(data, monkeypatch):
    """Boxes beyond the bound are made again in each pass: nothing of them is stored, answers are the same."""
    p, chunks, qs = data
    monkeypatch.setattr(I, "KEPT_BYTES", 0)
    index = I.build_index(chunks, Q)
    assert not index.entries.storageLevel.useDisk
    assert not I.append(index, chunks.limit(0)).entries.storageLevel.useDisk
    assert rows(I.knn_index(index, qs, 4)) == rows(B.knn_brute(chunks, qs, 4))
    old, new = to_chunks(p.where("series_id < 4"), Q, 50), to_chunks(p.where("series_id >= 4"), Q, 50)
    assert rows(I.knn_index(I.append(I.build_index(old, Q), new), qs, 4)) == rows(B.knn_brute(to_chunks(p, Q, 50), qs, 4))


@pytest.mark.parametrize("options", [{"n_pivots": 2}, {"normalized": True}, {"n_pivots": 0, "boxes": "float32"}, {"compress": False}], ids=str)
def test_passes_over_chunks_search_large_boxes(data, monkeypatch, options):
    """Runs of an index that isn't kept are bounded and verified in the workers: no candidate meets its chunk in a join."""
    _, chunks, qs = data
    sub = [I.Query(q.query_id, [0, 2], q.values[[0, 2]]) for q in qs]
    norm = options.get("normalized", False)
    kept, a = I.build_index(chunks, Q, **options), I.Trace([])
    I.knn_index(kept, qs, 3, trace=a).collect()
    monkeypatch.setattr(I, "KEPT_BYTES", 0)
    index, b = I.build_index(chunks, Q, **options), I.Trace([])
    for queries in (qs, sub):
        for o in ({}, {"browsing": False}, {"correction": "max"}, {"correction": "none"}):
            assert rows(I.knn_index(index, queries, 3, **o)) == rows(B.knn_brute(chunks, queries, 3, norm))
    found = I.knn_index(index, qs, 3, trace=b)
    assert "Join" not in found._jdf.queryExecution().optimizedPlan().toString()
    assert [(r["runs"], r["windows"], r["run_bounds"]) for r in a.rows] == [(r["runs"], r["windows"], r["run_bounds"]) for r in b.rows]
    assert rows(I.knn_index(index, qs, 3, exclusion=4)) == rows(I.knn_index(kept, qs, 3, exclusion=4))
    assert rows(I.range_query(index, sub, 40.0)) == rows(I.range_query(kept, sub, 40.0))
    levels = lambda i: sorted((r["level"], r["node_id"], r["n_entries"], r["n_windows"], *r["lo"], *r["hi"]) for r in i.nodes.collect())
    assert levels(index) == levels(kept)


@pytest.mark.parametrize("options", [{"n_pivots": 2}, {"normalized": True}, {"boxes": "float32", "fanout": 2}], ids=str)
def test_wide_boxes_are_bounded_in_the_channels_of_a_search(data, monkeypatch, options):
    """Beyond a width no box of a run, leaf or node is stored; bounds add up over blocks of channels; answers are the same."""
    p, chunks, qs = data
    sub = [I.Query(q.query_id, [c], q.values[[c]]) for c, q in zip((0, 2), qs, strict=True)]
    norm = options.get("normalized", False)
    monkeypatch.setattr(I, "MOST_SIDES", 4)
    monkeypatch.setattr(P, "BLOCK_DIMS", 1)
    index, trace = I.build_index(chunks, Q, **options), I.Trace([])
    assert index.wide and index.nodes is None
    for queries in (qs, sub):
        for o in ({}, {"browsing": False}, {"correction": "max"}):
            assert rows(I.knn_index(index, queries, 3, **o)) == rows(B.knn_brute(chunks, queries, 3, norm))
    found = I.knn_index(index, qs, 3, trace=trace)
    assert index.nodes is None and found.count() == 6 and all(r["run_bounds"] >= r["runs"] > 0 for r in trace.rows)
    if not norm:
        assert rows(I.range_query(index, sub, 40.0)) == rows(B.knn_brute(chunks, sub, 10**9).where("distance < 40"))
    with pytest.raises(I.LengthMismatch):
        I.knn_index(index, [I.Query(0, [0], np.zeros((1, Q - 1)))], 1)
    old, new = to_chunks(p.where("series_id < 4"), Q, 50), to_chunks(p.where("series_id >= 4"), Q, 50)
    more = I.append(I.build_index(old, Q, **options), new)
    assert more.nodes is None and rows(I.knn_index(more, qs, 4)) == rows(B.knn_brute(chunks, qs, 4, norm))
    assert index.levels()[0] == sum(1 for r in index.leaf_bounds(qs)[0])


def test_extremes_equal_all_distances(data):
    """Farthest and nearest window of each query in one pass, without a row a window."""
    _, chunks, qs = data
    cut = [I.Query(9, [0, 1, 2], np.array(chunks.where("series_id = 2 and chunk_id = 0").first()["vals"])[:, 5 : 5 + Q])]
    every = B.knn_brute(chunks, [*qs, *cut], 10**9).groupBy("query_id").agg(F.max("d2"), F.min("d2"), F.min(F.when(F.col("d2") > 0, F.col("d2")))).orderBy("query_id").collect()
    plain, above = (B.extremes(chunks, [*qs, *cut], least).orderBy("query_id") for least in (0.0, 0.00005))
    assert [tuple(r) for r in plain.collect()] == [tuple(r)[:3] for r in every]
    assert [tuple(r) for r in above.collect()] == [(r[0], r[1], r[3]) for r in every] and every[-1][2] == 0
