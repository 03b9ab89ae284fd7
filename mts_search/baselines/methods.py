"""Baselines: brute force (arrays and SQL), distance-profile scan, and the per-channel threshold wrapper over four one-channel indices."""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark import StorageLevel
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions import kernels as K
from ..operators.chunk_pass import CHUNK, chunk_rows, hits
from ..operators.index import Index, Query, ardc, boxes_batch, sample_windows, select_bins, top_k, verify

CHANNEL_ENTRY = "channel int, series_id bigint, chunk_id bigint, first_start bigint, last_start bigint, n_windows int, leaf_id bigint, lo array<double>, hi array<double>"


def _all_windows(chunks: DataFrame, queries: list[Query], k: int, normalized: bool, method: str) -> DataFrame:
    """Exact squared distances of what may be among the k best windows of a task: the profile of every chunk, then value by value."""
    alike: dict[tuple, list[Query]] = {}
    for qu in queries:
        alike.setdefault((qu.values.shape[1], *qu.channels), []).append(qu)
    blocks = [(list(channels), own[o : o + 64]) for (_, *channels), own in alike.items() for o in range(0, len(own), 64)]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        best: dict[int, tuple] = {}
        for rows in batches:
            got: dict[int, list] = {}
            for series, _, base, n, x in chunk_rows(rows):
                for channels, own in blocks:
                    q = own[0].values.shape[1]
                    sub = x[channels, : n + q - 1]
                    slack = 1e-6 * max(1.0, float(np.abs(sub).max(initial=1.0)) ** 2 if not normalized else 1.0)
                    for qu, d in zip(own, K.profiles(sub, np.array([qu.values for qu in own]), normalized, method), strict=True):
                        cut = np.partition(d, k - 1)[k - 1] if len(d) > k else np.inf
                        if qu.query_id in best and len(best[qu.query_id][2]) >= k:
                            cut = min(cut, np.partition(best[qu.query_id][2], k - 1)[k - 1])
                        at = np.flatnonzero(d <= cut * (1 + 1e-6) + slack)
                        for o in range(0, len(at), 4096):
                            some = at[o : o + 4096]
                            got.setdefault(qu.query_id, []).append((np.full(len(some), series, np.int64), some + base, K.direct(sub, qu.values, some, normalized)))
            for qid, parts in got.items():
                s, t, e = (np.concatenate(c) for c in zip(*([best[qid]] if qid in best else []), *parts, strict=True))
                if len(e) > k:
                    near = e <= np.partition(e, k - 1)[k - 1] * (1 + 1e-9) + 1e-9
                    s, t, e = s[near], t[near], e[near]
                best[qid] = (s, t, e)
        for qid, (s, t, e) in best.items():
            yield hits(qid, s, t, e)

    return chunks.where("series_id is not null").select(*CHUNK).mapInArrow(run, "query_id int, series_id bigint, start bigint, d2 double")


def knn_scan(chunks: DataFrame, queries: list[Query], k: int, normalized: bool = False, whole_numbers: bool = True) -> DataFrame:
    """The profile over every chunk: map-only, the best k of each task, then the best k of all."""
    return top_k(_all_windows(chunks, queries, k, normalized, "fft"), k, normalized, whole_numbers)


def knn_brute(chunks: DataFrame, queries: list[Query], k: int, normalized: bool = False, whole_numbers: bool = True) -> DataFrame:
    """Every window compared value by value."""
    return top_k(_all_windows(chunks, queries, k, normalized, "direct"), k, normalized, whole_numbers)


def extremes(chunks: DataFrame, queries: list[Query], least: float = 0.0) -> DataFrame:
    """query_id, far, near: largest squared distance of all windows, and the smallest whose root is ``least`` or more.

    One product gives the distances of a chunk's windows to all queries; those within its rounding of either end are
    computed again value by value. A row a query leaves a task.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        far, near = [-np.inf] * len(queries), [np.inf] * len(queries)
        for rows in batches:
            for *_, n, x in chunk_rows(rows):
                made: dict[tuple, tuple] = {}
                for i, qu in enumerate(queries):
                    q, key = qu.values.shape[1], (qu.values.shape[1], *qu.channels)
                    if key not in made:
                        sub = x[qu.channels]
                        w = np.lib.stride_tricks.sliding_window_view(sub, q, axis=1)[:, :n].transpose(1, 0, 2).reshape(n, -1)
                        made[key] = sub, w, (w * w).sum(axis=1)
                    sub, w, w2 = made[key]
                    y = qu.values.ravel()
                    d = w2 - 2 * (w @ y) + y @ y
                    slack = 1e-9 * float(w2.max() + y @ y) + 1e-8
                    above = d[d > slack]
                    at = np.flatnonzero((d >= d.max() - 2 * slack) | (d <= (above.min() if len(above) else slack) + 2 * slack))
                    e = np.concatenate([K.direct(sub, qu.values, at[o : o + 4096]) for o in range(0, len(at), 4096)])
                    far[i] = max(far[i], float(e.max()))
                    near[i] = min(near[i], float(e[np.sqrt(e) >= least].min(initial=np.inf)))
        at = [i for i in range(len(queries)) if far[i] >= 0]
        yield pa.RecordBatch.from_arrays([pa.array([queries[i].query_id for i in at], pa.int32()), pa.array([far[i] for i in at], pa.float64()), pa.array([near[i] if np.isfinite(near[i]) else None for i in at], pa.float64())], names=["query_id", "far", "near"])

    found = chunks.select(*CHUNK).mapInArrow(run, "query_id int, far double, near double")
    return found.groupBy("query_id").agg(F.max("far").alias("far"), F.min("near").alias("near"))


def distances_sql(points: DataFrame, queries: DataFrame, q: int) -> DataFrame:
    """(query_id, series_id, start, d2) of every window, relationally: a join on channel, grouped by start."""
    qs = F.broadcast(queries)
    n = queries.groupBy("query_id").agg(F.count(F.lit(1)).alias("need"))
    joined = points.join(qs, "channel").where(F.col("t") >= F.col("j"))
    sums = joined.groupBy("query_id", "series_id", (F.col("t") - F.col("j")).alias("start")).agg(F.sum((F.col("v") - F.col("qv")) * (F.col("v") - F.col("qv"))).alias("d2"), F.count(F.lit(1)).alias("n"))
    return sums.join(F.broadcast(n), "query_id").where("n = need").select("query_id", "series_id", "start", "d2")


def knn_brute_sql(points: DataFrame, queries: DataFrame, q: int, k: int) -> DataFrame:
    ranked = distances_sql(points, queries, q).withColumn("rank", F.row_number().over(Window.partitionBy("query_id").orderBy("d2", "series_id", "start")).cast("int")).where(F.col("rank") <= k)
    return ranked.select("query_id", "rank", "series_id", "start", F.col("d2").cast("bigint").alias("d2"), F.round(F.sqrt("d2"), 4).alias("distance"))


@dataclass
class ChannelIndex:
    """Boxes of one-channel features by channel. ``how``: sum of the dimensions' gaps, or the worst one (mean lookup)."""

    kind: str
    q: int
    normalized: bool
    how: str
    features: dict[int, tuple]
    chunks: DataFrame
    entries: DataFrame

    def of_query(self, channel: int, y: np.ndarray) -> np.ndarray:
        return _features(self.kind, y[None], self.q, self.features[channel], self.normalized)[0]


def _features(kind: str, x: np.ndarray, q: int, how: tuple, normalized: bool) -> np.ndarray:
    """Features of every window of one channel (1, m)."""
    if kind == "trail":
        return K.sliding_features(x, q, how[0], normalized)
    return K.segment_features(x[0], q, how[0], kind == "segtree", normalized)


def build_channel_index(
    chunks: DataFrame, q: int, kind: str = "trail", *, normalized: bool = False, d_target: float = 0.6, leaf_pct: float | None = None, segments: int | None = None, bucket: float | None = None, block: int = 16, alphabet: int = 64, weighting: str = "uniform", n_sample: int = 2000, seed: int = 42
) -> ChannelIndex:
    """All channels in one pass over the chunks.

    trail: kept bins in tiles (leaf 0.05 %); segtree: mean and deviation of adaptive segments in halved groups (leaf
    10 %); meanlookup: bucketed segment means, runs of equal keys; envelope: ranges of segment means over ``block``
    neighbouring windows, rounded outwards to ``alphabet`` levels.
    """
    chunks = chunks.persist(StorageLevel.DISK_ONLY)
    n = int(chunks.agg(F.sum("n_core")).first()[0] or 0)
    sample = sample_windows(chunks, q, n_sample, seed)
    leaf = max(1.0, (leaf_pct if leaf_pct is not None else {"segtree": 10.0}.get(kind, 0.05)) / 100 * n)
    how: dict[int, tuple] = {}
    for c in range(sample.shape[1]):
        one = sample[:, c]
        if kind == "trail":
            kept = select_bins(ardc(one[:100, None], normalized), d_target) if len(one) > 1 else {0: [0, 1]}
            spec = (K.dims_of(q, {0: kept[0]}, normalized),)
        else:
            parts = min(q, segments or {"segtree": 8, "envelope": 8, "meanlookup": min(q, 13)}[kind])
            cuts = K.adaptive_cuts(K.znorm(one) if normalized else one, parts) if kind == "segtree" else sorted({round(i * q / parts) for i in range(parts + 1)})
            spec = (cuts,)
        f = np.concatenate([_features(kind, w[None], q, spec, normalized) for w in one]) if len(one) else np.zeros((0, 1))
        if kind in ("trail", "segtree"):
            w = K.softmax_weights(f.var(axis=0) if len(f) > 1 else np.ones(f.shape[1]), weighting)
            spec += (K.learn_router(f, n, leaf, w, "kd" if kind == "segtree" else "str"),)
        else:
            spread = f.std(axis=0).max() if len(f) else 1.0
            levels = alphabet if kind == "envelope" else 16
            spec += (float(bucket or max(spread, 1e-9) * 6 / levels),)
        how[c] = spec

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for rows in batches:
            for r in rows.to_pylist():
                x = np.array(r["vals"], float)
                for c, spec in how.items():
                    f = _features(kind, x[c : c + 1], q, spec, normalized)[: r["n_core"]]
                    if kind in ("trail", "segtree"):
                        label = K.route(f, spec[1])
                    elif kind == "envelope":
                        label = np.arange(len(f)) // block
                    else:
                        keys = np.floor(f / spec[1]).astype(np.int64)
                        label = np.cumsum(np.concatenate([[0], (np.diff(keys, axis=0) != 0).any(axis=1)])) if len(keys) else np.zeros(0, int)
                    first, last = K.runs(label)
                    out = boxes_batch(r, first, last, label[first] if len(first) else label, f, np.zeros((len(f), 0)), float(np.abs(x[c]).max(initial=1.0))).select(["series_id", "chunk_id", "first_start", "last_start", "n_windows", "leaf_id", "lo", "hi"])
                    if kind == "envelope" and out.num_rows:
                        lo = np.floor(np.array(out.column("lo").to_pylist()) / spec[1]) * spec[1]
                        hi = np.ceil(np.array(out.column("hi").to_pylist()) / spec[1]) * spec[1]
                        out = out.set_column(6, "lo", pa.array(lo.tolist(), pa.list_(pa.float64()))).set_column(7, "hi", pa.array(hi.tolist(), pa.list_(pa.float64())))
                    yield pa.RecordBatch.from_arrays([pa.array([c] * out.num_rows, pa.int32()), *out.columns], names=["channel", *out.schema.names])

    entries = chunks.select("series_id", "chunk_id", "base_t", "n_core", "vals").mapInArrow(run, CHANNEL_ENTRY).persist(StorageLevel.DISK_ONLY)
    return ChannelIndex(kind, q, normalized, "max" if kind == "meanlookup" else "sum", how, chunks, entries)


def _bounded(index: ChannelIndex, queries: list[Query]) -> DataFrame:
    """Runs of every channel with their squared bound to each query that has the channel: one scan for all channels."""
    spark = index.entries.sparkSession
    rows = [(qu.query_id, c, [float(v) for v in index.of_query(c, qu.values[i])]) for qu in queries for i, c in enumerate(qu.channels)]
    frame = F.broadcast(spark.createDataFrame(rows, "query_id int, channel int, y array<double>"))
    gap = F.zip_with(F.arrays_zip("lo", "hi"), "y", lambda b, y: F.greatest(b["lo"] - y, y - b["hi"], F.lit(0.0)))
    square = F.transform(gap, lambda g: g * g)
    bound = F.array_max(square) if index.how == "max" else F.aggregate(square, F.lit(0.0), lambda s, g: s + g)
    return index.entries.join(frame, "channel").withColumn("lb", bound).drop("lo", "hi", "y")


def channel_distance(found: DataFrame, chunks: DataFrame, queries: list[Query], normalized: bool, q: int) -> DataFrame:
    """Squared distance by channel of found windows (query_id, series_id, start): (query_id, channel, max)."""
    known = {qu.query_id: qu for qu in queries}
    len_ = chunks.select("series_id", "chunk_id", "base_t", "n_core", "vals")
    wanted = found.groupBy("series_id").agg(F.collect_list(F.struct("query_id", "start")).alias("w"))
    joined = len_.join(F.broadcast(wanted), "series_id")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for rows in batches:
            out = []
            for r in rows.to_pylist():
                x = np.array(r["vals"], float)
                for w in r["w"]:
                    s = w["start"] - r["base_t"]
                    if 0 <= s < r["n_core"]:
                        qu = known[w["query_id"]]
                        for i, c in enumerate(qu.channels):
                            out.append((w["query_id"], c, float(K.direct(x[c : c + 1], qu.values[i : i + 1], np.array([s]), normalized)[0])))
            cols = list(zip(*out, strict=True)) or [(), (), ()]
            yield pa.RecordBatch.from_arrays([pa.array(cols[0], pa.int32()), pa.array(cols[1], pa.int32()), pa.array(cols[2], pa.float64())], names=["query_id", "channel", "d2"])

    return joined.mapInArrow(run, "query_id int, channel int, d2 double")


def knn_per_channel(index: ChannelIndex, queries: list[Query], k: int, whole_numbers: bool = True, trace: dict | None = None) -> DataFrame:
    """Threshold wrapper: k runs a channel, exact distances, per-channel thresholds of the best k, then all runs within one of them."""
    bounded = _bounded(index, queries).persist(StorageLevel.DISK_ONLY)
    near = bounded.withColumn("r", F.row_number().over(Window.partitionBy("query_id", "channel").orderBy("lb", "series_id", "first_start"))).where(F.col("r") <= k)
    first = top_k(verify(near.drop("r"), index.chunks, queries, k, index.normalized), k, index.normalized, False)
    tau = channel_distance(first, index.chunks, queries, index.normalized, index.q).groupBy("query_id", "channel").agg(F.max("d2").alias("tau"), F.count(F.lit(1)).alias("n"))
    # fewer than k windows in reach: no threshold, everything is verified
    within = bounded.join(F.broadcast(tau), ["query_id", "channel"], "left").where((F.coalesce("n", F.lit(0)) < k) | (F.col("lb") <= F.col("tau") * (1 + 1e-9) + 1e-9))
    runs = within.select("query_id", "series_id", "chunk_id", "first_start", "last_start").distinct()
    if trace is not None:
        one = runs.select("query_id", "series_id", F.explode(F.sequence("first_start", "last_start")).alias("start")).distinct()
        trace["windows"] = {r[0]: r[1] for r in one.groupBy("query_id").count().collect()}
    return top_k(verify(runs, index.chunks, queries, k, index.normalized), k, index.normalized, whole_numbers)


def knn_envelope(index: ChannelIndex, queries: list[Query], k: int, whole_numbers: bool = True, trace: dict | None = None) -> DataFrame:
    """Native multichannel use: blocks are the same in all channels, so their bounds add up; two probes over all blocks."""
    bounded = _bounded(index, queries).groupBy("query_id", "series_id", "chunk_id", "first_start", "last_start").agg(F.sum("lb").alias("lb"), F.max("n_windows").alias("n_windows")).persist(StorageLevel.DISK_ONLY)
    near = bounded.withColumn("r", F.row_number().over(Window.partitionBy("query_id").orderBy("lb", "series_id", "first_start"))).where(F.col("r") <= k)
    first = verify(near, index.chunks, queries, k, index.normalized)
    tau = first.withColumn("r", F.row_number().over(Window.partitionBy("query_id").orderBy("d2"))).where(F.col("r") == k).select("query_id", F.col("d2").alias("tau"))
    within = bounded.join(F.broadcast(tau), "query_id", "left").where(F.col("tau").isNull() | (F.col("lb") <= F.col("tau") * (1 + 1e-9) + 1e-9))
    if trace is not None:
        trace["windows"] = {r[0]: r[1] for r in within.groupBy("query_id").agg(F.sum("n_windows")).collect()}
    return top_k(verify(within, index.chunks, queries, k, index.normalized), k, index.normalized, whole_numbers)


def choose_plan(index: Index, queries: list[Query], k: int, sample: int = 200) -> str:
    """Index or scan, by the share of sampled windows whose bound lies under the sample's k-th distance."""
    spec = index.spec
    w = sample_windows(index.chunks, spec.q, sample, 7)
    if not len(w) or any(qu.values.shape[1] != spec.q for qu in queries):
        return "scan"
    f = K.window_features(w, spec.dims, spec.normalized)
    shares = []
    for qu in queries:
        full = np.zeros((spec.c, spec.q))
        full[qu.channels] = qu.values
        y = K.window_features(full[None], spec.dims, spec.normalized)[0]
        on = [i for i, d in enumerate(spec.dims) if d[0] in qu.channels]
        a, b = (K.znorm(w), K.znorm(full)) if spec.normalized else (w, full)
        d2 = ((a[:, qu.channels] - b[qu.channels]) ** 2).sum(axis=(1, 2))
        lb = ((f[:, on] - y[on]) ** 2).sum(axis=1)
        shares.append(float((lb <= np.sort(d2)[min(k, len(d2)) - 1]).mean()))
    return "index" if np.median(shares) < 0.5 else "scan"


#: Queries from which building an index can pay: fewer are scanned, whatever the series.
BREAK_EVEN = 45


def knn(points_or_chunks, queries: list[Query], k: int, method: str = "index", **options) -> DataFrame:
    """Dispatch by name: index, scan, brute, trail, meanlookup, segtree, envelope or auto.

    auto: a scan for fewer queries than an index takes to pay, else what ``choose_plan`` says of the index built.
    """
    chunks = points_or_chunks
    if method == "auto" and len(queries) < BREAK_EVEN:
        return knn_scan(chunks, queries, k, options.get("normalized", False))
    if method in ("scan", "brute"):
        return (knn_scan if method == "scan" else knn_brute)(chunks, queries, k, **options)
    from ..operators.index import build_index, knn_index

    q = queries[0].values.shape[1]
    if method in ("index", "auto"):
        built = build_index(chunks, q, **options)
        if method == "auto" and choose_plan(built, queries, k) == "scan":
            return knn_scan(chunks, queries, k, built.spec.normalized)
        return knn_index(built, queries, k)
    built = build_channel_index(chunks, q, method, **options)
    return (knn_envelope if method == "envelope" else knn_per_channel)(built, queries, k)
