"""The two-probe index: adaptive bins, weighted tiling, run compression, pivots; build and search.

Build: one shuffle makes chunks; a bounded sample of windows fixes kept bins, tiling and pivots on the
driver; one map pass turns every chunk into runs of neighbouring windows with boxes (features never
leave the worker); the runs are the index, grouped by leaf, and the leaves by nodes. Search: the query
goes down the nodes first. In the first probe it takes the nearest leaves until they hold k windows,
bounds their runs and verifies the k nearest: the k-th distance is the threshold. In the second it goes
down all nodes within the threshold and bounds the runs of the leaves reached, and no others; runs
within the threshold are verified. On a saved index the leaves reached become partition filters, and the
threshold becomes filters on flat box columns that row-group statistics answer.
"""

from __future__ import annotations

import json
from collections.abc import Iterator
from dataclasses import asdict, dataclass, field

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark import StorageLevel
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions import kernels as K
from ..functions.columns import box_agg
from ..session import written
from . import chunk_pass as P
from .series import query_cuts

ENTRY = "series_id bigint, chunk_id bigint, first_start bigint, last_start bigint, n_windows int, leaf_id bigint, lo array<double>, hi array<double>, plo array<double>, phi array<double>"
EPS = 1e-9
#: Beyond these the flat bound expression would leave generated code; an aggregate over arrays takes over.
FLAT_DIMS = 40
BROADCAST_ROWS = 100_000
#: Box sides of a node that are aggregated as columns; beyond, rows a dimension are.
WIDE_DIMS = 200
#: Numbers of leaf boxes that the driver may hold, to go down to the leaves without a job.
HELD_VALUES = 4_000_000
#: Leaves of a slab, the partition of a saved index; slabs that a partition filter may list; flat box columns.
SLAB, MOST_SLABS, FLAT_SIDES = 64, 20_000, 4
#: Bytes of run boxes, at a run a window, up to which they are kept on disk; beyond, each pass makes them from the chunks (chunk_pass).
KEPT_BYTES = 2_000_000_000
#: Queries of a batch from which on kept runs are left aside too: a pass over the chunks bounds a run for all of them at once.
MANY_QUERIES = 8
#: Numbers of a box up to which runs and nodes are kept; beyond, each search bounds the leaves in its own channels (chunk_pass).
MOST_SIDES = 10_000


class LengthMismatch(ValueError):
    """The index holds windows of another length."""


@dataclass
class Spec:
    q: int
    c: int
    normalized: bool
    kept: dict[int, list[int]]
    dims: list[tuple[int, int, str, float]]
    pivots: np.ndarray
    weighting: str
    layout: str
    leaf: float
    n_windows: int
    weights: list[float]
    router: object = None
    compress: bool = True
    float32: bool = False
    phases: dict[str, float] = field(default_factory=dict)


@dataclass
class Index:
    spec: Spec
    chunks: DataFrame
    entries: DataFrame
    nodes: DataFrame | None = None
    counts: dict[int, int] | None = None
    held: tuple | None = None
    kept: bool = True
    fanout: int = 64
    bounded: tuple | None = None
    routed: bool = False  # every run stands in its router's leaf, so passes over the chunks make the same runs

    @property
    def wide(self) -> bool:
        return not self.kept and _wide(self.spec)

    def leaf_bounds(self, queries: list[Query]) -> dict[int, list]:
        """Rows (leaf, bound, entries, windows) of every leaf by query, of the last queries asked for; leaves are few."""
        if self.bounded is None or self.bounded[0] is not queries:
            found: dict[int, list] = {qu.query_id: [] for qu in queries}
            for r in P.leaf_bounds(self, queries).orderBy("leaf_id").collect():
                found[r["query_id"]].append((r["leaf_id"], r["nlb"], r["n_entries"], r["n_windows"]))
            self.bounded = (queries, found)
        return self.bounded[1]

    def leaf_boxes(self) -> tuple | None:
        """Leaf boxes (ids, entries, windows, lo, hi) on the driver, where they are at most HELD_VALUES numbers."""
        if self.held is None and 2 * self.levels().get(0, 0) * max(1, len(self.spec.dims)) <= HELD_VALUES:
            rows = self.nodes.where(F.col("level") == 0).select("node_id", "n_entries", "n_windows", "lo", "hi").orderBy("node_id").collect()
            shape = (len(rows), len(self.spec.dims))
            self.held = (*(np.array([r[i] for r in rows], np.int64) for i in range(3)), *(np.array([r[i] for r in rows], float).reshape(shape) for i in (3, 4)))
        return self.held

    def levels(self) -> dict[int, int]:
        """Number of nodes by level (0: leaves); a handful of rows, read once."""
        if self.nodes is None:
            self.nodes = build_levels(_leaf_source(self.entries, self.chunks, self.spec, self.kept), self.fanout, len(self.spec.dims))
        if self.counts is None:
            self.counts = {r["level"]: r["count"] for r in self.nodes.groupBy("level").count().collect()}
        return self.counts


def sample_windows(chunks: DataFrame, q: int, size: int = 100, seed: int = 42) -> np.ndarray:
    """(windows, c, q): windows of least hash, at most one a chunk until chunks run out; a bounded sample."""
    keys = sample_keys(chunks, size, seed)
    cut = F.transform("vals", lambda line: F.slice(line, F.col("o") + 1, q))
    rows = chunks.join(F.broadcast(keys), ["series_id", "chunk_id"]).select("series_id", "chunk_id", "try", cut.alias("w")).toArrow().sort_by([(c, "ascending") for c in ("try", "series_id", "chunk_id")])
    if not rows.num_rows:
        return np.zeros((0, 0, q))
    w = rows.column("w").combine_chunks()
    return np.asarray(w.flatten().flatten().to_numpy(zero_copy_only=False), float).reshape(len(w), -1, q)


def sample_keys(chunks: DataFrame, size: int, seed: int) -> DataFrame:
    """(series_id, chunk_id, try, o): chunk and place of the sample's windows."""
    keys = chunks.select("series_id", "chunk_id", "base_t", "n_core")
    tries = F.explode(F.sequence(F.lit(0), F.lit(15)))
    keys = keys.select("series_id", "chunk_id", "base_t", "n_core", tries.alias("try"))
    offset = F.pmod(F.xxhash64("series_id", "chunk_id", "try", F.lit(seed)), F.col("n_core").cast("bigint"))
    return keys.select("series_id", "chunk_id", "try", offset.cast("int").alias("o")).orderBy("try", F.xxhash64("series_id", "chunk_id", "try", F.lit(seed + 1)), "series_id", "chunk_id").limit(size)


def pair_shares(sample: np.ndarray, normalized: bool = False) -> np.ndarray:
    """(pairs, channels, bins): share of each pair's squared distance; NaN in channels where the pair is equal."""
    w = K.znorm(sample) if normalized else sample
    q = w.shape[-1]
    spec = np.fft.rfft(w, axis=-1)
    weight = np.array([K.bin_weight(b, q) for b in range(K.bins_of(q))])
    i, j = np.triu_indices(len(spec), 1)
    d = weight * np.abs(spec[j] - spec[i]) ** 2
    return _shares(d)


def energy_shares(sample: np.ndarray, normalized: bool = False) -> np.ndarray:
    """(windows, channels, bins): share of each window's energy; NaN in channels of zeros."""
    w = K.znorm(sample) if normalized else sample
    q = w.shape[-1]
    return _shares(np.array([K.bin_weight(b, q) for b in range(K.bins_of(q))]) * np.abs(np.fft.rfft(w, axis=-1)) ** 2)


def _shares(e: np.ndarray) -> np.ndarray:
    s = e.sum(axis=2, keepdims=True)
    return np.where(s > 1e-12, e / np.where(s > 0, s, 1), np.nan)


def ardc(sample: np.ndarray, normalized: bool = False) -> np.ndarray:
    """Average share of a pair's squared distance in each (channel, bin)."""
    w = K.znorm(sample) if normalized else sample
    q = w.shape[-1]
    spec = np.fft.rfft(w, axis=-1)
    weight = np.array([K.bin_weight(b, q) for b in range(K.bins_of(q))])
    total, n = np.zeros(spec.shape[1:]), np.zeros(spec.shape[1])
    for i in range(len(spec) - 1):  # a row of pairs at a time, so that many channels fit
        d = _shares(weight * np.abs(spec[i + 1 :] - spec[i]) ** 2)
        total += np.nan_to_num(d).sum(axis=0)
        n += (~np.isnan(d[..., 0])).sum(axis=0)
    return total / np.maximum(n, 1)[:, None]


def energy_share(sample: np.ndarray, normalized: bool = False) -> np.ndarray:
    """Average share of a window's energy in each (channel, bin); windows of zeros count as 0."""
    return np.nan_to_num(energy_shares(sample, normalized)).mean(axis=0)


def select_bins(share: np.ndarray, d_target: float) -> dict[int, list[int]]:
    """Per channel the bins of largest share until they hold the target (ties by bin)."""
    out = {}
    for c, row in enumerate(share):
        order = sorted(range(len(row)), key=lambda b: (-row[b], b))
        kept, held = [], 0.0
        for b in order:
            if held >= d_target - 1e-12 or row[b] <= 0 and kept:
                break
            kept.append(b)
            held += row[b]
        out[c] = sorted(kept)
    return out


def build_index(
    chunks: DataFrame, q: int, *, normalized: bool = False, d_target: float = 0.6, bins: str = "ardc", f: int | None = None, sample: int = 100, seed: int = 42, leaf_pct: float = 0.05, max_leaf: int = 100_000,
    weighting: str = "softmax", layout: str = "str", n_pivots: int = 1, compress: bool = True, fanout: int = 64, boxes: str = "double", router_sample: int = 2000, keep_chunks: bool = True,
) -> Index:
    """Index over the chunks' windows of length q; ``bins``: ardc, energy or first (with ``f``).

    ``keep_chunks``: False where they are a table already. Chunks in blocks of channels have an index of their own (``wide``).
    """
    from time import perf_counter

    if "block_id" in chunks.columns:
        from . import wide as blocked

        return blocked.build(chunks, q, normalized=normalized, d_target=d_target, bins=bins, f=f, sample=sample, seed=seed, leaf_pct=leaf_pct, max_leaf=max_leaf, weighting=weighting, layout=layout, n_pivots=n_pivots, compress=compress, boxes=boxes, router_sample=router_sample)
    t0 = perf_counter()
    chunks = chunks.persist(StorageLevel.DISK_ONLY) if keep_chunks else chunks
    n = int(chunks.agg(F.sum("n_core")).first()[0] or 0)
    wide = sample_windows(chunks, q, router_sample, seed)
    few = wide[:sample]
    c = few.shape[1]
    if bins == "first":
        kept = {ch: list(range(min(f or 3, K.bins_of(q)))) for ch in range(c)}
    elif len(few) > 1:
        kept = select_bins((ardc if bins == "ardc" else energy_share)(few, normalized), d_target)
    else:
        kept = {ch: [0, 1] if q > 1 else [0] for ch in range(c)}
    dims = K.dims_of(q, kept, normalized)
    feats = K.window_features(wide, dims, normalized)
    weights = K.softmax_weights(feats[:sample].var(axis=0, ddof=1) if len(few) > 1 else np.ones(len(dims)), weighting)
    leaf = max(1.0, min(leaf_pct / 100 * n, max_leaf))
    router = K.learn_router(feats, n, leaf, weights, layout)
    t1 = perf_counter()
    pivots = np.zeros((0, c, q))
    if n_pivots and len(few):
        rest = K.remainder(few, kept, normalized)
        pivots = K.kmeans(rest.reshape(len(rest), -1), min(n_pivots, len(rest)), seed).reshape(-1, c, q)
    t2 = perf_counter()
    spec = Spec(q, c, normalized, kept, dims, pivots, weighting, layout, leaf, n, [float(x) for x in weights], router, compress, boxes == "float32")
    entries = chunks.select("series_id", "chunk_id", "base_t", "n_core", "vals").mapInArrow(_entries_of(spec), ENTRY)
    entries, kept = _kept(entries, spec, n)
    nodes = None if not kept and _wide(spec) else build_levels(_leaf_source(entries, chunks, spec, kept), fanout, len(dims))
    spec.phases = {"sample_bins_tiling": t1 - t0, "pivots": t2 - t1}
    return Index(spec, chunks, entries, nodes, kept=kept, fanout=fanout, routed=True)


def _wide(spec: Spec) -> bool:
    return 2 * len(spec.dims) > MOST_SIDES


def _kept(entries: DataFrame, spec: Spec, n_windows: int) -> tuple[DataFrame, bool]:
    """The runs on disk, where their boxes are small; on noise-like series they are far larger than the chunks."""
    size = 16 * (len(spec.dims) + spec.c * len(spec.pivots)) * n_windows
    if size <= KEPT_BYTES and not _wide(spec):
        return entries.persist(StorageLevel.DISK_ONLY), True
    return entries.where(F.lit(True)), False  # a plan of its own, not that of equal runs which another index keeps


def _leaf_source(entries: DataFrame, chunks: DataFrame, spec: Spec, kept: bool) -> DataFrame:
    """What leaf boxes are made of: the runs, or boxes that each task has joined."""
    return entries if kept else P.leaf_rows(chunks, spec)


def _entries_of(spec: Spec):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for rows in batches:
            for r in rows.to_pylist():
                x = np.array(r["vals"], float)
                feats = K.sliding_features(x, spec.q, spec.dims, spec.normalized)[: r["n_core"]]
                gaps = K.pivot_gaps(x, spec.q, spec.dims, K.sliding_features(x, spec.q, spec.dims, spec.normalized), spec.pivots, spec.normalized)[: r["n_core"]] if len(spec.pivots) else np.zeros((len(feats), 0))
                leaf = K.route(feats, spec.router)
                first, last = K.runs(leaf) if spec.compress else (np.arange(len(feats)), np.arange(len(feats)))
                yield boxes_batch(r, first, last, leaf[first], feats, gaps, float(np.abs(x).max(initial=1.0)), spec.float32)

    return run


def boxes_batch(r: dict, first, last, leaf, feats, gaps, size: float, float32: bool = False) -> pa.RecordBatch:
    """Runs as entry rows; bounds are widened by rounding error, and outwards to single precision if asked."""
    if not len(first):
        return pa.RecordBatch.from_pylist([], schema=_schema())
    slack = 1e-9 * max(1.0, size) * np.sqrt(max(1, feats.shape[1]))
    lo, hi = np.minimum.reduceat(feats, first, axis=0) - slack, np.maximum.reduceat(feats, first, axis=0) + slack
    near = 1e-6 * max(1.0, size)  # square roots of small differences lose more
    plo, phi = (np.maximum(np.minimum.reduceat(gaps, first, axis=0) - near, 0), np.maximum.reduceat(gaps, first, axis=0) + near) if gaps.shape[1] else (np.zeros((len(first), 0)),) * 2
    if float32:
        lo, plo = (np.nextafter(v.astype(np.float32), np.float32(-np.inf)).astype(float) for v in (lo, plo))
        hi, phi = (np.nextafter(v.astype(np.float32), np.float32(np.inf)).astype(float) for v in (hi, phi))
    n = len(first)
    return pa.RecordBatch.from_arrays(
        [
            pa.array([r["series_id"]] * n, pa.int64()), pa.array([r["chunk_id"]] * n, pa.int64()), pa.array(first + r["base_t"], pa.int64()), pa.array(last + r["base_t"], pa.int64()), pa.array(last - first + 1, pa.int32()), pa.array(leaf, pa.int64()),
            *(pa.array(v.tolist(), pa.list_(pa.float64())) for v in (lo, hi, plo, phi)),
        ],
        schema=_schema(),
    )


def _schema() -> pa.Schema:
    v = pa.list_(pa.float64())
    return pa.schema([("series_id", pa.int64()), ("chunk_id", pa.int64()), ("first_start", pa.int64()), ("last_start", pa.int64()), ("n_windows", pa.int32()), ("leaf_id", pa.int64()), ("lo", v), ("hi", v), ("plo", v), ("phi", v)])




def build_levels(entries: DataFrame, fanout: int = 64, d: int | None = None) -> DataFrame:
    """Nodes of all levels up to a root: each is the box of its children (parent = id div fanout)."""
    def boxes(df: DataFrame, key: Column) -> DataFrame:
        sums = [F.sum("n_entries").alias("n_entries"), F.sum("n_windows").alias("n_windows")]
        if d is not None and d <= WIDE_DIMS:
            return df.groupBy(key.alias("node_id")).agg(*sums, *box_agg("lo", "hi", d))
        return df.select(key.alias("node_id"), "n_entries", "n_windows", "lo", "hi").groupBy("node_id").applyInArrow(_joined, "node_id bigint, n_entries bigint, n_windows bigint, lo array<double>, hi array<double>")

    n_entries = F.col("n_entries") if "n_entries" in entries.columns else F.lit(1).cast("bigint").alias("n_entries")
    level = boxes(entries.select("leaf_id", "lo", "hi", n_entries, F.col("n_windows").cast("bigint").alias("n_windows")), F.col("leaf_id")).persist(StorageLevel.DISK_ONLY)
    out, depth = level.withColumn("level", F.lit(0)), 0
    top = level.agg(F.max("node_id")).first()[0] or 0
    while top > 0:
        depth += 1
        level = boxes(level, F.floor(F.col("node_id") / fanout))
        out = out.unionByName(level.withColumn("level", F.lit(depth)))
        top //= fanout
    return out.withColumn("parent_id", F.floor(F.col("node_id") / fanout)).persist(StorageLevel.DISK_ONLY)


def _joined(rows: pa.Table) -> pa.Table:
    """One box of all boxes of a node."""
    sides = []
    for name, side in (("lo", np.minimum), ("hi", np.maximum)):
        own = None
        for part in rows.column(name).chunks:
            for one in part:
                v = one.values.to_numpy(zero_copy_only=False)
                own = v.copy() if own is None else side(own, v)
        sides.append(P.lists(own[None]))
    sums = [pa.array([sum(rows.column(c).to_pylist())], pa.int64()) for c in ("n_entries", "n_windows")]
    return pa.table([rows.column("node_id").slice(0, 1).combine_chunks(), *sums, *sides], names=["node_id", "n_entries", "n_windows", "lo", "hi"])


# --- queries ------------------------------------------------------------------------------------------------------


@dataclass
class Query:
    query_id: int
    channels: list[int]
    values: np.ndarray  # (len(channels), q)


def collect_queries(points: DataFrame) -> list[Query]:
    """Queries from their points (query_id, channel, j, qv); a workload is small by nature."""
    rows = points.groupBy("query_id", "channel").agg(F.transform(F.array_sort(F.collect_list(F.struct("j", "qv"))), lambda p: p["qv"].cast("double")).alias("v")).orderBy("query_id", "channel").collect()
    out: dict[int, list] = {}
    for r in rows:
        out.setdefault(r["query_id"], []).append((r["channel"], r["v"]))
    return [Query(i, [c for c, _ in ls], np.array([v for _, v in ls], float)) for i, ls in out.items()]


def cut_queries(chunks: DataFrame, q: int, n_queries: int, noise: int, channels: list[int] | None = None, held_out: bool = False) -> list[Query]:
    """The queries of ``query_points``, from chunks with windows of length q: each is cut from the one chunk that holds its window."""
    if "block_id" in chunks.columns:
        from . import wide as blocked

        return blocked.cut_queries(chunks, q, n_queries, noise, channels, held_out)
    lengths = chunks.groupBy("series_id").agg((F.max(F.col("base_t") + F.col("n_core")) + q - 1).cast("bigint").alias("m"))
    cut = query_cuts(lengths, q, n_queries, held_out)
    lines = "vals" if channels is None else F.array(*[F.get("vals", F.lit(c)) for c in sorted(set(channels))])
    line = lambda x: F.slice(x, (F.col("start") - F.col("base_t") + 1).cast("int"), q)
    inside = (F.col("start") >= F.col("base_t")) & (F.col("start") < F.col("base_t") + F.col("n_core"))
    rows = chunks.join(F.broadcast(cut), "series_id").where(inside).select("query_id", "start", F.transform(lines, line).alias("w")).toArrow().sort_by("query_id")
    out = []
    for i, start, w in zip(rows.column("query_id").to_pylist(), rows.column("start").to_pylist(), rows.column("w"), strict=True):
        known = w.values.is_valid().to_numpy(zero_copy_only=False)  # a channel that isn't there is null
        own = np.array(sorted(set(channels)) if channels is not None else range(len(known)), np.int64)[known]
        v = w.values.flatten().to_numpy(zero_copy_only=False).reshape(-1, q)
        t = start + np.arange(q, dtype=np.int64)
        if len(own):
            out.append(Query(i, own.tolist(), v + noise * ((t * 7919 + own[:, None] * 104729 + i * 31) % 5 - 2)))
    return out


def _frame_of(index: Index, queries: list[Query]) -> DataFrame | None:
    """The queries as a broadcast frame; none for a wide index, whose leaves and runs are bounded in passes over the chunks."""
    for qu in queries:
        if qu.values.shape[1] != index.spec.q:
            raise LengthMismatch(f"the index holds windows of length {index.spec.q}, the query has {qu.values.shape[1]}")
    return None if index.wide else F.broadcast(query_frame(index.entries.sparkSession, index, queries))


def query_frame(spark: SparkSession, index: Index, queries: list[Query]) -> DataFrame:
    """One row a query: features (null for dimensions of other channels) and pivot distances of its remainder."""
    spec, rows = index.spec, []
    for qu in queries:
        known = set(qu.channels)
        full = np.zeros((spec.c, spec.q))
        full[qu.channels] = qu.values
        y = K.window_features(full[None], spec.dims, spec.normalized)[0]
        y = [float(v) if d[0] in known else None for v, d in zip(y, spec.dims, strict=True)]
        p = len(spec.pivots)
        gaps: list[float | None] = [None] * (spec.c * p)
        near = 0
        if p:
            rest = K.remainder(full[None], spec.kept, spec.normalized)[0]
            d = np.sqrt(((rest[None] - spec.pivots) ** 2).sum(axis=2))  # (p, c)
            near = int(np.argmin((d[:, qu.channels] ** 2).sum(axis=1)))
            for c in qu.channels:
                for j in range(p):
                    gaps[c * p + j] = float(d[j, c])
        rows.append((qu.query_id, y, gaps, near))
    return spark.createDataFrame(rows, "query_id int, y array<double>, gaps array<double>, nearest int")


def _gap2(lo: Column, y: Column, hi: Column) -> Column:
    g = F.greatest(lo - y, y - hi, F.lit(0.0))
    return F.coalesce(g * g, F.lit(0.0))


def _total(terms: list[Column]) -> Column:
    """Balanced sum, so that the expression stays shallow."""
    while len(terms) > 1:
        terms = [terms[i] + terms[i + 1] if i + 1 < len(terms) else terms[i] for i in range(0, len(terms), 2)]
    return terms[0] if terms else F.lit(0.0)


def lower_bound(spec: Spec, correction: str = "nearest", pivots: bool = True) -> Column:
    """Squared lower bound of a box to a query: flat arithmetic on array elements; other channels' terms are null, so 0."""
    d = len(spec.dims)
    if d <= FLAT_DIMS:
        at = lambda a, i: F.get(a, F.lit(i))
        base = _total([F.when(at("y", i).isNull(), 0.0).otherwise(_gap2(at("lo", i), at("y", i), at("hi", i))) for i in range(d)])
    else:
        base = F.aggregate(F.arrays_zip("lo", "hi", "y"), F.lit(0.0), lambda s, x: s + F.when(x["y"].isNull(), 0.0).otherwise(_gap2(x["lo"], x["y"], x["hi"])))
    p = len(spec.pivots)
    if not p or correction == "none" or not pivots:
        return base
    at = lambda a, i: F.get(a, F.lit(i) if isinstance(i, int) else i)
    terms = []
    for c in range(spec.c):
        gap = [F.when(at("gaps", c * p + j).isNull(), 0.0).otherwise(_gap2(at("plo", c * p + j), at("gaps", c * p + j), at("phi", c * p + j))) for j in range(p)]
        if correction == "max":
            terms.append(F.greatest(*gap) if p > 1 else gap[0])
        else:
            pick = gap[0]
            for j in range(1, p):
                pick = F.when(F.col("nearest") == j, gap[j]).otherwise(pick)
            terms.append(pick)
    return base + _total(terms)


def verify(candidates: DataFrame, chunks: DataFrame, queries: list[Query], k: int | None, normalized: bool, radius2: float | None = None, method: str = "auto", few: bool = False) -> DataFrame:
    """Exact squared distances of the windows in candidate runs: the profile of each run, then value by value.

    With k, each batch returns only what may be among the k best. Windows whose profile distance is within rounding
    of the cut are recomputed directly, so cancellation can't lose one.
    """
    known = {qu.query_id: qu for qu in queries}
    small = candidates.select("query_id", "series_id", "chunk_id", "first_start", "last_start")
    grouped = small.groupBy("series_id", "chunk_id").agg(F.collect_list(F.struct("query_id", "first_start", "last_start")).alias("wanted"))
    joined = chunks.select("series_id", "chunk_id", "base_t", "vals").join(F.broadcast(grouped) if few else grouped, ["series_id", "chunk_id"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for rows in batches:
            best: dict[int, list] = {}
            for r in rows.to_pylist():
                x = np.array(r["vals"], float)
                alike: dict[tuple, list[int]] = {}  # queries of one form on one run
                for query_id, starts in _runs_by_query(r["wanted"], r["base_t"]).items():
                    for run_of in starts:
                        alike.setdefault((run_of, known[query_id].values.shape[1], *known[query_id].channels), []).append(query_id)
                for ((a, b), q, *channels), ids in alike.items():
                    sub = x[channels]
                    blocks = (ids[o : o + 64] for o in range(0, len(ids), 64))
                    for query_id, d in ((i, d) for own in blocks for i, d in zip(own, K.profiles(sub[:, a : b + q], np.array([known[i].values for i in own]), normalized, method), strict=True)):
                        qu = known[query_id]
                        cut = radius2 if radius2 is not None else (np.partition(d, k - 1)[k - 1] if k is not None and len(d) > k else np.inf)
                        slack = 1e-6 * max(1.0, float(np.abs(sub[:, a : b + q]).max(initial=1.0)) ** 2 if not normalized else 1.0)
                        at = np.flatnonzero(d <= cut * (1 + 1e-6) + slack) + a
                        for o in range(0, len(at), 4096):
                            e = K.direct(sub, qu.values, at[o : o + 4096], normalized)
                            best.setdefault(query_id, []).append(np.column_stack([np.full(len(e), r["series_id"]), at[o : o + 4096] + r["base_t"], e]))
            for query_id, parts in best.items():
                m = np.concatenate(parts)
                if k is not None and len(m) > k:
                    m = m[m[:, 2] <= np.partition(m[:, 2], k - 1)[k - 1] * (1 + 1e-9) + 1e-9]
                yield pa.RecordBatch.from_arrays([pa.array([query_id] * len(m), pa.int32()), pa.array(m[:, 0].astype(np.int64)), pa.array(m[:, 1].astype(np.int64)), pa.array(m[:, 2])], names=["query_id", "series_id", "start", "d2"])

    return joined.mapInArrow(run, "query_id int, series_id bigint, start bigint, d2 double")


def _runs_by_query(wanted: list[dict], base: int) -> dict[int, list[tuple[int, int]]]:
    """Runs of a chunk by query, overlapping and touching ones merged."""
    out: dict[int, list[tuple[int, int]]] = {}
    for w in sorted(wanted, key=lambda w: (w["query_id"], w["first_start"])):
        a, b = w["first_start"] - base, w["last_start"] - base
        have = out.setdefault(w["query_id"], [])
        if have and a <= have[-1][1] + 1:
            have[-1] = (have[-1][0], max(have[-1][1], b))
        else:
            have.append((a, b))
    return out


def top_k(found: DataFrame, k: int, normalized: bool, whole_numbers: bool = True, exclusion: int = 0) -> DataFrame:
    """query_id, rank, series_id, start, (d2,) distance: total order by distance, series, start."""
    key = F.round(F.sqrt("d2"), 6) if normalized else F.col("d2")
    found = found.dropDuplicates(["query_id", "series_id", "start"])
    if exclusion:
        few = found.withColumn("r", F.row_number().over(Window.partitionBy("query_id").orderBy(key, "series_id", "start"))).where(F.col("r") <= k * (2 * exclusion + 1)).drop("r")
        found = few.groupBy("query_id").applyInPandas(lambda p: _apart(p, k, exclusion, normalized), "query_id int, series_id bigint, start bigint, d2 double")
    ranked = found.withColumn("rank", F.row_number().over(Window.partitionBy("query_id").orderBy(key, "series_id", "start")).cast("int")).where(F.col("rank") <= k)
    return finish(ranked, normalized, whole_numbers)


def _apart(rows: pd.DataFrame, k: int, exclusion: int, normalized: bool) -> pd.DataFrame:
    """The k nearest windows of a query such that no two of one series start within ``exclusion``; nearest first."""
    rows = rows.assign(key=np.sqrt(rows["d2"]).round(6) if normalized else rows["d2"]).sort_values(["key", "series_id", "start"])
    taken: dict[int, list[int]] = {}
    keep = []
    for s, t in zip(rows["series_id"], rows["start"], strict=True):
        ok = len(keep) - keep.count(False) < k and all(abs(t - u) > exclusion for u in taken.get(s, ()))
        keep.append(ok)
        if ok:
            taken.setdefault(s, []).append(t)
    return rows[keep].drop(columns="key")


def finish(ranked: DataFrame, normalized: bool, whole_numbers: bool = True) -> DataFrame:
    d2 = [] if normalized else [F.round("d2").cast("bigint").alias("d2") if whole_numbers else F.col("d2")]
    return ranked.select("query_id", "rank", "series_id", "start", *d2, F.round(F.sqrt("d2"), 4).alias("distance"))


@dataclass
class Trace:
    """What a search did: per query the node and run boxes bounded, the runs and windows verified (exact distances)."""

    rows: list[dict]


def _cuts(queries: list[Query], reach: dict[int, float], eps: float) -> Column:
    """The squared threshold of a row's query, widened by rounding; infinite where fewer than k windows are known."""
    cut = F.create_map(*[x for qu in queries for x in (F.lit(qu.query_id), F.lit(float(reach.get(qu.query_id, np.inf))))])
    return F.element_at(cut, F.col("query_id")) * (1 + eps) + eps


def _few(df: DataFrame, rows: int) -> DataFrame:
    """Broadcast where the bound on its rows allows it; else a shuffle join."""
    return F.broadcast(df) if rows <= 10 * BROADCAST_ROWS else df


def descend(index: Index, frame: DataFrame | None, queries: list[Query], reach: dict[int, float] | None = None, least: int | None = None, eps: float = EPS) -> DataFrame:
    """query_id, leaf_id, nlb, n_entries, n_windows of the leaves that a way down the nodes reaches.

    ``reach``: a node is entered if its bound is within the query's squared threshold. ``least``: the nearest nodes of
    each level are entered until they hold so many windows. Leaf boxes that the driver holds are bounded there; else
    the start is the lowest level that is small enough to be bounded as a whole, and each level below is a join.
    Leaves of a wide index are bounded in a pass over the chunks.
    """
    found = _on_driver(index, queries, reach, least, eps)
    if found is not None:
        rows = [(i, *r) for i, own in found.items() for r in zip(*(c.tolist() for c in own), strict=True)]
        return index.entries.sparkSession.createDataFrame(rows, "query_id int, leaf_id bigint, nlb double, n_entries bigint, n_windows bigint")
    n_queries = len(queries)
    within = None if reach is None else _cuts(queries, reach, eps)
    counts = index.levels()
    start = min((lv for lv, n in counts.items() if n <= BROADCAST_ROWS), default=max(counts, default=0))
    reached = None
    for level in range(start, -1, -1):
        nodes = index.nodes.where(F.col("level") == level).select("node_id", "parent_id", "n_entries", "n_windows", "lo", "hi")
        if reached is not None:
            nodes = nodes.join(_few(reached.select("query_id", F.col("node_id").alias("parent_id")), n_queries * counts[level + 1]), "parent_id").join(frame, "query_id")
        else:
            nodes = frame.crossJoin(nodes)
        reached = nodes.withColumn("nlb", lower_bound(index.spec, pivots=False)).select("query_id", "node_id", "n_entries", "n_windows", "nlb")
        if within is not None:
            reached = reached.where(F.col("nlb") <= within)
        if least is not None:
            before = F.sum("n_windows").over(Window.partitionBy("query_id").orderBy("nlb", "node_id").rowsBetween(Window.unboundedPreceding, -1))
            reached = reached.withColumn("before", F.coalesce(before, F.lit(0))).where(F.col("before") < least).drop("before")
    return reached.withColumnRenamed("node_id", "leaf_id")


def _on_driver(index: Index, queries: list[Query], reach: dict[int, float] | None, least: int | None, eps: float) -> dict[int, tuple] | None:
    """Per query the leaves reached, their bounds, entries and windows, where the driver holds what tells them."""
    held = None if index.wide else index.leaf_boxes()
    if held is None and not index.wide:
        return None
    found = {}
    for qu, y in zip(queries, [None] * len(queries) if index.wide else _features_of(index, queries), strict=True):
        if index.wide:
            own = index.leaf_bounds(queries)[qu.query_id]
            ids, nlb, n_entries, n_windows = (np.array(c) for c in zip(*own, strict=True)) if own else (np.zeros(0, np.int64),) * 4
        else:
            ids, n_entries, n_windows, lo, hi = held
            on = [i for i, d in enumerate(index.spec.dims) if d[0] in qu.channels]
            nlb = K.box_gap2(y[on], lo[:, on], hi[:, on])
        if reach is not None:
            at = np.flatnonzero(nlb <= reach.get(qu.query_id, np.inf) * (1 + eps) + eps)
        else:
            at = np.lexsort((ids, nlb))
            at = at[: int(np.searchsorted(np.cumsum(n_windows[at]), least)) + 1]
        found[qu.query_id] = (ids[at], nlb[at], n_entries[at], n_windows[at])
    return found


def reached_leaves(index: Index, frame: DataFrame | None, queries: list[Query], reach: dict[int, float] | None = None, least: int | None = None, eps: float = EPS) -> dict[int, np.ndarray]:
    """The leaves that ``descend`` gives by query: at most those of a router, which a bounded sample has made, or of their compacted form."""
    found = _on_driver(index, queries, reach, least, eps)
    if found is not None:
        return {i: own[0] for i, own in found.items() if len(own[0])}
    out: dict[int, list] = {}
    for r in descend(index, frame, queries, reach, least, eps).select("query_id", "leaf_id").collect():
        out.setdefault(r["query_id"], []).append(r["leaf_id"])
    return {i: np.array(v, np.int64) for i, v in out.items()}


def bounded_runs(index: Index, frame: DataFrame, leaves: DataFrame, n_queries: int, correction: str, flat: list[Column] = ()) -> DataFrame:
    """The runs of the leaves reached, with their bound ``lb``."""
    entries = index.entries
    if "slab" in entries.columns:
        slabs = [r[0] for r in leaves.select(F.floor(F.col("leaf_id") / SLAB).alias("slab")).distinct().limit(MOST_SLABS + 1).collect()]
        if len(slabs) <= MOST_SLABS:  # beyond, the join alone picks the leaves
            entries = entries.where(F.col("slab").isin(slabs))
        for one in flat:
            entries = entries.where(one)
    pairs = _few(leaves.select("query_id", "leaf_id"), n_queries * index.levels().get(0, 0))
    met = entries.join(pairs, "leaf_id").join(frame, "query_id")
    return met.withColumn("lb", lower_bound(index.spec, correction)).select("query_id", "series_id", "chunk_id", "first_start", "last_start", "n_windows", "leaf_id", "lb")


def flat_filters(index: Index, queries: list[Query], reach: dict[int, float], eps: float) -> list[Column]:
    """Filters on the flat box columns that every run within some query's threshold passes."""
    out = []
    for d in range(min(FLAT_SIDES, len(index.spec.dims))):
        if f"lo_{d}" not in index.entries.columns or any(index.spec.dims[d][0] not in qu.channels for qu in queries):
            continue
        ys = _features_of(index, queries)
        r = [np.sqrt(reach.get(qu.query_id, np.inf) * (1 + eps) + eps) for qu in queries]
        low, high = min(float(y[d]) - x for y, x in zip(ys, r, strict=True)), max(float(y[d]) + x for y, x in zip(ys, r, strict=True))
        if np.isfinite(low) and np.isfinite(high):
            out += [F.col(f"lo_{d}") <= high, F.col(f"hi_{d}") >= low]
    return out


def _features_of(index: Index, queries: list[Query]) -> list[np.ndarray]:
    spec, out = index.spec, []
    for qu in queries:
        full = np.zeros((spec.c, spec.q))
        full[qu.channels] = qu.values
        out.append(K.window_features(full[None], spec.dims, spec.normalized)[0])
    return out


def knn_index(index: Index, queries: list[Query], k: int, *, browsing: bool = True, mode: str = "subsequence", correction: str = "nearest", eps: float = EPS, exclusion: int = 0, whole_numbers: bool = True, trace: Trace | None = None) -> DataFrame:
    """Two probes down the nodes: the nearest leaves give a threshold from exact distances; all runs within it are verified.

    ``browsing=False`` verifies the runs of the first probe again in the second. ``exclusion``: windows of a series
    whose starts differ by so much or less from a nearer one's are left out; k of the others are returned.
    """
    if not isinstance(index, Index):
        from . import wide as blocked

        if mode != "subsequence" or trace is not None:
            raise ValueError("blocks of channels are searched without whole matching and trace")
        return blocked.knn(index, queries, k, browsing=browsing, correction=correction, eps=eps, exclusion=exclusion, whole_numbers=whole_numbers)
    spec, spark = index.spec, index.entries.sparkSession
    if mode == "whole" and index.chunks.where((F.col("n_core") > 1) | (F.col("chunk_id") > 0)).limit(1).count():
        raise LengthMismatch("whole matching needs series as long as the window")
    if k <= 0 or not queries:
        return finish(spark.createDataFrame([], "query_id int, rank int, series_id bigint, start bigint, d2 double"), spec.normalized, whole_numbers)
    n = len(queries)
    # of each chosen window at most 2 x exclusion others of its series are nearer and left out: so many are enough
    deep = k * (2 * exclusion + 1)
    frame = _frame_of(index, queries)
    kept = index.kept and not (index.routed and n >= MANY_QUERIES)
    near = bounded_runs(index, frame, descend(index, frame, queries, least=deep), n, correction) if kept else P.nearest_runs(index, queries, reached_leaves(index, frame, queries, least=deep), deep, correction)
    rank = F.row_number().over(Window.partitionBy("query_id").orderBy("lb", "series_id", "first_start"))
    rows = near.withColumn("r", rank).where(F.col("r") <= deep).drop("r").toArrow()  # at most k runs a query
    nearest = spark.createDataFrame(rows, near.schema)
    found_first = verify(nearest, index.chunks, queries, deep, spec.normalized, few=n * deep <= BROADCAST_ROWS).toArrow()  # the k nearest of those
    first = spark.createDataFrame(found_first, "query_id int, series_id bigint, start bigint, d2 double")
    by_query: dict[int, list[float]] = {}
    for i, d2 in zip(found_first.column("query_id").to_pylist(), found_first.column("d2").to_pylist(), strict=True):
        by_query.setdefault(i, []).append(d2)
    reach = {i: sorted(d)[deep - 1] for i, d in by_query.items() if len(d) >= deep}
    if not kept:
        done: dict[int, set] = {}
        for r in rows.to_pylist() if browsing else []:
            done.setdefault(r["query_id"], set()).add((r["series_id"], r["first_start"]))
        found_leaves = reached_leaves(index, frame, queries, reach)
        second = P.windows_within(index, queries, found_leaves, reach, eps, deep, correction, done, counted=trace is not None)
        if trace is not None:
            second = second.persist(StorageLevel.DISK_ONLY)  # counts and windows come from one pass; what may be among the k best of a task
            own = nearest.groupBy("query_id").agg(F.count(F.lit(1)).alias("runs"), F.sum("n_windows").alias("windows"))
            seen, second = second.where("runs is not null").select("query_id", "runs", "windows"), second.where("runs is null").drop("runs", "windows")
            seen = (seen.unionByName(own) if browsing else seen).groupBy("query_id").agg(F.sum("runs").alias("runs"), F.sum("windows").alias("windows"))
            _traced(trace, index, seen, _on_driver(index, queries, reach, None, eps) or descend(index, frame, queries, reach))
        return top_k(first.unionByName(second) if browsing else second, k, spec.normalized, whole_numbers, exclusion)
    leaves = descend(index, frame, queries, reach)
    within = bounded_runs(index, frame, leaves, n, correction, flat_filters(index, queries, reach, eps)).where(F.col("lb") <= _cuts(queries, reach, eps))
    if browsing:
        within = within.join(F.broadcast(nearest.select("query_id", "series_id", "first_start")), ["query_id", "series_id", "first_start"], "left_anti")
    second = verify(within, index.chunks, queries, deep, spec.normalized)
    found = first.unionByName(second) if browsing else second
    if trace is not None:
        seen = nearest.unionByName(within) if browsing else within
        _traced(trace, index, seen.groupBy("query_id").agg(F.count(F.lit(1)).alias("runs"), F.sum("n_windows").alias("windows")), leaves)
    return top_k(found, k, spec.normalized, whole_numbers, exclusion)


def _traced(trace: Trace, index: Index, done: DataFrame, leaves: DataFrame | dict[int, tuple]) -> None:
    # leaves of the first probe lie within the threshold too, so the second probe's runs hold the first's
    if isinstance(leaves, dict):
        bounds = done.sparkSession.createDataFrame([(i, int(own[2].sum()), len(own[0])) for i, own in leaves.items() if len(own[0])], "query_id int, run_bounds bigint, leaves bigint")
    else:
        bounds = leaves.groupBy("query_id").agg(F.sum("n_entries").alias("run_bounds"), F.count(F.lit(1)).alias("leaves"))
    if index.wide:
        bounded = max((len(v) for v in index.bounded[1].values()), default=0)
    else:
        bounded = max(min((x for x in index.levels().values() if x <= BROADCAST_ROWS), default=0), index.levels().get(0, 0))
    trace.rows = [r.asDict() | {"node_bounds": 2 * bounded, "exact_distances": r["windows"]} for r in done.join(bounds, "query_id", "left").orderBy("query_id").collect()]


def range_query(index: Index, queries: list[Query], radius: float, *, correction: str = "nearest", eps: float = EPS, whole_numbers: bool = True, ranked: bool = True) -> DataFrame:
    """All windows strictly nearer than ``radius``: one probe down the nodes, then exact distances.

    ``ranked=False`` leaves out the rank, which sorts all hits of a query in one task.
    """
    spec, spark = index.spec, index.entries.sparkSession
    reach = {qu.query_id: radius * radius for qu in queries}
    cut, n = _cuts(queries, reach, eps), len(queries)
    frame = _frame_of(index, queries)
    if index.kept:
        within = bounded_runs(index, frame, descend(index, frame, queries, reach), n, correction, flat_filters(index, queries, reach, eps)).where(F.col("lb") <= cut)
        found = verify(within, index.chunks, queries, None, spec.normalized, radius * radius)
    else:
        found = P.windows_within(index, queries, reached_leaves(index, frame, queries, reach), reach, eps, None, correction)
    found = found.where(F.sqrt("d2") < radius)
    if not ranked:
        return finish(found.withColumn("rank", F.lit(None).cast("int")), spec.normalized, whole_numbers).drop("rank")
    found = found.withColumn("rank", F.row_number().over(Window.partitionBy("query_id").orderBy("d2", "series_id", "start")).cast("int"))
    return finish(found, spec.normalized, whole_numbers)


def with_timestamps(found: DataFrame, base_ts: str, step: str) -> DataFrame:
    """Adds start_ts = base + start * step (both SQL literals, for example a timestamp and INTERVAL 7 DAYS)."""
    return found.withColumn("start_ts", F.expr(f"{base_ts} + start * {step}"))


def append(index: Index, new_chunks: DataFrame) -> Index:
    """A delta segment: the new chunks go to the leaves of the same spec; boxes are those of their members, so search stays exact."""
    spec = index.spec
    delta = new_chunks.select("series_id", "chunk_id", "base_t", "n_core", "vals").mapInArrow(_entries_of(spec), ENTRY)
    n = spec.n_windows + int(new_chunks.agg(F.sum("n_core")).first()[0] or 0)
    entries, kept = _kept(index.entries.select(*delta.columns).unionByName(delta), spec, n)
    chunks = index.chunks.unionByName(new_chunks.select(*index.chunks.columns))
    kept = kept or index.kept  # runs that are kept may have been moved to other leaves than the router's
    nodes = None if not kept and _wide(spec) else build_levels(_leaf_source(entries, chunks, spec, kept), d=len(spec.dims))
    return Index(spec, chunks, entries, nodes, kept=kept, routed=index.routed)


def compact(index: Index, fill: float = 2.0, rounds: int = 32) -> Index:
    """Regrouping after appends: a leaf with over ``fill`` times the leaf size is split until none is left.

    A split cuts the dimension in which the centres of the leaf's boxes lie widest at their median; all leaves over the
    limit are split in one pass, so no leaf is ever collected. Leaves of a single run can't be split.
    """
    d, entries = len(index.spec.dims), index.entries
    names = [c.strip().split(" ")[0] for c in ENTRY.split(", ")]
    entries = entries.select(*names)
    centre = lambda i: (F.get("lo", i) + F.get("hi", i)) / 2
    for _ in range(rounds if d else 0):
        spans = [(F.max(centre(F.lit(i))) - F.min(centre(F.lit(i)))).alias(f"s{i}") for i in range(d)]
        sizes = entries.groupBy("leaf_id").agg(F.sum("n_windows").alias("n"), *spans).where(F.col("n") > fill * index.spec.leaf)
        widest = F.greatest(*[F.struct(F.col(f"s{i}").alias("s"), F.lit(-i).alias("i")) for i in range(d)]) if d > 1 else F.struct(F.col("s0").alias("s"), F.lit(0).alias("i"))
        over = sizes.withColumn("w", widest).where("w.s > 0").select("leaf_id", (-F.col("w.i")).alias("dim"))
        cuts = entries.join(over, "leaf_id").withColumn("c", centre(F.col("dim"))).groupBy("leaf_id", "dim").agg(F.percentile_approx("c", 0.5).alias("cut"), F.max("c").alias("top"))
        # the cut goes below the largest centre, so that both sides hold a run
        cuts = written(cuts.withColumn("cut", F.when(F.col("cut") < F.col("top"), F.col("cut"))), "cuts")
        if cuts.isEmpty():
            break
        first = (entries.agg(F.max("leaf_id")).first()[0] or 0) + 1
        fresh = cuts.select("leaf_id", "dim", "cut", "top", (F.lit(first) + F.row_number().over(Window.orderBy("leaf_id")) - 1).alias("other"))
        moved = entries.join(fresh, "leaf_id", "left")
        c = centre(F.col("dim"))
        right = F.coalesce(F.when(F.col("cut").isNull(), c >= F.col("top")).otherwise(c > F.col("cut")), F.lit(False))
        entries = written(moved.withColumn("leaf_id", F.when(right, F.col("other")).otherwise(F.col("leaf_id"))).select(*names), "entries")
    return Index(index.spec, index.chunks, entries, build_levels(entries, d=d))


def save_index(index: Index, path: str) -> None:
    """Entries sorted by leaf, partitioned by slab and with flat box columns; chunks, nodes, and the spec as one JSON row."""
    spark, spec = index.entries.sparkSession, index.spec
    flat = [F.get(c, F.lit(i)).alias(f"{c}_{i}") for i in range(min(FLAT_SIDES, len(spec.dims))) for c in ("lo", "hi")]
    names = [c.strip().split(" ")[0] for c in ENTRY.split(", ")]
    index.entries.select(*names, *flat, F.floor(F.col("leaf_id") / SLAB).alias("slab")).repartition("slab").sortWithinPartitions("leaf_id").write.partitionBy("slab").mode("overwrite").parquet(f"{path}/entries")
    index.chunks.write.mode("overwrite").parquet(f"{path}/chunks")
    index.levels()
    index.nodes.write.mode("overwrite").parquet(f"{path}/nodes")
    told = asdict(spec) | {"pivots": spec.pivots.tolist(), "router": _listed(spec.router)}
    spark.createDataFrame([(json.dumps(told),)], "spec string").write.mode("overwrite").parquet(f"{path}/spec")


def _listed(node):
    return None if node is None else [node[0], node[1].tolist(), [_listed(n) for n in node[2]], node[3]]


def _nested(node):
    return None if node is None else (node[0], np.array(node[1]), [_nested(n) for n in node[2]], node[3])


def load_index(spark: SparkSession, path: str) -> Index:
    told = json.loads(spark.read.parquet(f"{path}/spec").first()[0])
    told["pivots"] = np.array(told["pivots"], float).reshape(-1, told["c"], told["q"])
    told["router"] = _nested(told["router"])
    told["kept"] = {int(c): b for c, b in told["kept"].items()}
    told["dims"] = [tuple(d) for d in told["dims"]]
    return Index(Spec(**told), spark.read.parquet(f"{path}/chunks"), spark.read.parquet(f"{path}/entries"), spark.read.parquet(f"{path}/nodes"))
