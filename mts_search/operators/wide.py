"""The index over series of very many channels, whose chunks are rows of CHANNEL_BLOCK channels each (column ``block_id``).

Shares, boxes, bounds and squared distances are sums over channels: each is made by block, and the blocks' parts are added
up by chunk. No row, task or driver holds all channels of a chunk. Kept bins and pivots stay in a table by block; the driver
has the variances of the dimensions, the router of the heaviest ones, and the queries.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark import StorageLevel
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions import kernels as K
from ..session import written
from . import chunk_pass as P
from . import index as I
from .series import CHANNEL_BLOCK, query_cuts

#: Heaviest dimensions that the router may cut: in order of weight, few are cut before every branch is a leaf.
ROUTER_DIMS = 16
#: Bytes of chunks that a task takes.
TASK_BYTES = 1 << 24
#: Vectors that a task adds up before it passes them on.
HELD_ROWS = 4096


@dataclass
class BlockIndex:
    q: int
    normalized: bool
    leaf: float
    n_windows: int
    d: int  # dimensions of all channels
    router: object
    float32: bool
    chunks: DataFrame
    parts: DataFrame  # block_id, kept, pivots
    runs: DataFrame  # series_id, chunk_id, base_t, first, last, leaf: the runs of a chunk
    tasks: int


def _matrix(v) -> np.ndarray:
    """A list of equally long lists of an Arrow array."""
    lines = v.values
    return np.asarray(lines.flatten().to_numpy(zero_copy_only=False), float).reshape(len(lines), -1)


def build(chunks: DataFrame, q: int, *, normalized: bool = False, d_target: float = 0.6, bins: str = "ardc", f: int | None = None, sample: int = 100, seed: int = 42, leaf_pct: float = 0.05, max_leaf: int = 100_000, weighting: str = "softmax", layout: str = "str", n_pivots: int = 1, compress: bool = True, boxes: str = "double", router_sample: int = 2000) -> BlockIndex:
    """As ``build_index``; with at most one pivot, the mean of the sample's remainders."""
    if n_pivots > 1:
        raise ValueError("blocks of channels have one pivot at most")
    whole = chunks.where("block_id = 0")
    n = int(whole.agg(F.sum("n_core")).first()[0] or 0)
    n_blocks = (chunks.agg(F.max("block_id")).first()[0] or 0) + 1
    keys = I.sample_keys(whole, router_sample, seed).toArrow()
    keys = chunks.sparkSession.createDataFrame(keys, "series_id bigint, chunk_id bigint, try int, o int")
    cut = F.transform("vals", lambda line: F.slice(line, F.col("o") + 1, q))
    windows = chunks.join(F.broadcast(keys), ["series_id", "chunk_id"]).select("block_id", "try", "series_id", "chunk_id", cut.alias("w"))

    def learn(rows: pa.Table) -> pa.Table:
        rows = rows.sort_by([(c, "ascending") for c in ("try", "series_id", "chunk_id")])
        wide = np.stack([_matrix(w) for w in rows.column("w")])
        few = wide[:sample]
        c = wide.shape[1]
        if bins == "first":
            kept = {ch: list(range(min(f or 3, K.bins_of(q)))) for ch in range(c)}
        elif len(few) > 1:
            kept = I.select_bins((I.ardc if bins == "ardc" else I.energy_share)(few, normalized), d_target)
        else:
            kept = {ch: [0, 1] if q > 1 else [0] for ch in range(c)}
        dims = K.dims_of(q, kept, normalized)
        feats = K.window_features(wide, dims, normalized)
        var = feats[:sample].var(axis=0, ddof=1) if len(few) > 1 else np.ones(len(dims))
        pivots = K.remainder(few, kept, normalized).mean(axis=0).tolist() if n_pivots else []
        top = np.argsort(-var, kind="stable")[:ROUTER_DIMS]
        values = [rows.column("block_id")[0].as_py(), [kept[ch] for ch in range(c)], pivots, var.tolist(), top.tolist(), feats[:, top].T.tolist()]
        return pa.table([pa.array([v], t) for v, t in zip(values, _PART_TYPES, strict=True)], names=["block_id", "kept", "pivots", "var", "top", "feats"])

    parts = written(windows.groupBy("block_id").applyInArrow(learn, "block_id bigint, kept array<array<int>>, pivots array<array<double>>, var array<double>, top array<int>, feats array<array<double>>"), "parts")
    var = parts.select("block_id", "var").toArrow().sort_by("block_id")
    sizes = [len(v) for v in var.column("var")]
    every = np.concatenate([np.asarray(v.values.to_numpy(zero_copy_only=False), float) for v in var.column("var")]) if sizes else np.zeros(0)
    weights = K.softmax_weights(every, weighting)
    first = dict(zip(var.column("block_id").to_pylist(), np.cumsum([0, *sizes[:-1]]).tolist(), strict=True)) if sizes else {}
    heavy = np.argsort(-weights, kind="stable")[:ROUTER_DIMS]
    of = {int(g): b for g in heavy for b, at in first.items() if at <= g < at + sizes[list(first).index(b)]}
    feats = {}
    for r in parts.where(F.col("block_id").isin(sorted(set(of.values())))).select("block_id", "kept", "top", "feats").collect() if of else []:
        dims = K.dims_of(q, dict(enumerate(r["kept"])), normalized)
        feats |= {first[r["block_id"]] + i: (r["block_id"], dims[i], np.array(v)) for i, v in zip(r["top"], r["feats"], strict=True)}
    heavy = [int(g) for g in heavy if int(g) in feats]
    leaf = max(1.0, min(leaf_pct / 100 * n, max_leaf))
    router = K.learn_router(np.stack([feats[g][2] for g in heavy], axis=1), n, leaf, weights[heavy], layout) if heavy else None
    runs = _runs(chunks, q, normalized, router, [feats[g][:2] for g in heavy], compress)
    cells = whole.agg(F.sum(F.size("vals") * (F.col("n_core") + q - 1))).first()[0] or 0
    tasks = max(chunks.sparkSession.sparkContext.defaultParallelism, -(-8 * cells * n_blocks // TASK_BYTES))
    return BlockIndex(q, normalized, leaf, n, len(every), router, boxes == "float32", chunks, parts.select("block_id", "kept", "pivots"), runs, tasks)


_PART_TYPES = [pa.int64(), pa.list_(pa.list_(pa.int32())), pa.list_(pa.list_(pa.float64())), pa.list_(pa.float64()), pa.list_(pa.int32()), pa.list_(pa.list_(pa.float64()))]


def _runs(chunks: DataFrame, q: int, normalized: bool, router, dims: list[tuple], compress: bool) -> DataFrame:
    """The runs of every chunk, from its features in the router's dimensions."""
    used = sorted(P._dims_in(router))
    router = P._part_of(router, {d: i for i, d in enumerate(used)})
    by_block: dict[int, list] = {}
    for i, d in enumerate(used):
        by_block.setdefault(dims[d][0], []).append((i, dims[d][1]))

    def features(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for rows in batches:
            blocks = rows.column(5).to_pylist()
            for block, (series, chunk, base, n, x) in zip(blocks, P.chunk_rows(rows), strict=True):
                own = by_block.get(block, [])
                feats = K.sliding_features(x, q, [d for _, d in own], normalized)[:n]
                found = pa.array([feats[:, j].tolist() for j in range(len(own))] or [None], pa.list_(pa.float64()))
                yield pa.RecordBatch.from_arrays([pa.array([series] * len(found), pa.int64()), pa.array([chunk] * len(found), pa.int64()), pa.array([base] * len(found), pa.int64()), pa.array([n] * len(found), pa.int32()), pa.array([i for i, _ in own] or [-1], pa.int32()), found], names=["series_id", "chunk_id", "base_t", "n_core", "i", "f"])

    def label(rows: pa.Table) -> pa.Table:
        n = rows.column("n_core")[0].as_py()
        found = dict(zip(rows.column("i").to_pylist(), rows.column("f").to_pylist(), strict=True))
        leaf = K.route(np.array([found[i] for i in range(len(used))], float).T.reshape(n, -1), router) if used else np.zeros(n, np.int64)
        first, last = K.runs(leaf) if compress else (np.arange(n), np.arange(n))
        lists = [pa.array([v.tolist()], pa.list_(pa.int64())) for v in (first, last, leaf[first])]
        return pa.table([*(rows.column(c).slice(0, 1).combine_chunks() for c in ("series_id", "chunk_id", "base_t")), *lists], names=["series_id", "chunk_id", "base_t", "first", "last", "leaf"])

    some = chunks.where(F.col("block_id").isin([0, *by_block])).select(*P.CHUNK, "block_id")
    made = some.mapInArrow(features, "series_id bigint, chunk_id bigint, base_t bigint, n_core int, i int, f array<double>")
    return written(made.groupBy("series_id", "chunk_id").applyInArrow(label, "series_id bigint, chunk_id bigint, base_t bigint, first array<bigint>, last array<bigint>, leaf array<bigint>"), "runs")


def cut_queries(chunks: DataFrame, q: int, n_queries: int, noise: int, channels: list[int] | None = None, held_out: bool = False) -> list[I.Query]:
    """As ``index.cut_queries``, from blocks."""
    lengths = chunks.where("block_id = 0").groupBy("series_id").agg((F.max(F.col("base_t") + F.col("n_core")) + q - 1).cast("bigint").alias("m"))
    cut = query_cuts(lengths, q, n_queries, held_out)
    some = chunks if channels is None else chunks.where(F.col("block_id").isin(sorted({c // CHANNEL_BLOCK for c in channels})))
    line = lambda x: F.slice(x, (F.col("start") - F.col("base_t") + 1).cast("int"), q)
    inside = (F.col("start") >= F.col("base_t")) & (F.col("start") < F.col("base_t") + F.col("n_core"))
    rows = some.join(F.broadcast(cut), "series_id").where(inside).select("query_id", "block_id", "start", F.transform("vals", line).alias("w")).toArrow().sort_by([("query_id", "ascending"), ("block_id", "ascending")])
    found: dict[int, list] = {}
    for i, block, start, w in zip(*(rows.column(c).to_pylist() for c in ("query_id", "block_id", "start")), rows.column("w"), strict=True):
        v = _matrix(w)
        own = block * CHANNEL_BLOCK + np.arange(len(v), dtype=np.int64)
        on = np.ones(len(own), bool) if channels is None else np.isin(own, channels)
        t = start + np.arange(q, dtype=np.int64)
        found.setdefault(i, []).append((own[on], v[on] + noise * ((t * 7919 + own[on][:, None] * 104729 + i * 31) % 5 - 2)))
    return [I.Query(i, np.concatenate([c for c, _ in parts]).tolist(), np.concatenate([v for _, v in parts])) for i, parts in found.items() if sum(len(c) for c, _ in parts)]


def _by_block(index: BlockIndex, queries: list[I.Query]) -> DataFrame:
    """(block_id, query_id, own, y): the queries' lines by block, ``own`` their places in it."""
    rows = []
    for qu in queries:
        channels = np.array(qu.channels)
        for b in np.unique(channels // CHANNEL_BLOCK).tolist():
            on = np.flatnonzero(channels // CHANNEL_BLOCK == b)
            rows.append((b, qu.query_id, (channels[on] - b * CHANNEL_BLOCK).astype(np.int32), P.lists(qu.values[on])))
    cols = [pa.array([r[0] for r in rows], pa.int64()), pa.array([r[1] for r in rows], pa.int32()), pa.array([r[2] for r in rows], pa.list_(pa.int32())), pa.array([r[3].to_pylist() for r in rows], pa.list_(pa.list_(pa.float64())))]
    return index.chunks.sparkSession.createDataFrame(pa.table(cols, names=["block_id", "query_id", "own", "y"]), "block_id bigint, query_id int, own array<int>, y array<array<double>>")


def _added(df: DataFrame, of) -> DataFrame:
    """Vectors ``v`` that ``of`` makes of each row, added up by (series, chunk, query)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: dict[tuple, np.ndarray] = {}

        def out() -> pa.RecordBatch:
            cols = [pa.array([k[i] for k in held], t) for i, t in enumerate((pa.int64(), pa.int64(), pa.int32()))]
            return pa.RecordBatch.from_arrays([*cols, pa.array(list(held.values()), pa.list_(pa.float64()))], names=["series_id", "chunk_id", "query_id", "v"])

        for rows in batches:
            for i in range(rows.num_rows):
                r = {c: rows.column(c)[i] for c in rows.schema.names}
                key = tuple(r[c].as_py() for c in ("series_id", "chunk_id", "query_id"))
                v = of(r)
                held[key] = held[key] + v if key in held else v
                if len(held) >= HELD_ROWS:
                    yield out()
                    held = {}
        yield out()

    def total(rows: pa.Table) -> pa.Table:
        v = np.sum([np.asarray(one.values.to_numpy(zero_copy_only=False), float) for one in rows.column("v")], axis=0)
        return pa.table([*(rows.column(c).slice(0, 1).combine_chunks() for c in ("series_id", "chunk_id", "query_id")), pa.array([v], pa.list_(pa.float64()))], names=["series_id", "chunk_id", "query_id", "v"])

    schema = "series_id bigint, chunk_id bigint, query_id int, v array<double>"
    return df.mapInArrow(run, schema).groupBy("series_id", "chunk_id", "query_id").applyInArrow(total, schema)


def _met(index: BlockIndex, asked: DataFrame, few: DataFrame, on: list[str], queries: list[I.Query]) -> DataFrame:
    """The blocks that hold channels of the queries, with the queries' lines and a small row a chunk."""
    blocks = sorted({c // CHANNEL_BLOCK for qu in queries for c in qu.channels})
    chunks = index.chunks.where(F.col("block_id").isin(blocks)) if len(blocks) <= 100 else index.chunks
    asked = asked.repartition(index.tasks, "block_id")
    return chunks.repartition(index.tasks, "block_id").join(asked.hint("shuffle_merge"), "block_id").join(F.broadcast(few) if index.n_windows <= 10 * I.BROADCAST_ROWS else few, on)


def bounds(index: BlockIndex, queries: list[I.Query], correction: str = "nearest") -> DataFrame:
    """query_id, series_id, chunk_id, first_start, last_start, n_windows, leaf_id, lb of every run, and the bound ``nlb`` of its leaf's box in its chunk."""
    q, normalized, d, float32 = index.q, index.normalized, index.d, index.float32

    def of(r: dict) -> np.ndarray:
        own = r["own"].values.to_numpy()
        x, y = _matrix(r["vals"])[own], _matrix(r["y"])
        first, leaf = (r[c].values.to_numpy() for c in ("first", "leaf"))
        n = x.shape[1] - q + 1
        kept = r["kept"].as_py()
        kept = {i: kept[c] for i, c in enumerate(own)}
        dims = K.dims_of(q, kept, normalized)
        feats = K.sliding_features(x, q, dims, normalized)
        size = max(1.0, float(np.abs(x).max(initial=1.0)))
        lo, hi = P.boxes(first, feats[:n], 1e-9 * size * np.sqrt(max(1, d)), float32)
        at = K.window_features(y[None], dims, normalized)[0]
        lb = K.box_gap2(at, lo, hi)
        if correction != "none" and len(r["pivots"].values):
            pivots = _matrix(r["pivots"])[own]
            plo, phi = P.boxes(first, K.pivot_gaps(x, q, dims, feats, pivots[None], normalized)[:n], 1e-6 * size, float32)
            g = np.sqrt(((K.remainder(y[None], kept, normalized)[0] - pivots) ** 2).sum(axis=1))
            lb = lb + K.box_gap2(g, np.maximum(plo, 0), phi)
        order = np.argsort(leaf, kind="stable")
        _, starts, which = np.unique(leaf[order], return_index=True, return_inverse=True)
        of_leaf = K.box_gap2(at, np.minimum.reduceat(lo[order], starts, axis=0), np.maximum.reduceat(hi[order], starts, axis=0))
        nlb = np.empty(len(lb))
        nlb[order] = of_leaf[which]
        return np.concatenate([lb, nlb])

    asked = index.parts.join(_by_block(index, queries), "block_id")
    sums = _added(_met(index, asked, index.runs.drop("base_t"), ["series_id", "chunk_id"], queries), of)
    each = sums.join(index.runs, ["series_id", "chunk_id"]).withColumn("n", F.size("first"))
    one = F.explode(F.arrays_zip("first", "last", "leaf", F.slice("v", F.lit(1), F.col("n")).alias("lb"), F.slice("v", F.col("n") + 1, F.col("n")).alias("nlb")))
    rows = each.select("query_id", "series_id", "chunk_id", "base_t", one.alias("r"))
    return rows.select("query_id", "series_id", "chunk_id", (F.col("base_t") + F.col("r.first")).alias("first_start"), (F.col("base_t") + F.col("r.last")).alias("last_start"), (F.col("r.last") - F.col("r.first") + 1).cast("int").alias("n_windows"), F.col("r.leaf").alias("leaf_id"), F.col("r.lb").alias("lb"), F.col("r.nlb").alias("nlb"))


def verify(index: BlockIndex, runs: DataFrame, queries: list[I.Query]) -> DataFrame:
    """Exact squared distances of the windows in some runs, value by value."""
    q, normalized = index.q, index.normalized
    inside = F.flatten(F.sort_array(F.collect_list(F.sequence("first_start", "last_start"))))
    wanted = runs.groupBy("series_id", "chunk_id", "query_id").agg(inside.alias("starts")).persist(StorageLevel.DISK_ONLY)

    def of(r: dict) -> np.ndarray:
        x, y = _matrix(r["vals"])[r["own"].values.to_numpy()], _matrix(r["y"])
        at = r["starts"].values.to_numpy() - r["base_t"].as_py()
        return np.concatenate([K.direct(x, y, at[o : o + 256], normalized) for o in range(0, len(at), 256)])

    sums = _added(_met(index, _by_block(index, queries), wanted, ["series_id", "chunk_id", "query_id"], queries), of)
    one = F.explode(F.arrays_zip("starts", "v"))
    return sums.join(wanted, ["series_id", "chunk_id", "query_id"]).select("query_id", "series_id", one.alias("r")).select("query_id", "series_id", F.col("r.starts").alias("start"), F.col("r.v").alias("d2"))


def knn(index: BlockIndex, queries: list[I.Query], k: int, *, browsing: bool = True, correction: str = "nearest", eps: float = I.EPS, exclusion: int = 0, whole_numbers: bool = True) -> DataFrame:
    """As ``knn_index``: the nearest leaves give a threshold from exact distances; all runs within it are verified."""
    spark = index.chunks.sparkSession
    for qu in queries:
        if qu.values.shape[1] != index.q:
            raise I.LengthMismatch(f"the index holds windows of length {index.q}, the query has {qu.values.shape[1]}")
    if k <= 0 or not queries:
        return I.finish(spark.createDataFrame([], "query_id int, rank int, series_id bigint, start bigint, d2 double"), index.normalized, whole_numbers)
    deep = k * (2 * exclusion + 1)
    every = bounds(index, queries, correction).persist(StorageLevel.DISK_ONLY)
    leaves = every.groupBy("query_id", "leaf_id").agg(F.min("nlb").alias("nlb"), F.sum("n_windows").alias("n"))
    before = F.sum("n").over(Window.partitionBy("query_id").orderBy("nlb", "leaf_id").rowsBetween(Window.unboundedPreceding, -1))
    nearest = leaves.withColumn("before", F.coalesce(before, F.lit(0))).where(F.col("before") < deep)
    rank = F.row_number().over(Window.partitionBy("query_id").orderBy("lb", "series_id", "first_start"))
    near = every.drop("nlb").join(nearest.select("query_id", "leaf_id"), ["query_id", "leaf_id"]).withColumn("r", rank).where(F.col("r") <= deep).drop("r")
    near = spark.createDataFrame(near.toArrow(), near.schema)  # at most k runs a query
    found_first = verify(index, near, queries).toArrow()
    first = spark.createDataFrame(found_first, "query_id int, series_id bigint, start bigint, d2 double")
    by_query: dict[int, list[float]] = {}
    for i, d2 in zip(found_first.column("query_id").to_pylist(), found_first.column("d2").to_pylist(), strict=True):
        by_query.setdefault(i, []).append(d2)
    cut = I._cuts(queries, {i: sorted(d)[deep - 1] for i, d in by_query.items() if len(d) >= deep}, eps)
    reached = leaves.where(F.col("nlb") <= cut).select("query_id", "leaf_id")
    within = every.join(reached, ["query_id", "leaf_id"]).where(F.col("lb") <= cut)
    if browsing:
        within = within.join(F.broadcast(near.select("query_id", "series_id", "first_start")), ["query_id", "series_id", "first_start"], "left_anti")
    second = verify(index, within, queries)
    return I.top_k(first.unionByName(second) if browsing else second, k, index.normalized, whole_numbers, exclusion)
