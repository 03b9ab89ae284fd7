"""Search in passes over the chunks, for an index whose boxes of runs are too large to keep.

Runs, their boxes and bounds are made again in each pass and stay in the Python worker: no box and no candidate run
is shuffled or written. A pass gives leaf boxes, the nearest runs, the nearest windows or counts, one small result a task.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions import kernels as K

LEAF = "leaf_id bigint, n_entries bigint, n_windows bigint, lo array<double>, hi array<double>"
CHUNK = ("series_id", "chunk_id", "base_t", "n_core", "vals")
#: Numbers of leaf boxes that a task holds before it passes them on.
HELD_BOXES = 8_000_000
#: Dimensions whose features are made at once in a search.
BLOCK_DIMS = 2048


def chunk_rows(rows: pa.RecordBatch) -> Iterator[tuple[int, int, int, int, np.ndarray]]:
    """(series, chunk, base, windows, values (c, m)) of every chunk, without Python lists."""
    series, chunk, base, core = (rows.column(i).to_pylist() for i in range(4))
    vals = rows.column(4)
    for i in range(rows.num_rows):
        lines = vals[i].values
        at = lines.offsets.to_numpy()
        x = lines.values.to_numpy(zero_copy_only=False)[at[0] : at[-1]].reshape(len(lines), -1)
        yield series[i], chunk[i], base[i], core[i], np.asarray(x, float)


def lists(m: np.ndarray) -> pa.Array:
    """Rows of a matrix as lists."""
    return pa.ListArray.from_arrays(pa.array(np.arange(len(m) + 1, dtype=np.int32) * np.int32(m.shape[1])), pa.array(np.ascontiguousarray(m, float).ravel()))


def _part_of(router, at: dict[int, int]):
    return None if router is None else (at[router[0]], router[1], [_part_of(n, at) for n in router[2]], router[3])


def _dims_in(router) -> set[int]:
    return set() if router is None else {router[0]}.union(*[_dims_in(n) for n in router[2]])


class Runs:
    """The runs of a chunk with boxes in the dimensions of some channels only (all, if none are given)."""

    def __init__(self, spec, channels: list[int] | None = None, gaps: bool = True):
        self.spec = spec
        self.channels = list(range(spec.c)) if channels is None else sorted(channels)
        own = set(self.channels)
        extra = _dims_in(spec.router)
        self.at = [i for i, d in enumerate(spec.dims) if d[0] in own]
        every = sorted({*self.at, *extra})
        place = {d: i for i, d in enumerate(every)}
        self.dims = [spec.dims[i] for i in every]
        self.router = _part_of(spec.router, place)
        self.cols = np.array([place[i] for i in self.at], int)
        place_c = {c: i for i, c in enumerate(self.channels)}
        self.own_dims = [(place_c[spec.dims[i][0]], *spec.dims[i][1:]) for i in self.at]
        self.pivots = spec.pivots[:, self.channels] if gaps and len(spec.pivots) else spec.pivots[:0]

    def of(self, x: np.ndarray, n: int):
        """first, last, leaf, windows' features and pivot gaps, and the slack of both."""
        spec = self.spec
        every = K.sliding_features(x, spec.q, self.dims, spec.normalized)
        leaf = K.route(every[:n], self.router)
        feats = every[:, self.cols]
        gaps = K.pivot_gaps(x[self.channels], spec.q, self.own_dims, feats, self.pivots, spec.normalized)[:n] if len(self.pivots) else np.zeros((n, 0))
        first, last = K.runs(leaf) if spec.compress else (np.arange(n), np.arange(n))
        size = max(1.0, float(np.abs(x).max(initial=1.0)))
        return first, last, leaf[first] if n else leaf, feats[:n], gaps, 1e-9 * size * np.sqrt(max(1, len(spec.dims))), 1e-6 * size


def boxes(first: np.ndarray, values: np.ndarray, slack: float, float32: bool = False) -> tuple[np.ndarray, np.ndarray]:
    if not len(first):
        return values[:0], values[:0]
    lo, hi = (np.minimum.reduceat(values, first, axis=0) - slack, np.maximum.reduceat(values, first, axis=0) + slack) if values.shape[1] else (np.zeros((len(first), 0)),) * 2
    if float32:
        lo, hi = np.nextafter(lo.astype(np.float32), np.float32(-np.inf)).astype(float), np.nextafter(hi.astype(np.float32), np.float32(np.inf)).astype(float)
    return lo, hi


def leaf_rows(chunks: DataFrame, spec) -> DataFrame:
    """Boxes of the leaves, a row a leaf and task, or more where they are many numbers."""
    made = Runs(spec, gaps=False)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        d = len(spec.dims)
        ids, sums, lows, highs = np.zeros(0, np.int64), np.zeros((0, 2), np.int64), np.zeros((0, d)), np.zeros((0, d))

        def out() -> Iterator[pa.RecordBatch]:
            step = max(1, 1_000_000 // max(1, d))
            for i in range(0, len(ids), step):
                at = slice(i, i + step)
                yield pa.RecordBatch.from_arrays([pa.array(ids[at]), *(pa.array(sums[at, j]) for j in (0, 1)), lists(lows[at]), lists(highs[at])], names=["leaf_id", "n_entries", "n_windows", "lo", "hi"])

        for rows in batches:
            for *_, n, x in chunk_rows(rows):
                first, last, leaf, feats, _, slack, _ = made.of(x, n)
                if not n:
                    continue
                order = np.argsort(leaf, kind="stable")
                own, at = np.unique(leaf[order], return_index=True)
                lo, hi = boxes(first, feats, slack, spec.float32)
                lo, hi = (np.minimum.reduceat(lo[order], at, axis=0), np.maximum.reduceat(hi[order], at, axis=0)) if lo.shape[1] else (np.zeros((len(own), 0)),) * 2
                more = np.setdiff1d(own, ids, assume_unique=True)
                if len(more):
                    if 2 * (len(ids) + len(more)) * d > HELD_BOXES and len(ids):
                        yield from out()
                        ids, sums, lows, highs, more = ids[:0], sums[:0], lows[:0], highs[:0], own
                    place = np.searchsorted(ids, more)
                    ids, sums = np.insert(ids, place, more), np.insert(sums, place, 0, axis=0)
                    lows, highs = np.insert(lows, place, np.inf, axis=0), np.insert(highs, place, -np.inf, axis=0)
                rows_of = np.searchsorted(ids, own)
                sums[rows_of] += np.column_stack([np.add.reduceat(np.ones(len(order), np.int64), at), np.add.reduceat((last - first + 1)[order], at)])
                lows[rows_of] = np.minimum(lows[rows_of], lo)
                highs[rows_of] = np.maximum(highs[rows_of], hi)
        yield from out()

    return chunks.select(*CHUNK).mapInArrow(run, LEAF)


def _blocks(spec, queries: list, gaps: bool) -> list[Runs]:
    """The queries' channels in blocks of at most BLOCK_DIMS dimensions, or of one channel: bounds add up over channels."""
    sizes = np.bincount([d[0] for d in spec.dims], minlength=spec.c) if spec.dims else np.zeros(spec.c, int)
    blocks, held = [], BLOCK_DIMS
    for c in sorted({c for qu in queries for c in qu.channels}):
        if held + sizes[c] > BLOCK_DIMS:
            blocks.append([])
            held = 0
        blocks[-1].append(c)
        held += sizes[c]
    return [Runs(spec, own, gaps) for own in blocks]


def _bounder(spec, blocks: list[Runs], queries: list, correction: str) -> dict[int, list]:
    """Per query and block the columns of its channels, its features, and the pivot gaps that the correction takes."""
    out, p = {}, len(spec.pivots) if correction != "none" else 0
    for qu in queries:
        full = np.zeros((spec.c, spec.q))
        full[qu.channels] = qu.values
        y = K.window_features(full[None], spec.dims, spec.normalized)[0]
        if p:
            rest = K.remainder(full[None], spec.kept, spec.normalized)[0]
            d = np.sqrt(((rest[None] - spec.pivots) ** 2).sum(axis=2))
            near = int(np.argmin((d[:, qu.channels] ** 2).sum(axis=1)))
            picked = range(p) if correction == "max" else [near]
        known, parts = set(qu.channels), []
        for made in blocks:
            own = [(i, c) for i, c in enumerate(made.channels) if c in known]
            if not own:
                parts.append(None)
                continue
            on = [j for j, i in enumerate(made.at) if spec.dims[i][0] in known]
            g, where = None, None
            if p:
                g = np.array([[d[j, c] for j in picked] for _, c in own])
                where = np.array([[i * p + j for j in picked] for i, _ in own], int)
            parts.append((np.array(on, int), y[[made.at[j] for j in on]], where, g))
        out[qu.query_id] = parts
    return out


def _bounds(of_query: tuple, lo: np.ndarray, hi: np.ndarray, plo: np.ndarray, phi: np.ndarray) -> np.ndarray:
    on, y, where, g = of_query
    lb = K.box_gap2(y, lo[:, on], hi[:, on])
    if where is not None:
        gap = np.maximum(np.maximum(plo[:, where] - g, g - phi[:, where]), 0) ** 2
        lb = lb + gap.max(axis=2).sum(axis=1)
    return lb


def leaf_bounds(index, queries: list) -> DataFrame:
    """Bounds of the leaves in the queries' channels only, where whole boxes are too wide to keep: the least of a leaf's chunks."""
    spec = index.spec
    blocks = _blocks(spec, queries, False)
    of_query = _bounder(spec, blocks, queries, "none")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        sums: dict[int, np.ndarray] = {}
        least: dict[tuple[int, int], float] = {}
        for rows in batches:
            for *_, n, x in chunk_rows(rows):
                if not n:
                    continue
                bounds: dict[int, np.ndarray] = {}
                for i, made in enumerate(blocks):
                    first, last, leaf, feats, _, slack, _ = made.of(x, n)
                    order = np.argsort(leaf, kind="stable")
                    own, at = np.unique(leaf[order], return_index=True)
                    lo, hi = boxes(first, feats, slack, spec.float32)
                    lo, hi = (np.minimum.reduceat(lo[order], at, axis=0), np.maximum.reduceat(hi[order], at, axis=0)) if lo.shape[1] else (np.zeros((len(own), 0)),) * 2
                    for qid, parts in of_query.items():
                        if parts[i] is not None:
                            bounds[qid] = bounds.get(qid, 0.0) + _bounds(parts[i], lo, hi, None, None)
                counts = np.column_stack([np.add.reduceat(np.ones(len(order), np.int64), at), np.add.reduceat((last - first + 1)[order], at)])
                for j, one in enumerate(own.tolist()):
                    sums[one] = sums.get(one, 0) + counts[j]
                    for qid, lb in bounds.items():
                        least[qid, one] = min(least.get((qid, one), np.inf), float(lb[j]))
        keys = list(least)
        cols = [pa.array([k[0] for k in keys], pa.int32()), pa.array([k[1] for k in keys], pa.int64()), pa.array([least[k] for k in keys], pa.float64())]
        yield pa.RecordBatch.from_arrays([*cols, *(pa.array([int(sums[k[1]][j]) for k in keys], pa.int64()) for j in (0, 1))], names=["query_id", "leaf_id", "nlb", "n_entries", "n_windows"])

    found = index.chunks.select(*CHUNK).mapInArrow(run, "query_id int, leaf_id bigint, nlb double, n_entries bigint, n_windows bigint")
    return found.groupBy("query_id", "leaf_id").agg(F.min("nlb").alias("nlb"), F.sum("n_entries").alias("n_entries"), F.sum("n_windows").alias("n_windows"))


def _search(index, queries: list, leaves: dict[int, np.ndarray], correction: str):
    """A function of a chunk: its runs, and per query the runs in its leaves with their bounds."""
    spec = index.spec
    blocks = _blocks(spec, queries, correction != "none")
    of_query = _bounder(spec, blocks, queries, correction)
    n_leaves = 1 if spec.router is None else spec.router[3]
    inside: dict[int, np.ndarray] = {}  # whether a leaf is a query's; made in the worker

    def leaves_of(qid: int) -> np.ndarray:
        if qid not in inside:
            inside[qid] = np.zeros(n_leaves, bool)
            inside[qid][leaves.get(qid, np.zeros(0, np.int64))] = True
        return inside[qid]

    def runs(x: np.ndarray, n: int):
        found = {}
        for i, made in enumerate(blocks):
            first, last, leaf, feats, gaps, slack, near = made.of(x, n)
            lo, hi = boxes(first, feats, slack, spec.float32)
            plo, phi = boxes(first, gaps, near, spec.float32)
            plo = np.maximum(plo, 0)
            for qid, parts in of_query.items():
                if parts[i] is None:
                    continue
                at, before = found[qid] if qid in found else (np.flatnonzero(leaves_of(qid)[leaf]), 0.0)
                if len(at):
                    found[qid] = (at, before + _bounds(parts[i], lo[at], hi[at], plo[at], phi[at]))
        return first, last, leaf, found

    return runs


def nearest_runs(index, queries: list, leaves: dict[int, np.ndarray], least: int, correction: str) -> DataFrame:
    """Of every task the ``least`` runs of smallest bound in a query's leaves (ties by series and start)."""
    runs = _search(index, queries, leaves, correction)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        best: dict[int, np.ndarray] = {}
        for rows in batches:
            got: dict[int, list] = {}
            for series, chunk, base, n, x in chunk_rows(rows):
                first, last, leaf, found = runs(x, n)
                for qid, (at, lb) in found.items():
                    if len(at) > least:  # starts rise, so a stable sort keeps the ties' order
                        few = np.argsort(lb, kind="stable")[:least]
                        at, lb = at[few], lb[few]
                    m = np.empty(len(at), _RUN)
                    m["lb"], m["series_id"], m["first_start"], m["chunk_id"], m["last_start"], m["leaf_id"] = lb, series, first[at] + base, chunk, last[at] + base, leaf[at]
                    got.setdefault(qid, []).append(m)
            for qid, parts in got.items():
                m = np.concatenate([best[qid], *parts]) if qid in best else np.concatenate(parts)
                best[qid] = m[np.lexsort((m["first_start"], m["series_id"], m["lb"]))[:least]]
        for qid, m in best.items():
            cols = [m["series_id"], m["chunk_id"], m["first_start"], m["last_start"]]
            yield pa.RecordBatch.from_arrays([pa.array([qid] * len(m), pa.int32()), *(pa.array(c) for c in cols), pa.array((m["last_start"] - m["first_start"] + 1).astype(np.int32)), pa.array(m["leaf_id"]), pa.array(m["lb"])], names=_NEAR)

    return index.chunks.select(*CHUNK).mapInArrow(run, "query_id int, series_id bigint, chunk_id bigint, first_start bigint, last_start bigint, n_windows int, leaf_id bigint, lb double")


_RUN = [("lb", float), ("series_id", np.int64), ("first_start", np.int64), ("chunk_id", np.int64), ("last_start", np.int64), ("leaf_id", np.int64)]
_NEAR = ["query_id", "series_id", "chunk_id", "first_start", "last_start", "n_windows", "leaf_id", "lb"]


def windows_within(index, queries: list, leaves: dict[int, np.ndarray], reach: dict[int, float], eps: float, k: int | None, correction: str, done: dict[int, set] | None = None, counted: bool = False) -> DataFrame:
    """Exact squared distances of the windows in runs within the threshold; with k what may be among the k best of a task.

    ``done``: runs (series, first start) that are verified already. ``counted``: with rows of the runs and their windows by query, whose other columns are null.
    """
    spec, runs, done = index.spec, _search(index, queries, leaves, correction), done or {}
    known = {qu.query_id: qu for qu in queries}

    def verified(qu, x: np.ndarray, a: np.ndarray, b: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Starts and distances: the profile from the first run to the last, then value by value where it is near."""
        q, lo, hi = spec.q, int(a[0]), int(b[-1]) + 1
        edge = np.zeros(hi - lo + 1, int)
        edge[a - lo] += 1
        edge[b + 1 - lo] -= 1
        sub = x[qu.channels]
        if (b - a + 1).sum() * spec.q < 16 * (hi - lo + spec.q):  # a few windows cost less than the profile's transforms
            at = np.flatnonzero(np.cumsum(edge[:-1])) + lo
            return at, K.direct(sub, qu.values, at, spec.normalized)
        d = np.where(np.cumsum(edge[:-1]) > 0, K.profile(sub[:, lo : hi - 1 + q], qu.values, spec.normalized), np.inf)
        cut = reach.get(qu.query_id, np.inf)
        if k is not None and len(d) > k:
            cut = min(cut, np.partition(d, k - 1)[k - 1])
        slack = 1e-6 * max(1.0, float(np.abs(sub[:, lo : hi - 1 + q]).max(initial=1.0)) ** 2 if not spec.normalized else 1.0)
        at = np.flatnonzero(np.isfinite(d) & (d <= cut * (1 + 1e-6) + slack)) + lo
        parts = [K.direct(sub, qu.values, at[o : o + 4096], spec.normalized) for o in range(0, len(at), 4096)]
        return at, np.concatenate(parts) if parts else np.zeros(0)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = {qid: [0, 0] for qid in known}
        best: dict[int, tuple] = {}
        for rows in batches:
            got: dict[int, list] = {}
            for series, _, base, n, x in chunk_rows(rows):
                first, last, _, found = runs(x, n)
                for qid, (at, lb) in found.items():
                    at = at[lb <= reach.get(qid, np.inf) * (1 + eps) + eps]
                    if qid in done:
                        at = np.array([i for i in at if (series, int(first[i]) + base) not in done[qid]], int)
                    if not len(at):
                        continue
                    total[qid][0] += len(at)
                    total[qid][1] += int((last[at] - first[at] + 1).sum())
                    starts, e = verified(known[qid], x, first[at], last[at])
                    got.setdefault(qid, []).append((np.full(len(e), series, np.int64), starts + base, e))
            for qid, parts in got.items():
                s, t, e = (np.concatenate(c) for c in zip(*([best[qid]] if qid in best else []), *parts, strict=True))
                if k is None:
                    yield out(qid, s, t, e)
                    continue
                if len(e) > k:
                    near = e <= np.partition(e, k - 1)[k - 1] * (1 + 1e-9) + 1e-9
                    s, t, e = s[near], t[near], e[near]
                best[qid] = (s, t, e)
        for qid, (s, t, e) in best.items():
            yield out(qid, s, t, e)
        if counted:
            ids = [qid for qid, n in total.items() if n[0]]
            empty = [pa.nulls(len(ids), t) for t in (pa.int64(), pa.int64(), pa.float64())]
            counts = [pa.array([total[i][j] for i in ids], pa.int64()) for j in (0, 1)]
            yield pa.RecordBatch.from_arrays([pa.array(ids, pa.int32()), *empty, *counts], names=["query_id", "series_id", "start", "d2", "runs", "windows"])

    def out(*found) -> pa.RecordBatch:
        rows = hits(*found)
        if not counted:
            return rows
        return pa.RecordBatch.from_arrays([*rows.columns, *[pa.nulls(rows.num_rows, pa.int64())] * 2], names=[*rows.schema.names, "runs", "windows"])

    return index.chunks.select(*CHUNK).mapInArrow(run, "query_id int, series_id bigint, start bigint, d2 double" + ", runs bigint, windows bigint" * counted)


def hits(qid: int, s: np.ndarray, t: np.ndarray, e: np.ndarray) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array([qid] * len(s), pa.int32()), pa.array(s.astype(np.int64)), pa.array(t.astype(np.int64)), pa.array(e)], names=["query_id", "series_id", "start", "d2"])
