"""Cost and accuracy measures: time by phase, sizes, pruning, contrast, coverage, tightness, box quality, scaling, cost model."""

from __future__ import annotations

import math
from time import perf_counter

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..baselines import methods as B
from ..functions import kernels as K
from . import index as I


def timed(action) -> tuple[object, float]:
    t = perf_counter()
    out = action()
    return out, perf_counter() - t


def timed_build(chunks: DataFrame, q: int, **options) -> tuple[I.Index, dict[str, float]]:
    """Index and seconds by phase: sample/bins/tiling, pivots, runs (features of all windows), levels."""
    index, total = timed(lambda: I.build_index(chunks, q, **options))
    _, runs = timed(index.entries.count)
    nodes, levels = timed(lambda: I.build_levels(index.entries, d=len(index.spec.dims)).count())
    return index, index.spec.phases | {"build": total, "runs": runs, "levels": levels, "nodes": float(nodes)}


def bench_queries(method, queries: list[I.Query], runs: int = 10, timeout_s: float = 43_200) -> dict[str, float]:
    """Median seconds of a batch and of one query over several runs; stops at the timeout."""
    seen, began = [], perf_counter()
    for _ in range(runs):
        seen.append(timed(lambda: method(queries).collect())[1])
        if perf_counter() - began > timeout_s:
            break
    return {"batch_s": float(np.median(seen)), "query_s": float(np.median(seen)) / max(1, len(queries)), "runs": len(seen)}


def index_size(index: I.Index, points: DataFrame) -> DataFrame:
    """Bytes of boxes and pivot intervals against the bytes of the values, in the arrays themselves."""
    entry = index.entries.agg(F.sum((F.size("lo") + F.size("hi") + F.size("plo") + F.size("phi")) * 8 + 44).alias("index_bytes"), F.count(F.lit(1)).alias("entries"), F.sum("n_windows").alias("windows"))
    data = points.agg((F.count(F.lit(1)) * 8).alias("data_bytes"))
    return entry.crossJoin(data).withColumn("percent", F.round(100 * F.col("index_bytes") / F.col("data_bytes"), 2)).withColumn("windows_per_entry", F.round(F.col("windows") / F.col("entries"), 3)).withColumn("versus_windows", F.round(F.col("windows") * index.spec.q * index.spec.c * 8 / F.col("index_bytes"), 2))


def pruning_windows(verified: dict[int, int], total: int) -> float:
    """Median share of windows that were never verified."""
    return float(np.median([1 - v / total for v in verified.values()])) if verified else 1.0


def pruning_nodes(index: I.Index, queries: list[I.Query], tau: dict[int, float]) -> DataFrame:
    """Share of nodes of all levels that the threshold keeps from being visited (another base than windows)."""
    index.levels()
    nodes = index.nodes
    frame = F.broadcast(I.query_frame(nodes.sparkSession, index, queries))
    cut = F.create_map(*[x for i, t in tau.items() for x in (F.lit(i), F.lit(float(t)))])
    seen = frame.crossJoin(nodes.select("level", "node_id", "lo", "hi")).withColumn("lb", I.lower_bound(index.spec, pivots=False))
    return seen.groupBy("query_id").agg(F.round(1 - F.count_if(F.col("lb") <= F.element_at(cut, F.col("query_id"))) / F.count(F.lit(1)), 4).alias("nodes_pruned"))


def coverage(sample: np.ndarray, normalized: bool = False) -> list[dict]:
    """Share of distance and of energy in the top bins of each channel, their running sums, and the running sums' 90 % interval.

    The interval is that of the single pairs' (windows') own running sums over the bins of largest mean share.
    """
    out = []
    for kind, each in (("distance", I.pair_shares(sample, normalized)), ("energy", I.energy_shares(sample, normalized))):
        for c in range(each.shape[1]):
            rows = each[~np.isnan(each[:, c]).any(axis=1), c]
            share = rows.mean(axis=0) if len(rows) else np.zeros(each.shape[2])
            order = np.argsort(-share, kind="stable")
            run = np.cumsum(rows[:, order], axis=1)
            lo, hi = np.quantile(run, (0.05, 0.95), axis=0) if len(run) else (np.cumsum(share[order]),) * 2
            out += [{"kind": kind, "channel": c, "place": i + 1, "bin": int(b), "share": float(share[b]), "cumulative": float(share[order[: i + 1]].sum()), "low": float(lo[i]), "high": float(hi[i])} for i, b in enumerate(order)]
    return out


def tightness(sample: np.ndarray, spec: I.Spec, corrected: bool = True) -> float:
    """Mean of bound over distance on sample pairs."""
    f = K.window_features(sample, spec.dims, spec.normalized)
    w = K.znorm(sample) if spec.normalized else sample
    rest = K.remainder(sample, spec.kept, spec.normalized)
    gaps = np.sqrt(((rest[:, None] - spec.pivots[None]) ** 2).sum(axis=3)) if corrected and len(spec.pivots) else None
    got = []
    for i in range(len(w) - 1):
        d2 = ((w[i + 1 :] - w[i]) ** 2).sum(axis=(1, 2))
        lb = ((f[i + 1 :] - f[i]) ** 2).sum(axis=1)
        if gaps is not None:
            lb = lb + ((gaps[i + 1 :] - gaps[i]) ** 2).max(axis=1).sum(axis=1)
        got.append(np.sqrt(lb[d2 > 0] / d2[d2 > 0]))
    return float(np.concatenate(got).mean()) if got else 1.0


def box_quality(index: I.Index) -> DataFrame:
    """Mean margin (sum of extents) and mean log-volume of the runs' boxes."""
    ext = F.transform(F.arrays_zip("lo", "hi"), lambda b: b["hi"] - b["lo"])
    sum_of = lambda a, f: F.aggregate(a, F.lit(0.0), lambda s, x: s + f(x))
    return index.entries.agg(F.avg(sum_of(ext, lambda x: x)).alias("margin"), F.avg(sum_of(ext, lambda x: F.log1p(x))).alias("log_volume"), F.avg("n_windows").alias("windows_per_entry"))


def recall_at_k(found: DataFrame, truth: DataFrame, k: int) -> float:
    keys = ["query_id", "series_id", "start"]
    n = truth.count()
    return found.select(*keys).join(truth.select(*keys), keys, "left_semi").count() / n if n else 1.0


def scaling(sizes: list[float], seconds: list[float]) -> float:
    """Slope of log time against log size."""
    return float(np.polyfit(np.log(sizes), np.log(np.maximum(seconds, 1e-9)), 1)[0])


def cost_model(n: float, m: float, q: float, c: float, f: float, entries: float) -> dict[str, float]:
    """Operation counts in closed form: summaries, storage, brute force, profile."""
    return {"summary": n * m * q * f, "storage": n * (m - q) * f * c, "brute": n * (m - q + 1) * c * q, "profile": n * c * m * math.log2(max(m, 2)), "bounds": entries * c * f * 2}


def amortize(build: float, per_query: list[float], scan: list[float]) -> tuple[list[float], list[float], int | None]:
    """Running totals of index and scan, and the first query at which the index is cheaper."""
    a, b = (build + np.cumsum(per_query)).tolist(), np.cumsum(scan).tolist()
    return a, b, next((i + 1 for i, (x, y) in enumerate(zip(a, b, strict=True)) if x < y), None)


def difficulty_report(rows: DataFrame) -> DataFrame:
    """Time and contrast by origin and noise of the queries: columns origin, noise, seconds, contrast."""
    return rows.groupBy("origin", "noise").agg(F.avg("seconds").alias("seconds"), F.avg("contrast").alias("contrast"), F.count(F.lit(1)).alias("n"))


def study(chunks: DataFrame, points: DataFrame, queries: list[I.Query], q: int, k: int, methods: tuple[str, ...] = ("index", "scan", "brute", "trail", "meanlookup", "segtree", "envelope"), normalized: bool = False) -> list[dict]:
    """One row a method: build and query seconds, pruning, index size and recall against brute force."""
    total = int(chunks.agg(F.sum("n_core")).first()[0])
    truth = B.knn_brute(chunks, queries, k, normalized).select("query_id", "series_id", "start").persist()
    out = []
    for m in methods:
        row = {"method": m, "build_s": 0.0, "index_percent": 0.0, "pruned": 0.0}
        if m == "index":
            index, phases = timed_build(chunks, q, normalized=normalized)
            row["build_s"] = phases["build"] + phases["runs"]
            trace = I.Trace([])
            found, row["query_s"] = timed(lambda index=index, trace=trace: I.knn_index(index, queries, k, trace=trace).collect())
            row["pruned"] = pruning_windows({r["query_id"]: r["windows"] for r in trace.rows}, total)
            row["index_percent"] = index_size(index, points).first()["percent"]
        elif m in ("scan", "brute"):
            found, row["query_s"] = timed(lambda m=m: (B.knn_scan if m == "scan" else B.knn_brute)(chunks, queries, k, normalized).collect())
        else:
            built, row["build_s"] = timed(lambda m=m: B.build_channel_index(chunks, q, m, normalized=normalized))
            row["build_s"] += timed(built.entries.count)[1]
            seen: dict = {}
            found, row["query_s"] = timed(lambda m=m, built=built, seen=seen: (B.knn_envelope if m == "envelope" else B.knn_per_channel)(built, queries, k, trace=seen).collect())
            row["pruned"] = pruning_windows(seen.get("windows", {}), total)
            data = points.count() * 8
            row["index_percent"] = round(100 * (built.entries.agg(F.sum((F.size("lo") + F.size("hi")) * 8 + 48)).first()[0] or 0) / data, 2)
        hits = chunks.sparkSession.createDataFrame([(r["query_id"], r["series_id"], r["start"]) for r in found], "query_id int, series_id bigint, start bigint")
        row["recall"] = recall_at_k(hits, truth, k)
        out.append(row)
    return out


