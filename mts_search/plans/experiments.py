"""Experiment workloads as reports (timings and sizes have no SQL twin)."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..baselines import methods as B
from ..operators import index as I
from ..operators import metrics as M
from ..operators.series import chunk_points, indexed_part, query_points, to_chunks, windows
from ..session import ship
from .workloads import _once, chunks_of, index_of, points_of, queries_of

NAME = "supplier_week_cum"


def _frame(spark: SparkSession, rows: list[dict]) -> DataFrame:
    cols = list(rows[0])
    kind = {c: "string" if isinstance(rows[0][c], str) else "double" for c in cols}
    return spark.createDataFrame([tuple(r[c] if kind[c] == "string" else float(r[c]) for c in cols) for r in rows], ", ".join(f"{c} {kind[c]}" for c in cols))


def _measured(spark, d, report) -> list[dict]:
    """Rows of a report, measured once an application; reports made from it share them."""
    return _once(spark, (d, report.__name__), lambda: report(spark, d))


def bench_methods(spark, d):
    """All methods on the same queries: build and query seconds, pruning, index size, recall (must be 1)."""
    ship(spark)
    return _frame(spark, M.study(chunks_of(spark, d, NAME), points_of(spark, d, NAME), queries_of(spark, d, NAME), 52, 1))


def _bench_scale_n(spark, d) -> list[dict]:
    ship(spark)
    p, out = points_of(spark, d, NAME), []
    n = p.select("series_id").distinct().count()
    qs = queries_of(spark, d, NAME)
    for part in (1, 2, 3, 4):
        some = p.where(F.col("series_id") <= n * part // 4)
        chunks = to_chunks(some, 52).persist()
        index, phases = M.timed_build(chunks, 52)
        _, s = M.timed(lambda index=index: I.knn_index(index, qs, 1).collect())
        _, scan = M.timed(lambda chunks=chunks: B.knn_scan(chunks, qs, 1).collect())
        size = M.index_size(index, some).first()
        out.append({"series": n * part // 4, "build_s": phases["build"] + phases["runs"], "query_s": s, "scan_s": scan, "index_bytes": size["index_bytes"], "index_percent": size["percent"]})
    return out


def bench_scale_n(spark, d):
    """Time and index size by the number of series: 1/4, 1/2, 3/4 and all."""
    return _frame(spark, _measured(spark, d, _bench_scale_n))


def _bench_qlen(spark, d) -> list[dict]:
    ship(spark)
    p, out = points_of(spark, d, NAME), []
    for q in (13, 26, 52, 104):
        chunks = to_chunks(p, q).persist()
        qs = I.collect_queries(query_points(p, q, 2))
        index = I.build_index(chunks, q)
        index.entries.count()
        trace = I.Trace([])
        _, s = M.timed(lambda: I.knn_index(index, qs, 1, trace=trace).collect())  # noqa: B023
        _, scan = M.timed(lambda: B.knn_scan(chunks, qs, 1).collect())  # noqa: B023
        out.append({"q": q, "index_s": s, "scan_s": scan, "pruned": M.pruning_windows({r["query_id"]: r["windows"] for r in trace.rows}, index.spec.n_windows)})
    return out


def bench_qlen(spark, d):
    """Query length against index and scan time; the scan's doesn't depend on it."""
    return _frame(spark, _measured(spark, d, _bench_qlen))


def bench_leaf(spark, d):
    """Leaf size grid: runs, verified windows and seconds; answers are equal throughout."""
    out, qs = [], None
    for pct in (0.0001, 0.01, 0.05, 0.1, 1.0, 100.0):
        index = index_of(spark, d, NAME, leaf_pct=pct)
        qs = qs or queries_of(spark, d, NAME)
        trace = I.Trace([])
        _, s = M.timed(lambda: I.knn_index(index, qs, 1, trace=trace).collect())  # noqa: B023
        out.append({"leaf_pct": pct, "entries": index.entries.count(), "query_s": s, "pruned": M.pruning_windows({r["query_id"]: r["windows"] for r in trace.rows}, index.spec.n_windows)})
    return _frame(spark, out)


def bench_init(spark, d):
    """Seconds of the build by phase."""
    ship(spark)
    _, phases = M.timed_build(chunks_of(spark, d, NAME), 52)
    return _frame(spark, [{"phase": k, "seconds": v} for k, v in phases.items()])


def index_size(spark, d):
    """Bytes against the data, raw and normalised."""
    out = None
    for norm in (False, True):
        one = M.index_size(index_of(spark, d, NAME, normalized=norm), points_of(spark, d, NAME)).withColumn("normalized", F.lit(norm))
        out = one if out is None else out.unionByName(one)
    return out


def ablate_pivots(spark, d):
    """0, 1, 2 and 5 pivots: build overhead, bound tightness and verified windows."""
    ship(spark)
    chunks, qs, out = chunks_of(spark, d, NAME), queries_of(spark, d, NAME), []
    for n in (0, 1, 2, 5):
        index, phases = M.timed_build(chunks, 52, n_pivots=n)
        trace = I.Trace([])
        _, s = M.timed(lambda: I.knn_index(index, qs, 10, trace=trace).collect())  # noqa: B023
        out.append({"pivots": n, "build_s": phases["build"] + phases["runs"], "query_s": s, "tightness": M.tightness(I.sample_windows(chunks, 52, 60), index.spec), "pruned": M.pruning_windows({r["query_id"]: r["windows"] for r in trace.rows}, index.spec.n_windows)})
    return _frame(spark, out)


def ablate_tiling(spark, d):
    """Weighted against uniform tiling: box margins and verified windows."""
    out = []
    for w in ("uniform", "softmax", "share", "softmax_std"):
        index = index_of(spark, d, NAME, weighting=w)
        q = M.box_quality(index).first()
        trace = I.Trace([])
        I.knn_index(index, queries_of(spark, d, NAME), 10, trace=trace).collect()
        out.append({"weighting": w, "margin": q["margin"], "log_volume": q["log_volume"], "windows_per_entry": q["windows_per_entry"], "pruned": M.pruning_windows({r["query_id"]: r["windows"] for r in trace.rows}, index.spec.n_windows)})
    return _frame(spark, out)


def node_pruning_channels(spark, d):
    """Share of nodes pruned and relative contrast by the number of query channels, of 5 and of as many as there are suppliers."""
    out = None
    for name, sizes in ((NAME, (1, 2, 5)), ("many_channels", (4, 16, 64, 10**9))):
        index = index_of(spark, d, name)
        for n in sorted({min(n, index.spec.c) for n in sizes}):
            qs = queries_of(spark, d, name, list(range(n)))
            whole = B.knn_brute(chunks_of(spark, d, name), qs, 10**9).groupBy("query_id").agg(F.max("distance").alias("far"), F.min(F.when(F.col("distance") > 0, F.col("distance"))).alias("near"))
            tau = {r["query_id"]: r["distance"] ** 2 + 1e-3 for r in I.knn_index(index, qs, 1).collect()}
            contrast = whole.select("query_id", F.round(F.col("far") / F.col("near"), 4).alias("contrast"))
            one = M.pruning_nodes(index, qs, tau).join(contrast, "query_id").withColumn("channels", F.lit(n)).withColumn("series", F.lit(name))
            out = one if out is None else out.unionByName(one)
    return out


def _workload(spark, d, n: int, noise: float = 0.1, held_out: bool = False) -> list[I.Query]:
    """n queries of all channels: cuts by hash with Gaussian noise, the first by hash."""
    rows = _noisy(spark, d, NAME, n, noise, held_out).select(F.dense_rank().over(Window.orderBy("series_id", "start")).alias("query_id"), "channel", "j", "qv")
    return I.collect_queries(rows)


def _bench_queries(spark, d) -> list[dict]:
    ship(spark)
    qs, chunks = _workload(spark, d, 100), chunks_of(spark, d, NAME)
    index, phases = M.timed_build(chunks, 52)
    build = phases["build"] + phases["runs"] + phases["levels"]
    trace = I.Trace([])
    I.knn_index(index, qs, 1, whole_numbers=False, trace=trace).collect()
    pruned = M.pruning_windows({r["query_id"]: r["windows"] for r in trace.rows}, index.spec.n_windows)
    bounded = float(np.median([r["run_bounds"] for r in trace.rows])) / max(1, index.entries.count())
    out = [{"method": "index", "build_s": build, **M.bench_queries(lambda q: I.knn_index(index, q, 1, whole_numbers=False), qs), "pruned": pruned, "runs_bounded": bounded}]
    for name, f in (("scan", B.knn_scan), ("brute", B.knn_brute)):
        out.append({"method": name, "build_s": 0.0, **M.bench_queries(lambda q, f=f: f(chunks, q, 1, whole_numbers=False), qs), "pruned": 0.0, "runs_bounded": 1.0})
    return out


def bench_queries(spark, d):
    """100 noisy queries as one batch, ten times: index, scan and brute; the build apart; median seconds and windows pruned."""
    return _frame(spark, _measured(spark, d, _bench_queries))


def amortized_measured(spark, d):
    """Measured break-even of the index against the scan, up to 3000 queries (0: not within them)."""
    got = {r["method"]: r for r in _measured(spark, d, _bench_queries)}
    a, b, first = M.amortize(got["index"]["build_s"], [got["index"]["query_s"]] * 3000, [got["scan"]["query_s"]] * 3000)
    return _frame(spark, [{"queries": n, "index_s": a[n - 1], "scan_s": b[n - 1], "break_even": first or 0} for n in (1, 10, 45, 100, 1000, 3000)])


def difficulty(spark, d):
    """Seconds and contrast by noise and origin of the queries: the harder, the lower the contrast."""
    ship(spark)
    rows = []
    for origin in ("indexed", "held out"):
        out = origin == "held out"
        chunks, index = chunks_of(spark, d, NAME, out), index_of(spark, d, NAME, out)
        for noise in (0.1, 0.4, 1.6):
            qs = _workload(spark, d, 10, noise, out)
            trace = I.Trace([])
            _, s = M.timed(lambda: I.knn_index(index, qs, 1, whole_numbers=False, trace=trace).collect())  # noqa: B023
            # distances of four places, as a search gives them; the least that isn't 0
            far = B.extremes(chunks, qs, 0.00005).select((F.round(F.sqrt("far"), 4) / F.round(F.sqrt("near"), 4)).alias("contrast")).agg(F.avg("contrast")).first()[0]
            rows.append({"origin": origin, "noise": noise, "seconds": s / len(qs), "contrast": far or 0.0})
    return M.difficulty_report(_frame(spark, rows))


def build_by_n(spark, d):
    """Build seconds and index size of all methods, raw and normalised, on half and all of the series."""
    ship(spark)
    p, out = points_of(spark, d, NAME), []
    n = p.select("series_id").distinct().count()
    for part in (1, 2):
        some = p.where(F.col("series_id") <= n * part // 2).persist()
        chunks = to_chunks(some, 52).persist()
        data = some.count() * 8
        for norm in (False, True):
            for m in ("index", "trail", "meanlookup", "segtree", "envelope"):
                if m == "index":
                    built, s = M.timed(lambda: I.build_index(chunks, 52, normalized=norm))  # noqa: B023
                    size = F.size("lo") + F.size("hi") + F.size("plo") + F.size("phi")
                else:
                    built, s = M.timed(lambda: B.build_channel_index(chunks, 52, m, normalized=norm))  # noqa: B023
                    size = F.size("lo") + F.size("hi")
                held, more = M.timed(lambda: built.entries.agg(F.sum(size * 8 + 44)).first()[0])  # noqa: B023
                out.append({"method": m, "normalized": str(norm).lower(), "series": n * part // 2, "build_s": s + more, "index_bytes": held or 0, "index_percent": 100 * (held or 0) / data})
    return _frame(spark, out)


def search_counts(spark, d):
    """Node bounds, run bounds, runs and exact distances of each query of the default workloads, raw, and their shares."""
    out = []
    for name in ("supplier_week_cum", "supplier_week", "nation"):
        index, trace = index_of(spark, d, name), I.Trace([])
        I.knn_index(index, queries_of(spark, d, name), 10, trace=trace).collect()
        entries = index.entries.count()
        out += [{"series": name, **{k: v for k, v in r.items() if k != "windows"}, "runs_bounded": r["run_bounds"] / entries, "windows_verified": r["windows"] / index.spec.n_windows} for r in trace.rows]
    return _frame(spark, out)


def coverage(spark, d):
    """Running share of distance and energy in the top bins (the distance needs fewer)."""
    ship(spark)
    w = I.sample_windows(chunks_of(spark, d, NAME), 52, 100)
    return _frame(spark, M.coverage(w))


def chooser(spark, d):
    """Index or scan by estimated difficulty, for easy and held-out queries."""
    rows = [{"queries": label, "plan": B.choose_plan(index_of(spark, d, n), queries_of(spark, d, n), 1)} for label, n in (("cumulative", NAME), ("flat", "supplier_week"))]
    return _frame(spark, rows)


def _noisy(spark, d, name: str, n: int, noise: float = 0.1, held_out: bool = False):
    """n cuts of 52 steps by hash, with Gaussian noise of ``noise`` deviations of each channel (counter hash, no rand()).

    ``held_out``: cut from the series that ``indexed_part`` leaves out.
    """
    every = chunks_of(spark, d, name)  # the windows of 52 steps are theirs
    if held_out:
        every = every.join(F.broadcast(indexed_part(every).select("series_id").distinct()), "series_id", "left_anti")
    starts = windows(every, 52).orderBy(F.xxhash64("series_id", "start", F.lit(42)), "series_id", "start").limit(n)
    starts = spark.createDataFrame(starts.toArrow())  # n rows, picked once
    p = chunk_points(every, starts.select("series_id").distinct())
    stats = p.groupBy("series_id", "channel").agg(F.stddev_pop("v").alias("sd"))
    cut = p.join(F.broadcast(starts), "series_id").where("t >= start and t < start + 52").join(F.broadcast(stats), ["series_id", "channel"])
    u = lambda s: (F.pmod(F.xxhash64("series_id", "channel", "t", "start", F.lit(s)), F.lit(1 << 40)) + 0.5) / float(1 << 40)
    g = F.sqrt(-2 * F.log(u("r"))) * F.cos(2 * F.pi() * u("phi"))
    return cut.select("series_id", "start", "channel", (F.col("t") - F.col("start")).alias("j"), (F.col("v") + noise * F.col("sd") * g).alias("qv"))


def gen_queries(spark, d):
    """The default workload: 100 noisy cuts."""
    return _noisy(spark, d, "supplier_week", 100)


def scaling_exponents(spark, d):
    """Slopes of log time against log size, from the reports above."""
    a, b = _measured(spark, d, _bench_scale_n), _measured(spark, d, _bench_qlen)
    return _frame(spark, [{"axis": "series (index)", "slope": M.scaling([r["series"] for r in a], [r["query_s"] for r in a])}, {"axis": "series (scan)", "slope": M.scaling([r["series"] for r in a], [r["scan_s"] for r in a])}, {"axis": "query length (scan)", "slope": M.scaling([r["q"] for r in b], [r["scan_s"] for r in b])}])


def cost_model(spark, d):
    s = index_of(spark, d, NAME).spec
    m = 357
    n = s.n_windows / (m - s.q + 1)
    got = M.cost_model(n, m, s.q, s.c, float(np.mean([len(b) for b in s.kept.values()])), index_of(spark, d, NAME).entries.count())
    return _frame(spark, [{"term": k, "operations": v} for k, v in got.items()])


QUERIES = {
    "bench_methods": bench_methods, "bench_scale_n": bench_scale_n, "bench_qlen": bench_qlen, "bench_leaf": bench_leaf, "bench_init": bench_init, "index_size": index_size, "ablate_pivots": ablate_pivots, "ablate_tiling": ablate_tiling,
    "node_pruning_channels": node_pruning_channels, "coverage": coverage, "choose_plan": chooser, "gen_queries": gen_queries, "cost_model": cost_model,
    "bench_queries": bench_queries, "amortized_measured": amortized_measured, "difficulty": difficulty, "build_by_n": build_by_n, "search_counts": search_counts, "scaling_exponents": scaling_exponents,
}
