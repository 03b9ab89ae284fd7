"""Exact-search workloads as named queries, each with its brute-force SQL."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..baselines import methods as B
from ..functions import kernels as K
from ..operators import fixtures as X
from ..operators import index as I
from ..operators.series import chunk_lengths, chunk_points, indexed_part, query_points, to_chunks
from ..session import ship, written

#: Series, queries and indices that several named queries of one application share.
_MEMO: dict[tuple, object] = {}


def _once(spark: SparkSession, key: tuple, make):
    key = (spark.sparkContext.applicationId, *key)
    if key not in _MEMO:
        _MEMO[key] = make()
    return _MEMO[key]


def release() -> None:
    """Drop what the named queries share: the next one builds its own."""
    for held in _MEMO.values():
        for df in (held, *(getattr(held, n, None) for n in ("entries", "nodes", "chunks"))):
            if isinstance(df, DataFrame):
                df.unpersist()
    _MEMO.clear()


def points_of(spark, sf_dir, name) -> DataFrame:
    return _once(spark, (sf_dir, name, "points"), lambda: X.FIXTURES[name].points(spark, sf_dir).persist())


def chunks_of(spark, sf_dir, name, held_out=False) -> DataFrame:
    fx = X.FIXTURES[name]

    def make():
        if fx.chunks is not None:
            ship(spark)
            if not held_out:
                return written(fx.chunks(spark, sf_dir, fx.q), "chunks", 1 << 19)
            every = chunks_of(spark, sf_dir, name)
            return indexed_part(every)
        p = points_of(spark, sf_dir, name)
        return to_chunks(indexed_part(p) if held_out else p, fx.q).persist()

    return _once(spark, (sf_dir, name, "chunks", held_out), make)


def queries_of(spark, sf_dir, name, channels=None, held_out=False, n=None, noise=None, q=None) -> list[I.Query]:
    fx = X.FIXTURES[name]
    key = (sf_dir, name, "queries", tuple(channels or ()), held_out, n, noise, q)
    if fx.chunks is not None and (q or fx.q) == fx.q:
        return _once(spark, key, lambda: I.cut_queries(chunks_of(spark, sf_dir, name), fx.q, n or fx.n_queries, fx.noise if noise is None else noise, channels, held_out))
    if fx.chunks is not None:
        every = chunks_of(spark, sf_dir, name)
        some = lambda: query_points(lambda s: chunk_points(every, s), q or fx.q, n or fx.n_queries, fx.noise if noise is None else noise, channels, held_out, chunk_lengths(every))
        return _once(spark, key, lambda: I.collect_queries(some()))
    return _once(spark, key, lambda: I.collect_queries(query_points(points_of(spark, sf_dir, name), q or fx.q, n or fx.n_queries, fx.noise if noise is None else noise, channels, held_out)))


def index_of(spark, sf_dir, name, held_out=False, **options) -> I.Index:
    ship(spark)
    key = (sf_dir, name, "index", held_out, *sorted(options.items()))
    return _once(spark, key, lambda: I.build_index(chunks_of(spark, sf_dir, name, held_out), X.FIXTURES[name].q, keep_chunks=X.FIXTURES[name].chunks is None, **options))


def channel_index_of(spark, sf_dir, name, kind, **options) -> B.ChannelIndex:
    ship(spark)
    key = (sf_dir, name, "channel", kind, *sorted(options.items()))
    return _once(spark, key, lambda: B.build_channel_index(chunks_of(spark, sf_dir, name), X.FIXTURES[name].q, kind, **options))


def by_index(name: str, k: int, channels=None, held_out=False, noise=None, n=None, search: dict | None = None, **options):
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        index = index_of(spark, sf_dir, name, held_out, **options)
        return I.knn_index(index, queries_of(spark, sf_dir, name, channels, held_out, n, noise), k, **(search or {}))

    fx = X.FIXTURES[name]
    return run, X.knn_sql(fx.sql, fx.q, k, n or fx.n_queries, fx.noise if noise is None else noise, channels, options.get("normalized", False), held_out)


def by_baseline(name: str, k: int, method: str, channels=None, normalized: bool = False):
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        ship(spark)
        qs = queries_of(spark, sf_dir, name, channels)
        if method in ("scan", "brute"):
            return (B.knn_scan if method == "scan" else B.knn_brute)(chunks_of(spark, sf_dir, name), qs, k, normalized)
        built = channel_index_of(spark, sf_dir, name, method, normalized=normalized)
        return (B.knn_envelope if method == "envelope" else B.knn_per_channel)(built, qs, k)

    fx = X.FIXTURES[name]
    return run, X.knn_sql(fx.sql, fx.q, k, fx.n_queries, fx.noise, channels, normalized)


def brute_sql(name: str, k: int, q: int | None = None, channels=None):
    fx = X.FIXTURES[name]

    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        p = points_of(spark, sf_dir, name)
        some = p if channels is None else p.where(F.col("channel").isin(channels))
        return B.knn_brute_sql(some, query_points(p, q or fx.q, fx.n_queries, fx.noise, channels), q or fx.q, k)

    return run, X.knn_sql(fx.sql, q or fx.q, k, fx.n_queries, fx.noise, channels)


def other_length(name: str, q: int, k: int):
    """A length the index doesn't hold: the planner falls back to the scan."""
    fx = X.FIXTURES[name]

    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        ship(spark)
        qs = queries_of(spark, sf_dir, name, q=q)
        index = index_of(spark, sf_dir, name)
        try:
            return I.knn_index(index, qs, k)
        except I.LengthMismatch:
            return B.knn_scan(to_chunks(points_of(spark, sf_dir, name), q), qs, k)

    return run, X.knn_sql(fx.sql, q, k, fx.n_queries, fx.noise)


def range_week(spark: SparkSession, sf_dir: str) -> DataFrame:
    index = index_of(spark, sf_dir, "supplier_week")
    return I.range_query(index, queries_of(spark, sf_dir, "supplier_week", [0]), RADIUS)


RADIUS = 236.5


def whole_embeddings(spark: SparkSession, sf_dir: str) -> DataFrame:
    ship(spark)
    index = _once(spark, (sf_dir, "whole"), lambda: I.build_index(to_chunks(points_of(spark, sf_dir, "embeddings"), 64), 64))
    return I.knn_index(index, queries_of(spark, sf_dir, "embeddings", q=64), 5, mode="whole")


def after_append(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Index over weeks before 300, then the windows that end later appended as a delta segment."""
    ship(spark)
    fx = X.FIXTURES["supplier_week"]
    p = points_of(spark, sf_dir, "supplier_week")
    base = I.build_index(to_chunks(p.where("t < 300"), fx.q), fx.q)
    first_new = 300 - fx.q + 1
    new = to_chunks(p.where(F.col("t") >= first_new).withColumn("t", F.col("t") - first_new), fx.q)
    new = new.withColumn("base_t", F.col("base_t") + first_new).withColumn("chunk_id", F.col("chunk_id") + 1_000_000)
    return I.knn_index(I.append(base, new), queries_of(spark, sf_dir, "supplier_week"), 10)


def after_compact(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The same after regrouping the leaves that the appended segment has overfilled."""
    ship(spark)
    fx = X.FIXTURES["nation"]
    p = points_of(spark, sf_dir, "nation")
    base = I.build_index(to_chunks(p.where("t < 200"), fx.q), fx.q, leaf_pct=1.0)
    first_new = 200 - fx.q + 1
    new = to_chunks(p.where(F.col("t") >= first_new).withColumn("t", F.col("t") - first_new), fx.q)
    new = new.withColumn("base_t", F.col("base_t") + first_new).withColumn("chunk_id", F.col("chunk_id") + 1_000_000)
    return I.knn_index(I.compact(I.append(base, new)), queries_of(spark, sf_dir, "nation"), 5)


def with_dates(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Hits with the first day of their weeks."""
    found = by_index("supplier_week", 5)[0](spark, sf_dir)
    return I.with_timestamps(found, "date'1995-01-02'", "interval 7 days").withColumn("start_ts", F.to_date("start_ts"))


def apart(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The three nearest windows of which no two of one series start within 26 weeks."""
    return I.knn_index(index_of(spark, sf_dir, "nation"), queries_of(spark, sf_dir, "nation", n=1), 3, exclusion=26).select("rank", "series_id", "start", "d2")


def clusters(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Suppliers' quantity lines in three groups: nearest of three seed lines, then nearest of the groups' mean lines."""
    p = points_of(spark, sf_dir, "supplier_week_cum").where("channel = 0").select("series_id", "t", F.col("v").cast("double").alias("v"))
    ids = p.select("series_id").distinct().withColumn("r", F.row_number().over(Window.orderBy("series_id")) - 1)
    n = F.count(F.lit(1)).over(Window.partitionBy())
    seeds = ids.withColumn("n", n).where("r in (0, n div 3, 2 * n div 3)").select("series_id", F.row_number().over(Window.orderBy("r")).alias("g"))
    lines = p.join(F.broadcast(seeds), "series_id").select("g", "t", F.col("v").alias("m"))
    for _ in range(2):
        d = p.join(F.broadcast(lines), "t").groupBy("series_id", "g").agg(F.sum((F.col("v") - F.col("m")) ** 2).alias("d2"))
        of = d.groupBy("series_id").agg(F.min(F.struct("d2", "g")).alias("m")).select("series_id", F.col("m.g").alias("g"))
        lines = p.join(F.broadcast(of), "series_id").groupBy("g", "t").agg(F.avg("v").alias("m"))
    return of.select("series_id", F.col("g").cast("bigint").alias("cluster"))


_NEAREST = "select series_id, g from (select p.series_id, l.g, row_number() over (partition by p.series_id order by sum((p.v - l.m) ** 2), l.g) as k from p join {0} l using (t) group by 1, 2) where k = 1"
CLUSTER_SQL = f"""with p as materialized (select series_id, t, cast(v as double) as v from ({X.supplier_sql(cumulative=True)}) where channel = 0), ids as (select series_id, row_number() over (order by series_id) - 1 as r, count(*) over () as n from (select distinct series_id from p)),
s as (select series_id, row_number() over (order by r) as g from ids where r in (0, n // 3, 2 * n // 3)), l0 as (select g, t, v as m from p join s using (series_id)),
a as ({_NEAREST.format('l0')}), l1 as (select g, t, avg(v) as m from p join a using (series_id) group by 1, 2), b as ({_NEAREST.format('l1')}) select series_id, g as cluster from b"""


def doc_lines(spark: SparkSession, sf_dir: str) -> DataFrame:
    ship(spark)
    return B.knn_scan(chunks_of(spark, sf_dir, "doc_lines"), queries_of(spark, sf_dir, "doc_lines"), 5)


def incident(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Which past 12-week stretches of suppliers of region 1 resemble weeks 200-211 of its third supplier, on quantity and revenue?

    The region filter prunes the points before windows are made; the relevant channels are chosen at query time. One query
    doesn't pay for an index, so the planner scans.
    """
    ship(spark)
    nation = X.table(spark, sf_dir, "nation").where("n_regionkey = 1").select("n_nationkey")
    ids = X.table(spark, sf_dir, "supplier").join(F.broadcast(nation), F.col("s_nationkey") == F.col("n_nationkey")).select(F.col("s_suppkey").alias("series_id"))
    p = X.supplier(spark, sf_dir).join(F.broadcast(ids), "series_id", "left_semi").persist()
    third = p.select("series_id").distinct().orderBy("series_id").limit(3).agg(F.max("series_id").alias("series_id"))
    cut = p.where("channel in (0, 1) and t between 200 and 211").join(F.broadcast(third), "series_id").select(F.lit(0).alias("query_id"), "channel", (F.col("t") - 200).alias("j"), F.col("v").alias("qv"))
    queries = I.collect_queries(cut)
    return B.knn(to_chunks(p, 12), queries, 10, "auto")


INCIDENT_SQL = f"""with base as ({X.supplier_sql()}), pts as materialized (select b.* from base b join supplier s on s.s_suppkey = b.series_id join nation n on n.n_nationkey = s.s_nationkey where n.n_regionkey = 1),
third as (select max(series_id) as id from (select distinct series_id from pts order by 1 limit 3)),
qp as (select channel, t - 200 as j, v as qv from pts, third where series_id = third.id and channel in (0, 1) and t between 200 and 211),
w as (select p.series_id, p.t - qp.j as start, sum((p.v - qp.qv) * (p.v - qp.qv)) as d2, count(*) as c from pts p join qp on p.channel = qp.channel and p.t >= qp.j group by 1, 2)
select cast(0 as integer) as query_id, cast(row_number() over (order by d2, series_id, start) as integer) as rank, series_id, start, cast(d2 as bigint) as d2, round(sqrt(d2), 4) as distance from w where c = 24 qualify rank <= 10"""


def classify(spark: SparkSession, sf_dir: str, block: int = 20_000) -> DataFrame:
    """1NN label of every tenth vector among the others, by whole matching: a stated query set against all rows, in blocks.

    A pass over the vectors a block of queries; each batch gives its nearest vector of every query, by one matrix product
    (whole numbers below 2 ** 53, so exact), and the smallest of those is taken.
    """
    ship(spark)
    v = X.table(spark, sf_dir, "embeddings").select("vec_id", "label", F.transform("embedding", lambda x: F.round(x.cast("double") * 1e6)).alias("e"))
    base = v.where("vec_id % 10 <> 0")
    out, held = None, []

    def search(queries: list) -> DataFrame:
        ids, truth = [r["vec_id"] for r in queries], [r["label"] for r in queries]
        y = np.array([r["e"] for r in queries], float)

        def run(batches):
            for rows in batches:
                if not rows.num_rows:
                    continue
                own = np.argsort(np.array(rows.column(0).to_pylist()), kind="stable")
                x = np.array(rows.column(2).to_pylist(), float)[own]
                d2 = (y * y).sum(axis=1)[:, None] + (x * x).sum(axis=1)[None] - 2 * y @ x.T
                at = own[d2.argmin(axis=1)]
                yield pa.RecordBatch.from_arrays([pa.array(ids, pa.int64()), pa.array(truth, rows.column(1).type), rows.column(0).take(pa.array(at)), rows.column(1).take(pa.array(at)), pa.array(d2.min(axis=1))], names=["query_id", "truth", "vec_id", "label", "d2"])

        kind = v.schema["label"].dataType.simpleString()
        return base.mapInArrow(run, f"query_id bigint, truth {kind}, vec_id bigint, label {kind}, d2 double")

    for r in v.where("vec_id % 10 = 0").toLocalIterator():
        held.append(r)
        if len(held) == block:
            out = search(held) if out is None else out.unionByName(search(held))
            held = []
    if held or out is None:
        out = search(held) if out is None else out.unionByName(search(held))
    best = out.groupBy("query_id", "truth").agg(F.min(F.struct("d2", "vec_id", "label")).alias("m"))
    return best.select("query_id", F.col("m.vec_id").alias("vec_id"), F.col("m.label").alias("predicted"), (F.col("m.label") == F.col("truth")).alias("correct"))


CLASSIFY_SQL = """with v as (select vec_id, label, [cast(round(cast(x as double) * 1e6) as bigint) for x in embedding] as e from embeddings),
p as (select a.vec_id as query_id, a.label as truth, b.vec_id, b.label, list_sum([(z[1] - z[2]) * (z[1] - z[2]) for z in list_zip(a.e, b.e)]) as d2 from v a, v b where a.vec_id % 10 = 0 and b.vec_id % 10 <> 0)
select query_id, vec_id, label as predicted, label = truth as correct from (select *, row_number() over (partition by query_id order by d2, vec_id) as r from p) where r = 1"""


def discords(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The three windows of nation's series farthest from their nearest window of another series, over all starts of both.

    Pairs of series meet by a cross join; each gives the nearest distance of every window of the one.
    """
    ship(spark)
    p = points_of(spark, sf_dir, "nation").where("channel = 0")
    lines = p.groupBy("series_id").agg(F.sort_array(F.collect_list(F.struct("t", "v"))).alias("l")).select("series_id", F.col("l.t")[0].alias("base"), F.col("l.v").alias("v"))
    other = lines.select(F.col("series_id").alias("o"), F.col("v").alias("y"))
    pairs = lines.repartition("series_id").join(F.broadcast(other), F.col("series_id") != F.col("o")).select("series_id", "base", "v", "y")

    def run(batches):
        for rows in batches:
            ids, starts, best = [], [], []
            for r in rows.to_pylist():
                d = K.nearest(np.array(r["v"], np.int64), np.array(r["y"], np.int64), 52)
                ids += [r["series_id"]] * len(d)
                starts += range(r["base"], r["base"] + len(d))
                best += d.tolist()
            yield pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in (ids, starts, best)], names=["series_id", "start", "d2"])

    d = pairs.mapInArrow(run, "series_id bigint, start bigint, d2 bigint")
    return d.groupBy("series_id", "start").agg(F.min("d2").alias("nearest_d2")).orderBy(F.desc("nearest_d2"), "series_id", "start").limit(3)


#: Of two series and a shift between their starts the distances are running sums along the diagonal.
DISCORD_SQL = f"""with pts as materialized (select series_id, t, v from ({X.nation_week_sql()}) where channel = 0),
g as (select a.series_id as x, b.series_id as y, a.t as tx, b.t - a.t as lag, (a.v - b.v) * (a.v - b.v) as e from pts a join pts b on a.series_id < b.series_id),
d as (select x, y, tx, tx + lag as ty, sum(e) over w as d2, count(*) over w as n from g window w as (partition by x, y, lag order by tx rows between current row and 51 following)),
f as (select x as series_id, tx as start, min(d2) as d2 from d where n = 52 group by 1, 2 union all select y, ty, min(d2) from d where n = 52 group by 1, 2)
select series_id, start, cast(min(d2) as bigint) as nearest_d2 from f group by 1, 2 order by 3 desc, 1, 2 limit 3"""


def topk_per_series(spark: SparkSession, sf_dir: str) -> DataFrame:
    p = points_of(spark, sf_dir, "supplier_week").where("channel = 0")
    d = B.distances_sql(p, query_points(points_of(spark, sf_dir, "supplier_week"), 52, 1, 1, [0]), 52)
    r = F.row_number().over(Window.partitionBy("series_id").orderBy("d2", "start"))
    return d.withColumn("r", r).where("r = 1").select("series_id", "start", F.col("d2").cast("bigint").alias("d2"))


def _all_distances(name: str, channels: list[int], n: int, noise: int = 1, held_out: bool = False) -> str:
    """SQL of (query_id, series_id, start, d2) of every window."""
    fx = X.FIXTURES[name]
    return X.knn_sql(fx.sql, fx.q, 1 << 30, n, noise, channels, held_out=held_out)


def contrast(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Farthest over nearest window distance per query: the higher, the easier."""
    ship(spark)
    step = 1_000_000  # of the queries' numbers in one pass
    queries = [I.Query(noise * step + qu.query_id, qu.channels, qu.values) for noise in (1, 4, 16) for qu in queries_of(spark, sf_dir, "supplier_week", [0], n=2, noise=noise)]
    found = B.extremes(chunks_of(spark, sf_dir, "supplier_week"), queries)
    contrast = F.round(F.sqrt("far") / F.nullif(F.sqrt("near"), F.lit(0.0)), 4).alias("contrast")
    return found.select((F.col("query_id") % step).alias("query_id"), F.floor(F.col("query_id") / step).cast("int").alias("noise"), contrast)


CONTRAST_SQL = " union all ".join(f"select query_id, cast({z} as integer) as noise, round(sqrt(max(d2)) / nullif(sqrt(min(d2)), 0), 4) as contrast from ({_all_distances('supplier_week', [0], 2, z)}) group by 1" for z in (1, 4, 16))


def wrapper_step(spark: SparkSession, sf_dir: str, candidates: bool) -> DataFrame:
    """Thresholds by channel from the exact best 5 (step 3), or the windows within one of them (step 4)."""
    p, q = points_of(spark, sf_dir, "nation"), 52
    qs = query_points(p, q, 1, 1, [0, 1])
    per = p.join(F.broadcast(qs), "channel").where(F.col("t") >= F.col("j")).groupBy("channel", "series_id", (F.col("t") - F.col("j")).alias("start")).agg(F.sum((F.col("v") - F.col("qv")) * (F.col("v") - F.col("qv"))).alias("d2"), F.count(F.lit(1)).alias("n")).where(F.col("n") == q).drop("n")
    best = per.groupBy("series_id", "start").agg(F.sum("d2").alias("d")).orderBy("d", "series_id", "start").limit(5)
    tau = per.join(F.broadcast(best), ["series_id", "start"], "left_semi").groupBy("channel").agg(F.max("d2").cast("bigint").alias("tau"))
    if not candidates:
        return tau
    return per.join(F.broadcast(tau), "channel").where(F.col("d2") <= F.col("tau")).select("series_id", "start").distinct()


def _wrapper_sql(candidates: bool) -> str:
    head = f"""with pts as materialized ({X.nation_week_sql()}), ids as (select series_id, row_number() over (order by series_id) - 1 as rank from (select distinct series_id from pts)),
    cut as (select series_id, 100 % (344 - 52 + 1) as start from ids where rank = 7 % (select count(*) from ids)),
    qp as (select p.channel, p.t - cut.start as j, p.v + (((((p.t * 7919 + p.channel * 104729) % 5) + 5) % 5) - 2) as qv from pts p join cut on p.series_id = cut.series_id and p.t >= cut.start and p.t < cut.start + 52 where p.channel in (0, 1)),
    per as materialized (select p.channel, p.series_id, p.t - qp.j as start, sum((p.v - qp.qv) * (p.v - qp.qv)) as d2 from pts p join qp on p.channel = qp.channel and p.t >= qp.j group by 1, 2, 3 having count(*) = 52),
    best as (select series_id, start from per group by 1, 2 order by sum(d2), 1, 2 limit 5), tau as (select per.channel, cast(max(d2) as bigint) as tau from per join best using (series_id, start) group by 1)"""
    return head + (" select distinct series_id, start from per join tau using (channel) where d2 <= tau" if candidates else " select channel, tau from tau")


def walks_found(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Nearest windows in generated walks (no SQL twin for the generator); 16 series x 64 channels x 512."""
    ship(spark)
    p = X.walks(spark, 16).persist()
    chunks = _once(spark, (sf_dir, "walks"), lambda: to_chunks(p, 128).persist())
    queries = I.collect_queries(query_points(p, 128, 2, 1, list(range(0, 64, 8))))
    return I.knn_index(I.build_index(chunks, 128), queries, 1, whole_numbers=False)


def verify_exact(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Rows that the index and brute force don't share, on generated walks: empty, or the index is wrong."""
    ship(spark)
    p = X.walks(spark, 8, 8, 256).persist()
    chunks = to_chunks(p, 64).persist()
    queries = I.collect_queries(query_points(p, 64, 3, 1))
    a = I.knn_index(I.build_index(chunks, 64), queries, 5, whole_numbers=False).select("query_id", "rank", "series_id", "start")
    b = B.knn_brute(chunks, queries, 5, whole_numbers=False).select("query_id", "rank", "series_id", "start")
    return a.exceptAll(b).union(b.exceptAll(a))


def walks_stats(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Points, mean and deviation by channel of the nations' running sums, the walks of the given tables."""
    p = X.nation_week(spark, sf_dir, cumulative=True)
    return p.groupBy("channel").agg(F.count(F.lit(1)).alias("n"), F.round(F.avg("v"), 4).alias("mean"), F.round(F.stddev_pop("v"), 4).alias("sd"))


WALKS_SQL = f"select channel, count(*) as n, round(avg(v), 4) as mean, round(stddev_pop(v), 4) as sd from ({X.nation_week_sql(cumulative=True)}) group by 1"


QUERIES: dict = {}
ORACLE_SQL: dict = {}


def _add(name: str, pair) -> None:
    QUERIES[name], ORACLE_SQL[name] = pair


for _f in ("supplier_week", "event_line", "cohort_hour", "embeddings", "nation"):
    _add(f"knn_{_f}", by_index(_f, 5 if _f in ("cohort_hour", "nation") else 10))
    _add(f"knn_norm_{_f}", by_index(_f, 5, n=1, normalized=True))
    _add(f"knn_one_{_f}", by_index(_f, 1))
_add("knn_supplier_week_cum", by_index("supplier_week_cum", 10))
_add("knn_embeddings_4x16", by_index("embeddings_4x16", 10))
_add("knn_conv_turns", by_index("conv_turns", 3))
for _p in (0, 1, 2, 5):
    _add(f"knn_pivots_{_p}", by_index("supplier_week_cum", 5, n_pivots=_p))
_add("knn_pivots_max", by_index("supplier_week_cum", 5, n_pivots=2, search={"correction": "max"}))
_add("knn_no_correction", by_index("supplier_week_cum", 5, n_pivots=1, search={"correction": "none"}))
_add("knn_no_browsing", by_index("supplier_week_cum", 5, n_pivots=1, search={"browsing": False}))
for _w in ("uniform", "share", "softmax_std", "softmax"):
    _add(f"knn_weighting_{_w}", by_index("supplier_week_cum", 5, weighting=_w))
for _l in ("0.01", "0.05", "1", "100"):
    _add(f"knn_leaf_{_l.replace('.', '_')}", by_index("supplier_week_cum", 5, leaf_pct=float(_l)))
for _d in (20, 40, 60, 80, 100):
    _add(f"knn_dtarget_{_d}", by_index("nation", 5, d_target=_d / 100))
_add("knn_bins_first", by_index("nation", 5, bins="first", f=3))
_add("knn_bins_energy", by_index("nation", 5, bins="energy"))
_add("knn_layout_kd", by_index("supplier_week_cum", 5, layout="kd"))
_add("knn_no_compression", by_index("nation", 5, compress=False))
_add("knn_float32_boxes", by_index("nation", 5, boxes="float32"))
_add("knn_ood", by_index("supplier_week", 5, held_out=True))
for _n in (0, 4, 16):
    _add(f"knn_noise_{_n}", by_index("supplier_week", 5, noise=_n))
for _k, _c in {"1": [0], "2": [0, 1], "3": [1, 3, 4], "all": None}.items():
    _add(f"knn_channels_{_k}", by_index("supplier_week", 5, channels=_c))
for _k, _c in {"2": [0, 5], "4": [0, 2, 5, 9], "16": list(range(16)), "64": list(range(64)), "all": None}.items():
    _add(f"knn_many_channels_{_k}", by_index("many_channels_blocks", 1, channels=_c))
for _m in ("brute", "scan", "trail", "meanlookup", "segtree", "envelope"):
    _add(f"knn_{_m}", by_baseline("nation", 5, _m))
    _add(f"knn_{_m}_norm", by_baseline("nation", 3, _m, normalized=True))
_add("knn_trail_channels", by_baseline("supplier_week_cum", 5, "trail", [0, 1]))
_add("knn_scan_supplier_week", by_baseline("supplier_week", 10, "scan"))
_add("knn_brute_sql", brute_sql("nation", 5))
_add("knn_brute_sql_channel", brute_sql("supplier_week", 5, channels=[0]))
for _q in (13, 26, 104):
    _add(f"knn_q{_q}", other_length("nation", _q, 5))
_fx = X.FIXTURES["supplier_week"]
_add("range_supplier_week", (range_week, X.knn_sql(_fx.sql, 52, 0, 2, 1, [0], radius=RADIUS)))
_add("knn_whole_embeddings", (whole_embeddings, X.knn_sql(X.embeddings_sql(), 64, 5, 2, 1000, whole=True)))
_add("knn_after_append", (after_append, X.knn_sql(_fx.sql, 52, 10)))
_add("knn_after_compact", (after_compact, X.knn_sql(X.FIXTURES["nation"].sql, 52, 5)))
_add("knn_timestamps", (with_dates, f"select *, date '1995-01-02' + cast(start * 7 as integer) as start_ts from ({X.knn_sql(_fx.sql, 52, 5)})"))
_add("cluster_suppliers", (clusters, CLUSTER_SQL))
_add("knn_doc_lines", (doc_lines, X.knn_sql(X.doc_lines_sql(), 4, 5)))
_add("usecase_supplier_incident", (incident, INCIDENT_SQL))
_add("knn_classify", (classify, CLASSIFY_SQL))
_add("top_discords", (discords, DISCORD_SQL))
_add("topk_per_series", (topk_per_series, f"select series_id, start, d2 from (select *, row_number() over (partition by series_id order by d2, start) as r from ({_all_distances('supplier_week', [0], 1)})) where r = 1"))
_add("contrast_noise", (contrast, CONTRAST_SQL))
_add("threshold_tau", (lambda s, d: wrapper_step(s, d, False), _wrapper_sql(False)))
_add("wrapper_candidates", (lambda s, d: wrapper_step(s, d, True), _wrapper_sql(True)))
QUERIES |= {"knn_apart": apart, "knn_walks": walks_found, "verify_exact": verify_exact}
_add("walks_stats", (walks_stats, WALKS_SQL))
