"""Series from tables: bucketing, gap filling, chunking with halo, window enumeration, query workloads."""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass, replace

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

INT = "bigint"
#: Channels of a row, where chunks of very many channels are split (``wide``).
CHANNEL_BLOCK = 64


def build_series(df: DataFrame, entity: Column, t: Column, channels: list[Column], length: int | None, fill: str = "zero", cumulative: bool = False) -> DataFrame:
    """Long points (series_id, channel, t, v): one aggregate per (entity, t), gaps filled, optional running sums.

    ``length``: steps of the calendar (None: up to each series' own last step). ``fill``: zero, locf, linear or none.
    """
    rows = df.withColumn("series_id", entity.cast("bigint")).withColumn("t", t.cast("bigint"))
    wide = rows.groupBy("series_id", "t").agg(*[c.cast(INT).alias(f"c{i}") for i, c in enumerate(channels)])
    names = [f"c{i}" for i in range(len(channels))]
    if fill != "none":
        last = F.lit(length - 1) if length else F.max("t")
        calendar = wide.groupBy("series_id").agg(last.cast("bigint").alias("last")).select("series_id", F.explode(F.sequence(F.lit(0).cast("bigint"), "last")).alias("t"))
        wide = calendar.join(wide, ["series_id", "t"], "left")
    over = Window.partitionBy("series_id").orderBy("t")
    back = over.rowsBetween(Window.unboundedPreceding, 0)
    if fill == "zero":
        wide = wide.fillna(0, names)
    elif fill == "locf":
        wide = wide.select("series_id", "t", *[F.coalesce(F.last(c, ignorenulls=True).over(back), F.lit(0)).alias(c) for c in names])
    elif fill == "linear":
        ahead = over.rowsBetween(0, Window.unboundedFollowing)
        cols = []
        for c in names:
            p, n = F.last(c, ignorenulls=True).over(back), F.first(c, ignorenulls=True).over(ahead)
            tp, tn = F.last(F.when(F.col(c).isNotNull(), F.col("t")), ignorenulls=True).over(back), F.first(F.when(F.col(c).isNotNull(), F.col("t")), ignorenulls=True).over(ahead)
            between = p + (n - p) * (F.col("t") - tp) / F.nullif(tn - tp, F.lit(0))
            cols.append(F.coalesce(F.col(c).cast("double"), between, p.cast("double"), n.cast("double"), F.lit(0.0)).alias(c))
        wide = wide.select("series_id", "t", *cols)
    if cumulative:
        wide = wide.select("series_id", "t", *[F.sum(c).over(back).alias(c) for c in names])
    return wide.select("series_id", F.posexplode(F.array(*names)).alias("channel", "v"), "t").select("series_id", F.col("channel").cast("int").alias("channel"), "t", "v")


def to_chunks(points: DataFrame, q: int, chunk_len: int = 4096) -> DataFrame:
    """(series_id, chunk_id, base_t, vals) with q-1 values of halo on the right: every window lies in one chunk.

    One shuffle by (series, chunk); a point goes to the chunks whose windows hold it (two at most if chunk_len >= q).
    """
    last = F.floor(F.col("t") / chunk_len)
    first = F.greatest(F.lit(0).cast("bigint"), F.floor((F.col("t") - (q - 1)) / chunk_len))
    dealt = points.select("series_id", "channel", "t", F.col("v").cast("double").alias("v"), F.explode(F.sequence(first, last)).alias("chunk_id"))
    lines = dealt.groupBy("series_id", "chunk_id", "channel").agg(F.transform(F.array_sort(F.collect_list(F.struct("t", "v"))), lambda p: p["v"]).alias("line"))
    chunks = lines.groupBy("series_id", "chunk_id").agg(F.transform(F.array_sort(F.collect_list(F.struct("channel", "line"))), lambda p: p["line"]).alias("vals"))
    return chunks.select("series_id", "chunk_id", (F.col("chunk_id") * chunk_len).alias("base_t"), F.least(F.lit(chunk_len), F.size(F.get("vals", F.lit(0))) - (q - 1)).cast("int").alias("n_core"), "vals").where("n_core > 0")


def rows_to_chunks(rows: DataFrame, length: int, q: int, finish=None, cumulative: bool = False, chunk_len: int = 4096, n_series: int | None = None) -> DataFrame:
    """Chunks as ``to_chunks`` makes them, from rows (series_id, t, c0, c1, ...) whose values of a step are added up; gaps are 0.

    One shuffle by series, of packed blocks: a task adds up PACKED_ROWS rows at a time and sends those of each partition as one
    compressed value (``packed``). The task that reads them adds up its series in one array of about HELD_BYTES. ``finish``: a function of a series' sums (c, length).
    ``n_series``: about how many series there are, where it is known.
    """
    names = [c for c in rows.columns if c not in ("series_id", "t")]
    some = rows.select("series_id", "t", *[F.col(c).cast(INT).alias(c) for c in names])
    core, cells = length - q + 1, len(names) * length
    kind = "series_id bigint, chunk_id bigint, base_t bigint, n_core int, vals array<array<double>>"
    if core <= 0:
        return some.sparkSession.createDataFrame([], kind)
    if n_series is None:
        n_series = some.agg(F.approx_count_distinct("series_id")).first()[0] or 0
    size = n_series * cells * 8
    tasks = max(1, -(-size // HELD_BYTES), min(some.sparkSession.sparkContext.defaultParallelism, -(-size // LEAST_BYTES)))
    parts = range(-(-core // chunk_len))

    def out(series: list[int], sums: list[np.ndarray]) -> pa.RecordBatch:
        own = []
        for x in sums:
            x = x if finish is None else finish(x)
            own.append(np.cumsum(x, axis=1) if cumulative else x)
        vals = [x[:, i * chunk_len : i * chunk_len + chunk_len + q - 1] for x in own for i in parts]
        sizes = np.concatenate([[0], np.cumsum(np.repeat([v.shape[1] for v in vals], len(names)))])
        lines = pa.ListArray.from_arrays(pa.array(sizes.astype(np.int32)), pa.array(np.concatenate([v.ravel() for v in vals]).astype(float)))
        outer = pa.ListArray.from_arrays(pa.array(np.arange(len(vals) + 1, dtype=np.int32) * np.int32(len(names))), lines)
        ids = [None if s == NULL else s for s in series for _ in parts]
        numbers = [i for _ in series for i in parts]
        return pa.RecordBatch.from_arrays([pa.array(ids, pa.int64()), pa.array(numbers, pa.int64()), pa.array([i * chunk_len for i in numbers], pa.int64()), pa.array([v.shape[1] - q + 1 for v in vals], pa.int32()), outer], names=["series_id", "chunk_id", "base_t", "n_core", "vals"])

    def pack(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held, n = [], 0
        for b in batches:
            held.append(b)
            n += b.num_rows
            if n >= PACKED_ROWS:
                yield _dealt(pa.Table.from_batches(held), length, tasks)
                held, n = [], 0
        if n:
            yield _dealt(pa.Table.from_batches(held), length, tasks)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        place: dict[int, int] = {}
        sums = np.zeros((0, cells), np.int64)
        for b in batches:
            for block in b.column(1):
                series, t, *values = unpacked(block.as_py())
                own, which = np.unique(series, return_inverse=True)
                at = np.array([place.setdefault(s, len(place)) for s in own.tolist()], int)
                if len(place) > len(sums):
                    sums = np.concatenate([sums, np.zeros((max(256, len(sums) // 2, len(place) - len(sums)), cells), np.int64)])
                ok = np.flatnonzero(t < length)
                cell = at[which[ok]] * cells + t[ok]  # each once: a block's rows are added up
                flat = sums.reshape(-1)
                for i, v in enumerate(values):
                    flat[cell + i * length] += v[ok]
        ids = list(place)
        for o in range(0, len(ids), 256):
            yield out(ids[o : o + 256], [x.reshape(len(names), length) for x in sums[o : min(o + 256, len(ids))]])

    return some.mapInArrow(pack, "part int, block binary").repartitionById(tasks, "part").mapInArrow(run, kind)


def _dealt(rows: pa.Table, length: int, tasks: int) -> pa.RecordBatch:
    """Rows (series, t, values) added up by series and step, one packed block a partition."""
    series, t = (rows.column(i).fill_null(NULL).to_numpy() for i in (0, 1))
    # rows without a series or a step of the calendar give a series of zeros, as SQL's join on the series does: step ``length``
    ok = (t >= 0) & (t < length) & (series != NULL)
    t = np.where(ok, t, length)
    part = (mixed(series) % np.uint64(tasks)).astype(np.int64)
    order = np.lexsort((t, series, part))
    series, t, part = series[order], t[order], part[order]
    first = np.flatnonzero(np.concatenate([[True], (series[1:] != series[:-1]) | (t[1:] != t[:-1])]))
    values = [np.add.reduceat(np.where(ok, rows.column(i).fill_null(0).to_numpy(), 0)[order], first) for i in range(2, rows.num_columns)]
    cols = [series[first], t[first], *values]
    parts, starts = np.unique(part[first], return_index=True)
    ends = [*starts[1:], len(first)]
    return pa.RecordBatch.from_arrays([pa.array(parts.astype(np.int32)), pa.array([packed([c[a:b] for c in cols]) for a, b in zip(starts, ends, strict=True)], pa.binary())], names=["part", "block"])


def mixed(x: np.ndarray) -> np.ndarray:
    """A hash of whole numbers, wrapping modulo 2 ** 64."""
    h = x.astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15)
    return (h ^ (h >> np.uint64(32))) * np.uint64(0xD6E8FEB86659FD93) >> np.uint64(32)


def packed(cols: list[np.ndarray]) -> bytes:
    """Columns of whole numbers, the first sorted, in as few bytes as their values need: differences of the first, then bytes of like weight together."""
    head, body = [len(cols), len(cols[0]), int(cols[0][0])], []
    for c in (np.diff(cols[0], prepend=cols[0][:1]), *cols[1:]):
        low, high = int(c.min()), int(c.max())
        width = next(w for w in (1, 2, 4, 8) if -(1 << 8 * w - 1) <= low and high < 1 << 8 * w - 1)
        head.append(width)
        body.append(c.astype(f"<i{width}").view(np.uint8).reshape(-1, width).T.tobytes())
    return np.array(head, "<i8").tobytes() + pa.compress(b"".join(body), codec="zstd", asbytes=True)


def unpacked(block: bytes) -> list[np.ndarray]:
    n_cols, n, base = np.frombuffer(block, "<i8", 3).tolist()
    widths = np.frombuffer(block, "<i8", n_cols, 24).tolist()
    body = np.frombuffer(pa.decompress(block[24 + 8 * n_cols :], decompressed_size=n * sum(widths), codec="zstd", asbytes=True), np.uint8)
    out, at = [], 0
    for width in widths:
        out.append(np.ascontiguousarray(body[at : at + n * width].reshape(width, n).T).view(f"<i{width}")[:, 0].astype(np.int64))
        at += n * width
    out[0] = np.int64(base) + np.cumsum(out[0])
    return out


#: Bytes of the sums that a task of ``rows_to_chunks`` holds, and that it has at least where cores are left.
HELD_BYTES, LEAST_BYTES = 1 << 25, 1 << 20
#: Rows that a task adds up before it sends them on, about 8 bytes a number.
PACKED_ROWS = 1 << 19
#: Stands for a series without id among whole numbers.
NULL = -(1 << 63)


def chunk_lengths(chunks: DataFrame) -> DataFrame:
    """(series_id, m): the length of every series of some chunks."""
    return chunks.groupBy("series_id").agg(F.max(F.col("base_t") + F.size(F.get("vals", F.lit(0)))).cast("bigint").alias("m"))


def chunk_points(chunks: DataFrame, series: DataFrame) -> DataFrame:
    """Points of a few series from their chunks; whole numbers."""
    some = chunks.join(F.broadcast(series), "series_id").select("series_id", "base_t", F.posexplode("vals").alias("channel", "line"))
    long = some.select("series_id", "channel", "base_t", F.posexplode("line").alias("i", "v"))
    return long.select("series_id", "channel", (F.col("base_t") + F.col("i")).alias("t"), F.col("v").cast(INT).alias("v")).dropDuplicates(["series_id", "channel", "t"])


def windows(chunks: DataFrame, q: int, stride: int = 1) -> DataFrame:
    """(series_id, start) of every window; values are never stored."""
    return chunks.select("series_id", F.explode(F.sequence("base_t", F.col("base_t") + F.col("n_core") - 1)).alias("start")).where(F.col("start") % stride == 0)


def mts_distance(x: Column, y: Column) -> Column:
    """Euclidean distance of two channel-major arrays over their common channels and common length."""
    line = lambda a, b: F.aggregate(F.zip_with(F.slice(a, 1, F.least(F.size(a), F.size(b))), F.slice(b, 1, F.least(F.size(a), F.size(b))), lambda u, v: (u - v) * (u - v)), F.lit(0.0), lambda s, d: s + d)
    n = F.least(F.size(x), F.size(y))
    return F.sqrt(F.aggregate(F.zip_with(F.slice(x, 1, n), F.slice(y, 1, n), line), F.lit(0.0), lambda s, d: s + d))


@dataclass(frozen=True)
class Fixture:
    """A family of series on the given tables: how Spark and SQL build it, its shape and its queries.

    ``points`` gives (series_id, channel, t, v); ``sql`` is a DuckDB select of the same.
    """

    name: str
    points: object
    sql: str
    q: int
    channels: int
    n: str  # SQL scalar: number of series (ids count from `first`)
    m: str  # SQL scalar: length of the series that queries are cut from
    first: int = 0
    noise: int = 1
    n_queries: int = 2
    chunks: object = None  # gives the chunks straight from the tables, where series are too many to keep their points

    def with_(self, **k) -> Fixture:
        return replace(self, **k)


def noise_of(t: Column, channel: Column, j: Column) -> Column:
    """Whole-number noise in -2..2 that both engines can compute."""
    return F.pmod(t * 7919 + channel.cast("bigint") * 104729 + j.cast("bigint") * 31, F.lit(5)) - 2


def query_points(points: DataFrame, q: int, n_queries: int = 2, noise: int = 1, channels: list[int] | None = None, held_out: bool = False, ids: DataFrame | None = None) -> DataFrame:
    """(query_id, channel, j, qv): noisy cuts of the data at series (7 + 13 j) mod n, start (100 + 37 j) mod (m - q + 1).

    ``held_out``: cut from every tenth series (rank mod 10 = 9), which the search then leaves out. ``ids``: series and
    their lengths, where ``points`` is a function that gives the points of some series.
    """
    cut = query_cuts(points.groupBy("series_id").agg((F.max("t") + 1).alias("m")) if ids is None else ids, q, n_queries, held_out)
    points = points(cut.select("series_id").distinct()) if callable(points) else points
    part = points if channels is None else points.where(F.col("channel").isin(channels))
    cut = part.join(F.broadcast(cut), "series_id").where((F.col("t") >= F.col("start")) & (F.col("t") < F.col("start") + q))
    return cut.select("query_id", "channel", (F.col("t") - F.col("start")).alias("j"), (F.col("v") + noise * noise_of(F.col("t"), F.col("channel"), F.col("query_id"))).alias("qv"))


def query_cuts(ids: DataFrame, q: int, n_queries: int, held_out: bool = False) -> DataFrame:
    """(query_id, series_id, start): where queries are cut, from series and their lengths m."""
    ids = ids.where(F.col("m") >= q).withColumn("rank", F.row_number().over(Window.orderBy("series_id")) - 1)
    if held_out:
        ids = ids.where("rank % 10 = 9").withColumn("rank", F.row_number().over(Window.orderBy("series_id")) - 1)
    ids = ids.withColumn("n", F.count(F.lit(1)).over(Window.partitionBy()))
    wanted = ids.sparkSession.range(n_queries).select(F.col("id").cast("int").alias("query_id"))
    return wanted.join(ids, F.expr("rank = (7 + 13 * query_id) % n")).select("query_id", "series_id", F.expr("(100 + 37 * query_id) % (m - {0} + 1)".format(q)).alias("start"))


def indexed_part(points: DataFrame) -> DataFrame:
    """The points without every tenth series, from which out-of-distribution queries are cut."""
    ids = points.select("series_id").distinct().withColumn("rank", F.row_number().over(Window.orderBy("series_id")) - 1)
    return points.join(F.broadcast(ids.where("rank % 10 <> 9").select("series_id")), "series_id")
