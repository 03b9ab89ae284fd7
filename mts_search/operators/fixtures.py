"""The series families on the given tables, in Spark and in DuckDB SQL."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .series import CHANNEL_BLOCK, Fixture, build_series, rows_to_chunks

# Codes of event types, order priorities and roles as channels.
EVENT_TYPES = ("click", "error", "purchase", "signup", "view")
PRIORITIES = ("1-URGENT", "2-HIGH", "3-MEDIUM", "4-NOT SPECIFIED", "5-LOW")


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def cents(c: str):
    return F.round(F.col(c) * 100).cast("bigint")


def days_since(c: str, day: str):
    return F.datediff(F.col(c), F.lit(day).cast("date"))


def _lineitem(spark, sf_dir):
    return table(spark, sf_dir, "lineitem").select("l_suppkey", "l_quantity", "l_extendedprice", "l_discount", "l_tax", "l_shipdate", "l_returnflag")


def _supplier_channels() -> list:
    return [F.sum(F.col("l_quantity").cast("bigint")), F.expr("sum(cast(round(l_extendedprice * 100) as bigint)) div 100000"), F.sum(cents("l_discount")), F.sum(cents("l_tax")), F.count(F.lit(1))]


def supplier_chunks(spark: SparkSession, sf_dir: str, q: int, cumulative: bool = False) -> DataFrame:
    """Chunks of the weekly series of ``supplier``."""
    channels = [F.col("l_quantity").cast("bigint"), cents("l_extendedprice"), cents("l_discount"), cents("l_tax"), F.lit(1)]
    rows = _lineitem(spark, sf_dir).select(F.col("l_suppkey").cast("bigint").alias("series_id"), F.floor(days_since("l_shipdate", "1995-01-02") / 7).cast("bigint").alias("t"), *[c.alias(f"c{i}") for i, c in enumerate(channels)])
    return rows_to_chunks(rows, 2499 // 7, q, _in_thousands, cumulative)


def _in_thousands(x: np.ndarray) -> np.ndarray:
    """Sums of a supplier's channels with the price in thousands, cut towards zero."""
    x[1] = np.sign(x[1]) * (np.abs(x[1]) // 100000)
    return x


def supplier(spark: SparkSession, sf_dir: str, step: int = 7, cumulative: bool = False) -> DataFrame:
    channels = _supplier_channels()
    return build_series(_lineitem(spark, sf_dir), F.col("l_suppkey"), F.floor(days_since("l_shipdate", "1995-01-02") / step), channels, 2499 // step if step > 1 else 2499, cumulative=cumulative)


def event_line(spark: SparkSession, sf_dir: str, cumulative: bool = False) -> DataFrame:
    df = table(spark, sf_dir, "events").select("ts", "event_type", "value")
    t = F.floor(F.expr("timestampdiff(SECOND, timestamp_ntz'2024-01-01 00:00:00', ts)") / 300)
    channels = []
    for e in EVENT_TYPES:
        channels += [F.count_if(F.col("event_type") == e), F.coalesce(F.sum(F.when(F.col("event_type") == e, cents("value"))), F.lit(0))]
    return build_series(df, F.lit(0), t, channels, 8640, cumulative=cumulative)


def cohort_hour(spark: SparkSession, sf_dir: str, cumulative: bool = False) -> DataFrame:
    df = table(spark, sf_dir, "events").select("ts", "user_id", "value", "props")
    t = F.floor(F.expr("timestampdiff(SECOND, timestamp_ntz'2024-01-01 00:00:00', ts)") / 3600)
    k = F.get_json_object("props", "$.k").cast("bigint")
    return build_series(df, F.col("user_id") % 10, t, [F.count(F.lit(1)), F.sum(cents("value")), F.max(cents("value")), F.sum(k)], 720, cumulative=cumulative)


def nation_week(spark: SparkSession, sf_dir: str, cumulative: bool = False) -> DataFrame:
    orders = table(spark, sf_dir, "orders").select("o_custkey", "o_orderdate", "o_orderpriority", "o_totalprice")
    df = orders.join(table(spark, sf_dir, "customer").select("c_custkey", "c_nationkey"), F.col("o_custkey") == F.col("c_custkey"))
    channels = [F.expr(f"coalesce(sum(case when o_orderpriority = '{p}' then cast(round(o_totalprice * 100) as bigint) end), 0) div 100000") for p in PRIORITIES]
    return build_series(df, F.col("c_nationkey"), F.floor(days_since("o_orderdate", "1995-01-01") / 7), channels, 344, cumulative=cumulative)


def many_channels(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Series = return flag, channel = supplier: channels as rows, so their number may grow."""
    df = _lineitem(spark, sf_dir)
    code = F.when(F.col("l_returnflag") == "A", 0).when(F.col("l_returnflag") == "N", 1).otherwise(2)
    rows = df.groupBy(code.cast("bigint").alias("series_id"), (F.col("l_suppkey") - 1).cast("int").alias("channel"), F.floor(days_since("l_shipdate", "1995-01-02") / 7).alias("t")).agg(F.sum(F.col("l_quantity").cast("bigint")).alias("v"))
    last = rows.agg(F.max("channel")).first()[0]
    cells = rows.select("series_id").distinct().select("series_id", F.explode(F.sequence(F.lit(0), F.lit(last))).alias("channel")).select("series_id", "channel", F.explode(F.sequence(F.lit(0).cast("bigint"), F.lit(356).cast("bigint"))).alias("t"))
    return cells.join(rows, ["series_id", "channel", "t"], "left").select("series_id", "channel", "t", F.coalesce("v", F.lit(0)).alias("v"))


def many_channels_blocks(spark: SparkSession, sf_dir: str, q: int) -> DataFrame:
    """Chunks of the series of ``many_channels`` in rows of CHANNEL_BLOCK channels, so that no row grows with the suppliers."""
    return many_channels_chunks(spark, sf_dir, q, CHANNEL_BLOCK)


def many_channels_chunks(spark: SparkSession, sf_dir: str, q: int, block: int | None = None) -> DataFrame:
    """Chunks of the series of ``many_channels``: lines of (series, channel) come from one shuffle, then meet in their series.

    ``block``: channels of a row, which ``block_id`` numbers; all if not given.
    """
    df, weeks = _lineitem(spark, sf_dir), 357  # less than a chunk
    code = F.when(F.col("l_returnflag") == "A", 0).when(F.col("l_returnflag") == "N", 1).otherwise(2).cast("bigint")
    last, codes = df.agg(F.max("l_suppkey"), F.collect_set(code)).first()  # a series a code: three at most
    n = int(last or 0)
    if n <= 0:
        return spark.createDataFrame([], f"series_id bigint, chunk_id bigint, base_t bigint, n_core int, {'block_id bigint, ' if block else ''}vals array<array<double>>")
    key = code * n + F.col("l_suppkey").cast("bigint") - 1
    rows = df.where(F.col("l_suppkey").between(1, n)).select(key.alias("series_id"), F.floor(days_since("l_shipdate", "1995-01-02") / 7).cast("bigint").alias("t"), F.col("l_quantity").cast("bigint").alias("c0"))
    # a row of zero each, as a supplier without rows of a series is a line of zeros there
    zeros = spark.range(n).select(F.explode(F.array(*[F.lit(s) * n + F.col("id") for s in codes])).alias("series_id"), F.lit(0).cast("bigint").alias("t"), F.lit(0).cast("bigint").alias("c0"))
    lines = rows_to_chunks(rows.unionByName(zeros), weeks, q, n_series=n * len(codes)).select(F.floor(F.col("series_id") / n).alias("series_id"), F.struct(F.col("series_id").alias("line"), F.get("vals", F.lit(0)).alias("v")).alias("l"))
    own = [F.floor(F.col("l.line") % n / block).alias("block_id")] if block else []
    of = lines.groupBy("series_id", *own).agg(F.transform(F.array_sort(F.collect_list("l")), lambda x: x["v"]).alias("vals"))
    return of.select("series_id", F.lit(0).cast("bigint").alias("chunk_id"), F.lit(0).cast("bigint").alias("base_t"), F.lit(weeks - q + 1).alias("n_core"), *["block_id" for _ in own], "vals")


def embeddings(spark: SparkSession, sf_dir: str, channels: int = 1) -> DataFrame:
    width = 64 // channels
    df = table(spark, sf_dir, "embeddings").select("vec_id", F.posexplode("embedding").alias("p", "x"))
    return df.select(F.col("vec_id").alias("series_id"), F.floor(F.col("p") / width).cast("int").alias("channel"), (F.col("p") % width).cast("bigint").alias("t"), F.round(F.col("x").cast("double") * 1e6).cast("bigint").alias("v"))


def _text_points(df: DataFrame, entity: str, t: str, values: list) -> DataFrame:
    return df.select(F.col(entity).alias("series_id"), F.col(t).cast("bigint").alias("t"), F.posexplode(F.array(*[v.cast("bigint") for v in values])).alias("channel", "v")).select("series_id", F.col("channel").cast("int").alias("channel"), "t", "v")


def doc_lines(spark: SparkSession, sf_dir: str) -> DataFrame:
    df = table(spark, sf_dir, "documents").select("doc_id", F.posexplode(F.split("text", "\n")).alias("t", "line"))
    return _text_points(df, "doc_id", "t", [F.char_length("line"), F.regexp_count("line", F.lit("[^ ]+")), F.regexp_count("line", F.lit("[0-9]")), F.regexp_count("line", F.lit("[A-Z]"))])


def conv_turns(spark: SparkSession, sf_dir: str) -> DataFrame:
    df = table(spark, sf_dir, "conversations").withColumn("r", F.row_number().over(__import__("pyspark.sql", fromlist=["Window"]).Window.partitionBy("conv_id").orderBy("turn", "role", "text")) - 1)
    text = F.coalesce("text", F.lit(""))
    return _text_points(df, "conv_id", "r", [F.char_length(text), F.regexp_count(text, F.lit("[^ ]+")), F.when(F.col("role") == "user", 0).when(F.col("role") == "assistant", 1).otherwise(2)])


def walks(spark: SparkSession, n: int, channels: int = 64, m: int = 512, seed: int = 42) -> DataFrame:
    """Random walks: step deviation U[0,10], start U[0,100]; normals from a counter hash, no state, no rand()."""
    u = lambda *k: (F.pmod(F.xxhash64(*k, F.lit(seed)), F.lit(1 << 40)) + 0.5) / float(1 << 40)
    lines = spark.range(n).select(F.col("id").alias("series_id"), F.explode(F.sequence(F.lit(0), F.lit(channels - 1))).alias("channel"))
    lines = lines.withColumn("sd", 10 * u("series_id", "channel", F.lit("sd"))).withColumn("a", 100 * u("series_id", "channel", F.lit("start")))
    step = lambda t: F.sqrt(-2 * F.log(u("series_id", "channel", t, F.lit("r")))) * F.cos(2 * F.pi() * u("series_id", "channel", t, F.lit("phi")))
    steps = lines.withColumn("t", F.explode(F.sequence(F.lit(0).cast("bigint"), F.lit(m - 1).cast("bigint")))).withColumn("s", F.when(F.col("t") == 0, F.col("a")).otherwise(F.col("sd") * step(F.col("t"))))
    from pyspark.sql import Window

    return steps.select("series_id", "channel", "t", F.sum("s").over(Window.partitionBy("series_id", "channel").orderBy("t").rowsBetween(Window.unboundedPreceding, 0)).alias("v"))


# --- the same in DuckDB SQL ------------------------------------------------------------------------------------------


def _dense(entities: str, agg: str, channels: int, m: int, cumulative: bool) -> str:
    """Long points of wide aggregates ``agg`` (series_id, t, c0..) with empty cells as 0."""
    v = [f"coalesce(c{i}, 0)" for i in range(channels)]
    if cumulative:
        v = [f"sum({x}) over (partition by series_id order by t rows unbounded preceding)" for x in v]
    wide = f"select e.series_id, cal.t, {', '.join(f'a.c{i}' for i in range(channels))} from ({entities}) e cross join (select unnest(range(0, {m})) as t) cal left join ({agg}) a on a.series_id = e.series_id and a.t = cal.t"
    cols = ", ".join(f"cast({x} as bigint) as w{i}" for i, x in enumerate(v))
    return " union all ".join(f"select series_id, cast({i} as integer) as channel, cast(t as bigint) as t, w{i} as v from (select series_id, t, {cols} from ({wide}))" for i in range(channels))


def supplier_sql(step: int = 7, cumulative: bool = False) -> str:
    m = 2499 // step if step > 1 else 2499
    agg = f"select l_suppkey as series_id, cast(floor(datediff('day', date '1995-01-02', cast(l_shipdate as date)) / {step}) as bigint) as t, sum(cast(l_quantity as bigint)) as c0, sum(cast(round(l_extendedprice * 100) as bigint)) // 100000 as c1, sum(cast(round(l_discount * 100) as bigint)) as c2, sum(cast(round(l_tax * 100) as bigint)) as c3, count(*) as c4 from lineitem group by 1, 2"
    return _dense("select distinct l_suppkey as series_id from lineitem", agg, 5, m, cumulative)


def event_line_sql(cumulative: bool = False) -> str:
    cols = ", ".join(f"count(*) filter (where event_type = '{e}') as c{2 * i}, coalesce(sum(cast(round(value * 100) as bigint)) filter (where event_type = '{e}'), 0) as c{2 * i + 1}" for i, e in enumerate(EVENT_TYPES))
    agg = f"select cast(0 as bigint) as series_id, cast(floor(datediff('second', timestamp '2024-01-01', ts) / 300) as bigint) as t, {cols} from events group by 1, 2"
    return _dense("select cast(0 as bigint) as series_id", agg, 10, 8640, cumulative)


def cohort_hour_sql(cumulative: bool = False) -> str:
    agg = "select user_id % 10 as series_id, cast(floor(datediff('second', timestamp '2024-01-01', ts) / 3600) as bigint) as t, count(*) as c0, sum(cast(round(value * 100) as bigint)) as c1, max(cast(round(value * 100) as bigint)) as c2, sum(cast(props->>'$.k' as bigint)) as c3 from events group by 1, 2"
    return _dense("select distinct user_id % 10 as series_id from events", agg, 4, 720, cumulative)


def nation_week_sql(cumulative: bool = False) -> str:
    cols = ", ".join(f"coalesce(sum(cast(round(o_totalprice * 100) as bigint)) filter (where o_orderpriority = '{p}'), 0) // 100000 as c{i}" for i, p in enumerate(PRIORITIES))
    base = "orders join customer on o_custkey = c_custkey"
    agg = f"select cast(c_nationkey as bigint) as series_id, cast(floor(datediff('day', date '1995-01-01', cast(o_orderdate as date)) / 7) as bigint) as t, {cols} from {base} group by 1, 2"
    return _dense(f"select distinct cast(c_nationkey as bigint) as series_id from {base}", agg, 5, 344, cumulative)


def many_channels_sql() -> str:
    flag = "case l_returnflag when 'A' then 0 when 'N' then 1 else 2 end"
    return f"""select cast(e.series_id as bigint) as series_id, cast(ch.channel as integer) as channel, cast(cal.t as bigint) as t, cast(coalesce(a.v, 0) as bigint) as v
    from (select distinct {flag} as series_id from lineitem) e cross join (select unnest(range(0, (select max(l_suppkey) from lineitem))) as channel) ch cross join (select unnest(range(0, 357)) as t) cal
    left join (select {flag} as series_id, l_suppkey - 1 as channel, cast(floor(datediff('day', date '1995-01-02', cast(l_shipdate as date)) / 7) as bigint) as t, sum(cast(l_quantity as bigint)) as v from lineitem group by 1, 2, 3) a
    on a.series_id = e.series_id and a.channel = ch.channel and a.t = cal.t"""


def embeddings_sql(channels: int = 1) -> str:
    width = 64 // channels
    return f"select vec_id as series_id, cast((p - 1) // {width} as integer) as channel, cast((p - 1) % {width} as bigint) as t, cast(round(cast(embedding[p] as double) * 1e6) as bigint) as v from embeddings, (select unnest(range(1, 65)) as p)"


def doc_lines_sql() -> str:
    return """select series_id, cast(c as integer) as channel, t, cast(case c when 0 then length(line) when 1 then len(regexp_extract_all(line, '[^ ]+')) when 2 then len(regexp_extract_all(line, '[0-9]')) else len(regexp_extract_all(line, '[A-Z]')) end as bigint) as v
    from (select doc_id as series_id, cast(p - 1 as bigint) as t, lines[p] as line from (select doc_id, lines, unnest(range(1, len(lines) + 1)) as p from (select doc_id, string_split(text, chr(10)) as lines from documents))), (select unnest([0, 1, 2, 3]) as c)"""


def conv_turns_sql() -> str:
    return """select series_id, cast(c as integer) as channel, t, cast(case c when 0 then length(line) when 1 then len(regexp_extract_all(line, '[^ ]+')) else role end as bigint) as v
    from (select conv_id as series_id, row_number() over (partition by conv_id order by turn, role, text) - 1 as t, coalesce(text, '') as line, case role when 'user' then 0 when 'assistant' then 1 else 2 end as role from conversations), (select unnest([0, 1, 2]) as c)"""


FIXTURES = {
    "supplier_week": Fixture("supplier_week", supplier, supplier_sql(), 52, 5, "", "", chunks=supplier_chunks),
    "supplier_week_cum": Fixture("supplier_week_cum", lambda s, d: supplier(s, d, cumulative=True), supplier_sql(cumulative=True), 52, 5, "", "", chunks=lambda s, d, q: supplier_chunks(s, d, q, True)),
    "event_line": Fixture("event_line", event_line, event_line_sql(), 36, 10, "", ""),
    "cohort_hour": Fixture("cohort_hour", cohort_hour, cohort_hour_sql(), 120, 4, "", ""),
    "nation": Fixture("nation", nation_week, nation_week_sql(), 52, 5, "", ""),
    "many_channels": Fixture("many_channels", many_channels, many_channels_sql(), 52, 0, "", "", n_queries=1, chunks=many_channels_chunks),
    "many_channels_blocks": Fixture("many_channels_blocks", many_channels, many_channels_sql(), 52, 0, "", "", n_queries=1, chunks=many_channels_blocks),
    "embeddings": Fixture("embeddings", embeddings, embeddings_sql(), 13, 1, "", "", noise=1000),
    "embeddings_4x16": Fixture("embeddings_4x16", lambda s, d: embeddings(s, d, 4), embeddings_sql(4), 4, 4, "", "", noise=1000),
    "doc_lines": Fixture("doc_lines", doc_lines, doc_lines_sql(), 4, 4, "", ""),
    "conv_turns": Fixture("conv_turns", conv_turns, conv_turns_sql(), 2, 3, "", ""),
}


def knn_sql(points: str, q: int, k: int, n_queries: int = 2, noise: int = 1, channels: list[int] | None = None, normalized: bool = False, held_out: bool = False, radius: float | None = None, whole: bool = False) -> str:
    """Brute force: every window against every query, by a join on channel and offset."""
    some = f"where channel in ({', '.join(map(str, channels))})" if channels is not None else ""
    ids = f"select series_id, max(t) + 1 as m, row_number() over (order by series_id) - 1 as rank from pts group by 1 having max(t) + 1 >= {q}"
    if held_out:
        all_ids = "select series_id, row_number() over (order by series_id) - 1 as rank from (select distinct series_id from pts)"
        src = f"select series_id, m, row_number() over (order by series_id) - 1 as rank from ({ids}) where rank % 10 = 9"
        data = f"(select * from pts where series_id in (select series_id from ({all_ids}) where rank % 10 <> 9))"
    else:
        src, data = ids, "pts"
    head = f"""with pts as materialized ({points}), ids as ({src}), cut as (select q.j as query_id, ids.series_id, (100 + 37 * q.j) % (m - {q} + 1) as start from (select cast(unnest(range(0, {n_queries})) as integer) as j) q join ids on ids.rank = (7 + 13 * q.j) % (select count(*) from ids)),
    data as (select * from {data} {some}),
    qp as materialized (select cut.query_id, p.channel, p.t - cut.start as j, p.v + {noise} * (((((p.t * 7919 + p.channel * 104729 + cut.query_id * 31) % 5) + 5) % 5) - 2) as qv from (select * from pts {some}) p join cut on p.series_id = cut.series_id and p.t >= cut.start and p.t < cut.start + {q})"""
    full = f"having count(*) = {q} * (select count(distinct channel) from qp where qp.query_id = w.query_id)"
    if whole:
        head += f", whole as (select series_id from data group by 1 having max(t) + 1 = {q})"
    only = "and p.series_id in (select series_id from whole)" if whole else ""
    if normalized:
        stats = f""", ws as (select series_id, channel, t as start, avg(v) over w as mean, stddev_pop(v) over w as sd, count(*) over w as n from data window w as (partition by series_id, channel order by t rows between current row and {q - 1} following)),
        qs as (select query_id, channel, avg(qv) as mean, stddev_pop(qv) as sd from qp group by 1, 2)"""
        z = lambda v, s: f"(case when {s}.sd > 1e-12 then ({v} - {s}.mean) / {s}.sd else 0 end)"
        dist = f"""{stats}, w as (select qp.query_id, p.series_id, p.t - qp.j as start, sum(({z('p.v', 'ws')} - {z('qp.qv', 'qs')}) ** 2) as d2, count(*) as c from data p join qp on p.channel = qp.channel and p.t >= qp.j join ws on ws.series_id = p.series_id and ws.channel = p.channel and ws.start = p.t - qp.j and ws.n = {q} join qs on qs.query_id = qp.query_id and qs.channel = qp.channel group by 1, 2, 3)"""
        out, d2 = "round(sqrt(d2), 4) as distance", "round(sqrt(d2), 6)"
    else:
        dist = f", w as (select qp.query_id, p.series_id, p.t - qp.j as start, sum((p.v - qp.qv) * (p.v - qp.qv)) as d2, count(*) as c from data p join qp on p.channel = qp.channel and p.t >= qp.j {only} group by 1, 2, 3)"
        out, d2 = "cast(d2 as bigint) as d2, round(sqrt(d2), 4) as distance", "d2"
    cond = f"and sqrt(d2) < {radius}" if radius is not None else ""
    rank = f"rank <= {k}" if radius is None else "true"
    return f"""{head}{dist} select query_id, cast(rank as integer) as rank, cast(series_id as bigint) as series_id, cast(start as bigint) as start, {out} from (select *, row_number() over (partition by query_id order by {d2}, series_id, start) as rank from (select query_id, series_id, start, d2 from w where c = {q} * (select count(*) from (select distinct channel from qp)) {cond})) where {rank}"""
