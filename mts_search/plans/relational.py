"""Supporting relational operators on the series tables, each beside its SQL; both over whole tables."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..operators import fixtures as X
from ..operators.series import build_series
from .workloads import points_of

SW = X.supplier_sql()
Q = 52


def sw(spark, d) -> DataFrame:
    return points_of(spark, d, "supplier_week")


def gap_fill_zero(spark, d):
    return sw(spark, d).select("series_id", "channel", "t", "v")


def gap_fill_locf(spark, d):
    df = X.table(spark, d, "lineitem").select("l_suppkey", "l_quantity", "l_shipdate")
    return build_series(df, F.col("l_suppkey"), F.floor(X.days_since("l_shipdate", "1995-01-02") / 7), [F.sum(F.col("l_quantity").cast("bigint"))], 357, fill="locf").select("series_id", "t", "v")


LOCF_SQL = """with a as (select l_suppkey as series_id, cast(floor(datediff('day', date '1995-01-02', cast(l_shipdate as date)) / 7) as bigint) as t, cast(sum(cast(l_quantity as bigint)) as bigint) as v from lineitem group by 1, 2),
cal as (select series_id, cast(unnest(range(0, 357)) as bigint) as t from (select distinct series_id from a))
select series_id, t, coalesce(last_value(v ignore nulls) over (partition by series_id order by t rows unbounded preceding), 0) as v from cal left join a using (series_id, t)"""


def asof_align(spark, d):
    """For each order day of nation 7 the latest event day (mod 30) at or before it: union and last non-null, one shuffle."""
    customers = X.table(spark, d, "customer").where("c_nationkey = 7").select("c_custkey")
    orders = X.table(spark, d, "orders").select("o_orderkey", "o_custkey", (X.days_since("o_orderdate", "1995-01-01") % 30).alias("day")).join(F.broadcast(customers), F.col("o_custkey") == F.col("c_custkey"), "left_semi")
    events = X.table(spark, d, "events").where("event_type = 'purchase'").select(X.days_since("ts", "2024-01-01").alias("day"), "value", "event_id", (F.col("user_id") % 10).alias("g"))
    latest = events.groupBy("g", "day").agg(F.max("event_id").alias("event_id"))
    both = orders.select((F.col("o_orderkey") % 10).alias("g"), "day", "o_orderkey", F.lit(None).cast("bigint").alias("event_id"), F.lit(1).alias("side")).unionByName(latest.select("g", "day", F.lit(None).cast("bigint").alias("o_orderkey"), "event_id", F.lit(0).alias("side")))
    last = F.last("event_id", ignorenulls=True).over(Window.partitionBy("g").orderBy("day", "side").rowsBetween(Window.unboundedPreceding, 0))
    return both.withColumn("event_id", last).where("side = 1").select("o_orderkey", "day", "event_id")


ASOF_SQL = """with o as (select o_orderkey, o_orderkey % 10 as g, datediff('day', date '1995-01-01', cast(o_orderdate as date)) % 30 as day from orders join customer on o_custkey = c_custkey where c_nationkey = 7),
e as (select user_id % 10 as g, datediff('day', date '2024-01-01', cast(ts as date)) as day, max(event_id) as event_id from events where event_type = 'purchase' group by 1, 2)
select o_orderkey, cast(o.day as integer) as day, e.event_id from o asof left join e on o.g = e.g and o.day >= e.day"""


def rolling_stats(spark, d):
    w = Window.partitionBy("series_id").orderBy("t").rowsBetween(0, Q - 1)
    p = sw(spark, d).where("channel = 0").select("series_id", F.col("t").alias("start"), F.avg("v").over(w).alias("m"), F.stddev_pop("v").over(w).alias("s"), F.count(F.lit(1)).over(w).alias("n"))
    return p.where(f"n = {Q}").select("series_id", "start", F.round("m", 4).alias("mean"), F.round("s", 4).alias("sd"))


ROLL_SQL = f"select series_id, t as start, round(m, 4) as mean, round(s, 4) as sd from (select series_id, t, avg(v) over w as m, stddev_pop(v) over w as s, count(*) over w as n from ({SW}) where channel = 0 window w as (partition by series_id order by t rows between current row and {Q - 1} following)) where n = {Q}"


def zscore_windows(spark, d):
    starts = spark.createDataFrame([(1, 10), (2, 100), (3, 200)], "series_id bigint, start bigint")
    p = sw(spark, d).where("channel = 0").join(F.broadcast(starts), "series_id").where(f"t >= start and t < start + {Q}")
    w = Window.partitionBy("series_id", "start")
    return p.select("series_id", "start", (F.col("t") - F.col("start")).alias("j"), F.round((F.col("v") - F.avg("v").over(w)) / F.stddev_pop("v").over(w), 4).alias("z"))


ZSCORE_SQL = f"select series_id, start, t - start as j, round((v - avg(v) over (partition by series_id, start)) / stddev_pop(v) over (partition by series_id, start), 4) as z from ({SW}) join (values (1, 10), (2, 100), (3, 200)) s(id, start) on series_id = id where channel = 0 and t >= start and t < start + {Q}"


def _window_sums(p: DataFrame, keys: list[str], **terms) -> DataFrame:
    """For each window of Q steps from ``t`` the sums of the terms, as differences of running sums: linear in the steps."""
    w = Window.partitionBy(*keys).orderBy("t")
    run = p.select(*keys, "t", *[F.sum(x).over(w.rowsBetween(Window.unboundedPreceding, 0)).alias(n) for n, x in terms.items()])
    ends = run.select(*keys, "t", *[(F.lead(n, Q - 1).over(w) - F.coalesce(F.lag(n).over(w), F.lit(0))).alias(n) for n in terms])
    return ends.where(F.col(next(iter(terms))).isNotNull())


def sliding_dft(spark, d):
    """Bins 1-3 of every window of every supplier: window sums of modulated values, turned by the start."""
    p = sw(spark, d).where("channel = 0")
    a = lambda b: F.lit(2 * math.pi * b / Q) * F.col("t")
    s = _window_sums(p, ["series_id"], **{f"{n}{b}": F.col("v") * f(a(b)) for b in (1, 2, 3) for n, f in (("c", F.cos), ("s", F.sin))})
    of = lambda b: F.struct(F.lit(b).alias("bin"), F.round(F.col(f"c{b}") * F.cos(a(b)) + F.col(f"s{b}") * F.sin(a(b)), 3).alias("re"), F.round(F.col(f"c{b}") * F.sin(a(b)) - F.col(f"s{b}") * F.cos(a(b)), 3).alias("im"))
    out = s.select("series_id", F.col("t").alias("start"), F.inline(F.array(*[of(b) for b in (1, 2, 3)])))
    return out.select("series_id", "start", "bin", (F.col("re") + 0.0).alias("re"), (F.col("im") + 0.0).alias("im"))


DFT_SQL = " union all ".join(
    f"select p.series_id, s.start, cast({b} as integer) as bin, round(sum(v * cos({2 * math.pi * b / Q!r} * (t - s.start))), 3) + 0.0 as re, round(-sum(v * sin({2 * math.pi * b / Q!r} * (t - s.start))), 3) + 0.0 as im from (select * from ({SW}) where channel = 0) p join (select unnest(range(0, {357 - Q + 1})) as start) s on p.t >= s.start and p.t < s.start + {Q} group by 1, 2" for b in (1, 2, 3)
)

#: Windows in the sample whose pairs show the bins' shares of distance and the bounds.
SAMPLE = 100


def _weight() -> F.Column:
    return F.when((F.col("bin") == 0) | (F.col("bin") == Q // 2), 1.0).otherwise(2.0)


def _with_bins(p: DataFrame) -> DataFrame:
    return p.withColumn("bin", F.explode(F.sequence(F.lit(0), F.lit(Q // 2))))


def _sample(p: DataFrame) -> DataFrame:
    """(series_id, start) of ``SAMPLE`` windows drawn by a multiplicative hash among every start of every series."""
    span = p.groupBy("series_id").agg(F.min("t").alias("a"), (F.max("t") - Q + 1).alias("b")).where("b >= a")
    every = span.select("series_id", F.explode(F.sequence("a", "b")).alias("start"))
    return every.orderBy((F.col("series_id") * 7919 + F.col("start") * 104729) % 10007, "series_id", "start").limit(SAMPLE)


def _spectra(spark, d) -> DataFrame:
    """(series_id, start, id, channel, bin, re, im, weight) of the sampled windows, all bins."""
    p = sw(spark, d)
    b = _with_bins(p.join(F.broadcast(_sample(p)), "series_id").where(f"t >= start and t < start + {Q}"))
    a = F.lit(2 * math.pi / Q) * F.col("bin") * (F.col("t") - F.col("start"))
    s = b.groupBy("series_id", "start", "channel", "bin").agg(F.sum(F.col("v") * F.cos(a)).alias("re"), (-F.sum(F.col("v") * F.sin(a))).alias("im"))
    return s.withColumn("weight", _weight()).withColumn("id", F.col("series_id") * 1000 + F.col("start"))


_SPEC_SQL = f"""with p as materialized ({SW}), span as (select series_id, min(t) as a, max(t) - {Q - 1} as b from p group by 1), every as (select series_id, cast(unnest(range(a, b + 1)) as bigint) as start from span),
picked as materialized (select * from every order by (series_id * 7919 + start * 104729) % 10007, series_id, start limit {SAMPLE}), b as (select unnest(range(0, {Q // 2 + 1})) as bin),
spec as materialized (select series_id * 1000 + start as id, channel, cast(bin as integer) as bin, sum(v * cos({2 * math.pi / Q!r} * bin * (t - start))) as re, -sum(v * sin({2 * math.pi / Q!r} * bin * (t - start))) as im, case when bin in (0, {Q // 2}) then 1.0 else 2.0 end as weight from p join picked using (series_id), b where t >= start and t < start + {Q} group by series_id, start, channel, b.bin)"""


def energy_by_bin(spark, d):
    """Mean share of a window's energy by bin over every window of every series; all bins together hold Q times the sum of squares."""
    a = F.lit(2 * math.pi / Q) * F.col("bin") * F.col("t")
    e = _window_sums(_with_bins(sw(spark, d).repartition("series_id", "channel")), ["series_id", "channel", "bin"], c=F.col("v") * F.cos(a), s=F.col("v") * F.sin(a), own=F.col("v") * F.col("v"))
    part = _weight() * (F.col("c") ** 2 + F.col("s") ** 2) / F.nullif(F.col("own") * F.lit(float(Q)), F.lit(0.0))
    share = e.groupBy("channel", "bin").agg(F.avg(part).alias("share"))
    run = F.sum("share").over(Window.partitionBy("channel").orderBy(F.desc("share"), "bin").rowsBetween(Window.unboundedPreceding, 0))
    return share.select("channel", "bin", F.round("share", 5).alias("share"), F.round(run, 5).alias("cumulative"))


ENERGY_SQL = f"""with p as materialized ({SW}), b as (select unnest(range(0, {Q // 2 + 1})) as bin),
e as (select channel, cast(bin as integer) as bin, sum(v * cos({2 * math.pi / Q!r} * bin * t)) over w as c, sum(v * sin({2 * math.pi / Q!r} * bin * t)) over w as s, sum(v * v) over w as own, count(*) over w as n from p, b window w as (partition by series_id, channel, bin order by t rows between current row and {Q - 1} following)),
s as (select channel, bin, avg(case when bin in (0, {Q // 2}) then 1.0 else 2.0 end * (c * c + s * s) / nullif(cast(own as double) * {Q}, 0)) as share from e where n = {Q} group by 1, 2)
select channel, bin, round(share, 5) as share, round(sum(share) over (partition by channel order by share desc, bin rows unbounded preceding), 5) as cumulative from s"""


def _pair_shares(spark, d) -> DataFrame:
    s = _spectra(spark, d)
    a, b = s.alias("a"), s.alias("b")
    pairs = a.join(b, (F.col("a.channel") == F.col("b.channel")) & (F.col("a.bin") == F.col("b.bin")) & (F.col("a.id") < F.col("b.id")))
    e = pairs.select(F.col("a.id").alias("i"), F.col("b.id").alias("k"), F.col("a.channel").alias("channel"), F.col("a.bin").alias("bin"), (F.col("a.weight") * ((F.col("a.re") - F.col("b.re")) ** 2 + (F.col("a.im") - F.col("b.im")) ** 2)).alias("e"))
    return e.withColumn("share", F.col("e") / F.nullif(F.sum("e").over(Window.partitionBy("i", "k", "channel")), F.lit(0.0))).groupBy("channel", "bin").agg(F.avg("share").alias("share"))


_ARDC = f"{_SPEC_SQL}, x as (select a.id as i, b.id as k, a.channel, a.bin, a.weight * ((a.re - b.re) ** 2 + (a.im - b.im) ** 2) as e from spec a join spec b on a.channel = b.channel and a.bin = b.bin and a.id < b.id), s as (select channel, bin, avg(share) as share from (select *, e / nullif(sum(e) over (partition by i, k, channel), 0) as share from x) group by 1, 2)"


def ardc_by_bin(spark, d):
    return _pair_shares(spark, d).select("channel", "bin", F.round("share", 5).alias("share"))


def ardc_selected_bins(spark, d):
    s = _pair_shares(spark, d)
    before = F.coalesce(F.sum("share").over(Window.partitionBy("channel").orderBy(F.desc("share"), "bin").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0.0))
    return s.withColumn("before", before).where("before < 0.6").select("channel", "bin")


SELECTED_SQL = f"{_ARDC} select channel, bin from (select *, coalesce(sum(share) over (partition by channel order by share desc, bin rows between unbounded preceding and 1 preceding), 0) as before from s) where before < 0.6"


def _bound_pairs(spark, d, pivot: bool) -> DataFrame:
    """Bound from bins 0-3 against the true squared distance of window pairs (Parseval: all bins give it exactly)."""
    s = _spectra(spark, d).where("channel = 0")
    a, b = s.alias("a"), s.alias("b")
    e = a.join(b, (F.col("a.bin") == F.col("b.bin")) & (F.col("a.id") < F.col("b.id"))).select(F.col("a.id").alias("i"), F.col("b.id").alias("k"), F.col("a.bin").alias("bin"), (F.col("a.weight") * ((F.col("a.re") - F.col("b.re")) ** 2 + (F.col("a.im") - F.col("b.im")) ** 2) / Q).alias("e"))
    out = e.groupBy("i", "k").agg(F.sum(F.when(F.col("bin") <= 3, F.col("e")).otherwise(0.0)).alias("lb2"), F.sum("e").alias("d2"))
    if pivot:  # pivot = mean remainder; its distance to each remainder, from the bins left out
        rest = s.where("bin > 3")
        mean = rest.groupBy("bin").agg(F.avg("re").alias("mr"), F.avg("im").alias("mi"))
        gap = rest.join(F.broadcast(mean), "bin").groupBy("id").agg(F.sqrt(F.sum(F.col("weight") * ((F.col("re") - F.col("mr")) ** 2 + (F.col("im") - F.col("mi")) ** 2)) / Q).alias("g"))
        out = out.join(F.broadcast(gap.select(F.col("id").alias("i"), F.col("g").alias("g1"))), "i").join(F.broadcast(gap.select(F.col("id").alias("k"), F.col("g").alias("g2"))), "k").withColumn("lb2", F.col("lb2") + (F.col("g1") - F.col("g2")) ** 2)
    return out.select("i", "k", F.round("lb2", 3).alias("lb2"), F.round("d2", 3).alias("d2"), F.round(F.sqrt(F.col("lb2") / F.nullif(F.col("d2"), F.lit(0.0))), 4).alias("tightness"))


def _bound_sql(pivot: bool) -> str:
    base = f"{_SPEC_SQL}, z as (select * from spec where channel = 0), e as (select a.id as i, b.id as k, a.bin, a.weight * ((a.re - b.re) ** 2 + (a.im - b.im) ** 2) / {Q} as e from z a join z b on a.bin = b.bin and a.id < b.id), o as (select i, k, sum(case when bin <= 3 then e else 0 end) as lb2, sum(e) as d2 from e group by 1, 2)"
    if pivot:
        base += f", m as (select bin, avg(re) as mr, avg(im) as mi from z where bin > 3 group by 1), g as (select id, sqrt(sum(weight * ((re - mr) ** 2 + (im - mi) ** 2)) / {Q}) as g from z join m using (bin) group by 1), o2 as (select o.i, o.k, lb2 + (g1.g - g2.g) ** 2 as lb2, d2 from o join g g1 on g1.id = o.i join g g2 on g2.id = o.k)"
    return f"{base} select i, k, round(lb2, 3) as lb2, round(d2, 3) as d2, round(sqrt(lb2 / nullif(d2, 0)), 4) as tightness from {'o2' if pivot else 'o'}"


#: Columns of lineitem in whole numbers, in Spark and in SQL.
_COUNTED = ("cast(l_quantity as bigint)", "cast(floor(l_extendedprice / 100) as bigint)", "cast(round(l_discount * 100) as bigint)", "cast(round(l_tax * 100) as bigint)")
#: Variance of such a column relative to its squared mean, from exact sums.
_SPREAD = "cast(count(*) as double) * cast(sum({0} * {0}) as double) / (cast(sum({0}) as double) * cast(sum({0}) as double)) - 1"


def tile_splits(spark, d):
    """Softmax weight of four line columns by their spread, and the parts each is cut into for tiles of 15 lines."""
    one = X.table(spark, d, "lineitem").agg(F.count(F.lit(1)).alias("n"), *[F.expr(_SPREAD.format(c)).alias(f"s{i}") for i, c in enumerate(_COUNTED)])
    df = one.select("n", F.posexplode(F.array(*[f"s{i}" for i in range(len(_COUNTED))])).alias("dim", "s"))
    e = df.withColumn("e", F.exp(F.col("s") - F.max("s").over(Window.partitionBy())))
    w = e.withColumn("weight", F.col("e") / F.sum("e").over(Window.partitionBy()))
    return w.select("dim", F.round("weight", 6).alias("weight"), F.ceil(F.pow(F.col("n") / F.lit(15.0), F.col("weight"))).cast("bigint").alias("splits"))


TILE_SQL = f"""with o as (select count(*) as n, {', '.join(f'{_SPREAD.format(c)} as s{i}' for i, c in enumerate(_COUNTED))} from lineitem), v as ({' union all '.join(f'select {i} as dim, n, s{i} as s from o' for i in range(len(_COUNTED)))}),
e as (select dim, n, exp(s - (select max(s) from v)) as e from v) select cast(dim as integer) as dim, round(e / sum(e) over (), 6) as weight, cast(ceil(pow(n / 15.0e0, e / sum(e) over ())) as bigint) as splits from e"""


def _labelled(spark, d) -> DataFrame:
    """Window means and deviations with an ntile(8) of the mean and an ntile(4) of the deviation within it."""
    p = rolling_stats(spark, d)
    p = p.withColumn("a", F.ntile(8).over(Window.orderBy("mean", "series_id", "start")))
    return p.withColumn("b", F.ntile(4).over(Window.partitionBy("a").orderBy("sd", "series_id", "start")))


_LABEL_SQL = f"with r as ({ROLL_SQL}), l1 as (select *, ntile(8) over (order by mean, series_id, start) as a from r), l as (select *, ntile(4) over (partition by a order by sd, series_id, start) as b from l1)"


def ntile_tiles(spark, d):
    return _labelled(spark, d).select("series_id", "start", F.col("a").cast("bigint").alias("a"), F.col("b").cast("bigint").alias("b"))


def _islands(df: DataFrame) -> DataFrame:
    w = Window.partitionBy("series_id", "a").orderBy("start")
    return df.withColumn("island", F.col("start") - F.row_number().over(w)).groupBy("series_id", "a", "island").agg(F.min("start").alias("first_start"), F.max("start").alias("last_start"), F.count(F.lit(1)).alias("n_windows"), F.min("mean").alias("lo_mean"), F.max("mean").alias("hi_mean"), F.min("sd").alias("lo_sd"), F.max("sd").alias("hi_sd"))


_ISLAND_SQL = f"{_LABEL_SQL}, i as (select *, start - row_number() over (partition by series_id, a order by start) as island from l), r2 as (select series_id, a, min(start) as first_start, max(start) as last_start, count(*) as n_windows, min(mean) as lo_mean, max(mean) as hi_mean, min(sd) as lo_sd, max(sd) as hi_sd from i group by series_id, a, island)"


def islands_runs(spark, d):
    return _islands(_labelled(spark, d)).select("series_id", F.col("a").cast("bigint").alias("a"), "first_start", "last_start", "n_windows")


def leaf_boxes(spark, d):
    return _islands(_labelled(spark, d)).select("series_id", F.col("a").cast("bigint").alias("a"), "first_start", "lo_mean", "hi_mean", "lo_sd", "hi_sd")


def box_range_filter(spark, d):
    return _islands(_labelled(spark, d)).where("lo_mean <= 60 and hi_mean >= 40 and lo_sd <= 40 and hi_sd >= 20").select("series_id", "first_start", "last_start")


def compression_stats(spark, d):
    return _islands(_labelled(spark, d)).agg(F.count(F.lit(1)).alias("runs"), F.sum("n_windows").alias("windows"), F.min("n_windows").alias("least"), F.max("n_windows").alias("most"), F.round(F.avg("n_windows"), 4).alias("mean"))


def interval_join_windows(spark, d):
    """Orders of nation 7 by week beside the number of runs, of all suppliers, whose windows cover the week."""
    weeks = _islands(_labelled(spark, d)).select(F.explode(F.sequence("first_start", F.col("last_start") + Q - 1)).alias("week")).groupBy("week").agg(F.count(F.lit(1)).alias("n_runs"))
    customers = X.table(spark, d, "customer").where("c_nationkey = 7").select("c_custkey")
    orders = X.table(spark, d, "orders").join(F.broadcast(customers), F.col("o_custkey") == F.col("c_custkey"), "left_semi").select("o_orderkey", F.floor(X.days_since("o_orderdate", "1995-01-02") / 7).alias("week"))
    return orders.join(F.broadcast(weeks), "week").groupBy("o_orderkey").agg(F.sum("n_runs").alias("n_runs"))


INTERVAL_SQL = f"{_ISLAND_SQL}, o as (select o_orderkey, floor(datediff('day', date '1995-01-02', cast(o_orderdate as date)) / 7) as week from orders join customer on o_custkey = c_custkey where c_nationkey = 7) select o_orderkey, count(*) as n_runs from o join r2 on week >= first_start and week <= last_start + {Q - 1} group by 1"


def semi_join_candidates(spark, d):
    nation = X.table(spark, d, "nation").where("n_regionkey = 1").select("n_nationkey")
    ids = X.table(spark, d, "supplier").join(F.broadcast(nation), F.col("s_nationkey") == F.col("n_nationkey"), "left_semi").select(F.col("s_suppkey").alias("series_id"))
    return rolling_stats(spark, d).join(F.broadcast(ids), "series_id", "left_semi").select("series_id", "start")


def anti_join_gaps(spark, d):
    seen = X.table(spark, d, "lineitem").select(F.col("l_suppkey").alias("series_id"), F.floor(X.days_since("l_shipdate", "1995-01-02") / 7).alias("t")).distinct()
    cal = seen.select("series_id").distinct().select("series_id", F.explode(F.sequence(F.lit(0).cast("bigint"), F.lit(356).cast("bigint"))).alias("t"))
    return cal.join(seen, ["series_id", "t"], "left_anti")


GAPS_SQL = "with s as (select distinct l_suppkey as series_id, cast(floor(datediff('day', date '1995-01-02', cast(l_shipdate as date)) / 7) as bigint) as t from lineitem) select * from (select series_id, cast(unnest(range(0, 357)) as bigint) as t from (select distinct series_id from s)) except select * from s"


def _report_rows(spark, d) -> DataFrame:
    s = X.table(spark, d, "supplier").join(F.broadcast(X.table(spark, d, "nation")), F.col("s_nationkey") == F.col("n_nationkey")).select(F.col("s_suppkey").alias("series_id"), F.col("n_regionkey").alias("region"), F.col("n_nationkey").alias("nation"))
    return sw(spark, d).where("channel = 0").join(F.broadcast(s), "series_id").withColumn("year", F.floor(F.col("t") / 52))


def _report(kind: str):
    def run(spark, d):
        r = _report_rows(spark, d)
        keys = [F.col("region"), F.col("nation"), F.col("year")]
        g = r.rollup(*keys) if kind == "rollup" else r.cube(F.col("region"), F.col("year")) if kind == "cube" else r.groupingSets([[F.col("region"), F.col("year")], [F.col("nation")], []], F.col("region"), F.col("year"), F.col("nation"))
        cols = ["region", "year"] if kind == "cube" else ["region", "nation", "year"]
        return g.agg(F.count(F.lit(1)).alias("n"), F.sum("v").alias("total"), F.grouping_id().cast("bigint").alias("level")).select(*cols, "n", "total", "level")

    base = f"(select r.*, n_regionkey as region, n_nationkey as nation, cast(t // 52 as bigint) as year from ({SW}) r join supplier on s_suppkey = series_id join nation on n_nationkey = s_nationkey where channel = 0)"
    by = {"rollup": "rollup (region, nation, year)", "cube": "cube (region, year)", "sets": "grouping sets ((region, year), (nation), ())"}[kind]
    ids = {"rollup": "region, nation, year", "cube": "region, year", "sets": "region, year, nation"}[kind]
    cols = "region, year" if kind == "cube" else "region, nation, year"
    return run, f"select {cols}, count(*) as n, cast(sum(v) as bigint) as total, grouping_id({ids}) as level from {base} group by {by}"


def pivot_channels(spark, d):
    e = X.table(spark, d, "events").select(F.floor(F.expr("timestampdiff(SECOND, timestamp_ntz'2024-01-01 00:00:00', ts)") / 3600).alias("hour"), "event_type")
    return e.groupBy("hour").pivot("event_type", list(X.EVENT_TYPES)).count().fillna(0)


_HOUR = "cast(floor(datediff('second', timestamp '2024-01-01', ts) / 3600) as bigint)"
PIVOT_SQL = f"select {_HOUR} as hour, {', '.join(f'''count(*) filter (where event_type = '{e}') as {e}''' for e in X.EVENT_TYPES)} from events group by 1"


def unpivot_channels(spark, d):
    return pivot_channels(spark, d).unpivot("hour", list(X.EVENT_TYPES), "channel", "n")


UNPIVOT_SQL = f"unpivot ({PIVOT_SQL}) on {', '.join(X.EVENT_TYPES)} into name channel value n"


def tumbling_channels(spark, d):
    e = X.table(spark, d, "events").withColumn("ts", F.col("ts").cast("timestamp"))
    return e.groupBy(F.window("ts", "1 hour"), "event_type").agg(F.count(F.lit(1)).alias("n")).select(F.unix_seconds("window.start").alias("start_s"), "event_type", "n")


def sliding_channels(spark, d):
    e = X.table(spark, d, "events").withColumn("ts", F.col("ts").cast("timestamp"))
    return e.groupBy(F.window("ts", "1 hour", "30 minutes")).agg(F.count(F.lit(1)).alias("n")).select(F.unix_seconds("window.start").alias("start_s"), "n")


def session_lengths(spark, d):
    e = X.table(spark, d, "events").withColumn("ts", F.col("ts").cast("timestamp"))
    return e.groupBy("user_id", F.session_window("ts", "6 hours")).agg(F.count(F.lit(1)).alias("n")).select("user_id", F.unix_seconds("session_window.start").alias("start_s"), "n")


TUMBLE_SQL = "select cast(epoch(time_bucket(interval '1 hour', ts)) as bigint) as start_s, event_type, count(*) as n from events group by 1, 2"
SLIDE_SQL = "select s as start_s, count(*) as n from (select unnest([cast(floor(epoch(ts) / 1800) as bigint) * 1800, cast(floor(epoch(ts) / 1800) as bigint) * 1800 - 1800]) as s from events) group by 1"
SESSION_SQL = "with e as (select user_id, ts, case when ts >= lag(ts) over (partition by user_id order by ts) + interval '6 hours' or lag(ts) over (partition by user_id order by ts) is null then 1 else 0 end as new from events), s as (select *, sum(new) over (partition by user_id order by ts rows unbounded preceding) as k from e) select user_id, cast(floor(epoch(min(ts))) as bigint) as start_s, count(*) as n from s group by user_id, k"


def set_ops_windows(spark, d):
    top = lambda c: sw(spark, d).where(f"channel = {c}").groupBy("series_id").agg(F.sum("v").alias("v")).orderBy(F.desc("v"), "series_id").limit(20).select("series_id")
    a, b = top(0), top(1)
    tag = lambda df, name: df.select("series_id", F.lit(name).alias("op"))
    return tag(a.union(b).distinct(), "union").union(tag(a.intersect(b), "intersect")).union(tag(a.exceptAll(b), "except"))


SETS_SQL = f"with p as materialized ({SW}), a as (select series_id from p where channel = 0 group by 1 order by sum(v) desc, 1 limit 20), b as (select series_id from p where channel = 1 group by 1 order by sum(v) desc, 1 limit 20) select series_id, 'union' as op from (select * from a union select * from b) union all select series_id, 'intersect' from (select * from a intersect select * from b) union all select series_id, 'except' from (select * from a except select * from b)"


def lag_lead_trend(spark, d):
    w = Window.partitionBy("series_id", "channel").orderBy("t")
    p = sw(spark, d).withColumn("d", F.col("v") - F.lag("v").over(w)).withColumn("e", F.lead("v").over(w) - F.col("v"))
    return p.groupBy("series_id", "channel").agg(F.count_if((F.col("d") > 0) & (F.col("e") < 0)).alias("peaks"), F.sum(F.abs("d")).alias("path"))


TREND_SQL = f"select series_id, channel, count(*) filter (where d > 0 and e < 0) as peaks, cast(sum(abs(d)) as bigint) as path from (select *, v - lag(v) over w as d, lead(v) over w - v as e from ({SW}) window w as (partition by series_id, channel order by t)) group by 1, 2"


def distinct_counts(spark, d):
    return sw(spark, d).withColumn("bucket", F.floor(F.col("v") / 50)).groupBy("channel", "bucket").agg(F.countDistinct("series_id").alias("suppliers"))


def percentile_channels(spark, d):
    return sw(spark, d).groupBy("channel").agg(*[F.round(F.percentile("v", p), 4).alias(n) for p, n in ((0.05, "p05"), (0.5, "p50"), (0.95, "p95"))])


PCT_SQL = f"select channel, round(quantile_cont(v, 0.05), 4) as p05, round(quantile_cont(v, 0.5), 4) as p50, round(quantile_cont(v, 0.95), 4) as p95 from ({SW}) group by 1"


def array_distance(spark, d):
    v = X.table(spark, d, "embeddings").select("vec_id", F.transform("embedding", lambda x: x.cast("double")).alias("e"))
    base = v.where("vec_id = 0").select(F.col("e").alias("b"))
    dist = F.sqrt(F.aggregate(F.zip_with("e", "b", lambda x, y: (x - y) * (x - y)), F.lit(0.0), lambda s, x: s + x))
    return v.crossJoin(F.broadcast(base)).select("vec_id", F.round(dist, 4).alias("distance"))


ARRAY_SQL = "select a.vec_id, round(sqrt(list_sum([(cast(z[1] as double) - cast(z[2] as double)) ** 2 for z in list_zip(a.embedding, b.embedding)])), 4) as distance from embeddings a, embeddings b where b.vec_id = 0"


def cross_corr_channels(spark, d):
    wide = sw(spark, d).groupBy("series_id", "t").pivot("channel", [0, 1, 2, 3, 4]).agg(F.first("v"))
    pairs = [(a, b) for a in range(5) for b in range(a + 1, 5)]
    got = wide.agg(*[F.corr(str(a), str(b)).alias(f"c{a}{b}") for a, b in pairs])
    return got.select(F.inline(F.array(*[F.struct(F.lit(a).alias("a"), F.lit(b).alias("b"), F.round(f"c{a}{b}", 4).alias("corr")) for a, b in pairs])))


CORR_SQL = f"select cast(x.channel as integer) as a, cast(y.channel as integer) as b, round(corr(x.v, y.v), 4) as corr from ({SW}) x join ({SW}) y on x.series_id = y.series_id and x.t = y.t and x.channel < y.channel group by 1, 2"


def json_props_channel(spark, d):
    return X.table(spark, d, "events").groupBy(F.floor(F.expr("timestampdiff(SECOND, timestamp_ntz'2024-01-01 00:00:00', ts)") / 3600).alias("hour")).agg(F.sum(F.get_json_object("props", "$.k").cast("bigint")).alias("k"))


def string_doc_channels(spark, d):
    t = F.col("text")
    return X.table(spark, d, "documents").select("doc_id", F.size(F.split(t, "\n")).alias("lines"), F.char_length(t).alias("chars"), F.regexp_count(t, F.lit("[^ \n]+")).alias("words"), F.regexp_count(t, F.lit("[0-9]")).alias("digits"))


DOC_SQL = "select doc_id, cast(len(string_split(text, chr(10))) as integer) as lines, cast(length(text) as integer) as chars, cast(len(regexp_extract_all(text, '[^ \\n]+')) as integer) as words, cast(len(regexp_extract_all(text, '[0-9]')) as integer) as digits from documents"

BUILD, COSTS_INDEX, COSTS_SCAN = 40.0, 0.05, 1.0


def amortized_cost(spark, d):
    """Running cost of index (build + queries) and scan by week, a query an order, and whether the index is ahead by then."""
    run = Window.orderBy("i").rowsBetween(Window.unboundedPreceding, 0)
    q = X.table(spark, d, "orders").groupBy(F.floor(X.days_since("o_orderdate", "1995-01-01") / 7).alias("i")).agg(F.count(F.lit(1)).alias("n"))
    c = q.withColumn("n", F.sum("n").over(run)).select("i", (F.lit(BUILD) + F.lit(COSTS_INDEX) * F.col("n")).alias("a"), (F.lit(COSTS_SCAN) * F.col("n")).alias("b"))
    return c.select("i", F.round("a", 4).alias("index_cost"), F.round("b", 4).alias("scan_cost"), (F.col("a") < F.col("b")).alias("ahead"))


AMORT_SQL = f"""with w as (select cast(floor(datediff('day', date '1995-01-01', cast(o_orderdate as date)) / 7) as bigint) as i, count(*) as n from orders group by 1), c as (select i, sum(n) over (order by i rows unbounded preceding) as n from w)
select i, round({BUILD}e0 + {COSTS_INDEX}e0 * n, 4) as index_cost, round({COSTS_SCAN}e0 * n, 4) as scan_cost, {BUILD}e0 + {COSTS_INDEX}e0 * n < {COSTS_SCAN}e0 * n as ahead from c"""

_ALL = {
    "gap_fill_zero": (gap_fill_zero, SW), "gap_fill_locf": (gap_fill_locf, LOCF_SQL), "asof_align": (asof_align, ASOF_SQL), "rolling_stats": (rolling_stats, ROLL_SQL), "zscore_windows": (zscore_windows, ZSCORE_SQL), "sliding_dft": (sliding_dft, DFT_SQL),
    "energy_by_bin": (energy_by_bin, ENERGY_SQL), "ardc_by_bin": (ardc_by_bin, f"{_ARDC} select channel, bin, round(share, 5) as share from s"), "ardc_selected_bins": (ardc_selected_bins, SELECTED_SQL),
    "lower_bound_pairs": (lambda s, d: _bound_pairs(s, d, False), _bound_sql(False)), "pivot_bound_pairs": (lambda s, d: _bound_pairs(s, d, True), _bound_sql(True)), "tile_splits": (tile_splits, TILE_SQL),
    "ntile_tiles": (ntile_tiles, f"{_LABEL_SQL} select series_id, start, a, b from l"), "islands_runs": (islands_runs, f"{_ISLAND_SQL} select series_id, a, first_start, last_start, n_windows from r2"), "leaf_boxes": (leaf_boxes, f"{_ISLAND_SQL} select series_id, a, first_start, lo_mean, hi_mean, lo_sd, hi_sd from r2"),
    "box_range_filter": (box_range_filter, f"{_ISLAND_SQL} select series_id, first_start, last_start from r2 where lo_mean <= 60 and hi_mean >= 40 and lo_sd <= 40 and hi_sd >= 20"),
    "compression_stats": (compression_stats, f"{_ISLAND_SQL} select count(*) as runs, cast(sum(n_windows) as bigint) as windows, min(n_windows) as least, max(n_windows) as most, round(avg(n_windows), 4) as mean from r2"),
    "interval_join_windows": (interval_join_windows, INTERVAL_SQL), "semi_join_candidates": (semi_join_candidates, f"select series_id, start from ({ROLL_SQL}) where series_id in (select s_suppkey from supplier join nation on s_nationkey = n_nationkey where n_regionkey = 1)"), "anti_join_gaps": (anti_join_gaps, GAPS_SQL),
    "rollup_report": _report("rollup"), "cube_report": _report("cube"), "grouping_sets_report": _report("sets"), "pivot_channels": (pivot_channels, PIVOT_SQL), "unpivot_channels": (unpivot_channels, UNPIVOT_SQL),
    "tumbling_channels": (tumbling_channels, TUMBLE_SQL), "sliding_channels": (sliding_channels, SLIDE_SQL), "session_lengths": (session_lengths, SESSION_SQL), "set_ops_windows": (set_ops_windows, SETS_SQL), "lag_lead_trend": (lag_lead_trend, TREND_SQL),
    "distinct_counts": (distinct_counts, f"select channel, cast(floor(v / 50) as bigint) as bucket, count(distinct series_id) as suppliers from ({SW}) group by 1, 2"), "percentile_channels": (percentile_channels, PCT_SQL), "array_distance": (array_distance, ARRAY_SQL), "cross_corr_channels": (cross_corr_channels, CORR_SQL),
    "json_props_channel": (json_props_channel, f"select {_HOUR} as hour, cast(sum(cast(props->>'$.k' as bigint)) as bigint) as k from events group by 1"), "string_doc_channels": (string_doc_channels, DOC_SQL), "amortized_cost": (amortized_cost, AMORT_SQL),
}
QUERIES = {k: v[0] for k, v in _ALL.items()}
ORACLE_SQL = {k: v[1] for k, v in _ALL.items()}
