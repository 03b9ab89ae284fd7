"""The engine's column functions on the vectors of ``embeddings``, each beside its SQL."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions import columns as C
from ..operators import fixtures as X
from ..session import ship


def _vectors(spark, d) -> DataFrame:
    ship(spark)
    return X.table(spark, d, "embeddings").select("vec_id", "label", F.transform("embedding", lambda x: x.cast("double")).alias("e"))


def _with_first(spark, d) -> DataFrame:
    """Every vector beside vector 0, one row."""
    v = _vectors(spark, d)
    return v.join(F.broadcast(v.where("vec_id = 0").select(F.col("e").alias("y"))))


_V = "v as (select vec_id, label, [cast(x as double) for x in embedding] as e from embeddings), o as (select e as y from v where vec_id = 0)"
_D2 = "list_sum([(z[1] - z[2]) ** 2 for z in list_zip(e, y)])"


def znorm_vectors(spark, d):
    v = _vectors(spark, d).withColumn("z", C.znorm_udf("e"))
    return v.select("vec_id", F.round(F.aggregate("z", F.lit(0.0), lambda s, x: s + x * x), 4).alias("squares"), F.round(F.get("z", F.lit(0)), 4).alias("first"))


ZNORM_SQL = f"with {_V}, m as (select vec_id, e, list_avg(e) as a, list_stddev_pop(e) as s from v) select vec_id, round(list_sum([((x - a) / s) ** 2 for x in e]), 4) as squares, round((e[1] - a) / s, 4) as first from m"


def dft_vectors(spark, d):
    parts = F.array(*[F.struct(F.lit(b).alias("bin"), C.dft_bin(F.col("e"), b).alias("x")) for b in (0, 1, 2)])
    s = _vectors(spark, d).select("vec_id", F.inline(parts))
    return s.select("vec_id", "bin", (F.round("x.re", 4) + 0.0).alias("re"), (F.round("x.im", 4) + 0.0).alias("im"))


DFT_SQL = f"with {_V} " + " union all ".join(
    f"select vec_id, cast({b} as integer) as bin, round(list_sum([x * cos({2 * math.pi * b!r} * (j - 1) / 64) for x, j in e]), 4) + 0.0 as re, round(-list_sum([x * sin({2 * math.pi * b!r} * (j - 1) / 64) for x, j in e]), 4) + 0.0 as im from v" for b in (0, 1, 2)
)


def fft_round_trip(spark, d):
    """Whether values come back from their one-sided spectrum."""
    back = C.idft_udf(C.rfft_udf("e"), F.size("e"))
    worst = F.array_max(F.zip_with("e", "b", lambda x, y: F.abs(x - y)))
    return _vectors(spark, d).withColumn("b", back).select("vec_id", (worst < 1e-9).alias("same"))


def contrast_by_label(spark, d):
    d2 = F.aggregate(F.zip_with("e", "y", lambda a, b: (a - b) * (a - b)), F.lit(0.0), lambda s, x: s + x)
    return _with_first(spark, d).where("vec_id <> 0").groupBy("label").agg(F.round(C.relative_contrast(d2), 4).alias("contrast"))


def nearest_by_label(spark, d):
    """The three smallest distances to vector 0 in each label."""
    d2 = F.aggregate(F.zip_with("e", "y", lambda a, b: (a - b) * (a - b)), F.lit(0.0), lambda s, x: s + x)
    got = _with_first(spark, d).groupBy("label").agg(C.topk_agg(F.round(F.sqrt(d2), 4), 3).alias("n"))
    return got.select("label", F.posexplode("n").alias("place", "distance"))


def label_boxes(spark, d):
    """Boxes of the first four values by label, their distance to vector 0, and the gap of its norm to the labels' norms."""
    norm = lambda c: F.sqrt(F.aggregate(c, F.lit(0.0), lambda s, x: s + x * x))
    v = _vectors(spark, d)
    boxes = v.groupBy("label").agg(*C.box_agg("e", "e", 4), F.min(norm("e")).alias("plo"), F.max(norm("e")).alias("phi"))
    first = v.where("vec_id = 0").select(F.slice("e", 1, 4).alias("y"), norm("e").alias("p"))
    got = boxes.join(F.broadcast(first))
    return got.select("label", F.round(F.get("lo", F.lit(0)), 6).alias("lo_0"), F.round(F.get("hi", F.lit(0)), 6).alias("hi_0"), F.round(C.box_min_dist2(F.col("lo"), F.col("hi"), F.col("y")), 6).alias("bound"), F.round(C.pivot_gap2(F.col("plo"), F.col("phi"), F.col("p")), 6).alias("gap"))


BOXES_SQL = f"""with {_V}, b as (select label, {', '.join(f'min(e[{i}]) as l{i}, max(e[{i}]) as h{i}' for i in range(1, 5))}, min(sqrt(list_sum([x * x for x in e]))) as plo, max(sqrt(list_sum([x * x for x in e]))) as phi from v group by 1)
select label, round(l1, 6) as lo_0, round(h1, 6) as hi_0, round({' + '.join(f'greatest(l{i} - y[{i}], y[{i}] - h{i}, 0) ** 2' for i in range(1, 5))}, 6) as bound, round(greatest(plo - sqrt(list_sum([x * x for x in y])), sqrt(list_sum([x * x for x in y])) - phi, 0) ** 2, 6) as gap from b, o"""

_ALL = {
    "znorm_vectors": (znorm_vectors, ZNORM_SQL), "dft_vectors": (dft_vectors, DFT_SQL), "fft_round_trip": (fft_round_trip, "select vec_id, true as same from embeddings"),
    "contrast_by_label": (contrast_by_label, f"with {_V}, d as (select label, {_D2} as d2 from v, o where vec_id <> 0) select label, round(sqrt(max(d2)) / sqrt(min(d2)), 4) as contrast from d group by 1"),
    "nearest_by_label": (nearest_by_label, f"with {_V}, d as (select label, round(sqrt({_D2}), 4) as distance from v, o), r as (select *, row_number() over (partition by label order by distance) - 1 as place from d) select label, cast(place as integer) as place, distance from r where place < 3"),
    "label_boxes": (label_boxes, BOXES_SQL),
}
QUERIES = {k: v[0] for k, v in _ALL.items()}
ORACLE_SQL = {k: v[1] for k, v in _ALL.items()}
