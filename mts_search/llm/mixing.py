"""Mixing sources to target weights by iterative proportional fitting.

Documents fall into cells of (source, language, topic). A cell's weight starts at 1; in turn, the
weights of each marginal's cells are scaled so that the marginal's share of weighted tokens meets its
target, until all shares agree (raking). A document stays with probability min(1, scale * weight of
its cell), where one scale is set so that the expected number of tokens meets the budget. The choice
is a hash of doc_id and seed, so it is the same in every run.

Default targets temper the corpus' own shares (share ** ``power``, normalised). Topics default to the
form of a text: of few words, of many words, of digits, of symbols, or prose.

Cells are few and go to the driver if there are at most ``most`` of them; beyond that the same raking
runs on a table in the cluster, one pass a marginal, with the same targets, tolerance and round limit.

Edge cases: null source or language is a value of its own; a null text is empty and has 0 tokens,
its document stays with its cell's probability (cells without tokens keep weight 1); a target for
values that don't occur is dropped and the rest normalised; repeated rows and rows with equal doc_id
share their fate.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import materialize, text_or_empty

DIMS = ("source", "lang", "topic")
TOLERANCE = 1e-9
MOST_ROUNDS = 500


def tokens_of(text: Column) -> Column:
    """Words of a text (runs of characters that aren't white space)."""
    return F.when(F.trim(text) == "", 0).otherwise(F.regexp_count(text, F.lit(r"\S+"))).cast("bigint")


def topic_of(text: Column, tokens: Column) -> Column:
    n = F.greatest(F.char_length(text), F.lit(1))
    digits = n - F.char_length(F.translate(text, "0123456789", ""))
    symbols = n - F.char_length(F.translate(text, "#%&*$|<>{}[]=+\\/@_~^", ""))
    return F.when(tokens < 50, "brief").when(digits > 0.1 * n, "digits").when(symbols > 0.1 * n, "symbols").when(tokens > 2000, "long").otherwise("prose")


@dataclass
class Rake:
    """Weight, probability and tokens of every cell; shares reached and wanted by marginal."""

    cells: list[tuple[tuple, float, float, int]]
    rounds: int
    gap: float
    scale: float


def target_shares(tokens: dict, power: float, given: dict | None = None) -> dict:
    """Shares wanted of each value: the given ones, or the corpus' own tempered; over the values that have tokens."""
    total = sum(tokens.values()) or 1
    raw = {v: (given.get(v, 0.0) if given else (n / total) ** power) for v, n in tokens.items() if n > 0}
    z = sum(raw.values())
    return {v: x / z for v, x in raw.items()} if z > 0 else {v: 1 / len(raw) for v in raw}


def rake(cells: dict[tuple, int], budget: float, power: float = 0.7, targets: dict[str, dict] | None = None, tolerance: float = TOLERANCE, most_rounds: int = MOST_ROUNDS) -> Rake:
    """Raking of the cells' weights (cell: tokens), then the probability of each cell."""
    keys = sorted(cells, key=lambda k: tuple((x is None, str(x)) for x in k))
    n = np.array([cells[k] for k in keys], float)
    w = np.ones(len(keys))
    dims = []
    for d, name in enumerate(DIMS):
        values = sorted({k[d] for k in keys}, key=lambda x: (x is None, str(x)))
        at = np.array([values.index(k[d]) for k in keys]) if keys else np.zeros(0, int)
        own = {v: float(n[at == i].sum()) for i, v in enumerate(values)}
        share = target_shares(own, power, (targets or {}).get(name))
        dims.append((at, np.array([share.get(v, 0.0) for v in values])))
    gap, rounds = 0.0, 0
    for rounds in range(1, most_rounds + 1):  # noqa: B007
        for at, share in dims:
            now = np.bincount(at, w * n, len(share))
            total = now.sum()
            with np.errstate(divide="ignore", invalid="ignore"):
                by = np.where(now > 0, share * total / now, 1.0)
            w = w * by[at]
        gap = max((float(np.abs(np.bincount(at, w * n, len(share)) / max((w * n).sum(), 1e-300) - share * (np.bincount(at, w * n, len(share)) > 0)).max()) for at, share in dims if len(share)), default=0.0)
        if gap < tolerance:
            break
    scale = scale_for(w, n, budget)
    return Rake([(k, float(x), float(min(1.0, scale * x)), int(m)) for k, x, m in zip(keys, w, n, strict=True)], rounds, gap, scale)


def scale_for(w: np.ndarray, n: np.ndarray, budget: float) -> float:
    """The scale at which sum(min(1, scale w) n) = budget (a share of all tokens); exact by the order of the weights."""
    total = n.sum()
    want = budget * total
    order = np.argsort(-w, kind="stable")
    w, n = w[order], n[order]
    full, rest = 0.0, float((w * n).sum())
    for i in range(len(w)):
        if w[i] > 0 and full + rest / w[i] >= want - 1e-12 * total:
            return (want - full) / rest if rest > 0 else 1.0 / w[i]
        full += n[i]
        rest -= w[i] * n[i]
    return 1.0 / w[w > 0].min() if (w > 0).any() else 1.0


def rake_table(cells: DataFrame, power: float, rounds: int = MOST_ROUNDS, tolerance: float = TOLERANCE, targets: dict[str, dict] | None = None) -> DataFrame:
    """The same raking for cells beyond the driver's bound: cells with tokens ``n`` gain ``w``; a pass a marginal, sums pre-aggregated."""
    cells = cells.withColumn("w", F.lit(1.0))
    spark = cells.sparkSession
    shares = {}
    for d in DIMS:
        own = cells.groupBy(d).agg(F.sum("n").alias("own")).where("own > 0")
        given = (targets or {}).get(d)
        if given:
            wanted = spark.createDataFrame([(v, float(x)) for v, x in given.items()], "__v string, __x double")
            own = own.join(wanted, own[d].eqNullSafe(wanted["__v"]), "left").withColumn("raw", F.coalesce("__x", F.lit(0.0)))
        else:
            own = own.withColumn("raw", F.pow(F.col("own").cast("double"), F.lit(power)))
        z, values = own.agg(F.sum("raw"), F.count(F.lit(1))).first()
        share = F.col("raw") / z if z else F.lit(1.0 / max(values, 1))
        shares[d] = materialize(own.select(F.col(d).alias("v"), share.alias("share")), "shares")

    def sums(d):
        every = cells.groupBy(d).agg(F.sum(F.col("w") * F.col("n")).alias("now")).where("now > 0")
        now = every.crossJoin(F.broadcast(every.agg(F.sum("now").alias("total"))))
        return now.join(shares[d], now[d].eqNullSafe(shares[d]["v"])).select("v", "share", "now", "total")

    for _ in range(rounds):
        for d in DIMS:
            by = sums(d).select("v", (F.col("share") * F.col("total") / F.col("now")).alias("by"))
            cells = cells.join(by, cells[d].eqNullSafe(by["v"]), "left").withColumn("w", F.col("w") * F.coalesce("by", F.lit(1.0))).drop("v", "by")
        cells = materialize(cells, "cells")
        gaps = [sums(d).agg(F.max(F.abs(F.col("now") / F.col("total") - F.col("share"))).alias("gap")) for d in DIMS]
        if (gaps[0].union(gaps[1]).union(gaps[2]).agg(F.max("gap")).first()[0] or 0.0) < tolerance:
            break
    return cells


def mix(docs: DataFrame, budget: float = 0.8, power: float = 0.7, targets: dict[str, dict] | None = None, seed: int = 42, most: int = 200_000, whole: bool = False) -> DataFrame:
    """doc_id, source, lang, topic, n_tokens, weight, probability, kept for every document; ``whole``: and its row, as the struct ``row``."""
    text = text_or_empty()
    own = [F.struct(*docs.columns).alias("__row")] if whole else []
    rows = docs.select(*own, F.col("doc_id").alias("__id"), F.col("source").cast("string").alias("__source"), F.col("lang").cast("string").alias("__lang"), tokens_of(text).alias("__n"), text.alias("__text"))
    rows = rows.withColumn("__topic", topic_of(F.col("__text"), F.col("__n"))).drop("__text")
    names = dict(zip(DIMS, ("__source", "__lang", "__topic"), strict=True))
    cells = rows.groupBy(*[F.col(c).alias(d) for d, c in names.items()]).agg(F.sum("__n").alias("n"))
    first = cells.limit(most + 1).collect()
    spark = docs.sparkSession
    schema = "source string, lang string, topic string, weight double, probability double"
    if len(first) <= most:
        got = rake({(r["source"], r["lang"], r["topic"]): r["n"] for r in first}, budget, power, targets)
        table = F.broadcast(spark.createDataFrame([(*k, w, p) for k, w, p, _ in got.cells], schema))
    else:
        table = rake_table(materialize(cells, "cells"), power, targets=targets)
        lo, hi = 0.0, 1e12
        total = table.agg(F.sum("n")).first()[0] or 1
        for _ in range(60):
            mid = (lo + hi) / 2 if hi < 1e12 else max(1.0, lo * 4)
            if table.agg(F.sum(F.least(F.lit(1.0), mid * F.col("w")) * F.col("n"))).first()[0] < budget * total:
                lo = mid
            else:
                hi = mid
        table = table.select(*DIMS, F.col("w").alias("weight"), F.least(F.lit(1.0), hi * F.col("w")).alias("probability"))
    table = table.select(*[F.col(d).alias(f"c_{d}") for d in DIMS], "weight", "probability")
    on = None
    for d, c in names.items():
        same = rows[c].eqNullSafe(table[f"c_{d}"])
        on = same if on is None else on & same
    draw = F.pmod(F.xxhash64(F.coalesce(F.col("__id").cast("string"), F.lit("")), F.lit(seed)), F.lit(1 << 40)) / F.lit(float(1 << 40))
    out = rows.join(table, on, "left")
    return out.select(
        *[F.col("__row").alias("row") for _ in own], F.col("__id").alias("doc_id"), *[F.col(c).alias(d) for d, c in names.items()], F.col("__n").alias("n_tokens"), F.coalesce("weight", F.lit(1.0)).alias("weight"), F.coalesce("probability", F.lit(1.0)).alias("probability"), (draw < F.coalesce("probability", F.lit(1.0))).alias("kept")
    )


def mixed(docs: DataFrame, **options) -> DataFrame:
    """The sampled documents, columns as given."""
    return mix(docs, whole=True, **options).where("kept").select("row.*")
