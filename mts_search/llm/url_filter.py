"""URL filter: host/path rules first, else a ratio of two character language models.

Two variable-order Markov models (contexts of 0 to ``order`` characters, Witten-Bell smoothing), one
of accepted and one of rejected URLs, give a length-normalised log-likelihood difference. A URL that
no rule fits is blocked if the difference is above a threshold, which is calibrated on URLs held out
of the fit. The models are fitted on all distinct URLs that the rules label and a few generic seed
addresses: four fifths of the addresses by hash are counted in the cluster, the last fifth is scored there.
To the driver go the counts, whose number is bounded by the contexts that occur, and a number a held-out address;
all rows are scored.

Edge cases: a null URL or one without ``://`` has empty host and path and no rule; the empty address
scores 0, and 0 is never above the threshold, so it is allowed. Repeated rows stay repeated.
"""

from __future__ import annotations

from collections import defaultdict
from collections.abc import Iterator
from dataclasses import dataclass
from math import log

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import materialize

# The default rules (host, path prefix, verdict).
RULES = (("net", "/", "block"), ("example.net", "/en/", "allow"), ("example.com", "/de/", "block"), ("org", "/fr/", "allow"))
# Words that mark unwanted addresses in general; each makes a seed for the rejected model.
SEED_WORDS = tuple("cheap-pills casino porn xxx viagra spam-farm free-money loan-offer poker betting torrent crack warez replica-watches".split())
UPPER, LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"


def host_and_path(url: Column) -> tuple[Column, Column]:
    """Host (A-Z lower-cased) and path of an address as columns; both empty without ``://``."""
    at = F.coalesce(F.instr(url, "://"), F.lit(0))
    rest = F.when(at > 0, F.expr("substring({u}, instr({u}, '://') + 3)".format(u="`__url`"))).otherwise(F.lit(""))
    return F.translate(F.regexp_extract(rest, r"^([^/?#]*)", 1), UPPER, LOWER), F.regexp_extract(rest, r"^[^/?#]*([^?#]*)", 1)


def best_rule(host: Column, path: Column, rules=RULES) -> Column:
    """The longest rule that fits, as a struct of rule and verdict; null if none does."""
    found = F.lit(None).cast("struct<rule:string,verdict:string>")
    for h, p, v in sorted(rules, key=lambda r: len(r[0] + r[1])):
        fits = ((host == h) | host.endswith("." + h)) & path.startswith(p)
        found = F.when(fits, F.struct(F.lit(h + p).alias("rule"), F.lit(v).alias("verdict"))).otherwise(found)
    return found


@dataclass
class Markov:
    """Counts of the character after each context, smoothed by the next shorter context."""

    order: int
    follow: dict[str, dict[str, int]]
    size: int = 256

    @classmethod
    def fit(cls, texts: list[str], order: int) -> Markov:
        follow: dict[str, dict[str, int]] = defaultdict(lambda: defaultdict(int))
        for t in texts:
            s = "\x02" + t + "\x03"
            for i in range(1, len(s)):
                for k in range(min(order, i) + 1):
                    follow[s[i - k : i]][s[i]] += 1
        return cls(order, {c: dict(f) for c, f in follow.items()})

    def chance(self, context: str, char: str) -> float:
        """Witten-Bell: a context seen n times with u kinds of follower gives u/(n+u) to its suffix."""
        p = 1.0 / self.size
        for k in range(len(context) + 1):
            f = self.follow.get(context[len(context) - k :])
            if f is None:
                break
            n, u = sum(f.values()), len(f)
            p = (f.get(char, 0) + u * p) / (n + u)
        return p


@dataclass
class Ratio:
    """Length-normalised log-likelihood difference, rejected minus accepted; memoises characters in context."""

    accepted: Markov
    rejected: Markov
    threshold: float = 0.0

    def __post_init__(self) -> None:
        self.memo: dict[tuple[str, str], float] = {}

    def __getstate__(self):
        return {**self.__dict__, "memo": {}}

    def score(self, address: str) -> float:
        if not address:
            return 0.0
        s, k, memo, total = "\x02" + address + "\x03", self.accepted.order, self.memo, 0.0
        for i in range(1, len(s)):
            at = (s[max(0, i - k) : i], s[i])
            d = memo.get(at)
            if d is None:
                d = log(self.rejected.chance(*at)) - log(self.accepted.chance(*at))
                if len(memo) < 1_000_000:
                    memo[at] = d
            total += d
        return total / (len(s) - 1)


def fit_ratio(accepted: list[str], rejected: list[str], order: int = 5, seeds: tuple[str, ...] = SEED_WORDS) -> Ratio:
    """Fits on four fifths and puts the threshold where the last fifth is divided best (never below 0)."""
    seeded = [f"{w}.{d}/" for w in seeds for d in ("example", "site", "web")] + ["www." + w for w in seeds]
    part = lambda xs, held: [x for i, x in enumerate(xs) if (i % 5 == 0) == held]
    # the domain suffix is what the rules decide on; the models look at the address without it
    ratio = Ratio(Markov.fit(part(accepted, False), order), Markov.fit(part(rejected, False) + seeded * max(1, len(rejected) // 50), order))
    good = np.array([ratio.score(x) for x in part(accepted, True)] or [0.0])
    bad = np.array([ratio.score(x) for x in part(rejected, True)] + [ratio.score(x) for x in seeded])
    cuts = np.unique(np.concatenate([good, bad, [0.0]]))
    cuts = cuts[cuts >= 0]
    value = [(good <= c).mean() + (bad > c).mean() for c in cuts]
    ratio.threshold = float(cuts[int(np.argmax(value))]) if len(cuts) else 0.0
    return ratio


def fit_whole(labelled: DataFrame, order: int = 5, seeds: tuple[str, ...] = SEED_WORDS) -> Ratio:
    """As ``fit_ratio``, on all rows (__address, v), each counted once; the fifth held out is chosen by hash."""
    spark = labelled.sparkSession
    once = materialize(labelled.distinct().withColumn("held", F.pmod(F.xxhash64("__address"), F.lit(5)) == 0), "labelled")

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        found: dict[tuple[str, str, str], int] = defaultdict(int)

        def told() -> pa.RecordBatch:
            v, context, char = zip(*found, strict=True) if found else ((), (), ())
            return pa.RecordBatch.from_arrays([pa.array(v, pa.string()), pa.array(context, pa.string()), pa.array(char, pa.string()), pa.array(found.values(), pa.int64())], names=["v", "context", "char", "n"])

        for rows in batches:
            for address, v in zip(rows.column(0).to_pylist(), rows.column(1).to_pylist(), strict=True):
                s = "\x02" + address + "\x03"
                for i in range(1, len(s)):
                    for k in range(min(order, i) + 1):
                        found[v, s[i - k : i], s[i]] += 1
                if len(found) > 500_000:
                    yield told()
                    found.clear()
        yield told()

    counts = once.where("not held").select("__address", "v").mapInArrow(count, "v string, context string, char string, n bigint").groupBy("v", "context", "char").agg(F.sum("n").alias("n"))
    follow: dict[str, dict[str, dict[str, int]]] = {v: defaultdict(lambda: defaultdict(int)) for v in ("allow", "block")}
    for v, context, char, n in zip(*(c.to_pylist() for c in counts.toArrow().columns), strict=True):
        follow[v][context][char] += n
    seeded = [f"{w}.{d}/" for w in seeds for d in ("example", "site", "web")] + ["www." + w for w in seeds]
    weight = max(1, once.where("v = 'block'").count() // 50)
    for context, chars in Markov.fit(seeded, order).follow.items():
        for char, n in chars.items():
            follow["block"][context][char] += n * weight
    ratio = Ratio(*(Markov(order, {c: dict(f) for c, f in follow[v].items()}) for v in ("allow", "block")))
    sent = spark.sparkContext.broadcast(ratio)

    def score(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for rows in batches:
            yield pa.RecordBatch.from_arrays([rows.column(1), pa.array([sent.value.score(a) for a in rows.column(0).to_pylist()], pa.float64())], names=["v", "score"])

    held = once.where("held").select("__address", "v").mapInArrow(score, "v string, score double").toArrow()
    v, scores = np.array(held.column("v").to_pylist(), object), held.column("score").to_numpy()
    ratio.threshold = cut_of(scores[v == "allow"], np.concatenate([scores[v == "block"], [ratio.score(x) for x in seeded]]))
    return ratio


def cut_of(good: np.ndarray, bad: np.ndarray) -> float:
    """The score, never below 0, that divides the two classes best; by sorting, so in time linear but for a logarithm."""
    good = good if len(good) else np.zeros(1)
    cuts = np.unique(np.concatenate([good, bad, [0.0]]))
    cuts = cuts[cuts >= 0]
    below = lambda x: np.searchsorted(np.sort(x), cuts, side="right") / len(x)
    return float(cuts[int(np.argmax(below(good) + 1 - below(bad)))])


def judge(df: DataFrame, key: str, url: str = "url", rules=RULES, sample: int | None = None, order: int = 5) -> DataFrame:
    """``key``, host, path, rule, verdict and the models' score for each row; ``sample`` bounds the URLs of the fit, None takes all."""
    at = df.select(F.col(key), F.col(url).cast("string").alias("__url"))
    host, path = host_and_path(F.col("__url"))
    at = at.select(key, host.alias("host"), path.alias("path"))
    at = at.withColumn("__best", best_rule(F.col("host"), F.col("path"), rules)).withColumn("__address", F.concat("host", "path"))
    labelled = at.where("__best is not null").select("__address", F.col("__best.verdict").alias("v"))
    if sample is None:
        ratio = fit_whole(labelled, order)
    else:
        # the first by hash; a bound on the hash that twice as many pass keeps the rest from being gathered at all
        place = F.pmod(F.xxhash64("__address"), F.lit(1 << 40))
        n = labelled.agg(F.approx_count_distinct("__address")).first()[0] or 1
        some = labelled.where(place < int(min(1.0, 2 * sample / n) * (1 << 40)))
        labelled = some.groupBy("__address", "v").count().drop("count").orderBy(place, "__address", "v").limit(sample).collect()
        ratio = fit_ratio([r[0] for r in labelled if r[1] == "allow"], [r[0] for r in labelled if r[1] == "block"], order)

    @F.pandas_udf("double")
    def score(batches: Iterator[pd.Series]) -> Iterator[pd.Series]:
        for s in batches:
            yield s.map(ratio.score)

    at = at.withColumn("score", score("__address"))
    method = F.when(F.col("score") > ratio.threshold, "block").otherwise("allow")
    return at.select(key, "host", "path", F.col("__best.rule").alias("rule"), F.coalesce(F.col("__best.verdict"), method).alias("verdict"), "score")
