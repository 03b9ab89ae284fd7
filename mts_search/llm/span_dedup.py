"""Removal of repeated passages by sliding spans of sentences.

Each text is cut into sentences (at line ends, and after . ! ? … before white space). From every
sentence starts the shortest run of consecutive sentences with ``least`` words or more, and at every
sentence ends the shortest such run; each run is hashed. Runs with equal hashes are joined over all
documents. The first occurrence (by doc_id, hash of the text, then place) stays; sentences covered by any other
occurrence of a repeated run are removed. Starts and ends both count, so that a repeated passage is
covered up to its last sentence.

Hashes are counted with partial aggregation before the shuffle, and occurrences join the repeated
hashes only, so a passage that a third of all documents hold is one row on that side.

Edge cases: null texts are empty; a text with fewer than ``least`` words in all has no runs and
stays; copies of a whole document lose all their sentences and get an empty text; rows that share
doc_id and text are one occurrence and treated alike; rows that share doc_id alone, or have none,
are documents of their own; a null doc_id sorts last.
"""

from __future__ import annotations

import numpy as np
import pandas as pd
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import ArrayType, StringType

from .common import materialize, text_or_empty

LEAST = 25
SENTENCE = r"[^\n]*?[.!?…]+(?=\s|$)|[^\n]+"
_LAST = (1 << 63) - 1


def sentences(text: Column) -> Column:
    """Sentences in order, trimmed, without the empty ones."""
    return F.filter(F.transform(F.regexp_extract_all(text, F.lit(SENTENCE), F.lit(0)), lambda s: F.trim(F.regexp_replace(s, r"\s+", " "))), lambda s: s != "")


def runs(docs: DataFrame, least: int = LEAST) -> DataFrame:
    """at (doc_id), digest (of the text), hash, start, stop of every shortest run from a start or to an end."""
    kept = docs.select("at", "digest", "sentences")

    def run(batches):
        for big in batches:
            for o in range(0, big.num_rows, 128):
                part = big.slice(o, 128)
                at, digests, hashes, start, stop = [], [], [], [], []
                for key, digest, s in zip(*(part.column(c).to_pylist() for c in range(3)), strict=True):
                    total = np.cumsum([0, *(x.count(" ") + 1 for x in s)])
                    if total[-1] < least:
                        continue
                    i = np.arange(len(s))
                    j = np.searchsorted(total, total[:-1] + least)  # first stop with enough words
                    fit = j <= len(s)
                    spans = set(zip(i[fit].tolist(), j[fit].tolist(), strict=True))
                    e = np.arange(1, len(s) + 1)
                    b = np.searchsorted(total, total[1:] - least, side="right") - 1  # last start with enough words
                    fit = total[1:] >= least
                    spans |= set(zip(b[fit].tolist(), e[fit].tolist(), strict=True))
                    for a, z in sorted(spans):
                        at.append(key)
                        digests.append(digest)
                        hashes.append(xxhash.xxh3_64_intdigest("\n".join(s[a:z]).encode("utf-8", "replace")) - (1 << 63))
                        start.append(a)
                        stop.append(z)
                yield pa.RecordBatch.from_arrays([*(pa.array(c, pa.int64()) for c in (at, digests, hashes)), pa.array(start, pa.int32()), pa.array(stop, pa.int32())], names=["at", "digest", "hash", "start", "stop"])

    return kept.mapInArrow(run, "at bigint, digest bigint, hash bigint, start int, stop int")


def deduplicate(docs: DataFrame, least: int = LEAST) -> DataFrame:
    """doc_id, n_sentences, n_removed, text: each document without its repeated passages.

    The kept sentences are joined by one newline; a document that loses nothing keeps its text as it was.
    """
    rows = docs.select(F.col("doc_id").cast("bigint").alias("doc_id"), text_or_empty().alias("text"))
    rows = rows.withColumn("at", F.coalesce("doc_id", F.lit(_LAST))).withColumn("digest", F.xxhash64("text", F.col("doc_id").isNull()))
    spans = runs(rows.select("at", "digest", sentences(F.col("text")).alias("sentences")), least)
    spans = materialize(spans, "spans")
    place = F.struct("at", "digest", "start")
    repeated = spans.groupBy("hash").agg(F.min(place).alias("first"), F.count(F.lit(1)).alias("times")).where("times > 1").select("hash", *[F.col(f"first.{c}").alias(f"first_{c}") for c in ("at", "digest", "start")])
    # written, so that both sides of the join come from a shuffle alone and the rows of a hot hash can be split
    again = spans.join(materialize(repeated, "repeated"), "hash").where((F.col("at") != F.col("first_at")) | (F.col("digest") != F.col("first_digest")) | (F.col("start") != F.col("first_start")))
    cover = again.select("at", "digest", "start", "stop").groupBy("at", "digest", "start").agg(F.max("stop").alias("stop")).groupBy("at", "digest").agg(F.sort_array(F.collect_list(F.struct("start", "stop"))).alias("cover"))
    out = rows.join(cover, ["at", "digest"], "left").withColumn("s", F.when(F.col("cover").isNotNull(), sentences(F.col("text"))))
    # the covered stretches, sorted, become one running reach: linear in the sentences
    out = out.withColumn("stay", _uncovered(F.col("s"), F.col("cover.start"), F.col("cover.stop")))
    return out.select(
        "doc_id", F.coalesce(F.size("s"), F.lit(0)).alias("n_sentences_checked"), F.when(F.col("cover").isNull(), 0).otherwise(F.size("s") - F.size("stay")).alias("n_removed"),
        F.when(F.col("cover").isNull(), F.col("text")).otherwise(F.array_join("stay", "\n")).alias("text"),
    )


@F.pandas_udf(ArrayType(StringType()))
def _uncovered(s: pd.Series, start: pd.Series, stop: pd.Series) -> pd.Series:
    """Sentences outside of the stretches [start, stop); null where there are no stretches."""
    out = []
    for own, a, z in zip(s, start, stop, strict=True):
        if own is None:
            out.append(None)
            continue
        reach = np.zeros(len(own), np.int64)
        reach[np.asarray(a, int)] = z  # starts are distinct
        stay = np.maximum.accumulate(reach) <= np.arange(len(own))
        out.append([x for x, keep in zip(own, stay, strict=True) if keep])
    return pd.Series(out, dtype=object)
