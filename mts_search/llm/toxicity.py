"""Toxicity by compression distance.

Two zstandard dictionaries are made, one for toxic and one for ordinary text. Both start with a part
trained on windows of ordinary texts, so that everyday words cost the same in both. Then each has a part
trained on what is left of its own class's windows without the words that both classes share, and ends in
the words by which its class differs most from the other (documents of the class that hold the word, by a
likelihood ratio), nearest to the end the strongest. Toxic texts are mostly everyday words: trained on whole
windows, the toxic part holds chance everyday words whose matches drown the rare ones (on held-out labels of
check_s 0.29 of the toxic texts are found with such parts of 4096 bytes, 0.93 with 256 bytes of remainders). A text is
cut into windows of a few words; a window's distance is how many bytes shorter it becomes with the toxic
dictionary than with the ordinary one. Per text the mean distance, the share of windows over a
threshold and the largest distance go through a logistic curve. The window threshold (a grid of
``cuts``), the number of class words and the curve are chosen by the loss on labelled texts held out of
the dictionaries.

The fit reads at most ``per_class`` labelled texts of each class (first by hash, a documented
bound); every text is scored whole.

Edge cases: a null or empty text has no windows and scores as distance 0 (an ordinary text); words
over 64 characters are cut into windows of 64; with labels of one class only, every score is 0.
Repeated rows stay repeated; rows with a null doc_id are scored too; of rows that share a labelled
doc_id the smallest text is learnt from. An empty table gives no rows. Other columns are kept, whatever
their names.
"""

from __future__ import annotations

import re
from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass
from math import log

import numpy as np
import pyarrow as pa
import zstandard as zs
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import fresh, text_or_empty

_PIECE = re.compile(r"\S{1,64}")
WORDS, PAD = 8, b" "


def windows(text: str, words: int = WORDS) -> list[bytes]:
    """Windows of ``words`` words, with a space on either side; over-long words are cut."""
    pieces = text.lower().split()
    if any(len(p) > 64 for p in pieces):
        pieces = [q for p in pieces for q in _PIECE.findall(p)]
    return [PAD + " ".join(pieces[i : i + words]).encode("utf-8", "replace") + PAD for i in range(0, len(pieces), words)]


def _compressor(content: bytes) -> zs.ZstdCompressor:
    params = zs.ZstdCompressionParameters.from_level(
        3, format=zs.FORMAT_ZSTD1_MAGICLESS, write_content_size=0, write_checksum=0, write_dict_id=0, min_match=6, strategy=zs.STRATEGY_LAZY, window_log=17, hash_log=15, chain_log=15, search_log=4
    )
    return zs.ZstdCompressor(dict_data=zs.ZstdCompressionDict(content, dict_type=zs.DICT_TYPE_RAWCONTENT), compression_params=params)


def lengths(compressor: zs.ZstdCompressor, items: list[bytes]) -> np.ndarray:
    """Compressed length of each item."""
    out = np.empty(len(items), np.int32)
    for at in range(0, len(items), 20_000):
        part = items[at : at + 20_000]
        got = compressor.multi_compress_to_buffer(part)
        out[at : at + len(part)] = [len(got[i]) for i in range(len(got))]
    return out


@dataclass
class Detector:
    toxic: bytes
    ordinary: bytes
    cut: float
    weights: tuple[float, float, float, float]

    def __getstate__(self):
        return {k: v for k, v in self.__dict__.items() if not k.startswith("_")}

    def distances(self, items: list[bytes]) -> np.ndarray:
        if not hasattr(self, "_pair"):
            self._pair = _compressor(self.ordinary), _compressor(self.toxic)
        return lengths(self._pair[0], items) - lengths(self._pair[1], items)

    def measures_at(self, texts: list[str], cuts) -> list[np.ndarray]:
        """For each threshold, per text: mean distance, share of windows over the threshold, largest distance (scaled)."""
        parts = [windows(t) for t in texts]
        n = np.array([len(p) for p in parts])
        out = [np.zeros((len(texts), 3)) for _ in cuts]
        if n.sum():
            d = self.distances([w for p in parts for w in p])
            has = n > 0
            at = np.concatenate([[0], np.cumsum(n[has])[:-1]])
            mean, most = np.add.reduceat(np.clip(d, -12, 12), at) / n[has], np.minimum(np.maximum.reduceat(d, at), 12) / 4
            for cut, x in zip(cuts, out, strict=True):
                x[has] = np.column_stack([mean, np.add.reduceat((d >= cut).astype(float), at) / n[has] * 10, most])
        return out

    def measures(self, texts: list[str]) -> np.ndarray:
        return self.measures_at(texts, [self.cut])[0]

    def scores(self, texts: list[str]) -> np.ndarray:
        z = self.measures(texts) @ np.array(self.weights[:3]) + self.weights[3]
        return 1 / (1 + np.exp(-np.clip(z, -50, 50)))


def _logistic(x: np.ndarray, y: np.ndarray, mass: np.ndarray, ridge: float = 1e-2) -> np.ndarray:
    """Weights and intercept by Newton steps; ``mass`` weighs the rows."""
    a = np.column_stack([x, np.ones(len(x))])
    w = np.zeros(a.shape[1])
    for _ in range(40):
        p = 1 / (1 + np.exp(-np.clip(a @ w, -30, 30)))
        h = (a * (mass * p * (1 - p))[:, None]).T @ a + ridge * np.eye(len(w))
        step = np.linalg.solve(h, a.T @ (mass * (y - p)) - ridge * w)
        w += np.clip(step, -4, 4)
        if np.abs(step).max() < 1e-6:
            break
    return w


def _class_words(own: Counter, other: Counter, n_own: int, n_other: int, top: int) -> list[str]:
    """Words by which a class differs most from the other, the strongest first."""
    gains = []
    for word, a in own.items():
        p, q = a / n_own, (other[word] + 0.5) / n_other
        if a >= 3 and 4 <= len(word) <= 64 and p > 4 * q:
            gains.append((a * log(p / q), word))
    return [w for _, w in sorted(gains, reverse=True)[:top]]


def _remainders(texts: list[str], words: set[str]) -> list[bytes]:
    """What is left of the texts' windows without the words that both classes share; windows of nothing else go."""
    out = []
    for t in texts:
        for w in windows(t):
            left = [x for x in w.decode("utf-8", "replace").split() if x in words]
            if left:
                out.append(PAD + " ".join(left).encode("utf-8", "replace") + PAD)
    return out


def _trained(size: int, pool: list[bytes]) -> bytes:
    """The content of a dictionary trained on windows (the windows themselves where they are too few to train on)."""
    try:
        return zs.train_dictionary(size, pool).as_bytes()
    except zs.ZstdError:
        return b"".join(pool)[-size:]


def fit(toxic: list[str], ordinary: list[str], odds: float | None = None, tops=(60, 90, 130), cuts=(1, 2, 3, 4, 5, 6), shared: int = 16_384, own: int = 256) -> Detector:
    """Dictionaries, number of class words, window threshold and curve; a third of the texts is held out for the choice.

    shared, own: bytes of the part trained for both dictionaries and of the part trained on each one's class.

    odds: toxic to ordinary texts in the whole set of labels, for which the curve is set; those of the given texts if None.
    """
    split = lambda xs, held: [x for i, x in enumerate(xs) if (i % 3 == 0) == held]
    t_fit, o_fit, t_held, o_held = split(toxic, False), split(ordinary, False), split(toxic, True), split(ordinary, True)
    if not t_fit or not o_fit or not t_held or not o_held:
        return Detector(b"", b"", 1.0, (0.0, 0.0, 0.0, -50.0))
    seen = [Counter(w for t in ts for w in set(t.lower().split())) for ts in (t_fit, o_fit)]
    base = _trained(shared, [w for t in o_fit for w in windows(t)])
    y = np.array([1] * len(t_held) + [0] * len(o_held))
    odds = odds or len(toxic) / len(ordinary)
    mass = np.where(y == 1, odds / len(t_held), 1 / len(o_held))
    mass *= len(y) / mass.sum()
    best: tuple[float, Detector] | None = None
    for top in tops:
        words = [_class_words(seen[0], seen[1], len(t_fit), len(o_fit), top), _class_words(seen[1], seen[0], len(o_fit), len(t_fit), top)]
        ends = [_trained(own, _remainders(ts, set(ws))) + (PAD + " ".join(reversed(ws)).encode("utf-8", "replace") + PAD if ws else b"") for ts, ws in zip((t_fit, o_fit), words, strict=True)]
        n = max(map(len, ends))
        ends = [b"\x01" * (n - len(e)) + e for e in ends]  # equally long, so that offsets into the shared part cost the same
        found = Detector(base + ends[0], base + ends[1], 1.0, (0.0, 0.0, 0.0, 0.0))
        for cut, x in zip(cuts, found.measures_at(t_held + o_held, cuts), strict=True):
            w = _logistic(x, y, mass)
            p = 1 / (1 + np.exp(-np.clip(x @ w[:3] + w[3], -30, 30)))
            loss = -np.mean(mass * np.where(y == 1, np.log(np.maximum(p, 1e-9)), np.log(np.maximum(1 - p, 1e-9))))
            if best is None or loss < best[0] - 1e-4:
                best = loss, Detector(found.toxic, found.ordinary, float(cut), tuple(float(v) for v in w))
    return best[1]


def learn(docs: DataFrame, labels: DataFrame, per_class: int = 4000) -> Detector:
    """Detector from labelled rows of the learning folds: crc32(doc_id) mod 5 is not 0."""
    marks = labels.where("doc_id is not null and toxic is not null and crc32(cast(doc_id as string)) % 5 <> 0").groupBy("doc_id").agg(F.max("toxic").alias("toxic"))
    total = {r[0]: r[1] for r in marks.groupBy("toxic").count().collect()}
    picked = None
    for c in (0, 1):
        part = marks.where(F.col("toxic") == c).orderBy(F.xxhash64("doc_id"), "doc_id").limit(per_class)
        picked = part if picked is None else picked.unionByName(part)
    rows = docs.select("doc_id", text_or_empty().alias("text")).join(F.broadcast(picked), "doc_id").groupBy("doc_id", "toxic").agg(F.min("text").alias("text")).collect()
    rows = sorted((r for r in rows if r["text"]), key=lambda r: (r["doc_id"], r["text"]))
    return fit([r["text"] for r in rows if r["toxic"] == 1], [r["text"] for r in rows if r["toxic"] == 0], total.get(1, 0) / max(1, total.get(0, 0)) or None)


def score(df: DataFrame, detector: Detector, keep: list[str], text: str = "text", column: str = "score") -> DataFrame:
    """``keep`` columns plus the score of each whole text; map-only."""
    kept = df.select(*[F.col(f"`{c}`") for c in keep], F.coalesce(F.col(text).cast("string"), F.lit("")).alias(fresh("__text", keep)))
    schema = ", ".join([*(f"`{f.name}` {f.dataType.simpleString()}" for f in kept.schema.fields[:-1]), f"`{column}` double"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for big in batches:
            for at in range(0, big.num_rows, 256):
                rows = big.slice(at, 256)
                s = detector.scores(rows.column(len(keep)).to_pylist())
                yield pa.RecordBatch.from_arrays([*(rows.column(i) for i in range(len(keep))), pa.array(s, pa.float64())], names=[*keep, column])

    return kept.mapInArrow(run, schema)
