"""Near-duplicate join on word n-grams: MinHash bands, Bayesian pruning, exact verification.

Texts are lower-cased words; a text's set holds its runs of five words (all its words if it has fewer).
Equal texts form a class, represented once. Classes that agree in a band of MinHash values become
candidates. A pair's values are compared a slice at a time; it is dropped as soon as the posterior
probability that its Jaccard similarity reaches the threshold, under a uniform prior, is below
``tolerance``. The rest is verified on the sets themselves. At 0.8 a pair misses all of the 28 bands
of 5 values with probability 1.5e-5.

Result: pairs between classes that hold every group together, plus membership. A bucket of at most
``SMALL`` classes has all its pairs tested. In a larger one a pivot is tested against the others, which
settles nearly all of a group of near copies with as many pairs as members. Where a large bucket's classes are
then still in several groups, all those outside of its largest group are compared with every class of another
group, in blocks of ``BLOCK``, inside one task each, which returns only links that join groups (fewer than it
has classes). So the ends of every pair that shares a bucket and reaches the threshold are in one group. Where links are
counted, the classes of a group that stand in large buckets are also compared with each other, all pairs, exactly, in blocks
of ``WITHIN``; a task returns numbers of links a class. So every link is counted once, and no rows grow with the square of a group.

Hot keys: copies are merged by partial aggregation. A class's many partners are dealt to salts of
``CHUNK`` partners, its text and signature going to each. Joins of thin rows by a hot class or bucket
are sort-merge joins, whose large partitions adaptive execution splits.

Edge cases: null texts are empty; empty texts (no words) have no links, their class is by exact
text; repeated rows belong to one class and are returned each; a null doc_id is allowed (its class
takes the smallest id that is there, null if there is none). An empty table gives no rows. Other columns
are not read by the join and are kept, whatever their names, by ``one_of_each``.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator
from dataclasses import dataclass
from functools import lru_cache
from math import lgamma

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import fresh, materialize, mix64, text_or_empty

#: Bytes of a lower-cased text that are no part of a word become spaces: all of ASCII but a-z, 0-9 and _.
TABLE = bytes(c if c >= 128 or chr(c).isalnum() or c == 95 else 32 for c in range(256))
N, THRESHOLD, BANDS, ROWS, SLICE, TOLERANCE = 5, 0.8, 28, 5, 20, 1e-6
#: Classes of a bucket whose pairs are all tested; classes a block of a larger one, and of a group; partners a salt.
SMALL, BLOCK, WITHIN, CHUNK = 32, 256, 512, 512
SIZE = BANDS * ROWS
#: Words of the table by which rows are left out before a shuffle.
MOST_WORDS = 1 << 20


def words(text: str) -> list[bytes]:
    """Runs of letters, digits, _ and characters beyond ASCII, lower-cased, as UTF-8."""
    return text.lower().encode("utf-8", "replace").translate(TABLE).split()


def shingles(text: str, n: int = N) -> frozenset:
    """The set of runs of ``n`` words; exact, for verification."""
    w = words(text)
    if len(w) < n:
        return frozenset([tuple(w)]) if w else frozenset()
    return frozenset(zip(*(w[i:] for i in range(n)), strict=False))


class Memo(dict):
    """Hash of each word met so far."""

    def __missing__(self, word: bytes) -> int:
        h = self[word] = xxhash.xxh3_64_intdigest(word) >> 1
        return h


class Hasher:
    """Hashes of word runs, with a bounded memo of word hashes."""

    def __init__(self) -> None:
        self.memo = Memo()

    def __call__(self, text: str, n: int = N) -> np.ndarray:
        w = words(text)
        if len(self.memo) > 400_000:
            self.memo.clear()
        a = np.fromiter(map(self.memo.__getitem__, w), np.int64, len(w)).view(np.uint64)
        if not len(a):
            return a
        k = min(n, len(a))
        acc = a[: len(a) - k + 1].copy()
        for i in range(1, k):
            acc *= np.uint64(0x9E3779B97F4A7C15)
            acc += a[i : len(a) - k + 1 + i]
        return np.unique(mix64(acc))


@lru_cache(4)
def _params(size: int, seed: int = 5) -> tuple[np.ndarray, np.ndarray]:
    g = np.random.default_rng(seed)
    odd = g.integers(0, 1 << 31, size, dtype=np.uint32) * np.uint32(2) + np.uint32(1)
    return odd[:, None], g.integers(0, 1 << 32, size, dtype=np.uint32)[:, None]


_ROOM: dict[int, np.ndarray] = {}


def minhash(hashes: np.ndarray, size: int = SIZE) -> np.ndarray:
    """``size`` 32-bit MinHash values of a set of 64-bit hashes, a bounded piece at a time."""
    a, b = _params(size)
    room = _ROOM.setdefault(size, np.empty((size, 512), np.uint32))
    h = (hashes >> np.uint64(32)).astype(np.uint32)
    best = np.full(size, 0xFFFFFFFF, np.uint32)
    for at in range(0, len(h), 512):
        part = h[None, at : at + 512]
        into = room[:, : part.shape[1]]
        np.multiply(a, part, out=into)
        np.add(into, b, out=into)
        into ^= into >> np.uint32(15)
        np.minimum(best, into.min(axis=1), out=best)
    return best


def signatures(docs: DataFrame) -> DataFrame:
    """doc_id, k (md5 of the text), n (size of its set), sig (low bytes of its MinHash values), bands."""
    kept = docs.select(F.col("doc_id").cast("bigint").alias("doc_id"), text_or_empty().alias("text"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        hasher = Hasher()
        for big in batches:
            for at in range(0, big.num_rows, 256):
                rows = big.slice(at, 256)
                texts = rows.column(1).to_pylist()
                k = [hashlib.md5(t.encode("utf-8", "replace")).digest() for t in texts]
                yield pa.RecordBatch.from_arrays([rows.column(0), pa.array(k, pa.binary()), *_signs(hasher, texts)], names=["doc_id", "k", "n", "sig", "bands"])

    return kept.mapInArrow(run, "doc_id bigint, k binary, n int, sig binary, bands array<bigint>")


def signed(texts: DataFrame) -> DataFrame:
    """k, text with n, sig and bands of the text."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        hasher = Hasher()
        for big in batches:
            for at in range(0, big.num_rows, 256):
                rows = big.slice(at, 256)
                yield pa.RecordBatch.from_arrays([*rows.columns, *_signs(hasher, rows.column(1).to_pylist())], names=["k", "text", "n", "sig", "bands"])

    return texts.mapInArrow(run, "k binary, text string, n int, sig binary, bands array<bigint>")


def _signs(hasher: Hasher, texts: list[str]) -> tuple[pa.Array, pa.Array, pa.Array]:
    """Size of the set, low bytes of the MinHash values, and band hashes of each text."""
    n, sig, bands = [], [], []
    for t in texts:
        h = hasher(t)
        n.append(len(h))
        if not len(h):
            sig.append(b"")
            bands.append([])
            continue
        m = minhash(h)
        sig.append((m & np.uint32(0xFF)).astype(np.uint8).tobytes())
        rows_of = m.reshape(BANDS, ROWS).astype(np.uint64)
        acc = np.arange(BANDS, dtype=np.uint64)
        for r in range(ROWS):
            acc = mix64(acc * np.uint64(0x9E3779B97F4A7C15) + rows_of[:, r] + np.uint64(1))
        bands.append(acc.view(np.int64).tolist())
    return pa.array(n, pa.int32()), pa.array(sig, pa.binary()), pa.array(bands, pa.list_(pa.int64()))


@lru_cache(8)
def least_matches(size: int = SIZE, step: int = SLICE, threshold: float = THRESHOLD, tolerance: float = TOLERANCE, bits: int = 8) -> tuple[int, ...]:
    """For each number of compared values (step, 2 step, ...) the fewest matches that still keep a pair."""
    grid = (np.arange(20_000) + 0.5) / 20_000
    p = grid + (1 - grid) / (1 << bits)  # low bits also agree by chance
    out = []
    for n in range(step, size + 1, step):
        least = n + 1
        for m in range(n, -1, -1):
            like = lgamma(n + 1) - lgamma(m + 1) - lgamma(n - m + 1) + m * np.log(p) + (n - m) * np.log1p(-np.minimum(p, 1 - 1e-12))
            w = np.exp(like - like.max())
            if w[grid >= threshold].sum() / w.sum() < tolerance:
                break
            least = m
        out.append(least)
    return tuple(out)


def survives(a: np.ndarray, b: np.ndarray, step: int = SLICE) -> np.ndarray:
    """Which rows of two matrices of signatures stay after comparing slice by slice."""
    alive = np.arange(len(a))
    matches = np.zeros(len(a), np.int32)
    for i, least in enumerate(least_matches(a.shape[1], step)):
        cut = slice(i * step, (i + 1) * step)
        matches[alive] += (a[alive, cut] == b[alive, cut]).sum(axis=1, dtype=np.int32)
        alive = alive[matches[alive] >= least]
        if not len(alive):
            break
    keep = np.zeros(len(a), bool)
    keep[alive] = True
    return keep


def buckets(classes: DataFrame) -> DataFrame:
    """bucket, band, k, n, size: the classes of every bucket that holds more than one."""
    members = classes.where("n > 0").select("k", "n", F.posexplode("bands").alias("band", "bucket"))
    # written, so that both sides of the join come from a shuffle alone and the rows of a hot bucket can be split
    sizes = materialize(members.groupBy("bucket").agg(F.count(F.lit(1)).alias("size")).where("size > 1"), "sizes")
    return members.join(sizes, "bucket")


def _pairs(left: DataFrame, right: DataFrame, threshold: float, apart: str) -> DataFrame:
    """Pairs (a, b) of classes in one bucket whose sizes allow the threshold, as often as they share such buckets."""
    x, y = left.alias("x"), right.alias("y")
    fits = F.expr(f"least(x.n, y.n) >= {threshold} * greatest(x.n, y.n)")
    return x.join(y, F.col("x.bucket") == F.col("y.bucket")).where(fits & F.expr(apart)).select(F.col("x.k").alias("a"), F.col("y.k").alias("b"))


def first_candidates(members: DataFrame, threshold: float = THRESHOLD) -> DataFrame:
    """All pairs of small buckets (``small``); in large ones the first class against the others."""
    small, large = members.where(F.col("size") <= SMALL), members.where(F.col("size") > SMALL)
    pivots = large.groupBy("bucket").agg(F.min(F.struct("k", "n")).alias("p")).select("bucket", "p.k", "p.n")
    pairs = lambda x, y, is_small: _pairs(x, y, threshold, "x.k < y.k").withColumn("small", F.lit(is_small))
    return pairs(small, small, True).union(pairs(pivots, large, False)).groupBy("a", "b").agg(F.max("small").alias("small"))


def in_large(members: DataFrame) -> DataFrame:
    """k, large: the bands in which a class stands in a large bucket, a bit each."""
    return members.where(F.col("size") > SMALL).groupBy("k").agg(F.bit_or(F.expr("shiftleft(1, band)")).alias("large"))


def within_groups(members: DataFrame, groups: DataFrame, texts: DataFrame, classes: DataFrame, threshold: float) -> DataFrame:
    """Numbers of links between classes of one group that stand in large buckets, all pairs of them compared block against block.

    Pairs that share a small bucket are left out: those were tested one by one.
    """
    some = in_large(members).join(groups, "k")
    size = some.groupBy("root").agg(F.count(F.lit(1)).alias("c")).where("c > 1").select("root", F.ceil(F.col("c") / WITHIN).cast("int").alias("blocks"))
    some = materialize(some.join(size, "root"), "within")
    rows = some.join(classes.select("k", "bands"), "k").join(texts, "k")
    rows = rows.withColumn("own", F.pmod(F.xxhash64("k"), F.col("blocks")).cast("int")).withColumn("other", F.explode(F.sequence(F.lit(0), F.col("blocks") - 1)))
    rows = rows.select("root", F.least("own", "other").alias("x"), F.greatest("own", "other").alias("y"), "own", "k", "large", "bands", "text")

    def run(rows: pa.Table) -> pa.Table:
        return links_in_group(rows, threshold)

    # comparing costs far more than moving, as in ``verify``
    tasks = int(rows.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    return rows.repartition(tasks, "root", "x", "y").groupBy("root", "x", "y").applyInArrow(run, "k binary, n bigint")


def links_in_group(rows: pa.Table, threshold: float) -> pa.Table:
    """k, n: the links of each class with the other block's classes, or within one block."""
    k, own, texts = (rows.column(c).to_pylist() for c in ("k", "own", "text"))
    x, y = rows.column("x")[0].as_py(), rows.column("y")[0].as_py()
    bands, large = np.array(rows.column("bands").to_pylist()), _bits(rows.column("large"))
    n = np.zeros(len(k), np.int64)
    left, right = ([i for i, o in enumerate(own) if o == side] for side in (x, y))
    for few in _pieces(left, texts):
        for others in _pieces(right, texts):
            at = np.array(others)
            for i, (size, sizes, both) in zip(few, shared([texts[i] for i in few], [texts[j] for j in others]), strict=True):
                hit = both >= threshold * (size + sizes - both) - 1e-9
                if x == y:
                    hit &= at > i
                met = at[hit]
                met = met[~((bands[met] == bands[i]) & ~large[i]).any(axis=1)]
                n[i] += len(met)
                n[met] += 1
    return pa.table({"k": rows.column("k"), "n": pa.array(n)})


def _bits(large) -> np.ndarray:
    """Which bands' buckets are large, a row a class."""
    return (np.array(large.to_pylist(), np.int64)[:, None] >> np.arange(BANDS)) & 1 == 1


def _pieces(rows: list[int], texts: list[str], most: int = 1_000_000) -> Iterator[list[int]]:
    """Rows whose texts have at most ``most`` characters together (or one text); runs of words cost some 30 bytes a character."""
    out, held = [], 0
    for i in rows:
        if out and held + len(texts[i]) > most:
            yield out
            out, held = [], 0
        out.append(i)
        held += len(texts[i])
    if out:
        yield out


def shared(left: list[str], right: list[str]) -> Iterator[tuple[int, np.ndarray, np.ndarray]]:
    """For each left text the size of its set, those of the right ones and of what they share; exact. No set may be empty."""
    number: dict[tuple, int] = {}

    def ids(text: str) -> np.ndarray:
        own = shingles(text)
        return np.fromiter((number.setdefault(r, len(number)) for r in own), np.int32, len(own))

    a, b = [ids(t) for t in left], [ids(t) for t in right]
    sizes = np.array([len(v) for v in b])
    flat, starts = np.concatenate(b), np.cumsum(sizes) - sizes
    mark = np.zeros(len(number), np.uint8)
    for v in a:
        mark[v] = 1
        yield len(v), sizes, np.add.reduceat(mark[flat], starts, dtype=np.int64)
        mark[v] = 0


def across_groups(members: DataFrame, groups: DataFrame, texts: DataFrame, threshold: float) -> DataFrame | None:
    """Links between groups in large buckets, found block against block; None where each such bucket is one group already.

    Rows with b are links that join groups; those without tell the number of all such links of a.
    """
    bits = in_large(members)
    large = members.where(F.col("size") > SMALL).select("bucket", "band", "k").join(groups, "k", "left").select("bucket", "band", "k", F.coalesce("root", "k").alias("label"))
    counts = large.groupBy("bucket", "label").agg(F.count(F.lit(1)).alias("c"))
    mixed = counts.groupBy("bucket").agg(F.max(F.struct("c", "label")).alias("m"), F.count(F.lit(1)).alias("labels"), F.sum("c").alias("all")).where("labels > 1")
    blocks = lambda n: F.ceil(n / BLOCK).cast("int")
    mixed = mixed.select("bucket", F.col("m.label").alias("main"), blocks(F.col("all") - F.col("m.c")).alias("nx"), blocks(F.col("all")).alias("ny"))
    large = materialize(large.join(mixed, "bucket").withColumn("outside", F.col("label") != F.col("main")).drop("main"), "large")
    if large.isEmpty():
        return None
    # signing the few texts again moves less than picking their signatures from among all
    told = signed(texts.join(large.select("k").distinct().hint("merge"), "k", "left_semi").select("k", "text"))
    rows = large.join(materialize(told.join(bits, "k"), "told"), "k")
    at = lambda n: F.pmod(F.xxhash64("k"), F.col(n)).cast("int")
    every = lambda n: F.explode(F.sequence(F.lit(0), F.col(n) - 1))
    cols = ["bucket", "x", "y", "band", "k", "label", "outside", "n", "sig", "bands", "large", "text"]
    left = rows.where("outside").withColumn("x", at("nx")).withColumn("y", every("ny")).select(cols)
    right = rows.withColumn("y", at("ny")).withColumn("x", every("nx")).select(cols).toDF(*cols)  # columns of its own

    def run(left: pa.Table, right: pa.Table) -> pa.Table:
        return links_of_blocks(left, right, threshold)

    keys = ["bucket", "x", "y"]
    return left.groupBy(*keys).cogroup(right.groupBy(*keys)).applyInArrow(run, "a binary, b binary, similarity double, links bigint")


def links_of_blocks(left: pa.Table, right: pa.Table, threshold: float) -> pa.Table:
    """Links between classes of different groups, one of ``left``, one of ``right``: those that join groups in this block, and numbers of all.

    A pair is tested in the first band that its classes share, and not where they share a small bucket.
    """
    out: list[tuple[bytes, bytes | None, float | None, int | None]] = []
    if left.num_rows and right.num_rows:
        (k, g, n, sig, bands), (k2, g2, n2, sig2, bands2) = ([t.column(c).to_pylist() for c in ("k", "label", "n", "sig", "bands")] for t in (left, right))
        outside = right.column("outside").to_pylist()
        texts, texts2 = left.column("text").to_pylist(), right.column("text").to_pylist()
        band = left.column("band")[0].as_py()
        n, n2, b, b2 = np.array(n), np.array(n2), np.array(bands), np.array(bands2)
        s, s2 = (np.frombuffer(b"".join(x), np.uint8).reshape(len(x), SIZE) for x in (sig, sig2))
        large, links, links2 = _bits(left.column("large")), np.zeros(len(k), np.int64), np.zeros(len(k2), np.int64)
        number = {v: i for i, v in enumerate({*g, *g2})}
        top = list(range(len(number)))

        def root(i: int) -> int:
            while top[i] != i:
                top[i] = top[top[i]]
                i = top[i]
            return i

        g, g2 = [number[v] for v in g], [number[v] for v in g2]
        sets: dict[int, frozenset] = {}
        held = 0
        for i in range(len(k)):
            own = None
            fit = np.minimum(n[i], n2) >= threshold * np.maximum(n[i], n2)
            fit &= np.array(g2) != g[i]
            fit &= (b2[:, :band] != b[i, :band]).all(axis=1)
            fit &= ~((b2 == b[i]) & ~large[i]).any(axis=1)
            fit &= np.array([not o or k[i] < x for x, o in zip(k2, outside, strict=True)])
            at = np.flatnonzero(fit)
            for j in at[survives(np.broadcast_to(s[i], (len(at), SIZE)), s2[at])].tolist():
                own = shingles(texts[i]) if own is None else own
                if j not in sets:
                    held += len(texts2[j])
                    if held > 2_000_000:  # sets cost some 20 bytes a character
                        sets.clear()
                        held = len(texts2[j])
                    sets[j] = shingles(texts2[j])
                both = len(own & sets[j])
                union = len(own) + len(sets[j]) - both
                if union and both >= threshold * union - 1e-9:
                    links[i] += 1
                    links2[j] += 1
                    p, q = root(g[i]), root(g2[j])
                    if p != q:
                        top[p] = q
                        out.append((min(k[i], k2[j]), max(k[i], k2[j]), both / union, None))
        out += [(c, None, None, int(m)) for c, m in zip([*k, *k2], [*links, *links2], strict=True) if m]
    cols = list(zip(*out, strict=True)) or [(), (), (), ()]
    return pa.table({"a": pa.array(cols[0], pa.binary()), "b": pa.array(cols[1], pa.binary()), "similarity": pa.array(cols[2], pa.float64()), "links": pa.array(cols[3], pa.int64())})


def _salted(pairs: DataFrame, sides: DataFrame) -> DataFrame:
    """Pairs (a, b) beside what ``sides`` (k, ...) tells of a; partners of one ``a`` are dealt to salts of CHUNK each."""
    many = pairs.groupBy("a").agg(F.ceil(F.count(F.lit(1)) / CHUNK).cast("int").alias("salts"))
    side = sides.join(many, sides["k"] == many["a"]).withColumn("salt", F.explode(F.sequence(F.lit(0), F.col("salts") - 1))).drop("k")
    dealt = pairs.join(many, "a").withColumn("salt", F.pmod(F.xxhash64("b"), F.col("salts")).cast("int")).drop("salts")
    return dealt.join(side.drop("salts"), ["a", "salt"]).drop("salt")


def prune(pairs: DataFrame, classes: DataFrame) -> DataFrame:
    """Pairs whose signatures, compared slice by slice, may still reach the threshold."""
    joined = _salted(pairs, classes.select("k", F.col("sig").alias("sa"))).join(classes.select(F.col("k").alias("b"), F.col("sig").alias("sb")), "b")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for rows in batches:
            if rows.num_rows:
                m = [np.frombuffer(b"".join(rows.column(c).to_pylist()), np.uint8).reshape(rows.num_rows, SIZE) for c in ("sa", "sb")]
                yield rows.select(["a", "b", "small"]).filter(pa.array(survives(*m)))

    return joined.select("a", "b", "small", "sa", "sb").mapInArrow(run, "a binary, b binary, small boolean")


def likely(rows: DataFrame, wanted: DataFrame, keys: list[str]) -> DataFrame:
    """The rows whose keys may be among the wanted ones; none of those is lost. So the others, a ninth excepted, are not shuffled.

    A bit of a table of 64-bit words stands for each key, 8 bits a wanted key. At most MOST_WORDS words are broadcast; with more
    keys than that is made for, more rows pass that the join then drops.
    """
    n_words = max(1, min(MOST_WORDS, wanted.count() // 8))
    word, bit = fresh("word", rows.columns), fresh("bit", rows.columns)
    h = F.xxhash64(*keys)
    at = {word: F.pmod(F.shiftright(h, 6), F.lit(n_words)).cast("bigint"), bit: F.expr(f"shiftleft(1L, cast(xxhash64({', '.join(keys)}) & 63 as int))")}
    words = wanted.withColumns(at).groupBy(word).agg(F.bit_or(bit).alias("mask"))
    words = words.select(F.col(word).alias("of"), "mask")
    met = rows.withColumns(at).join(F.broadcast(words), F.col(word) == F.col("of"))
    return met.where(F.col(bit).bitwiseAND(F.col("mask")) != 0).select(*rows.columns)


def with_texts(wanted: DataFrame, docs: DataFrame) -> DataFrame:
    """k, text of the wanted classes (k, rep); both sides grow with the corpus, so a merge join at every size."""
    texts = docs.select(F.col("doc_id").cast("bigint").alias("rep"), text_or_empty().alias("text")).withColumn("k", F.unhex(F.md5(F.encode("text", "UTF-8"))))
    texts = likely(texts, wanted, ["k", "rep"])
    on = (texts["k"] == wanted["k"]) & texts["rep"].eqNullSafe(wanted["rep"])
    return texts.join(wanted.hint("merge"), on, "left_semi").groupBy("k").agg(F.first("text").alias("text"))


def verify(pairs: DataFrame, texts: DataFrame, threshold: float = THRESHOLD) -> DataFrame:
    """Exact similarity of the pairs on their texts' sets: a, b, similarity, small of those that reach the threshold."""
    # comparing costs far more than moving: as many tasks as the session deals out, however few bytes there are
    tasks = int(pairs.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    joined = _salted(pairs, texts.select("k", F.col("text").alias("ta"))).repartition(tasks, "b")
    joined = joined.join(texts.select(F.col("k").alias("b"), F.col("text").alias("tb")).repartition(tasks, "b"), "b")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        at_b, set_b, kept = None, frozenset(), 0
        memo: dict[bytes, frozenset] = {}
        for rows in batches:
            out = []
            for a, b, small, ta, tb in zip(*(rows.column(c).to_pylist() for c in ("a", "b", "small", "ta", "tb")), strict=True):
                if b != at_b:
                    at_b, set_b = b, shingles(tb)
                if a not in memo:
                    if kept > 250_000:  # a run of words costs some 200 bytes
                        memo.clear()
                        kept = 0
                    memo[a] = shingles(ta)
                    kept += len(memo[a])
                set_a = memo[a]
                both = len(set_a & set_b)
                union = len(set_a) + len(set_b) - both
                if union and both >= threshold * union - 1e-9:
                    out.append((a, b, both / union, small))
            cols = list(zip(*out, strict=True)) or [(), (), (), ()]
            yield pa.RecordBatch.from_arrays([pa.array(cols[0], pa.binary()), pa.array(cols[1], pa.binary()), pa.array(cols[2], pa.float64()), pa.array(cols[3], pa.bool_())], names=["a", "b", "similarity", "small"])

    return joined.select("a", "b", "small", "ta", "tb").mapInArrow(run, "a binary, b binary, similarity double, small boolean")


@dataclass
class Joined:
    """rows: doc_id, k; classes: k, rep (smallest doc_id), copies, n, sig; links: a, b, similarity; groups: k, root of each linked class;
    numbers: k, n: parts of the number of all links of a class, if asked for."""

    rows: DataFrame
    classes: DataFrame
    links: DataFrame
    groups: DataFrame
    numbers: DataFrame | None = None


def join(docs: DataFrame, threshold: float = THRESHOLD, numbers: bool = False) -> Joined:
    """The join: verified links between classes of equal texts, and the groups they make; ``numbers``: all links counted."""
    sigs = materialize(signatures(docs), "signatures")
    classes = materialize(sigs.groupBy("k").agg(F.min("doc_id").alias("rep"), F.count(F.lit(1)).alias("copies"), F.first("n").alias("n"), F.first("sig").alias("sig"), F.first("bands").alias("bands")), "classes")
    members = materialize(buckets(classes), "members")

    wanted = materialize(members.select("k").distinct().join(classes.select("k", "rep"), "k"), "wanted")
    texts = materialize(with_texts(wanted, docs), "texts")  # of the classes that share a bucket: read once, used by both ways
    kept = materialize(prune(first_candidates(members, threshold), classes), "pruned")
    links = materialize(verify(kept, texts, threshold), "links")
    groups = components(links)
    told = None
    if numbers:
        told = links.where("small").select(F.explode(F.array("a", "b")).alias("k"), F.lit(1).cast("bigint").alias("n"))
        told = told.union(within_groups(members, groups, texts, classes, threshold))
    links = links.drop("small")
    more = across_groups(members, groups, texts, threshold)
    if more is not None:
        more = materialize(more, "links")
        links = links.union(more.where("b is not null").drop("links"))
        groups = components(links)
        told = told.union(more.where("b is null").select("a", "links")) if numbers else None
    return Joined(sigs.select("doc_id", "k"), classes, links, groups, told)


def counted(docs: DataFrame) -> DataFrame:
    """One row per document: doc_id, class_id, n_copies, n_links.

    class_id: smallest doc_id of its group of near duplicates (texts connected by links). n_copies: rows with its
    very text. n_links: all links between its text and other texts that share a bucket with it, in small buckets and
    large ones, or stand in large buckets and in one group with it.
    """
    found = join(docs, numbers=True)
    ends = found.numbers.groupBy("k").agg(F.sum("n").alias("n_links"))
    linked = found.groups.join(found.classes.select("k", "rep"), "k")
    first = linked.groupBy("root").agg(F.min("rep").alias("first"))
    linked = linked.join(first, "root").select("k", "first").join(ends, "k", "left")
    told = found.classes.select("k", "rep", "copies").join(linked, "k", "left")
    told = told.select("k", F.when(F.col("first").isNull(), F.col("rep")).otherwise(F.col("first")).alias("class_id"), F.col("copies").alias("n_copies"), F.coalesce("n_links", F.lit(0)).cast("bigint").alias("n_links"))
    return found.rows.join(materialize(told, "told"), "k").select("doc_id", "class_id", "n_copies", "n_links")


def components(links: DataFrame) -> DataFrame:
    """k, root: the smallest member of each linked class's connected component; smallest label and pointer jumping."""
    both = materialize(links.select("a", "b").union(links.select("b", "a")).toDF("u", "v"), "edges")
    label = materialize(both.groupBy("u").agg(F.min("v").alias("m")).select(F.col("u").alias("k"), F.least("u", "m").alias("root")), "labels")
    while True:
        seen = both.join(label.select(F.col("k").alias("v"), F.col("root").alias("r")), "v").groupBy(F.col("u").alias("k")).agg(F.min("r").alias("r"))
        step = label.join(seen, "k").select("k", F.least("root", "r").alias("root"), F.col("root").alias("old"))
        up = step.select(F.col("k").alias("root"), F.col("root").alias("above"))
        nxt = materialize(step.join(up, "root", "left").select("k", F.least("root", F.coalesce("above", "root")).alias("root"), "old"), "labels")
        if nxt.where(F.col("root") != F.col("old")).isEmpty():
            return nxt.select("k", "root")
        label = nxt.select("k", "root")


def one_of_each(docs: DataFrame) -> DataFrame:
    """The documents without near duplicates: of each group the row with the smallest doc_id stays (null last)."""
    found = join(docs)
    last = F.lit((1 << 63) - 1)
    rank = F.struct(F.coalesce("rep", last).alias("id"), F.col("k"))
    best = found.classes.select("k", "rep").join(found.groups, "k", "left").groupBy(F.coalesce("root", "k").alias("g")).agg(F.min(rank).alias("m"))
    k, at = fresh("__k", docs.columns), fresh("__at", docs.columns)
    stay = best.select(F.col("m.k").alias(k), F.col("m.id").alias(at))
    keyed = docs.withColumns({k: F.unhex(F.md5(F.encode(text_or_empty(), "UTF-8"))), at: F.coalesce(F.col("doc_id").cast("bigint"), last)})
    # rows that share doc_id and text meet in the partition that the join has made: no second shuffle
    return keyed.join(stay, [k, at], "left_semi").dropDuplicates([k, at]).drop(k, at)
