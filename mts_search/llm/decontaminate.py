"""Benchmark decontamination: windows of a document within a small edit distance of a benchmark item.

Words are the symbols. A window as long as an item is embedded by a random walk: at step j it writes
the word under its pointer and moves on by a random bit of (word, j). Texts a few edits apart write
strings that differ in few places (edit distance becomes Hamming distance). Tables of a few sampled
places each bucket the items; windows that share a bucket with an item are verified by exact edit
distance, with free ends, around the window. The number of tables is raised until simulated edits at
the limit are found again with the wanted recall.

Windows are tried where they can match at all: an item of n words within e edits shares at least
n - r + 1 - r e runs of r words with its window, all of them shifted alike to within e words (the
q-gram bound; r is 3, or less for short items). A stretch with that many gives the window's starts.
Every document is read whole.

The items go to the tasks in blocks of at most ``block`` items and ``most_words`` words (or one item), one
pass over the documents a block, so what is sent doesn't grow with the benchmark.

Edge cases: null or empty texts hold nothing; null or wordless items match nothing; repeated items are
reported each; a text that holds an item twice gives two rows; an empty benchmark keeps every document.
``clean`` judges every row by its own text, so rows that share a doc_id or have none don't affect each other;
all columns are kept, whatever their names.
"""

from __future__ import annotations

from collections import defaultdict
from collections.abc import Iterator
from dataclasses import dataclass, field
from itertools import groupby, repeat

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import mix64, text_or_empty
from .ngram_join import words

LIMIT, TARGET, PLACES, WALK = 0.2, 0.99, 3, 3


def edits_within(item: np.ndarray, text: np.ndarray, limit: int) -> tuple[int, int, int] | None:
    """Fewest word edits that turn ``item`` into some stretch of ``text``: (edits, start, end), None above ``limit``.

    One row of the table at a time; the inner minimum along the row is a running minimum.
    """
    n = len(text)
    col = np.arange(n + 1)
    cost = np.zeros(n + 1, np.int64)
    start = col.copy()
    for i, word in enumerate(item):
        step = cost[:-1] + (text != word)
        skip = cost[1:] + 1
        new = np.concatenate([[i + 1], np.minimum(step, skip)])
        from_ = np.concatenate([[0], np.where(step <= skip, start[:-1], start[1:])])
        keyed = (new - col) * (n + 2) + (n + 1 - from_)  # of equal costs the later start, so the shorter stretch
        best = np.minimum.accumulate(keyed)
        cost = best // (n + 2) + col
        start = (n + 1) - best % (n + 2)
        if cost.min() > limit:
            return None
    end = int(np.argmin(cost))
    return int(cost[end]), int(start[end]), end


def embed(windows: np.ndarray, seed: int, length: int) -> np.ndarray:
    """Random-walk embedding of rows of word hashes into strings of ``length`` symbols (0 after the end)."""
    rows, n = windows.shape
    padded = np.concatenate([windows, np.zeros((rows, 1), np.uint64)], axis=1)
    at = np.zeros(rows, np.int64)
    out = np.empty((rows, length), np.uint64)
    line = np.arange(rows)
    steps = mix64(np.arange(length, dtype=np.uint64) + np.uint64(seed * 1_000_003 + 1))
    for j in range(length):
        c = padded[line, at]
        out[:, j] = c
        move = (mix64(c ^ steps[j]) & np.uint64(1)).astype(np.int64)
        at = np.minimum(at + move, n)
    return out


@dataclass
class Index:
    """Bit-sampling tables over the embedded items, and the word runs by which windows are found."""

    limit: float
    tables: int
    ids: list
    items: list[np.ndarray]
    seeds: dict[int, tuple[np.ndarray, dict[int, list[tuple[int, int]]]]] = field(default_factory=dict)
    buckets: dict = field(default_factory=dict)
    vocabulary: dict = field(default_factory=dict)
    sampled: dict = field(default_factory=dict)

    def places(self, n: int) -> list[tuple[int, np.ndarray]]:
        """(walk, sampled places) of each table for windows of ``n`` words."""
        if n not in self.sampled:
            g = np.random.default_rng(n)
            self.sampled[n] = [(t // 4, np.sort(g.choice(int(2.5 * n) + 1, PLACES, replace=False))) for t in range(self.tables)]
        return self.sampled[n]

    def walks(self, windows: np.ndarray) -> Iterator[list[np.ndarray]]:
        """For each walk the buckets of the windows in its tables; a later walk is only made if asked for."""
        n = windows.shape[1]
        for walk, of in groupby(enumerate(self.places(n)), key=lambda x: x[1][0]):
            of = list(of)
            text = embed(windows, walk, 1 + max(int(at[-1]) for _, (_, at) in of))
            out = []
            for t, (_, at) in of:
                acc = np.full(len(windows), t + 1, np.uint64)
                for p in at:
                    acc = mix64(acc * np.uint64(31) + text[:, p])
                out.append(acc)
            yield out

    def keys(self, windows: np.ndarray) -> list[np.ndarray]:
        """Bucket of each window in each table."""
        return [k for of in self.walks(windows) for k in of]


def word_numbers(text: list[bytes], vocabulary: dict) -> np.ndarray:
    """Number of each word in the benchmark's vocabulary, 0 for others."""
    return np.fromiter(map(vocabulary.get, text, repeat(0)), np.int64, len(text))


def shared_runs(n: int, limit: float) -> tuple[int, int]:
    """(r, least): a window within the limit of an item of ``n`` words shares ``least`` runs of ``r`` words with it."""
    e = int(limit * n)
    for r in (3, 2, 1):
        if n - r + 1 - r * e >= 1:
            return r, n - r + 1 - r * e
    return 1, 1


def run_codes(ids: np.ndarray, r: int) -> np.ndarray:
    """A number for every run of ``r`` words, 0 if one of them is unknown."""
    n = len(ids) - r + 1
    if n <= 0:
        return np.zeros(0, np.int64)
    code, full = np.zeros(n, np.int64), np.ones(n, bool)
    for o in range(r):
        part = ids[o : o + n]
        code = code * 2_097_143 + part  # exact for a benchmark of up to 2 million words; else a collision only adds a window to verify
        full &= part > 0
    return np.where(full, code, 0)


def build(items: list[tuple[object, str]], limit: float = LIMIT, target: float = TARGET) -> Index:
    """Index of the items; the number of tables follows a simulation of edits at the limit."""
    index = Index(limit, 0, [], [])
    for key, text in items:
        w = words(text or "")
        if w:
            for x in w:
                index.vocabulary.setdefault(x, len(index.vocabulary) + 1)
            index.ids.append(key)
            index.items.append(word_numbers(w, index.vocabulary))
    index.tables = calibrate(index, target)
    for i, item in enumerate(index.items):
        r, _ = shared_runs(len(item), limit)
        table = index.seeds.setdefault(r, defaultdict(list))
        for o, code in enumerate(run_codes(item, r).tolist()):
            table[code].append((i, o))
    by_length = defaultdict(list)
    for i, item in enumerate(index.items):
        by_length[len(item)].append(i)
    for n, group in by_length.items():
        keys = index.keys(np.stack([mix64(index.items[i].astype(np.uint64)) for i in group]))
        table: dict[int, list[int]] = defaultdict(list)
        for k in keys:
            for i, h in zip(group, k.tolist(), strict=True):
                table[h].append(i)
        index.buckets[n] = dict(table)
    index.seeds = {r: (np.array(sorted(t), np.int64), dict(t)) for r, t in index.seeds.items()}
    return index


def calibrate(index: Index, target: float, trials: int = 8, sampled: int = 40) -> int:
    """Tables needed so that a share ``target`` of simulated windows at the limit shares a bucket with its item.

    The simulation takes ``sampled`` items, of all lengths that allow an edit; the number has no upper bound.
    """
    able = sorted((x for x in index.items if int(index.limit * len(x))), key=len)
    if not able:
        return 8  # without edits a window and its item are embedded alike
    g = np.random.default_rng(3)
    texts: list[np.ndarray] = []
    for at in np.unique(np.linspace(0, len(able) - 1, min(sampled, len(able))).astype(int)).tolist():
        item = able[at]
        n, rows = len(item), [item]
        for _ in range(trials):
            text = [int(x) for x in item]
            for _ in range(int(index.limit * n)):
                where, kind, fresh = int(g.integers(len(text))), int(g.integers(3)), int(1_000_000 + g.integers(1_000_000))
                if kind == 0:
                    text[where] = fresh
                elif kind == 1:
                    text.insert(where, fresh)
                elif len(text) > 1:
                    del text[where]
            rows.append(np.array((text + [int(x) for x in g.integers(1_000_000, 2_000_000, n)])[:n]))
        texts.append(mix64(np.stack(rows).astype(np.uint64)))
    most = 128
    while True:
        probe, first = Index(index.limit, most, [], []), []
        for rows in texts:
            hit = np.stack([k[1:] == k[0] for k in probe.keys(rows)])
            first += np.where(hit.any(axis=0), hit.argmax(axis=0), most).tolist()
        need = int(np.sort(first)[int(np.ceil(target * len(first))) - 1]) + 1
        if need <= most:
            return max(16, need)
        most *= 2


def find(index: Index, text: list[bytes]) -> list[tuple[int, int, int, int]]:
    """(item, start word, end word, edits) of every benchmark item in a document; overlapping finds of an item keep the best."""
    ids = word_numbers(text, index.vocabulary)
    shifts: dict[int, list[int]] = defaultdict(list)
    for r, (codes, table) in index.seeds.items():
        own = run_codes(ids, r)
        at = np.searchsorted(codes, own)
        at[at == len(codes)] = 0
        for p in np.flatnonzero(codes[at] == own).tolist():
            for i, o in table[int(own[p])]:
                shifts[i].append(p - o)
    windows: dict[int, dict[int, set[int]]] = defaultdict(lambda: defaultdict(set))  # length: start: items that may be there
    for i, found_at in shifts.items():
        n = len(index.items[i])
        _, least = shared_runs(n, index.limit)
        if len(found_at) < least:
            continue
        d = np.sort(found_at)
        # stretches of shifts that hold enough shared runs; each of their shifts is a start to try
        for k in np.flatnonzero(d[least - 1 :] - d[: len(d) - least + 1] <= 2 * int(index.limit * n)).tolist():
            for x in set(d[k : k + least].tolist()):
                windows[n][max(0, min(x, len(ids) - 1))].add(i)
    found: dict[int, list[tuple[int, int, int]]] = defaultdict(list)
    for n, starts in windows.items():
        padded = np.concatenate([ids, np.zeros(n, np.int64)])
        order = sorted(starts)
        for o in range(0, len(order), 512):
            block = order[o : o + 512]
            rows = mix64(padded[np.array(block)[:, None] + np.arange(n)].astype(np.uint64))
            table = index.buckets[n]
            wait = {s: set(starts[s]) for s in block}
            pairs: set[tuple[int, int]] = set()
            for tables in index.walks(rows):
                for k in tables:
                    for s, h in zip(block, k.tolist(), strict=True):
                        for i in table.get(h, ()):
                            pairs.add((s, i))
                            wait[s].discard(i)
                if not any(wait.values()):  # what may be there has been met; more walks find nothing new
                    break
            for s, i in sorted(pairs):
                slack = int(index.limit * n)
                if any(abs(s - x) <= slack for _, x, _ in found[i]):  # the stretch around this start is known
                    continue
                lo = max(0, s - slack)
                hit = edits_within(index.items[i], ids[lo : s + n + slack], slack)
                if hit:
                    found[i].append((hit[0], lo + hit[1], lo + hit[2]))
    out = []
    for i, hits in found.items():
        if not hits:
            continue
        taken: list[tuple[int, int, int]] = []
        for e, a, b in sorted(set(hits)):
            if all(b <= x or a >= y for _, x, y in taken):
                taken.append((e, a, b))
        out += [(i, a, b, e) for e, a, b in taken]
    return sorted(out, key=lambda x: (x[1], x[0]))


def indices(benchmark: DataFrame, limit: float, target: float, block: int, most_words: int) -> Iterator[Index]:
    """Indices of the benchmark's items, a bounded block each; one at least."""
    items: list[tuple[object, str]] = []
    size, made = 0, False
    for row in benchmark.select(F.col("item_id").cast("bigint").alias("item_id"), text_or_empty().alias("text")).orderBy("item_id", "text").toLocalIterator():
        n = row[1].count(" ") + 1
        if items and (len(items) == block or size + n > most_words):
            yield build(items, limit, target)
            items, size, made = [], 0, True
        items.append((row[0], row[1]))
        size += n
    if items or not made:
        yield build(items, limit, target)


def matches(docs: DataFrame, benchmark: DataFrame, limit: float = LIMIT, target: float = TARGET, block: int = 20_000, most_words: int = 2_000_000) -> DataFrame:
    """doc_id, item_id, start_word, n_words, edits, similarity of every benchmark item found in a document."""
    kept = docs.select(F.col("doc_id").cast("bigint").alias("doc_id"), text_or_empty().alias("text"))
    schema = "doc_id bigint, item_id bigint, start_word int, n_words int, edits int, similarity double"

    def search(index: Index) -> DataFrame:
        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for rows in batches:
                out = []
                for key, text in zip(rows.column(0).to_pylist(), rows.column(1).to_pylist(), strict=True):
                    for i, a, b, e in find(index, words(text)):
                        out.append((key, index.ids[i], a, b - a, e, 1 - e / len(index.items[i])))
                cols = list(zip(*out, strict=True)) or [()] * 6
                yield pa.RecordBatch.from_arrays(
                    [pa.array(c, t) for c, t in zip(cols, (pa.int64(), pa.int64(), pa.int32(), pa.int32(), pa.int32(), pa.float64()), strict=True)], names=["doc_id", "item_id", "start_word", "n_words", "edits", "similarity"]
                )

        return kept.mapInArrow(run, schema)

    result = None
    for index in indices(benchmark, limit, target, block, most_words):
        found = search(index)
        result = found if result is None else result.unionByName(found)
    return result


def clean(docs: DataFrame, benchmark: DataFrame, limit: float = LIMIT, target: float = TARGET, block: int = 20_000, most_words: int = 2_000_000) -> DataFrame:
    """The rows whose text holds no benchmark item, all columns as they are; a filter without a shuffle."""
    at = docs.columns.index("text")

    def without(rows: DataFrame, index: Index) -> DataFrame:
        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for big in batches:
                for o in range(0, big.num_rows, 256):  # few texts as Python strings at a time
                    part = big.slice(o, 256)
                    yield part.filter(pa.array([not t or not find(index, words(str(t))) for t in part.column(at).to_pylist()], pa.bool_()))

        return rows.mapInArrow(run, rows.schema)

    for index in indices(benchmark, limit, target, block, most_words):
        docs = without(docs, index)
    return docs
