"""Token ids as range asymmetric numeral system blocks.

Every text is tokenised and ended with one id. Documents are dealt to ranges of doc_id and sorted in
them; a range is written as consecutive blocks of whole documents. All blocks share one frequency
table, counted over all documents. In a block, ``lanes`` coders take turns on the ids; each row of
ids is coded by array operations over the lanes. A block names its documents (id, length, start), so
it can be decoded alone; checkpoints (states and stream position every ``every`` rows) let one block
be decoded in pieces; CRC-32 sums of the stream and of the ids guard against damage.

The output is a folder that can be read alone, by any session and at any time (``read_files``): ``blocks``,
a Parquet table whose rows are the blocks' bytes, and ``table``, the frequency of every id. A block holds the
number of its first id among all ids. Ranges' totals, one number a range, tell where ranges start; there are
at most 65,536 ranges, so beyond 16 million rows a range holds more rows, which a sort on disk takes.

Edge cases: a null or empty text has the end id only; null doc_id sorts last; rows with equal doc_id
are ordered by text and written each; a document of any length is one piece of one block; an empty
table gives no blocks.
"""

from __future__ import annotations

import json
import re
import struct
import uuid
import zlib
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import drop_at_end, materialize, scratch, text_or_empty
from .fingerprint import range_cuts, range_number

MAGIC, SCALE, LOW = b"RANS0001", 20, np.uint64(1 << 31)
LANES, BLOCK, EVERY = 1024, 1 << 18, 128
_LAST = (1 << 63) - 1
_GAP, _ODD = re.compile(r"[ \t\n\r]+"), re.compile(r"[\x1c-\x1f]")


@dataclass
class Table:
    """Frequencies scaled to 2**SCALE, their running sums, and the symbol of every slot."""

    freq: np.ndarray
    start: np.ndarray

    @classmethod
    def of(cls, counts: np.ndarray) -> Table:
        """Every id that occurs keeps a frequency of 1 or more; the largest give way."""
        counts = counts.astype(np.float64)
        seen = counts > 0
        total = 1 << SCALE
        freq = np.where(seen, np.maximum(1, np.floor(counts / max(counts.sum(), 1) * total)), 0).astype(np.int64)
        spare = total - int(freq.sum())
        order = np.argsort(-freq, kind="stable")
        i = 0
        while spare and len(order):
            s = order[i % len(order)]
            step = spare if spare > 0 else -min(-spare, max(0, int(freq[s]) - max(1, int(freq[s]) // 2)))
            freq[s] += step
            spare -= step
            i += 1
        return cls(freq.astype(np.uint64), np.concatenate([[0], np.cumsum(freq)[:-1]]).astype(np.uint64))

    @property
    def symbols(self) -> np.ndarray:
        if not hasattr(self, "_symbols"):
            self._symbols = np.repeat(np.arange(len(self.freq), dtype=np.uint32), self.freq.astype(np.int64))
        return self._symbols

    def __getstate__(self):
        return {"freq": self.freq, "start": self.start}


def encode(ids: np.ndarray, table: Table, lanes: int = LANES, every: int = EVERY) -> bytes:
    """One stream: header, checkpoints, words. The last row is filled up with the block's last id."""
    n = len(ids)
    rows = -(-n // lanes)
    filled = np.concatenate([ids, np.full(rows * lanes - n, ids[-1] if n else 0, ids.dtype)]).reshape(rows, lanes)
    state = np.full(lanes, LOW, np.uint64)
    words: list[np.ndarray] = []
    points: list[tuple[int, np.ndarray]] = []
    made = 0
    for r in range(rows - 1, -1, -1):
        f, c = table.freq[filled[r]], table.start[filled[r]]
        over = state >= (f << np.uint64(63 - SCALE))
        out = (state[over] & np.uint64(0xFFFFFFFF)).astype(np.uint32)
        words.append(out)
        made += len(out)
        state[over] >>= np.uint64(32)
        q = state // f
        state = (q << np.uint64(SCALE)) + (state - q * f) + c
        if r % every == 0:
            points.append((made, state.copy()))
    stream = np.concatenate(words[::-1]) if words else np.zeros(0, np.uint32)
    body = b"".join(struct.pack("<Q", made - m) + s.astype("<u8").tobytes() for m, s in reversed(points)) + stream.astype("<u4").tobytes()
    return struct.pack("<QIIIQ", n, lanes, every, len(points), len(stream)) + body


def decode(data: bytes, table: Table, piece: int | None = None) -> np.ndarray:
    """The ids of a stream, or those between checkpoint ``piece`` and the next."""
    n, lanes, every, points, size = struct.unpack_from("<QIIIQ", data)
    at = struct.calcsize("<QIIIQ")
    each = 8 + 8 * lanes
    words = np.frombuffer(data, "<u4", size, at + points * each).astype(np.uint64)
    rows = -(-n // lanes)
    symbols, mask = table.symbols, np.uint64((1 << SCALE) - 1)
    out = np.empty((rows, lanes), np.uint32)
    for p in range(points) if piece is None else [piece]:
        base = at + p * each
        (pos,) = struct.unpack_from("<Q", data, base)
        state = np.frombuffer(data, "<u8", lanes, base + 8).astype(np.uint64)
        for r in range(p * every, min(rows, (p + 1) * every)):
            slot = state & mask
            s = symbols[slot]
            out[r] = s
            state = table.freq[s] * (state >> np.uint64(SCALE)) + slot - table.start[s]
            need = state < LOW
            k = int(np.count_nonzero(need))
            if k:
                state[need] = (state[need] << np.uint64(32)) | words[pos : pos + k]
                pos += k
    if piece is None:
        return out.reshape(-1)[:n]
    return out[piece * every : (piece + 1) * every].reshape(-1)[: max(0, n - piece * every * lanes)]


def pack_block(part: int, start: int, docs: list[tuple[int | None, int]], ids: np.ndarray, table: Table) -> bytes:
    """A block: magic, sums, document table (doc_id, null flag, length), stream."""
    stream = encode(ids, table)
    keys = np.array([d or 0 for d, _ in docs], "<i8").tobytes()
    null = np.array([d is None for d, _ in docs], np.uint8).tobytes()
    sizes = np.array([k for _, k in docs], "<u8").tobytes()
    head = struct.pack("<IqIII", part, start, len(docs), zlib.crc32(stream), zlib.crc32(ids.astype("<u4").tobytes()))
    return MAGIC + head + keys + null + sizes + stream


def unpack_block(data: bytes, table: Table) -> tuple[int, int, list[tuple[int | None, np.ndarray]]]:
    """(range, number of the first id among all, documents with their ids); raises ValueError on damage."""
    if data[:8] != MAGIC:
        raise ValueError("not a block of this format")
    part, start, n, stream_sum, ids_sum = struct.unpack_from("<IqIII", data, 8)
    at = 8 + struct.calcsize("<IqIII")
    keys, null, sizes = np.frombuffer(data, "<i8", n, at), np.frombuffer(data, np.uint8, n, at + 8 * n), np.frombuffer(data, "<u8", n, at + 9 * n).astype(np.int64)
    stream = data[at + 17 * n :]
    if zlib.crc32(stream) != stream_sum:
        raise ValueError("damaged stream")
    ids = decode(stream, table)
    if zlib.crc32(ids.astype("<u4").tobytes()) != ids_sum:
        raise ValueError("damaged ids")
    return part, start, [(None if z else int(k), x) for k, z, x in zip(keys, null, np.split(ids, np.cumsum(sizes)[:-1]), strict=True)]


# The normaliser and splitter under which words and the marks behind them can be encoded apart.
NORMALIZER = {"type": "Sequence", "normalizers": [{"type": "NFC"}, {"type": "Replace", "pattern": {"Regex": "\\s+"}, "content": " "}, {"type": "Lowercase"}]}
SPLITTER = {
    "type": "Sequence",
    "pretokenizers": [
        {"type": "Split", "pattern": {"Regex": "'s|'t|'re|'ve|'m|'ll|'d|[\\p{L}]+|[\\p{N}]|[^\\s\\p{L}\\p{N}]+"}, "behavior": "Removed", "invert": True},
        {"type": "ByteLevel", "add_prefix_space": False, "trim_offsets": True, "use_regex": False},
    ],
}


def _byte_letters() -> dict[int, int]:
    """Byte-level vocabularies write a printable Latin-1 byte as itself and the others, in order, from U+0100 on."""
    plain = {*range(0x21, 0x7F), *range(0xA1, 0xAD), *range(0xAE, 0x100)}
    return dict(zip((b for b in range(256) if b not in plain), range(0x100, 0x200), strict=False))


class Memo(dict):
    """Ids, as bytes, of each piece met so far.

    Where the tokenizer normalises and splits as stated above, a piece of Latin letters and ASCII marks behind them is
    put together from its lower-case word, which goes to the tokenizer's model, and its marks; any other piece, and
    every piece of another tokenizer, goes through the whole tokenizer.
    """

    MARKS, LETTERS = '!"#$%&()*+,-./:;=?@[\\]^_`{|}~', _byte_letters()

    def __init__(self, tokenizer) -> None:
        super().__init__()
        self.tokenizer, self.model = tokenizer, tokenizer.model
        made = json.loads(tokenizer.to_str())
        self.parts = made["normalizer"] == NORMALIZER and made["pre_tokenizer"] == SPLITTER and made["model"]["type"] == "BPE" and not made["post_processor"]

    def __missing__(self, piece: str) -> bytes:
        if self.parts:
            low = piece.lower()
            core = low.rstrip(self.MARKS)
            if core.isalpha() and max(core) < "\u0250":
                if core == piece:
                    word = core if core.isascii() else core.encode().decode("latin-1").translate(self.LETTERS)
                    got = np.array([x.id for x in self.model.tokenize(word)], "<u4").tobytes()
                else:
                    got = self[core] + self[low[len(core) :]] if len(core) < len(low) else self[core]
                self[piece] = got
                return got
        got = self[piece] = np.array(self.tokenizer.encode(piece, add_special_tokens=False).ids, "<u4").tobytes()
        return got


class Pieces:
    """Ids of texts by white-space pieces, which the tokenizer treats independently.

    The bounded memo stays with the Python worker from task to task.
    """

    kept: dict[str, Memo] = {}

    def __init__(self, path: str, end: int, most: int = 1_000_000) -> None:
        if path not in self.kept:
            from tokenizers import Tokenizer

            self.kept[path] = Memo(Tokenizer.from_file(path))
        self.memo, self.most = self.kept[path], most
        self.tail = np.array([end], "<u4").tobytes()

    def __call__(self, texts: list[str]) -> list[np.ndarray]:
        if len(self.memo) > self.most:
            self.memo.clear()
        get, out = self.memo.__getitem__, []
        for t in texts:
            # the tokenizer takes four control characters for symbols that str.split takes for white space
            pieces = [p for p in _GAP.split(t) if p] if _ODD.search(t) else t.split()
            out.append(np.frombuffer(b"".join(map(get, pieces)) + self.tail, "<u4"))
        return out


def _narrow(ids: np.ndarray) -> bytes:
    """Ids for the intermediate table: 2 bytes each where they fit, else 4; the first byte tells."""
    return b"\x02" + ids.astype("<u2").tobytes() if not len(ids) or ids.max() < 65_536 else b"\x04" + ids.astype("<u4").tobytes()


def _wide(data: bytes) -> np.ndarray:
    return np.frombuffer(data, "<u2" if data[0] == 2 else "<u4", offset=1).astype(np.uint32)


@dataclass
class Written:
    """A folder of blocks and the session that wrote it."""

    spark: SparkSession
    path: str


def write(docs: DataFrame, path: str, end: int = 2, rows_each: int = 256, to: str | None = None) -> Written:
    """Tokenise, count, encode and write all documents to the folder ``to``; ``path`` is the tokenizer's file.

    Without ``to`` the output goes to the shared folder and is deleted when the application ends.
    """
    spark = docs.sparkSession
    out = to or f"{scratch(spark)}/tokens_{uuid.uuid4().hex}"
    rows = docs.select(F.col("doc_id").cast("bigint").alias("doc_id"), text_or_empty().alias("text")).withColumn("at", F.coalesce("doc_id", F.lit(_LAST)))
    cuts = range_cuts(rows, "at", rows_each)
    dealt = rows.withColumn("part", range_number(F.col("at"), cuts)).repartition("part").sortWithinPartitions("part", "at", "text").select("part", "doc_id", "text")

    def tokens(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        pieces = Pieces(path, end)
        now, start = None, 0
        for big in batches:
            for at in range(0, big.num_rows, 64):
                rows = big.slice(at, 64)
                ids = pieces(rows.column(2).to_pylist())
                starts = []
                for p, x in zip(rows.column(0).to_pylist(), ids, strict=True):
                    if p != now:
                        now, start = p, 0
                    starts.append(start)
                    start += len(x)
                yield pa.RecordBatch.from_arrays(
                    [rows.column(0), rows.column(1), pa.array(starts, pa.int64()), pa.array([len(x) for x in ids], pa.int64()), pa.array([_narrow(x) for x in ids], pa.binary())], names=["part", "doc_id", "start", "n", "ids"]
                )

    encoded = materialize(dealt.mapInArrow(tokens, "part int, doc_id bigint, start bigint, n bigint, ids binary"), "ids")
    totals = encoded.groupBy("part").agg(F.sum("n").alias("n")).orderBy("part").collect()
    starts, first = {}, 0
    for part, n in totals:
        starts[part] = first
        first += n

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = np.zeros(1 << 16, np.int64)
        for rows in batches:
            for data in rows.column(0).to_pylist():
                c = np.bincount(_wide(data))
                if len(c) > len(total):
                    total = np.concatenate([total, np.zeros(len(c) - len(total), np.int64)])
                total[: len(c)] += c
        at = np.flatnonzero(total)
        yield pa.RecordBatch.from_arrays([pa.array(at, pa.int64()), pa.array(total[at], pa.int64())], names=["id", "n"])

    seen = encoded.select("ids").mapInArrow(count, "id bigint, n bigint").groupBy("id").agg(F.sum("n").alias("n")).collect()  # as many rows as the vocabulary has at most
    counts = np.zeros(max([end, *(r[0] for r in seen)]) + 1, np.int64)
    for i, n in seen:
        counts[i] = n
    table = Table.of(counts)

    def blocks(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[tuple[int, int, int | None, np.ndarray]] = []
        size = 0

        def flush() -> pa.RecordBatch:
            part, start = held[0][0], starts[held[0][0]] + held[0][1]
            data = pack_block(part, start, [(d, len(x)) for _, _, d, x in held], np.concatenate([x for *_, x in held]), table)
            out = pa.RecordBatch.from_arrays([pa.array([part], pa.int32()), pa.array([start], pa.int64()), pa.array([data], pa.binary())], names=["part", "start", "block"])
            held.clear()
            return out

        for rows in batches:
            for part, doc, start, n, data in zip(*(rows.column(c).to_pylist() for c in ("part", "doc_id", "start", "n", "ids")), strict=True):
                if held and (held[0][0] != part or size + n > BLOCK or held[-1][1] + len(held[-1][3]) != start):
                    yield flush()
                    size = 0
                held.append((part, start, doc, _wide(data)))
                size += n
        if held:
            yield flush()

    encoded.mapInArrow(blocks, "part int, start bigint, block binary").write.parquet(f"{out}/blocks")
    spark.createDataFrame([(int(i), int(table.freq[i])) for i in np.flatnonzero(table.freq)], "id int, freq int").coalesce(1).write.parquet(f"{out}/table")
    if to is None:
        drop_at_end(spark, out)
    return Written(spark, out)


def read(written: Written) -> DataFrame:
    return read_files(written.spark, written.path)


def read_files(spark: SparkSession, path: str) -> DataFrame:
    """doc_id, start, n_tokens, ids_crc32 of every document, from the folder alone."""
    rows = spark.read.schema("id int, freq int").parquet(f"{path}/table").collect()  # as many rows as the vocabulary has at most
    freq = np.zeros(max((r[0] for r in rows), default=0) + 1, np.uint64)
    for i, f in rows:
        freq[i] = f
    table = Table(freq, np.concatenate([[0], np.cumsum(freq)[:-1]]).astype(np.uint64))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for rows in batches:
            for data in rows.column(0).to_pylist():
                _, start, docs = unpack_block(data, table)
                n = np.array([len(x) for _, x in docs], np.int64)
                first = start + np.concatenate([[0], np.cumsum(n)[:-1]])
                sums = [zlib.crc32(np.ascontiguousarray(x, "<u4")) for _, x in docs]
                yield pa.RecordBatch.from_arrays([pa.array([d for d, _ in docs], pa.int64()), pa.array(first, pa.int64()), pa.array(n, pa.int64()), pa.array(sums, pa.int64())], names=["doc_id", "start", "n_tokens", "ids_crc32"])

    return spark.read.schema("part int, start bigint, block binary").parquet(f"{path}/blocks").select("block").mapInArrow(run, "doc_id bigint, start bigint, n_tokens bigint, ids_crc32 bigint")
