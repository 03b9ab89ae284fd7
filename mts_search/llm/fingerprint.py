"""Document fingerprints as invertible Bloom lookup sketches, with DataFrame functions only.

A text is cut into paragraph pieces (lines; a long line at the ends of its sentences, 80 to 400
characters a piece). Each distinct piece's 64-bit digest goes into one cell of each of three
subtables; a cell holds a count, the xor of its digests and the xor of their check values. Sketches
of two versions subtract cell by cell. A cell of the difference with count 1 or -1 and a fitting
check value is pure: it gives one differing digest, which is then taken out of its other two cells,
and so on (peeling, one subtable a round). If the small sketch (the fingerprint itself) doesn't peel
to nothing, the pair is peeled from a larger one, whose size follows the two texts' numbers of
pieces. Likeness = shared digests / all digests of both.

All of it runs in one stage after one shuffle of the texts by range of doc_id: the cells of a
document stay in its partition, since their keys contain the range's number.

Edge cases: a null text is empty; empty texts have no cells and are like each other (1.0) and unlike
any other (0.0). Null doc_id sorts last; equal doc_ids are ordered by their text's hash, repeated
rows follow each other. A piece repeated in a text counts once. An empty table gives no rows. If
even the larger sketch doesn't peel (about once in 10^5 pairs), what is left in its cells counts as
differing.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import text_or_empty

#: Cells a subtable of the fingerprint itself, and of the larger sketch for each piece of the pair.
SMALL, LARGER, SWEEPS = 8, 8, 2
PIECE = r"[^\n]{80,399}?[.!?](?=\s|$)|[^\n]{1,400}"
_LOW = -(1 << 63)


def pieces(text: Column) -> Column:
    """Distinct 64-bit digests of the paragraph pieces of a text."""
    found = F.regexp_extract_all(text, F.lit(PIECE), F.lit(0))
    return F.array_distinct(F.transform(F.filter(found, lambda p: F.trim(p) != ""), lambda p: F.xxhash64(F.trim(p))))


def slot(key: Column, table: int, size: Column) -> Column:
    """Cell number of a digest in subtable ``table``; subtables follow each other."""
    return F.pmod(F.xxhash64(key, F.lit(table + 11)), size) + size * table


def check(key: Column) -> Column:
    return F.xxhash64(key, F.lit(77))


def range_cuts(df: DataFrame, key: str, rows_each: int = 256) -> list[int]:
    """Values of ``key`` that cut it into ranges of about equally many rows (at most 65,536 of them)."""
    n = df.count()
    parts = max(1, min(65_536, n // rows_each))
    if parts == 1:
        return []
    cuts = df.agg(F.percentile_approx(key, [i / parts for i in range(1, parts)], max(10_000, 8 * parts)).alias("c")).first()["c"]
    return sorted(set(cuts or []))


def range_number(key: Column, cuts: list[int]) -> Column:
    """How many cuts lie below a key: its range; looked up in two steps of about sqrt(n) comparisons."""
    if not cuts:
        return F.lit(0)
    width = max(1, int(len(cuts) ** 0.5))
    blocks = [cuts[i : i + width] for i in range(0, len(cuts), width)]
    first = F.array(*[F.lit(b[-1]) for b in blocks])
    nested = F.array(*[F.array(*[F.lit(v) for v in b]) for b in blocks])
    at = F.size(F.filter(first, lambda v: v < key))
    inner = F.size(F.filter(F.coalesce(F.get(nested, at), F.array().cast("array<bigint>")), lambda v: v < key))
    return F.least(at * width + inner, F.lit(len(cuts))).cast("int")  # the last block may be shorter


def with_next(docs: DataFrame, rows_each: int = 256) -> DataFrame:
    """Every document beside the text that follows it in descending doc_id; after the last comes the first.

    One shuffle by range of doc_id. The row on a range's upper border is also dealt to the range above,
    which needs it as the follower of its last row.
    """
    docs = docs.select(F.col("doc_id").cast("bigint").alias("doc_id"), text_or_empty().alias("text")).withColumn("at", F.coalesce("doc_id", F.lit(_LOW)))
    cuts = range_cuts(docs, "at", rows_each)
    top = docs.agg(F.max("at")).first()[0]
    if top is None:
        top = _LOW
    part = range_number(F.col("at"), cuts)
    above = part + 1
    border = F.array_contains(F.array(*[F.lit(c) for c in cuts]).cast("array<bigint>"), F.col("at")) if len(cuts) <= 64 else (range_number(F.try_add(F.col("at"), F.lit(1).cast("bigint")), cuts) > part)  # the largest id has no next: null, below every cut
    homes = F.filter(
        F.array(
            F.struct(part.alias("part"), F.lit(0).alias("guest")),
            F.when(border, F.struct(above.alias("part"), F.lit(1).alias("guest"))),
            F.when(F.col("at") == F.lit(top), F.struct(F.lit(0).alias("part"), F.lit(2).alias("guest"))),
        ),
        lambda s: s.isNotNull(),
    )
    dealt = docs.select("doc_id", "text", "at", F.inline(homes)).repartition("part")
    order = Window.partitionBy("part").orderBy(F.col("guest"), F.col("at").desc(), F.xxhash64("text"), "text")
    dealt = dealt.select("part", "guest", "doc_id", "text", F.lead("text").over(order).alias("next_text"), F.row_number().over(order).alias("pos"))
    return dealt.where("guest = 0").drop("guest")


def _cells(keys: Column, kinds: list[tuple[str, int]], size: Column) -> Column:
    """Array of cells to add for an array of digests: for each kind its sign, three cells a digest."""
    return F.flatten(
        F.transform(
            keys,
            lambda k: F.array(*[F.struct(F.lit(kind).alias("kind"), slot(k, t, size).alias("cell"), F.lit(sign).cast("bigint").alias("n"), k.alias("key"), check(k).alias("chk")) for kind, sign in kinds for t in range(3)]),
        )
    )


def _meta(index: int, value: Column) -> Column:
    return F.struct(F.lit(KINDS["meta"]).alias("kind"), F.lit(index).cast("bigint").alias("cell"), F.lit(1).cast("bigint").alias("n"), value.cast("bigint").alias("key"), F.lit(0).cast("bigint").alias("chk"))


#: What a row of cells belongs to: the sketches of a text, its edit and the next text; differences small and larger.
KINDS = {"meta": 0, "own": 1, "edit": 2, "next": 3, "edit_small": 4, "next_small": 5, "edit_large": 6, "next_large": 7}


def fingerprints(docs: DataFrame, rows_each: int = 256) -> DataFrame:
    """doc_id, n_chars, edited_sha256, fingerprint, edited_fingerprint, near_edited, near_next, and how it went."""
    rows = with_next(docs, rows_each)
    n = F.char_length("text")
    rows = rows.withColumn("edited", F.expr("concat(left(text, char_length(text) - cast(floor(char_length(text) / 3) as int)), left(coalesce(next_text, ''), cast(floor(char_length(text) / 3) as int)))"))
    sha = F.sha2(F.encode("edited", "UTF-8"), 256)
    rows = rows.select("part", "pos", "doc_id", n.cast("bigint").alias("n_chars"), sha.alias("sha"), pieces(F.col("text")).alias("own"), pieces(F.col("edited")).alias("edit"), pieces(F.coalesce("next_text", F.lit(""))).alias("next"))

    k = KINDS
    small = F.lit(SMALL).cast("bigint")
    size = lambda a, b: F.pow(F.lit(2.0), F.ceil(F.log2((F.size(a) + F.size(b)) * LARGER + 2.0))).cast("bigint")
    edit_size, next_size = size("own", "edit"), size("own", "next")
    words = [F.expr(f"cast(conv(substr(sha, {1 + 16 * i}, 16), 16, -10) as bigint)") for i in range(4)]
    meta = [F.col("doc_id"), F.col("n_chars"), *words, F.size("own"), F.size("edit"), F.size("next"), edit_size, next_size]
    cells = F.flatten(
        F.array(
            F.array(*[_meta(i, F.coalesce(m, F.lit(0))) for i, m in enumerate(meta)], *[_meta(99, F.col("doc_id").isNull().cast("bigint"))]),
            _cells(F.col("own"), [(k["own"], 1)], small),
            _cells(F.col("edit"), [(k["edit"], 1)], small),
            _cells(F.col("next"), [(k["next"], 1)], small),
            _cells(F.col("own"), [(k["edit_large"], 1)], edit_size),
            _cells(F.col("edit"), [(k["edit_large"], -1)], edit_size),
            _cells(F.col("own"), [(k["next_large"], 1)], next_size),
            _cells(F.col("next"), [(k["next_large"], -1)], next_size),
        )
    )
    # the sizes travel with the cells of the larger sketches: peeling needs them
    width = F.when(F.col("c.kind") == k["edit_large"], edit_size).when(F.col("c.kind") == k["next_large"], next_size).otherwise(small)
    table = rows.withColumn("c", F.explode(cells)).select("part", "pos", "c.kind", width.alias("size"), "c.cell", "c.n", "c.key", "c.chk")
    by = ["part", "pos", "kind", "size", "cell"]
    table = table.groupBy(*by).agg(F.sum("n").alias("n"), F.bit_xor("key").alias("key"), F.bit_xor("chk").alias("chk"), F.lit(0).cast("bigint").alias("got"))

    # subtract the small sketches: each goes, signed, into the differences it takes part in
    def into(*targets: tuple[int, int]) -> Column:
        return F.array(*[F.struct(F.lit(kind).alias("kind"), (F.col("n") * sign).alias("n")) for kind, sign in targets])

    spread = (
        F.when(F.col("kind") == k["own"], into((k["own"], 1), (k["edit_small"], 1), (k["next_small"], 1)))
        .when(F.col("kind") == k["edit"], into((k["edit"], 1), (k["edit_small"], -1)))
        .when(F.col("kind") == k["next"], into((k["next_small"], -1)))
        .otherwise(F.array(F.struct(F.col("kind"), F.col("n"))))
    )
    table = table.withColumn("s", F.explode(spread)).select("part", "pos", F.col("s.kind").alias("kind"), "size", "cell", F.col("s.n").alias("n"), "key", "chk", "got")
    table = _add(table)

    for _ in range(SWEEPS):
        for t in range(3):
            table = _add(_peel(table, t))

    def of(kind: str, what: Column) -> Column:
        return F.when(F.col("kind") == k[kind], what)

    m = lambda i: F.max(F.when((F.col("kind") == k["meta"]) & (F.col("cell") == i), F.col("key")))
    hex_of = lambda c, w: F.lower(F.lpad(F.hex(c), w, "0"))
    cell_text = F.struct("cell", F.concat(F.lpad(F.col("cell").cast("string"), 2, "0"), F.lit("."), F.hex("n"), F.lit("."), hex_of(F.col("key"), 16), hex_of(F.pmod(F.col("chk"), F.lit(1 << 32)), 8)).alias("t"))
    told = [F.array_join(F.transform(F.array_sort(F.collect_list(of(x, cell_text))), lambda s: s["t"]), "-") for x in ("own", "edit")]
    left = lambda kind: F.sum(of(kind, (F.col("cell") >= 0).cast("bigint")))
    got = lambda kind: F.coalesce(F.sum(of(kind, F.col("got"))), F.lit(0))
    done = table.groupBy("part", "pos").agg(
        m(0).alias("id"), m(99).alias("no_id"), m(1).alias("n_chars"), *[m(2 + i).alias(f"w{i}") for i in range(4)], m(6).alias("n_own"), m(7).alias("n_edit"), m(8).alias("n_next"),
        told[0].alias("fingerprint"), told[1].alias("edited_fingerprint"), *[f(x).alias(f"{name}_{x}") for x in ("edit_small", "next_small", "edit_large", "next_large") for name, f in (("left", left), ("got", got))],
    )

    def likeness(pair: str) -> Column:
        unpeeled = F.coalesce(F.col(f"left_{pair}_small"), F.lit(0)) > 0
        rest = F.ceil(F.coalesce(F.col(f"left_{pair}_large"), F.lit(0)) / 3)
        apart = F.when(unpeeled, F.col(f"got_{pair}_large") + rest).otherwise(F.col(f"got_{pair}_small"))
        both = F.col("n_own") + F.col(f"n_{pair}")
        return F.when(both == 0, 1.0).otherwise(F.greatest(F.lit(0.0), (both - apart) / (both + apart)))

    return done.select(
        F.when(F.col("no_id") == 0, F.col("id")).alias("doc_id"), "n_chars", F.concat(*[hex_of(F.col(f"w{i}"), 16) for i in range(4)]).alias("edited_sha256"), "fingerprint", "edited_fingerprint",
        likeness("edit").alias("near_edited"), likeness("next").alias("near_next"), F.col("n_own").alias("n_pieces"), (F.coalesce("left_edit_small", F.lit(0)) > 0).alias("retried_edited"), (F.coalesce("left_next_small", F.lit(0)) > 0).alias("retried_next"),
        (F.coalesce("left_edit_large", F.lit(0)) + F.coalesce("left_next_large", F.lit(0))).alias("unpeeled_cells"),
    )


def _add(table: DataFrame) -> DataFrame:
    """Sums cells; those of a difference that became empty go."""
    by = ["part", "pos", "kind", "size", "cell"]
    table = table.groupBy(*by).agg(F.sum("n").alias("n"), F.bit_xor("key").alias("key"), F.bit_xor("chk").alias("chk"), F.sum("got").alias("got"))
    return table.where((F.col("kind") < KINDS["edit_small"]) | (F.col("n") != 0) | (F.col("key") != 0) | (F.col("chk") != 0) | (F.col("got") != 0))


def _peel(table: DataFrame, t: int) -> DataFrame:
    """Takes the digests of pure cells in subtable ``t`` out of all their cells; counts them at cell -1."""
    pure = (F.col("kind") >= KINDS["edit_small"]) & (F.abs("n") == 1) & (F.floor(F.col("cell") / F.col("size")) == t) & (F.col("chk") == check(F.col("key"))) & (F.col("cell") == slot(F.col("key"), t, F.col("size")))
    zero = F.lit(0).cast("bigint")
    cell = lambda at, n, key, chk, got: F.struct(at.alias("cell"), n.alias("n"), key.alias("key"), chk.alias("chk"), got.alias("got"))
    out = [cell(slot(F.col("key"), o, F.col("size")), -F.col("n"), F.col("key"), F.col("chk"), zero) for o in range(3) if o != t]
    count = cell(F.lit(-1).cast("bigint"), zero, zero, zero, F.lit(1).cast("bigint"))
    same = F.array(cell(F.col("cell"), F.col("n"), F.col("key"), F.col("chk"), F.col("got")))
    return table.withColumn("c", F.explode(F.when(pure, F.array(*out, count)).otherwise(same))).select("part", "pos", "kind", "size", "c.cell", "c.n", "c.key", "c.chk", "c.got")
