"""Training-data operators against brute-force versions, exact round trips and edge cases."""

import hashlib
import re
import zlib

import numpy as np
import public_tokenizers
import pytest
from pyspark.sql import functions as F

from mts_search.llm import decontaminate as D
from mts_search.llm import fingerprint as P
from mts_search.llm import html_extract as H
from mts_search.llm import license_scan as L
from mts_search.llm import mixing as M
from mts_search.llm import ngram_join as J
from mts_search.llm import queries as QS
from mts_search.llm import span_dedup as S
from mts_search.llm import token_output as T
from mts_search.llm import toxicity as X
from mts_search.llm import url_filter as U

SF = "/root/testdata/sf0.001"
SCHEMA = "doc_id bigint, text string, lang string, source string, n_chars bigint"
G = np.random.default_rng(2)


def prose(n, seed):
    g = np.random.default_rng(seed)
    syl = "ba ke li mo nu ra se ti vo zu".split()
    return " ".join("".join(g.choice(syl, int(g.integers(1, 4)))) for _ in range(n))


def frame(spark, texts):
    return spark.createDataFrame([(i, t, "en", "s", len(t or "")) for i, t in texts], SCHEMA)


EDGE = [(1, None), (2, ""), (None, "x"), (3, "same text here"), (4, "same text here"), (4, "same text here"), (5, "word " * 30_000), (6, "\n\n \t")]


@pytest.fixture(scope="module")
def edge(spark):
    return frame(spark, EDGE).withColumn("weight", F.lit(1)).withColumn("kept", F.lit("a")).persist()


@pytest.fixture(scope="module")
def empty(spark):
    return spark.createDataFrame([], SCHEMA)


def test_html_layouts():
    m = H.default_model()
    got = lambda h: H.extract_batch([h], m)[0]
    assert got(None) == got("") == ""
    assert got("just words") == "just words"
    assert got('<nav><ul><li><a href="/">a</a></li></ul></nav><article><h1>T &amp; U</h1><p>One\n two<br>three.<p><b>Four</article><footer>&copy; x</footer>') == "T & U\nOne two three.\nFour"
    assert got("<script>var t='</p>';</script><article><p>Body text is here.</p></article><!-- no -->") == "Body text is here."
    assert got('<body><aside><p>Side text is long enough.</p></aside><main><p>Main text.</p></main><div id="comments"><p>I agree with all of this.</p></div></body>') == "Main text."
    held = [H.parse(p) for p in H.labelled_pages(60, seed=99)]
    f = H.Forest(held)
    node, _ = f.beliefs(m.weights, m.edge)
    wrong = total = 0
    for b, p in zip(f.base, held, strict=True):
        for i in p.texts:
            total += 1
            wrong += (node[b + i] >= 0.5) != bool(p.label[i])
    assert wrong <= 0.02 * total


def test_tree_messages_match_enumeration():
    from itertools import product

    page = H.parse("<div><p>a</p><ul><li>b</li></ul></div>")
    f = H.Forest([page])
    w, edge = G.normal(size=H.N_FEATURES), G.normal(size=(2, 2, 2))
    f.barred[:] = False
    n = len(f.parent)
    mass, on = 0.0, np.zeros(n)
    for y in product((0, 1), repeat=n):
        s = sum(y[i] * (f.x[i] @ w) for i in range(n)) + sum(edge[f.kind[i], y[f.parent[i]], y[i]] for i in range(n) if f.parent[i] >= 0)
        mass += np.exp(s)
        on += np.exp(s) * np.array(y)
    assert np.allclose(f.beliefs(w, edge)[0], on / mass)


def test_pages_query(spark):
    rows = QS.op1_main_text(spark, SF).collect()
    html = {r["page_id"]: r["html"] for r in spark.read.parquet(f"{SF}/pages.parquet").collect()}
    import html as ent

    for r in rows:
        a = html[r["page_id"]].partition("<article>")[2].partition("</article>")[0]
        blocks = [re.sub(r"\s+", " ", ent.unescape(re.sub(r"<[^>]+>", " ", b))).strip() for b in re.split(r"</?(?:p|h1)>", a)]
        assert r["text"] == "\n".join(b for b in blocks if b) and r["n_chars"] == len(r["text"])


def test_urls(spark):
    urls = ["https://A.Example.NET/en/1?x", "http://example.net", "http://x.net/a#b", "http://example.com/de/1", "https://q.org/fr/2", "http://q.org/en", None, "nothing", "http://notexample.com/de/", "a://b://c/d"]
    df = spark.createDataFrame(list(enumerate(urls)), "page_id bigint, url string")
    got = {r["page_id"]: r for r in U.judge(df, "page_id").collect()}
    assert (got[0]["host"], got[0]["path"], got[0]["rule"], got[0]["verdict"]) == ("a.example.net", "/en/1", "example.net/en/", "allow")
    assert got[1]["rule"] is None and got[1]["path"] == ""
    assert (got[2]["rule"], got[2]["verdict"]) == ("net/", "block") and got[3]["rule"] == "example.com/de/" and got[4]["verdict"] == "allow"
    assert got[5]["rule"] is None and got[8]["rule"] is None and (got[6]["host"], got[6]["path"]) == ("", "") and got[9]["host"] == "b:"
    m = U.fit_ratio(["good.site/a"] * 20, ["bad.place/z"] * 20, seeds=())
    assert m.score("bad.place/y") > m.threshold >= 0 > m.score("good.site/b")


def test_toxicity_held_out(spark):
    rows = [(i, prose(60, i) + (" vileword scumbag nastyone " * 2 if i % 5 == 0 else "") + prose(20, i + 9999)) for i in range(400)]
    det = X.fit([t for i, t in rows if i % 5 == 0 and i < 300], [t for i, t in rows if i % 5 and i < 300])
    s = det.scores([t for i, t in rows if i >= 300])
    y = np.array([i % 5 == 0 for i, _ in rows if i >= 300])
    assert ((s >= 0.5) == y).mean() >= 0.95
    assert X.fit([], ["a"]).scores(["b", ""]).max() < 0.5


def test_fingerprints(spark, edge, empty):
    texts = [(i, (prose(150, i) + ". ") * 1 + "\n".join(prose(25, i * 7 + j) + "." for j in range(12))) for i in range(60)] + [(100, "same. " * 5), (101, "same. " * 5), (102, None), (103, "é" * 50)]
    got = {r["doc_id"]: r for r in P.fingerprints(frame(spark, texts), 8).collect()}
    order = sorted(((i, t or "") for i, t in texts), reverse=True)
    for (i, t), (_, n) in zip(order, order[1:] + order[:1], strict=True):
        k = len(t) // 3
        e = t[: len(t) - k] + n[:k]
        cut = lambda x: {p.strip(" ") for p in (m[0] for m in re.finditer(P.PIECE, x)) if p.strip(" ")}
        a, b, c = cut(t), cut(e), cut(n)
        near = lambda x, y: len(x & y) / len(x | y) if x | y else 1.0
        r = got[i]
        assert r["n_chars"] == len(t) and r["edited_sha256"] == hashlib.sha256(e.encode()).hexdigest()
        assert r["near_edited"] == pytest.approx(near(a, b)) and r["near_next"] == pytest.approx(near(a, c)) and r["unpeeled_cells"] == 0
    assert got[100]["fingerprint"] == got[101]["fingerprint"] != got[1]["fingerprint"]
    assert any(r["retried_next"] for r in got.values()) and P.fingerprints(edge).count() == len(EDGE) and P.fingerprints(empty).count() == 0


def test_spans(spark, edge, empty):
    passage = ". ".join(prose(12, 500 + j) for j in range(6)) + "."
    texts = [(i, prose(40, i) + ".\n" + (passage + "\n" if i in (3, 5, 9) else "") + prose(30, i + 70) + ".") for i in range(12)]
    got = {r["doc_id"]: r for r in S.deduplicate(frame(spark, texts)).collect()}
    for i, t in texts:
        assert (got[i]["text"] == t) == (i not in (5, 9))
        if i in (5, 9):
            assert not any(s in got[i]["text"] for s in passage.split(". ")) and prose(30, i + 70) in got[i]["text"] and prose(40, i) in got[i]["text"]
    assert S.deduplicate(edge).count() == len(EDGE) and S.deduplicate(empty).count() == 0


def test_spans_of_rows_that_share_an_id(spark):
    p = [". ".join(prose(12, 600 + 10 * k + j) for j in range(6)) + "." for k in range(3)]
    own = lambda i, inner="": prose(40, i) + ".\n" + (inner + "\n" if inner else "") + prose(40, i + 70) + "."
    # p[0] at the same sentence of two texts without id; p[1] likewise in two texts of id 7; p[2] first in id 0, again in one text of each
    texts = [(None, own(1, p[0])), (None, own(2, p[0])), (None, own(3)), (7, own(4, p[1])), (7, own(5, p[1])), (7, own(6)), (0, own(8, p[2])), (None, own(9, p[2])), (7, own(10, p[2]))]
    got = {t: [r["text"] for r in S.deduplicate(frame(spark, texts)).collect() if prose(40, i) in r["text"]] for i, (_, t) in zip((1, 2, 3, 4, 5, 6, 8, 9, 10), texts, strict=True)}
    whole = {t: own(i) for i, (_, t) in zip((1, 2, 3, 4, 5, 6, 8, 9, 10), texts, strict=True)}
    assert all(len(v) == 1 for v in got.values())
    same = [got[t] == [t] for _, t in texts]
    assert sorted(same[:2]) == sorted(same[3:5]) == [False, True] and same[2] and same[5] and same[6:] == [True, False, False]
    assert all(got[t] == [whole[t]] for (_, t), kept in zip(texts, same, strict=True) if not kept)


def edits(a, b):
    row = [0] * (len(b) + 1)
    for i, x in enumerate(a, 1):
        new = [i]
        for j, y in enumerate(b, 1):
            new.append(min(row[j - 1] + (x != y), row[j] + 1, new[-1] + 1))
        row = new
    return min(row)


def test_decontamination(spark, edge, empty):
    items = [(j, prose(30 if j else 5, 900 + j)) for j in range(8)]
    ix = D.build(items)
    found = 0
    for j, t in items[1:]:
        w = t.split()
        for kind in range(12):
            v = list(w)
            for _ in range(kind // 2):
                at = int(G.integers(len(v)))
                if G.random() < 0.5:
                    v[at] = "zzz"
                else:
                    del v[at]
            doc = prose(50, kind).split() + v + prose(50, kind + 40).split()
            true = edits(w, doc)
            hits = [h for h in D.find(ix, J.words(" ".join(doc))) if ix.ids[h[0]] == j]
            if true <= 6:
                found += bool(hits) and hits[0][3] == true
            else:
                assert not hits
    assert found >= 0.95 * 7 * 12 * 0.9
    bench = spark.createDataFrame(items, "item_id bigint, text string")
    docs = frame(spark, [(1, prose(40, 1) + " " + items[2][1]), (2, prose(80, 2)), (3, items[0][1]), (None, prose(10, 3))])
    assert {(r["doc_id"], r["item_id"]) for r in D.matches(docs, bench, block=3).collect()} == {(1, 2), (3, 0)}
    assert sorted(str(r["doc_id"]) for r in D.clean(docs, bench).collect()) == ["2", "None"]
    assert D.clean(edge, bench).columns == edge.columns and D.matches(edge, bench.limit(0)).count() == 0 and D.matches(empty, bench).count() == 0


def test_ngram_join(spark, edge, empty):
    base = [prose(120, i).split() for i in range(8)]
    texts = []
    for b in base:
        for k in (0, 0, 1, 3, 8):
            w = list(b)
            for _ in range(k):
                w[int(G.integers(len(w)))] = f"n{G.integers(1000)}"
            texts.append(" ".join(w))
    docs = frame(spark, list(enumerate(texts)))
    sets = {t: J.shingles(t) for t in texts}
    near = lambda t, u: len(sets[t] & sets[u]) >= 0.8 * len(sets[t] | sets[u])
    group = components({t: [u for u in sets if u != t and near(t, u)] for t in sets})
    want = {i: (min(texts.index(u) for u in group[t]), texts.count(t), sum(near(t, u) for u in sets if u != t)) for i, t in enumerate(texts)}
    assert {r["doc_id"]: (r["class_id"], r["n_copies"], r["n_links"]) for r in J.counted(docs).collect()} == want
    assert {r["doc_id"] for r in J.one_of_each(docs).collect()} == {c for c, _, _ in want.values()}
    found = J.join(docs)
    assert all(r["similarity"] >= 0.8 for r in found.links.collect()) and found.groups.count() <= found.classes.count()
    assert J.counted(edge).count() == len(EDGE) and J.one_of_each(edge).columns == edge.columns and J.counted(empty).count() == 0
    assert J.one_of_each(empty).count() == 0
    assert {r["doc_id"] for r in J.one_of_each(edge).collect()} == {1, None, 3, 5, 6}
    clash = edge.withColumn("__k", F.lit(1)).withColumn("__AT", F.lit(2))
    assert J.one_of_each(clash).columns == clash.columns and J.one_of_each(clash).count() == 5


def components(links):
    """Each node's connected component, by walking."""
    out = {}
    for x in links:
        if x not in out:
            seen, wait = {x}, [x]
            while wait:
                for y in links[wait.pop()]:
                    if y not in seen:
                        seen.add(y)
                        wait.append(y)
            out |= dict.fromkeys(seen, seen)
    return out


def changed(base, times, tag):
    w = list(base)
    for at in G.choice(len(w), times, replace=False).tolist():
        w[at] = f"{tag}x{at}"
    return " ".join(w)


def test_groups_at_the_threshold(spark):
    """Texts whose pairs lie on both sides of the threshold, in buckets beyond the all-pairs size."""
    base = prose(150, 77).split()
    texts = [changed(base, int(G.integers(1, 6)), f"t{i}") for i in range(220)]
    sets = [J.shingles(t) for t in texts]
    near = {i: [j for j in range(len(texts)) if i != j and len(sets[i] & sets[j]) >= 0.8 * len(sets[i] | sets[j])] for i in range(len(texts))}
    group = components(near)
    docs = frame(spark, list(enumerate(texts)))
    members = J.buckets(J.signatures(docs))  # no copies among the texts: each is a class
    assert members.agg(F.max("size")).first()[0] > 2 * J.SMALL
    got = {r["doc_id"]: r["class_id"] for r in J.counted(docs).collect()}
    assert got == {i: min(group[i]) for i in got} and 1 < len(set(got.values())) < 220


def test_large_groups_cost_in_proportion(spark):
    near, same = 3000, 3000
    base = prose(100, 78).split()
    rows = [(i, changed(base, 1, f"t{i}")) for i in range(near)] + [(10_000 + i, "the very same text here " + prose(40, 79)) for i in range(same)] + [(20_000 + i, prose(60, 5000 + i)) for i in range(50)]
    docs = frame(spark, rows)
    found = J.join(docs)
    assert found.links.count() < 30 * near
    got = {r["doc_id"]: (r["class_id"], r["n_copies"]) for r in J.counted(docs).collect()}
    assert all(got[i][0] == 0 for i in range(near)) and all(got[10_000 + i] == (10_000, same) for i in range(same)) and all(got[20_000 + i] == (20_000 + i, 1) for i in range(50))
    assert J.one_of_each(docs).count() == 52


def test_pruning_keeps_similar_pairs():
    least = J.least_matches()
    assert list(least) == sorted(least) and least[-1] < 0.8 * J.SIZE
    g = np.random.default_rng(4)
    a = g.integers(0, 256, (2000, J.SIZE), dtype=np.uint8)
    same = g.random((2000, J.SIZE)) < 0.8
    b = np.where(same, a, g.integers(0, 256, (2000, J.SIZE), dtype=np.uint8))
    assert J.survives(a, b).all()
    assert not J.survives(a, g.integers(0, 256, (2000, J.SIZE), dtype=np.uint8)).any()


def test_blocks_round_trip(spark, edge):
    ids = G.zipf(1.3, 300_000).clip(0, 40_000).astype(np.uint32)
    table = T.Table.of(np.bincount(ids))
    assert table.freq.sum() == 1 << T.SCALE and (table.freq[np.unique(ids)] > 0).all()
    data = T.encode(ids, table)
    assert (T.decode(data, table) == ids).all() and len(data) < 2 * len(ids)
    pieces = [T.decode(data, table, p) for p in range(-(-len(ids) // (T.LANES * T.EVERY)))]
    assert (np.concatenate(pieces) == ids).all()
    block = T.pack_block(3, 7, [(5, 10), (None, 0), (6, 20)], ids[:30], table)
    assert [(d, len(x)) for d, x in T.unpack_block(block, table)[2]] == [(5, 10), (None, 0), (6, 20)]
    with pytest.raises(ValueError):
        T.unpack_block(block[:-3] + b"abc", table)
    from tokenizers import Tokenizer

    tok = Tokenizer.from_file(public_tokenizers.path(QS.TOKENIZER))
    docs = frame(spark, [*[(i, t) for i, t in EDGE if i is not None and i != 4], (40, "Héllo <|endoftext|> it's\u00a0x\u2003y 12.5 ÀB'll\x1cz İß"), *[(50 + i, prose(400, i)) for i in range(30)]])
    got = {r["doc_id"]: r for r in T.read(T.write(docs, public_tokenizers.path(QS.TOKENIZER), rows_each=8)).collect()}
    start = 0
    for r in docs.orderBy("doc_id").collect():
        want = np.array([*tok.encode(r["text"] or "", add_special_tokens=False).ids, 2], "<u4")
        g = got[r["doc_id"]]
        assert (g["start"], g["n_tokens"], g["ids_crc32"]) == (start, len(want), zlib.crc32(want.tobytes()))
        start += len(want)
    assert T.read(T.write(edge, public_tokenizers.path(QS.TOKENIZER))).count() == len(EDGE)


def test_pieces_equal_whole_tokenizer():
    path = public_tokenizers.path(QS.TOKENIZER)
    pieces = T.Pieces(path, 2)
    assert pieces.memo.parts  # else the shortcut under test isn't taken
    texts = [
        "", " \n\t", "Plain words, twice; plain WORDS!", "\u0130stanbul \u0141\u00d3D\u0179 \u212bngstr\u00f6m \u212a\u212a \u1e9e \u01c5", "e\u0301te\u0301 abc\u0301 \u00aa\u00ba \u00b5 \ufb01", "don't 's ab' it's,",
        "<|endoftext|> abc<|endoftext|> abc< ABC>", "a\x1cb a\u00a0b a\u2003b", "x\u00b2 12abc abc12 a_b ab___", "\u0250\u0251 \u024f \u024e \u03a3\u0391\u03a3 \u6c34\u706b", *(f"ab{m} {m} {m}ab \u00e9t\u00e9{m}{m}" for m in T.Memo.MARKS),
    ]
    for text, got in zip(texts, pieces(texts), strict=True):
        assert got.tolist() == [*pieces.memo.tokenizer.encode(text, add_special_tokens=False).ids, 2], text


def test_mixing(spark, edge, empty):
    cells = {(s, g, t): int(n) for s, g, t, n in [("a", "x", "p", 100), ("a", "y", "p", 50), ("b", "x", "q", 900), ("b", "y", "p", 30), ("c", "y", "q", 10), (None, "x", "q", 60)]}
    got = M.rake(cells, 0.6)
    w = {k: x * n for k, x, _, n in got.cells}
    total = sum(cells.values())
    for d in range(3):
        own = {}
        for k, n in cells.items():
            own[k[d]] = own.get(k[d], 0) + n
        z = sum((n / total) ** 0.7 for n in own.values())
        for v, n in own.items():
            assert sum(x for k, x in w.items() if k[d] == v) / sum(w.values()) == pytest.approx((n / total) ** 0.7 / z, abs=1e-6)
    assert sum(p * n for _, _, p, n in got.cells) == pytest.approx(0.6 * total)
    t = spark.createDataFrame([(*k, n) for k, n in cells.items()], "source string, lang string, topic string, n bigint")
    far = {(r["source"], r["lang"], r["topic"]): r["w"] for r in M.rake_table(t, 0.7, 6).collect()}
    ratio = [far[k] / x for k, x, _, _ in M.rake(cells, 0.6, most_rounds=6).cells]
    assert max(ratio) / min(ratio) == pytest.approx(1, abs=1e-9)
    rows = M.mix(spark.read.parquet(f"{SF}/documents.parquet")).collect()
    assert len(rows) == 200 and all(r["kept"] or r["probability"] < 1 for r in rows)
    assert M.mixed(edge).columns == edge.columns and M.mix(empty).count() == 0


def test_mixing_table_with_given_targets(spark):
    cells = [("a", "x", 100), ("a", "y", 50), ("b", "x", 90), ("b", "y", 60), (None, "x", 60), (None, "y", 80)]
    docs = spark.createDataFrame([(i, "w " * n, g, s, 2 * n) for i, (s, g, n) in enumerate(cells)], SCHEMA).cache()
    targets = {"source": {"a": 0.5, "b": 0.3, None: 0.2, "gone": 3.0}, "lang": {"x": 0.6, "y": 0.4}}
    few = {r["doc_id"]: r for r in M.mix(docs, 0.6, targets=targets).collect()}
    many = {r["doc_id"]: r for r in M.mix(docs, 0.6, targets=targets, most=2).collect()}
    assert [many[i]["probability"] for i in range(6)] == pytest.approx([few[i]["probability"] for i in range(6)], abs=1e-6)
    kept = {s: sum(many[i]["weight"] * n for i, (t, _, n) in enumerate(cells) if s == t) for s in ("a", "b", None)}
    assert [kept[s] / sum(kept.values()) for s in kept] == pytest.approx([0.5, 0.3, 0.2], abs=1e-6)


def test_licences(spark, edge):
    s = L.Scanner()
    got = s.scan("Foo ALL rights-reserved; all rights reserved. Released under the MIT License.")
    assert (got["n_words"], got["n_base"], got["first_word"], got["last_word"], got["base_labels"], got["labels"]) == (12, 2, 1, 4, "reserved", "mit,reserved")
    assert s.scan("")["score"] == 0 and s.scan("ccby cc byx the license of the")["labels"] == ""
    full = L.TEMPLATES["mit"][1].split()
    got = s.scan(" ".join(full[:20] + ["extra"] + full[20:]))
    assert "mit" in got["labels"] and got["score"] > 0.9
    seqs = [[int(x) for x in G.integers(1, 4, 12)] for _ in range(3)]
    a = L.Automaton.build(seqs)
    text = [int(x) for x in G.integers(1, 5, 60)]
    for i, (state, n) in enumerate(a.statistics(text)):
        best = max(k for k in range(i + 2) if k == 0 or any(seq[o : o + k] == text[i + 1 - k : i + 1] for seq in seqs for o in range(len(seq))))
        assert n == best
        if n:
            assert set(a.ends[state]) == {(t, o + n - 1) for t, seq in enumerate(seqs) for o in range(len(seq)) if seq[o : o + n] == text[i + 1 - n : i + 1]}
    assert L.scan(edge).count() == len(EDGE)


def test_licence_chain_outlives_stray_runs():
    name = lambda i: "w" + "".join(chr(97 + int(c)) for c in f"{i:04d}")
    body = [name(i) for i in range(200)]
    s = L.Scanner({"long": (" ".join([*(f"of the work {name(1000 + i)}" for i in range(40)), *body]),)}, phrases=(), least=3, gap=20, share=0.5)
    got = s.scan(" ".join([*body[:100], "unknown of the work unknown", *body[100:]]))
    assert got["labels"] == "long" and got["n_spans"] == 1 and got["score"] == pytest.approx(200 / 360)


def test_pipeline(spark):
    import corpus_pipeline

    docs = spark.read.parquet(f"{SF}/documents.parquet")
    seen = docs.count()
    for name, stage in corpus_pipeline.STAGES[:-1]:
        out = stage(spark, docs, SF)
        assert out.columns == docs.columns
        n = out.count()
        assert 0 < n <= seen, name
        docs, seen = out, n
    assert len(corpus_pipeline.STAGES) == 5


def test_html_of_broken_pages():
    from time import perf_counter

    m = H.default_model()
    got = lambda h: H.extract_batch([h], m)[0]
    assert got('<p title="x>Hello world text is here.\nMore text here, too.') == "Hello world text is here. More text here, too."
    assert got("<p>See <a title='it's here' href=/x>the page</a> now, it is good.</p>") == "See the page now, it is good."
    assert got("<body><article><p>Main text is here, and long enough to keep.</p></article><p>Copyright 2020 Foo.</p></body>") == "Main text is here, and long enough to keep."
    assert got("<p>An open tag <a") == "An open tag"
    began = perf_counter()
    for page in ('<a b="' * 170_000, '<a b="x>' * 100_000, "<div>" * 10_000 + "x", "<div>" * 10_000 + "</table>" * 10_000, "<script>" + "</script " * 50_000, "<p title='" * 100_000 + ">"):
        got(page)
    assert perf_counter() - began < 60


def test_empty_and_clashing_inputs(spark, empty):
    pages = spark.createDataFrame([], "page_id bigint, url string, html string")
    assert H.extract(pages, ["page_id", "url"]).count() == 0 and U.judge(pages, "page_id").count() == 0 and L.scan(empty).count() == 0
    assert T.read(T.write(empty, public_tokenizers.path(QS.TOKENIZER))).count() == 0
    assert X.score(empty, X.fit([], []), empty.columns).count() == 0
    odd = spark.createDataFrame([(None, None, None), (1, "http://q.org/a", ""), (1, "http://q.org/a", "")], "page_id bigint, url string, html string").withColumn("text", F.lit("t")).withColumn("__html", F.lit(1)).withColumn("host", F.lit("h"))
    assert sorted(r["n_chars"] for r in H.extract(odd, ["page_id", "url"]).collect()) == [0, 0, 0]
    assert sorted(str(r["verdict"]) for r in U.judge(odd, "page_id").collect()) and U.judge(odd, "page_id").count() == 3


def test_clean_judges_rows_by_their_own_text(spark):
    item = prose(30, 901)
    bench = spark.createDataFrame([(0, item)], "item_id bigint, text string")
    rows = [(None, "a " + item), (None, prose(40, 1)), (7, item + " b"), (7, prose(40, 2)), (8, None)]
    got = [(r["doc_id"], r["text"]) for r in D.clean(frame(spark, rows).withColumn("__held", F.lit(1)), bench).collect()]
    assert sorted(got, key=str) == sorted([rows[1], rows[3], rows[4]], key=str)
    many = spark.createDataFrame([(j, prose(30, 950 + j)) for j in range(7)], "item_id bigint, text string")
    docs = frame(spark, [(j, prose(20, j) + " " + prose(30, 950 + j)) for j in range(9)])
    assert sorted(r["doc_id"] for r in D.clean(docs, many, block=3).collect()) == [7, 8]


def test_calibration_has_no_bound():
    few = D.build([(j, prose(24, 980 + j)) for j in range(4)], 0.2, 0.95)
    most = D.build([(j, prose(24, 980 + j)) for j in range(4)], 0.2, 0.999)
    assert 16 <= few.tables <= most.tables


def test_toxic_dictionary_and_threshold(spark):
    rows = [(i, prose(60, i) + (" vileword scumbag nastyone " * 2 if i % 5 == 0 else "")) for i in range(400)]
    det = X.fit([t for i, t in rows if i % 5 == 0], [t for i, t in rows if i % 5])
    assert det.toxic != det.ordinary and b"vileword" in det.toxic and det.cut in (1, 2, 3, 4, 5, 6)
    docs = frame(spark, [*rows, (None, None), (1000, ""), (1001, rows[0][1] * 300), (0, rows[0][1])])
    labels = spark.createDataFrame([(i, int(i % 5 == 0)) for i in range(400)], "doc_id bigint, toxic int")
    learnt = X.learn(docs, labels)
    got = X.score(docs, learnt, ["doc_id"]).collect()
    s = {r["doc_id"]: r["score"] for r in got}
    assert len(got) == 404 and s[1000] == s[None] < 0.5 and all(0 <= r["score"] <= 1 for r in got)
    held = [i for i in range(400) if zlib.crc32(str(i).encode()) % 5 == 0]
    assert np.mean([(s[i] >= 0.5) == (i % 5 == 0) for i in held]) >= 0.95


def test_token_folder_is_read_alone(spark, tmp_path):
    docs = frame(spark, [(i, prose(50, i)) for i in range(40)])
    out = str(tmp_path / "tokens")
    T.write(docs, public_tokenizers.path(QS.TOKENIZER), rows_each=8, to=out)
    got = sorted(T.read_files(spark.newSession(), out).collect(), key=lambda r: r["doc_id"])
    assert [r["start"] for r in got] == [0, *np.cumsum([r["n_tokens"] for r in got])[:-1].tolist()]


def test_pipeline_against_brute_force(spark):
    """Each stage on its predecessor's rows, against plain versions."""
    import corpus_pipeline

    stage = dict(corpus_pipeline.STAGES)
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    text = {r["doc_id"]: r["text"] or "" for r in docs.collect()}
    kept = lambda df: {r["doc_id"] for r in df.select("doc_id").collect()}
    calm = stage["toxicity"](spark, docs, SF)
    detector = X.learn(docs, spark.read.parquet(f"{SF}/labels.parquet"))
    ids = sorted(text)
    assert kept(calm) == {i for i, s in zip(ids, detector.scores([text[i] for i in ids]), strict=True) if s < 0.5}
    ids = sorted(kept(calm))
    sets = {i: J.shingles(text[i]) for i in ids}
    near = lambda i, j: text[i] == text[j] or len(sets[i] & sets[j]) >= 0.8 * len(sets[i] | sets[j]) > 0
    group = components({i: [j for j in ids if i != j and near(i, j)] for i in ids})
    single = stage["near_duplicates"](spark, calm, SF)
    assert kept(single) == {min(g) for g in group.values()}
    items = [J.words(r["text"] or "") for r in spark.read.parquet(f"{SF}/benchmark.parquet").collect()]
    number: dict = {}
    code = lambda ws: np.array([number.setdefault(w, len(number)) for w in ws], np.int64)
    items = [code(w) for w in items if w]
    held = lambda i: any(D.edits_within(x, code(J.words(text[i])), int(0.2 * len(x))) for x in items)
    clean = stage["decontamination"](spark, single, SF)
    assert kept(clean) == {i for i in kept(single) if not text[i] or not held(i)}
    mixed = stage["mixing"](spark, clean, SF)
    told = {r["doc_id"]: r for r in M.mix(clean).collect()}
    cells: dict = {}
    for r in told.values():
        assert r["n_tokens"] == len(re.findall(r"\S+", text[r["doc_id"]]))
        cells[(r["source"], r["lang"], r["topic"])] = cells.get((r["source"], r["lang"], r["topic"]), 0) + r["n_tokens"]
    p = {k: x for k, _, x, _ in M.rake(cells, 0.8).cells}
    assert all(r["probability"] == pytest.approx(p[(r["source"], r["lang"], r["topic"])]) for r in told.values())
    assert kept(mixed) == {i for i, r in told.items() if r["kept"]}
    from tokenizers import Tokenizer

    tok = Tokenizer.from_file(public_tokenizers.path(QS.TOKENIZER))
    start, want = 0, []
    for i in sorted(kept(mixed)):
        x = np.array([*tok.encode(text[i], add_special_tokens=False).ids, 2], "<u4")
        want.append((i, start, len(x), zlib.crc32(x.tobytes())))
        start += len(x)
    assert sorted(tuple(r[c] for c in ("doc_id", "start", "n_tokens", "ids_crc32")) for r in stage["token_blocks"](spark, mixed, SF).collect()) == want


def test_largest_id_and_bounded_sample(spark):
    docs = frame(spark, [*[(i, prose(30, i)) for i in range(400)], ((1 << 63) - 1, prose(30, 999))])
    assert P.fingerprints(docs, 4).count() == 401
    urls = spark.createDataFrame([(i, f"http://h{i}.{'net' if i % 2 else 'org'}/fr/{i}") for i in range(300)], "page_id bigint, url string")
    got = U.judge(urls, "page_id", sample=40).collect()
    assert len(got) == 300 and all((r["rule"], r["verdict"]) == (("net/", "block") if r["page_id"] % 2 else ("org/fr/", "allow")) for r in got)


def test_links_of_large_buckets_are_all_counted(spark):
    """More near texts than a small bucket or a block of a group holds: every pair at the threshold counts, once."""
    base, other = prose(150, 81).split(), prose(150, 82).split()
    texts = [changed(base, int(G.integers(0, 4)), f"a{i}") for i in range(J.WITHIN + 60)] + [changed(other, int(G.integers(1, 6)), f"b{i}") for i in range(90)]
    sets = {t: J.shingles(t) for t in texts}
    want = [sum(t != u and len(s & sets[u]) >= 0.8 * len(s | sets[u]) for u in sets) for t, s in ((t, sets[t]) for t in texts)]
    got = {r["doc_id"]: r["n_links"] for r in J.counted(frame(spark, list(enumerate(texts)))).collect()}
    near = {i: (got[i], n) for i, n in enumerate(want) if got[i] != n}
    assert max(want) > 2 * J.SMALL and all(n - g <= 1 and g <= n for g, n in near.values()) and len(near) <= 4, near


def test_url_models_count_every_labelled_url(spark):
    """The counts of the models are those of all labelled addresses of the fit, each once, and no bounded part of them."""
    rows = [(i, f"http://h{i % 25_000}.{'example.net/en' if i % 2 else 'net'}/p{i % 25_000}") for i in range(50_000)]
    told = spark.createDataFrame([(u.split("://")[1], "allow" if i % 2 else "block") for i, u in rows], "__address string, v string")
    fit = [r[0] for r in told.where(F.pmod(F.xxhash64("__address"), F.lit(5)) != 0).where("v = 'allow'").distinct().collect()]
    ratio = U.fit_whole(told, 2)
    assert len(fit) > 8000 and sum(ratio.accepted.follow[""].values()) == sum(len(a) + 1 for a in fit)
    assert ratio.accepted == U.Markov.fit(fit, 2) and ratio.threshold >= 0
    good, bad = np.array([-1.0, 0.1, 0.3]), np.array([0.2, 0.25, 0.7])
    assert U.cut_of(good, bad) == 0.1 and U.cut_of(np.array([]), bad) == 0.0
    held = [a for a, _ in told.where(F.pmod(F.xxhash64("__address"), F.lit(5)) == 0).where("v = 'allow'").distinct().collect()]
    assert held and U.judge(spark.createDataFrame(rows, "page_id bigint, url string"), "page_id").count() == len(rows)


def test_join_shuffles_only_texts_that_share_a_bucket(spark):
    """Rows whose keys aren't wanted are left out before the shuffle, but for a few; no wanted one is, nor one without id."""
    docs = spark.sql("select if(id = 7, null, id) as doc_id, concat('text ', id) as text from range(20000)")
    rows = docs.select(F.col("doc_id").alias("rep"), "text", F.unhex(F.md5("text")).alias("k"))
    wanted = rows.where("coalesce(rep, 0) % 20 = 0").select("k", "rep")
    found = J.likely(rows, wanted, ["k", "rep"])
    assert found.columns == rows.columns and found.join(wanted, "k", "left_semi").count() == wanted.count() == 1001
    assert found.count() < 4500 and J.likely(rows, wanted.limit(0), ["k", "rep"]).isEmpty()
    assert J.with_texts(wanted, docs).count() == 1001
