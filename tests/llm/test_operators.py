"""The ten operators: brute force on small tables, and odd rows without a crash."""

import hashlib
import re
import zlib

import numpy as np
import pytest
from pyspark.sql import functions as F

from galoislake.llm import attribution, bytepairs, graph, lines, neighbours, packing, quality, secrets, shingles, urls, vectors, vocab

WORDS = "the of and river stone cloud paper light green house walk seven many bright under over slow winter music north".split()


def prose(seed, n):
    rng = np.random.default_rng(seed)
    return " ".join(WORDS[k] + (str(k) if rng.random() < 0.1 else "") for k in rng.integers(0, len(WORDS), n))


LONG = prose(1, 40_000)
ODD = [(1, prose(2, 60)), (2, None), (3, ""), (4, "  \n\t "), (5, LONG), (1, prose(2, 60)), (None, prose(2, 60)), (7, "x" * 3000), (8, "naïve café ½ 漢字 👩‍👧 password: abcdefgh1234")]


@pytest.fixture(scope="module")
def docs(spark):
    rows = [(i, t, f"s{k % 4}", 5, "clash", "clash", 1) for k, (i, t) in enumerate(ODD)]
    return spark.createDataFrame(rows, "doc_id long, text string, source string, n long, id string, score string, label int").repartition(3)


@pytest.fixture(scope="module")
def none(spark, docs):
    return docs.limit(0)


def by_text(frame, columns):
    return [tuple(r[c] for c in columns) for r in frame.collect()]


def test_quality(spark, docs, none):
    good = [(i, prose(i, 80)) for i in range(300)]
    bad = [(i, prose(i, 80).upper().replace(" ", "!! ")) for i in range(300, 600)]
    table = spark.createDataFrame(good + bad, "doc_id long, text string")
    labels = spark.createDataFrame([(i, int(i < 300)) for i in range(600)] + [(5, None), (9999, 1)], "doc_id long, quality int")
    got = quality.judge(table, labels).collect()
    assert {r.doc_id for r in got if r.held_out} == {i for i in range(600) if zlib.crc32(str(i).encode()) % 4 == 2}
    assert np.mean([(r.score >= 0.7) == (r.doc_id < 300) for r in got if r.held_out]) > 0.97
    odd = quality.judge(docs, labels).collect()
    assert len(odd) == len(ODD) and all(0 <= r.score <= 1 and r.predicted == int(r.score >= 0.7) for r in odd)
    assert quality.judge(none, labels).count() == 0
    assert {r.score for r in quality.judge(docs, labels.limit(0)).collect()} == {0.5}
    assert quality.keep_good(docs, labels).columns == docs.columns
    # Labels of the held-out fold change nothing.
    flipped = labels.selectExpr("doc_id", "CASE WHEN crc32(CAST(CAST(doc_id AS STRING) AS BINARY)) % 4 = 2 THEN 1 - quality ELSE quality END AS quality")
    assert np.allclose(quality.fit(table, labels).means, quality.fit(table, flipped).means)


def test_urls(spark):
    rows = ["http://A.example.NET/en/x?q#f", "https://example.net/en", "ftp://net/", "http://notnet.org/fr/", "http://www.example.com/de/1", "nothing", None, "://", "http://x.net?y", "http://b.a.org/fr/#", "http://a.org:80/fr/", "x://y://z.net/"]
    pages = spark.createDataFrame([(i % 11, u, "clash") for i, u in enumerate(rows)], "page_id long, url string, rule string")
    got = {(r.page_id, r.host, r.path): (r.rule, r.verdict) for r in urls.judge(pages).collect()}
    rules = [(v, *r.partition("/")) for v, r in urls.RULES]
    for i, u in enumerate(rows):
        m = re.match(r"(?s).*?://([^/?#]*)([^?#]*)", u or "")
        host, path = (m[1].lower(), m[2]) if m else ("", "")
        hits = [(len(h + s + p), h + s + p, v) for v, h, s, p in rules if (host == h or host.endswith("." + h)) and path.startswith(s + p)]
        assert got[i % 11, host, path] == (max(hits)[1:] if hits else (None, "allow")), u
    assert urls.judge(pages.limit(0)).count() == 0
    holes = spark.createDataFrame([("block", None), (None, "net/"), ("block", "org/")], "verdict string, rule string")
    assert {r.rule for r in urls.judge(pages, holes).collect()} == {None, "org/"}
    # Many nested rules, as a table: the sweep finds what trying every rule finds.
    rng = np.random.default_rng(3)
    names = [".".join(rng.choice(["a", "b", "c", "d-e", "f"], rng.integers(1, 4))) for _ in range(60)]
    rules = [(("block", "allow")[k % 2], n + ("/", "/x/", "/x/y")[k % 3]) for k, n in enumerate(names)]
    hosts = [".".join(rng.choice(["a", "b", "c", "d-e", "f", "g"], rng.integers(1, 5))) for _ in range(200)]
    paths = [("/", "/x/1", "/x/y/z")[k % 3] for k in range(200)]
    found = urls.sweep(hosts, paths, urls.ordered_rules(rules))
    for h, p, got in zip(hosts, paths, found, strict=True):
        best = max(((len(r), len(r.partition("/")[0])) for _, r in rules if (h == r.partition("/")[0] or h.endswith("." + r.partition("/")[0])) and p.startswith("/" + r.partition("/")[2])), default=None)
        assert (got and (len(got[0]), len(got[0].partition("/")[0]))) == best


def cloud(seed=0, n=400):
    rng = np.random.default_rng(seed)
    x = rng.standard_normal((n, 16))
    x[50:80] = x[50] + 0.05 * rng.standard_normal((30, 16))
    x[80:90] = x[80]
    return [(i, v.tolist(), i % 2 if i >= 100 else 0) for i, v in enumerate(x)] + [(900, None, 0), (901, [0.0] * 16, 0), (902, [float("nan")] * 16, 0), (903, [None] + [1.0] * 15, 0), (904, [1.0] * 16, None), (905, [], 1), (3, x[3].tolist(), 0)]


def test_neighbours(spark):
    rows = spark.createDataFrame(cloud(), "vec_id long, embedding array<double>, label int")
    got = {}
    for r in neighbours.search(rows, rows.where("vec_id % 10 = 0"), block=100, batch=7).collect():
        got.setdefault(r.query_id, []).append((r["rank"], r.vec_id, r.score))
    x = {i: np.array(v) for i, v, _ in cloud() if i < 900 or i == 904}
    hits = 0
    for q, found in got.items():
        want = sorted((-float(x[q] @ v / np.linalg.norm(x[q]) / np.linalg.norm(v)), i) for i, v in x.items() if i != q)[:5]
        assert [r for r, _, _ in sorted(found)] == [1, 2, 3, 4, 5] and len({i for _, i, _ in found}) == 5
        hits += len({i for _, i in want} & {i for _, i, _ in found})
        assert all(abs(s - float(x[q] @ x[i] / np.linalg.norm(x[q]) / np.linalg.norm(x[i]))) < 1e-12 for _, i, s in found)
    assert len(got) == 40 and hits >= 0.9 * 200
    assert neighbours.search(rows.limit(0), rows).count() == 0


@pytest.mark.parametrize("rows_a_pivot", [4000, 20])
def test_vectors(spark, rows_a_pivot):
    data = cloud()
    rows = spark.createDataFrame(data, "vec_id long, embedding array<double>, label int")
    got = {r.vec_id: (r.n_links, r.component_id, r.kept) for r in vectors.dedup(rows, rows_a_pivot=rows_a_pivot, home_block=16, visit_block=32).collect()}
    ok = {i: (np.array(v), k) for i, v, k in data if i < 900}
    links = {i: {j for j, (w, m) in ok.items() if j != i and m == k and v @ w / np.linalg.norm(v) / np.linalg.norm(w) >= 0.93} for i, (v, k) in ok.items()}
    for i in got:
        seen, todo = {i}, [i]
        while todo:
            todo += (new := links.get(todo.pop(), set()) - seen)
            seen |= new
        assert got[i] == (len(links.get(i, ())), min(seen), min(seen) == i), i
    assert vectors.dedup(rows.limit(0)).count() == 0


def test_lines_cut_documents_of_mostly_boilerplate(spark):
    shared = "this long line stands on as many sites as it takes to be boilerplate"
    rows = [(i, f"{shared}\nown {i}\n{shared}", f"s{i}") for i in range(12)] + [(20, shared, "s1"), (21, shared + "\n \n" + shared, "s2")]
    table = spark.createDataFrame(rows, "doc_id long, text string, source string")
    got = {r.doc_id: (r.text, r.n_lines, r.n_cut) for r in lines.cut_boilerplate(table, counts=True).collect()}
    assert got == {i: (f"own {i}", 3, 2) for i in range(12)} | {20: ("", 1, 1), 21: (" ", 3, 2)}
    spared = {r.doc_id: r.text for r in lines.cut_boilerplate(table, spare_copies=True).collect()}
    assert spared == {i: f"own {i}" for i in range(12)} | {i: t for i, t, _ in rows[12:]}


def test_components(spark):
    edges = [(i, i + 1) for i in range(60)] + [(100, k) for k in range(101, 300)] + [(500, 500)]
    got = {r.node: r.component for r in graph.components(spark.createDataFrame(edges, "a long, b long")).collect()}
    assert got == {i: 0 for i in range(61)} | {i: 100 for i in range(100, 300)}


def test_secrets(spark, docs, none):
    texts = ["Password = 'abcdefgh' x", "token: token=aaaa token=bbbbbbbbb", "AKIA12 AKIAABCDEFGHIJKL", "0" * 31 + " " + "f" * 32 + "G", "ſecret: abcdefghij"]
    spans = [[(a, b, k) for a, b, k in secrets.base_spans(t)] for t in texts]
    assert spans[0] == [(0, 20, "assign")] and [k for _, _, k in spans[2]] == ["access"] and spans[3] == [(32, 64, "hex")] and spans[4] == []
    got = secrets.find(docs, secrets.fit(docs)).collect()
    assert len(got) == len(ODD) and sum(r.n_assign for r in got) == 1
    assert secrets.find(none, secrets.fit(none)).count() == 0
    rows = [(i, f"note {prose(i, 5)} password: {hashlib.md5(str(i).encode()).hexdigest()[:18]} then {i}.{i % 9}.2024 and call 555-{i}") for i in range(400)]
    table = spark.createDataFrame(rows, "doc_id long, text string")
    field = secrets.fit(table)
    assert [k for _, _, k in secrets.scan("the auth key: a83bf0279cc1d04e77 was sent", field)] == ["crf"]
    assert secrets.scan("on 12.5.2024 call 555-1234", field) == []
    assert all("[secret]" in r.text and "password" not in r.text for r in secrets.mask(table, field).collect())


def test_chain_decoding_is_the_best_path():
    rng = np.random.default_rng(1)
    field = secrets.Field(rng.standard_normal((secrets.WIDTH, 3)), rng.standard_normal((3, 3)) + np.array([[0, 0, secrets._NEVER], [0, 0, 0], [0, 0, 0]]))
    rows = rng.integers(0, secrets.WIDTH, (6, 4)).tolist()
    unary = [field.weights[r].sum(axis=0) for r in rows]
    best = max(np.ndindex(*[3] * 6), key=lambda t: (t[0] == 2) * secrets._NEVER + sum(unary[i][k] for i, k in enumerate(t)) + sum(field.pairs[a, b] for a, b in zip(t, t[1:], strict=False)))
    assert field.decode(rows) == list(best)


def test_secrets_without_a_digit_and_whole_chains(spark):
    letters = ["".join(np.random.default_rng(i).choice(list("bcdfghjkmpqrtvwxzBCDFGHJKMPQRTVWXZ"), 24)) for i in range(400)]
    rows = [(i, f"note {prose(i, 30)} password: {x} then {prose(i + 1, 9)}") for i, x in enumerate(letters)]
    field = secrets.fit(spark.createDataFrame(rows, "doc_id long, text string"))
    text = "we sent the key QzXwRtBvKpMgHdTcJfWqZxNb to them"  # no digit, and no pattern finds it
    assert secrets.base_spans(text) == [] and secrets.scan(text, field) == [(16, 40, "crf")]
    # All tokens of several texts against trying every chain.
    rng = np.random.default_rng(2)
    texts = ["a1 b-c", "", " x", "ab cd\n\u00e9f", "k=v _ "]
    for size in (0.3, 2.0):
        field = secrets.Field(size * rng.standard_normal((secrets.WIDTH, 3)), rng.standard_normal((3, 3)) + np.array([[0, 0, secrets._NEVER], [0, 0, 0], [0, 0, 0]]))
        for _, chain in secrets._chains(texts):
            unary = sum(field.weights[f] for f in chain.features())
            tags = field.tags(chain)
            for low, high in zip(chain.border, chain.border[1:], strict=False):
                score = lambda t, low=low: sum(unary[low + 1 + i][k] for i, k in enumerate(t)) + sum(field.pairs[a, b] for a, b in zip((0, *t), (*t, 0), strict=True))
                assert tuple(tags[low + 1 : high]) == max(np.ndindex(*[3] * (high - low - 1)), key=score)


def test_secrets_learn_from_distinct_windows(spark, monkeypatch):
    copies = [(i, "one passage 77 that stands in every row of a large part of the table") for i in range(500)]
    rows = copies + [(1000 + i, f"line {i} token: {hashlib.md5(str(i).encode()).hexdigest()[:20]}") for i in range(60)]
    seen = []
    monkeypatch.setattr(secrets, "train", lambda samples, weights: seen.extend(zip(samples, weights, strict=True)))
    secrets.fit(spark.createDataFrame(rows, "doc_id long, text string").repartition(4), most=50)
    assert len(seen) == 50 and sum(m > 1 for _, m in seen) <= 1
    seen.clear()
    secrets.fit(spark.createDataFrame(rows, "doc_id long, text string").repartition(4))
    assert len(seen) >= 61 + 60 * secrets.VARIANTS and sorted(m for _, m in seen)[-1] == 1 + np.log2(500) and sorted(m for _, m in seen)[-2] == 1


def test_base_spans_and_digests(spark):
    rng = np.random.default_rng(8)
    bits = ["password", "PassWd", "secret", "token", "api_key", "apikey", ":", "=", " ", "  ", '"', "'", "abcdefgh", "x1/+_.=-y", "AKIA", "ABCDEFGHIJ12", "0123456789abcdef", "F", "ſ", "\n", "é", "漢"]
    rows = [(k, "".join(rng.choice(bits, int(rng.integers(0, 40))))) for k in range(300)] + ODD
    got = sorted((tuple(r) for r in secrets.find(spark.createDataFrame(rows, "doc_id long, text string").repartition(3), None).collect()), key=str)
    kinds = [("assign", re.compile(r"""(password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", re.I | re.A), 2, 8), ("access", re.compile("AKIA[A-Z0-9]+"), 0, 16), ("hex", re.compile("[0-9a-f]+"), 0, 32)]
    want = []
    for i, text in rows:
        spans = [(m.start(), n, name, m.end()) for n, (name, find, group, least) in enumerate(kinds) for m in find.finditer(text or "") if len(m[group]) >= least]
        shown = ",".join(f"{name}:{a}:{b}" for a, _, name, b in sorted(spans))
        want.append((i, *(sum(s[1] == n for s in spans) for n in range(3)), hashlib.sha256(shown.encode()).hexdigest(), shown))
    assert got == sorted(want, key=str)


def test_masking_leaves_no_tokens_in_a_worker():
    import pyarrow as pa

    field = secrets.Field(np.zeros((secrets.WIDTH, 3)) + [1, 0, 0], np.zeros((3, 3)))
    run = secrets.masker(field, "*")
    got = [b.to_pylist() for b in run(iter([pa.array([prose(1, 50), None, ""]), pa.array(["token=abcdefgh12 end"]), pa.array([], pa.string())]))]
    assert got == [[prose(1, 50), None, ""], ["* end"], []]
    assert len(secrets._KNOWN) == 1 and secrets._KNOWN.chars == 0  # the border


def test_secrets_in_formats_that_no_pattern_knows(spark):
    rng = np.random.default_rng(9)
    drawn = lambda: "".join(rng.choice(list("abcdefghijklmnopqrstuvwxyz0123456789"), 24))
    rows = [(i, f"{prose(i, 25)} token={drawn()}. {prose(i + 1, 25)} on {i % 28}.{i % 12}.2024 see http://site{i}.org/p{i}?q={i} Tel. 0{i}-55{i} id {i:08d} Donaudampfschiffahrt") for i in range(300)]
    table = spark.createDataFrame(rows, "doc_id long, text string")
    field = secrets.fit(table)
    forms = ["Bearer {}", "glpat-{}", "unlock code {}", "licence {} given", "db://root:{}@host"]
    hits = 0
    for k in range(50):
        value = drawn()
        text = f"{prose(k, 20)} {forms[k % 5].format(value)} {prose(k + 1, 20)}"
        at = text.index(value)
        hits += any(s < at + 24 and at < e for s, e, kind in secrets.scan(text, field) if kind == "crf")
    assert hits >= 45
    clean = [(f"{prose(900 + k, 60)} on 3.{k % 12}.2023 see http://other{k}.net/a{k}?b={k} Tel. 07{k}-41{k} id {k:08d} Dampfschiff") for k in range(100)]
    assert sum(len(spans) for spans in secrets.scans(clean, field)) <= 2


def test_packing(spark, docs, none):
    from tokenizers import Tokenizer

    got = packing.pack(docs, bins_at_once=2).collect()
    tokenizer = Tokenizer.from_file(vocab.vocabulary_path("word_bpe_49k.json"))
    tokenizer.encode_special_tokens = True
    want = []
    for i, t in ODD:
        ids = tokenizer.encode(t or "", add_special_tokens=False).ids + [0]
        want += [(i, k // 2048, k, len(ids[k : k + 2048]), zlib.crc32(np.array(ids[k : k + 2048], "<u4").tobytes())) for k in range(0, len(ids), 2048)]
    key = lambda r: (r[0] or -1, *r[1:])
    assert sorted(((r.doc_id, r.piece, r.start, r.length, r.ids_crc32) for r in got), key=key) == sorted(want, key=key)
    full = {}
    for r in got:
        full.setdefault(r.sequence_id, []).append((r.offset, r.length))
    for parts in full.values():
        parts.sort()
        assert all(o == sum(n for _, n in parts[:k]) for k, (o, _) in enumerate(parts)) and sum(n for _, n in parts) <= 2048
    assert packing.pack(none).count() == 0
    small = spark.createDataFrame([(1, "a b"), (2, None), (None, "c")], "doc_id int, text string")
    assert packing.pack(small).schema["doc_id"].dataType.simpleString() == "int" and packing.pack(small).count() == 3


def test_best_fit():
    rng = np.random.default_rng(2)
    sizes = rng.integers(1, 101, 500).tolist()
    bins, places, filled = packing.best_fit(sizes, 100)
    assert max(filled) <= 100 and sum(filled) == sum(sizes) and len(filled) <= 1.05 * sum(sizes) / 100 + 1
    assert all(places[i] + sizes[i] <= filled[b] for i, b in enumerate(bins))


def test_byte_pairs(spark, docs, none):
    path = vocab.vocabulary_path("byte_bpe_50k.tiktoken")
    encoder, _ = vocab.byte_encoder(path, vocab.split_pattern())
    got = sorted(tuple(np.frombuffer(r.ids, "<i4").tolist()) for r in bytepairs.encode(docs, most=10).collect())
    assert got == sorted(tuple(encoder.encode_ordinary(t or "")) for _, t in ODD)
    assert all(bytepairs.decode(np.array(g, "<i4").tobytes(), path) in {(t or "").encode() for _, t in ODD} for g in got)
    assert bytepairs.encode(none).count() == 0


def test_byte_pair_digests(spark, monkeypatch):
    path = vocab.vocabulary_path("byte_bpe_50k.tiktoken")
    encoder, _ = vocab.byte_encoder(path, vocab.split_pattern())
    rng = np.random.default_rng(5)
    odd = ["".join(rng.choice(list("aehinorstu"), n)) for n in (127, 128, 129, 3000)] + ["漢字仮名" * 60, " " * 500, "\n" * 300 + "x", "!?" * 200, "\x00\x1c a", "12345678901", "it's IT'S"]
    for most, remembered in ((5, 20), (1000, bytepairs.REMEMBERED)):
        monkeypatch.setattr(bytepairs, "REMEMBERED", remembered)
        rows = spark.createDataFrame([(k, t) for k, t in enumerate(odd)] + ODD + ODD, "doc_id long, text string").repartition(3)
        want = []
        for i, t in [*enumerate(odd), *ODD, *ODD]:
            ids = encoder.encode_ordinary(t or "")
            want.append((i, len(ids), hashlib.sha256(" ".join(map(str, ids)).encode()).hexdigest(), hashlib.sha256((t or "").encode()).hexdigest()))
        got = [tuple(r) for r in bytepairs.digests(rows, most=most).collect()]
        assert sorted(got, key=str) == sorted(want, key=str)


def test_folded_words_find_places_without_a_search(spark):
    path = vocab.vocabulary_path("byte_bpe_50k.tiktoken")
    encoder, _ = vocab.byte_encoder(path, vocab.split_pattern())
    rng = np.random.default_rng(3)
    words = [b"a", "ñ".encode(), b"aaaaaa", b" ofanstheran", *(bytes(rng.choice(np.frombuffer(b"theanding ", np.uint8), n)) for n in (2, 9, 30, bytepairs.LONG))]
    starts = spark.createDataFrame([(k, [vocab.ranks(path)[bytes([b])] for b in w]) for k, w in enumerate(words)], "k int, start array<int>")
    folded = starts.select("k", bytepairs.Coder(spark, path).fold(F.col("start")).alias("ids"))
    assert [r.ids for r in folded.orderBy("k").collect()] == [encoder._encode_single_piece(w) for w in words]
    assert "array_position" not in folded._jdf.queryExecution().toString()


def test_pieces_of_agreed_characters_are_those_of_the_pattern():
    import regex

    pattern = vocab.split_pattern()
    want, got = regex.compile(pattern).findall, vocab.cutter(pattern)
    for c in map(chr, (i for i in range(1 << 16) if not 0xD800 <= i < 0xE000)):
        for text in (c, f"a{c}1{c}", f" {c}\n {c} \n", f"'s{c}'re {c}'{c}"):
            if vocab._agreed(c):
                assert got(text) == want(text)
    for text in (LONG, "", "x² ½\x1c\x85 naïve", "it's I'LL we'll  \n\u00a0 x_1 12a", *(t or "" for _, t in ODD)):
        assert got(text) == want(text)


def test_long_words_take_the_same_merges():
    path = vocab.vocabulary_path("byte_bpe_50k.tiktoken")
    encoder, _ = vocab.byte_encoder(path, vocab.split_pattern())
    rng = np.random.default_rng(6)
    for k in range(60):
        n = int(rng.integers(1, 400))
        word = (bytes(rng.integers(97, 123, n).astype(np.uint8)), b"a" * n, bytes(rng.choice(np.frombuffer(b"theanding ", np.uint8), n)))[k % 3]
        assert bytepairs.merge_long(word, vocab.ranks(path)) == encoder._encode_single_piece(word)


def test_lines(spark, docs, none):
    shared = "this line stands on many sites"
    body = "\n".join(prose(k, 12) for k in range(3))
    rows = [(i, f"{shared}\n{body} {i}\n\n{shared}", f"s{i % 6}") for i in range(12)] + [(50, None, "s1"), (51, "", None), (52, shared, "s2"), (53, shared + "\n" + shared, None)]
    table = spark.createDataFrame(rows, "doc_id long, text string, source string")
    got = {r.doc_id: (r.text, r.n_lines, r.n_cut) for r in lines.cut_boilerplate(table, min_sites=5, counts=True).collect()}
    for i in range(12):  # the first two lines of every body are on all six sites as well
        assert got[i] == (body.split("\n")[2] + f" {i}\n", 6, 4)
    assert got[50] == (None, 0, 0) and got[51] == ("", 1, 0) and got[52] == ("", 1, 1)
    named = lines.cut_boilerplate(table.selectExpr("*", "'x' AS n_lines", "7 AS n_cut"), min_sites=5, counts=True)
    assert named.columns == ["doc_id", "text", "source", "n_lines", "n_cut"] and {r.doc_id: r.n_cut for r in named.collect()}[52] == 1
    assert lines.cut_boilerplate(docs).columns == docs.columns and lines.cut_boilerplate(docs).count() == len(ODD)
    assert lines.cut_boilerplate(none).count() == 0


def test_shingles(spark, docs, none):
    rng = np.random.default_rng(4)
    rows = []
    for f in range(12):  # families of near copies, some of them exact
        base = prose(100 + f, 60 if f else 400).split()
        for k in range(20):
            w = list(base)
            for at in rng.integers(0, len(w), k % 5):
                w[at] = f"edit{rng.integers(1e9)}"
            rows.append((int(rng.integers(1e6)), " ".join(w).title() if k % 7 == 0 else " ".join(w)))
    rows += [(2_000_000 + k, prose(9, 30) + f" tail {k}") for k in range(30)] + [(3_000_000, "one two"), (3_000_001, "ONE\ttwo"), (3_000_002, None), (3_000_003, " "), (3_000_004, "one two\u00a0")]
    rows = list(dict(rows).items())
    table = spark.createDataFrame(rows, "doc_id long, text string").repartition(4)
    low = str.maketrans("ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")
    sets = {}
    for i, t in rows:
        w = re.findall(r"[^\x20\x09-\x0D]+", (t or "").translate(low))
        sets[i] = {tuple(w[k : k + 5]) for k in range(max(1, len(w) - 4))} if w else set()
    root = {i: i for i in sets}

    def top(i):
        while root[i] != i:
            i = root[i]
        return i

    for i in sets:
        for j in sets:
            if i < j and sets[i] and 100 * len(sets[i] & sets[j]) >= 80 * len(sets[i] | sets[j]):
                a, b = sorted((top(i), top(j)))
                root[b] = a
    got = {r.doc_id: (r.n_shingles, r.component_id) for r in shingles.near_duplicates(table).collect()}
    assert got == {i: (len(s), top(i)) for i, s in sets.items()}
    odd = shingles.near_duplicates(docs).collect()
    assert len(odd) == len(ODD) and all(r.component_id is None for r in odd if r.doc_id is None)
    assert shingles.near_duplicates(none).count() == 0
    kept = shingles.keep_one(table)
    assert kept.columns == table.columns and {r.doc_id for r in kept.collect()} == {i for i in sets if top(i) == i}


@pytest.mark.parametrize("rule", attribution.RULES)
def test_token_counts(spark, docs, none, rule):
    encoder, _ = vocab.byte_encoder(vocab.vocabulary_path("byte_bpe_50k.tiktoken"), vocab.split_pattern())
    got = attribution.count_tokens(docs, rule=rule).collect()
    assert sum(r.n_tokens for r in got) == sum(len(encoder.encode_ordinary(t or "")) for _, t in ODD)
    assert len(got) == sum((t or "").count("\n") + (not (t or "").endswith("\n") or not t) for _, t in ODD)
    assert attribution.count_tokens(none).count() == 0
    two = spark.createDataFrame([(1, "a b\n\n\nc", None), (2, "é", "zwei drei\n")], "doc_id long, text string, source string")
    parts = attribution.count_tokens(two, ("text", "source"), rule).collect()
    whole = {1: "a b\n\n\nc\n", 2: "é\nzwei drei\n"}
    for i, t in whole.items():
        mine = sorted((r.section, r.start, r.end, r.n_tokens) for r in parts if r.doc_id == i)
        assert mine[0][1] == 0 and all(a[2] == b[1] for a, b in zip(mine, mine[1:], strict=False)) and mine[-1][2] == len(t)
        assert sum(m[3] for m in mine) == len(encoder.encode_ordinary(t))


def test_boundary_tokens_go_by_the_rule():
    spans, sizes = [(0, 0, 2), (0, 2, 3), (0, 3, 9)], np.array([1, 5, 3])
    assert [attribution.allot("abcdefghi", spans, sizes, r)[0].tolist() for r in attribution.RULES] == [[2, 0, 1], [1, 0, 2], [1, 0, 2]]
