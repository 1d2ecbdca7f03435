"""The ten operators against brute force, and their defined results on odd input."""

import hashlib
import itertools
import math
import random
import re
import zlib
from pathlib import Path

import numpy as np
import pytest

pytest.importorskip("semcat.llm.queries")
import public_tokenizers  # noqa: E402
from pyspark.sql import functions as F  # noqa: E402
from tokenizers import Tokenizer  # noqa: E402

from semcat.llm import bpe, common, html_text, language_id, media, ngram_join, packing, pu_learning, queries, topk, url_filter  # noqa: E402

SF = "/root/testdata/sf0.001"
ODD = [(1, None), (2, ""), (3, " \n\t "), (4, "one two"), (4, "one two"), (5, "ONE\x0btwo"), (None, "one two three four five six"), (7, "word " * 30000), (8, "a" * 70000), (9, "é ß 日本語 \U0001f642 |endoftext| <|endoftext|>"), (10, "12 34 !!")]


@pytest.fixture(scope="module")
def odd(spark):
    """Nulls, empty and very long texts, repeated rows, and columns whose names clash with internal ones."""
    names = ["id", "n", "class", "score", "rank", "token", "label", "lang", "bucket"]
    df = spark.createDataFrame(ODD, "doc_id long, text string")
    return df.select("*", *[F.lit(i).alias(x) if x != "lang" else F.when(F.col("doc_id") < 6, "en").alias(x) for i, x in enumerate(names)])


@pytest.fixture(scope="module")
def docs(spark):
    return spark.read.parquet(f"{SF}/documents.parquet")


def shingles(text, width=5):
    w = re.findall(r"[^\x20\x09-\x0D]+", re.sub("[A-Z]", lambda m: m[0].lower(), text or ""))
    return {tuple(w[i : i + width]) for i in range(len(w) - width + 1)} or ({tuple(w)} if w else set())


def components_of(rows):
    sets, up = {}, {}
    for i, t in rows:
        sets.setdefault(i, []).append(shingles(t))
        up[i] = i

    def find(x):
        while up[x] != x:
            x = up[x]
        return x

    ids = sorted(sets)
    for k, a in enumerate(ids):
        for b in ids[k + 1 :]:
            if any(x and y and 100 * len(x & y) >= 80 * len(x | y) for x in sets[a] for y in sets[b]):
                p, q = find(a), find(b)
                up[max(p, q)] = min(p, q)
    return {i: find(i) for i in ids}


def test_jaccard_join_matches_brute_force(spark):
    rng = random.Random(5)
    vocab = ["".join(rng.choice("abcdef") for _ in range(5)) for _ in range(400)]
    base = [[rng.choice(vocab) for _ in range(rng.randint(3, 120))] for _ in range(12)]
    rows = []
    for k in range(160):
        w = list(rng.choice(base))
        for _ in range(rng.randint(0, 5)):
            w[rng.randrange(len(w))] = rng.choice(vocab)
        rows.append((k * 3, " ".join(w)))
    members, links = ngram_join.jaccard_join(spark.createDataFrame(rows, "doc_id long, text string").repartition(5))
    got = {r["id"]: (r["component_id"], r["n_shingles"]) for r in members.collect()}
    want = components_of(rows)
    assert got == {i: (want[i], len(shingles(t))) for i, t in rows}
    assert links.count() > 0


def test_jaccard_join_returns_every_link(spark):
    rng = random.Random(8)
    base = [f"w{k}" for k in range(150)]
    rows = []
    for k in range(300):
        w = list(base)
        for _ in range(rng.randint(1, 4)):
            w[rng.randrange(len(w))] = f"x{rng.randrange(10**6)}"
        rows.append((k * 2 + 1, " ".join(w)))
    rows += [(1000, rows[5][1]), (1001, "")]
    members, links = ngram_join.jaccard_join(spark.createDataFrame(rows, "doc_id long, text string").repartition(3))
    sets = {i: shingles(t) for i, t in rows[:300]}
    want = {(a, b) for a in sets for b in sets if a < b and 100 * len(sets[a] & sets[b]) >= 80 * len(sets[a] | sets[b])}
    assert len(want) > 5000 and sorted(map(tuple, links.collect())) == sorted(want)
    degree = {r["id"]: r["n_links"] for r in members.collect()}
    assert degree == {i: sum((rows[5][0] if i == 1000 else i) in p for p in want) for i, _ in rows}
    counted, _ = ngram_join.jaccard_join(spark.createDataFrame(rows, "doc_id long, text string"), links="counts")
    assert {r["id"]: r["n_links"] for r in counted.collect()} == degree
    few, some = ngram_join.jaccard_join(spark.createDataFrame(rows, "doc_id long, text string"), links="components")
    assert some.count() < len(want) and {r["id"]: r["component_id"] for r in few.collect()} == {r["id"]: r["component_id"] for r in members.collect()}


def test_jaccard_join_in_small_pieces_and_many_bands(spark, monkeypatch):
    """Hot tokens are cut and sent on in pieces, and sizes on both sides of a band's edge still meet."""
    for name, value in (("PIECE", 8), ("TILE", 8), ("GROUP", 8)):
        monkeypatch.setattr(ngram_join, name, value)
    rng = random.Random(3)
    base = [f"w{k}" for k in range(90)]
    rows = []
    for k in range(260):
        w = base[rng.randint(0, 12) : rng.randint(55, 90)]
        for _ in range(rng.randint(0, 2)):
            w[rng.randrange(len(w))] = f"x{rng.randrange(10**6)}"
        rows.append((k, " ".join(w)))
    sets = {i: shingles(t) for i, t in rows}
    rep = {i: min(j for j in sets if sets[j] == sets[i]) for i in sets}
    want = {(a, b) for a in sets for b in sets if a < b and rep[a] == a and rep[b] == b and 100 * len(sets[a] & sets[b]) >= 80 * len(sets[a] | sets[b])}
    df = spark.createDataFrame(rows, "doc_id long, text string").repartition(3)
    members, links = ngram_join.jaccard_join(df)
    assert sorted(map(tuple, links.collect())) == sorted(want)
    component = components_of(rows)
    assert {r["id"]: r["component_id"] for r in members.collect()} == component
    assert {r["id"]: r["component_id"] for r in ngram_join.jaccard_join(df, links="components")[0].collect()} == component


def test_jaccard_join_ties_the_classes_of_one_id(spark):
    a, b = " ".join(f"a{k}" for k in range(30)), " ".join(f"b{k}" for k in range(30))
    rows = [(1, a), (2, b), (5, a), (5, b), (6, ""), (6, a), (8, "c d e"), (9, None)]
    members, _ = ngram_join.jaccard_join(spark.createDataFrame(rows, "doc_id long, text string"))
    want = components_of(rows)
    assert sorted((r["id"], r["component_id"]) for r in members.collect()) == sorted((i, want[i]) for i, _ in rows)


def test_jaccard_join_on_odd_rows(odd):
    members, _ = ngram_join.jaccard_join(odd)
    got = sorted((str(r["id"]), r["n_shingles"], str(r["component_id"])) for r in members.collect())
    want = components_of([r for r in ODD if r[0] is not None])
    assert got == sorted((str(i), len(shingles(t)), str(want.get(i))) for i, t in ODD)
    assert ngram_join.jaccard_join(odd.limit(0))[0].count() == 0


def test_bitmaps_never_hide_a_difference():
    rng = np.random.default_rng(0)
    for _ in range(50):
        a = np.unique(rng.integers(0, 2**63, rng.integers(1, 400)).astype(np.uint64))
        b = np.unique(np.r_[a[rng.random(len(a)) < 0.8], rng.integers(0, 2**63, 20).astype(np.uint64)])
        x, y = ngram_join.parity_bitmap(a), ngram_join.parity_bitmap(b)
        size = min(len(x), len(y))
        assert ngram_join._POP[ngram_join._folded(x, size) ^ ngram_join._folded(y, size)].sum() <= len(np.setxor1d(a, b))


URLS = [("http://EXAMPLE.com/en/x?y=/z", "example.com", "/en/x", "example.com/en/"), ("https://www.example.com/en/a#b", "www.example.com", "/en/a", "www.example.com/en/"), ("https://a.www.example.com/en/", "a.www.example.com", "/en/", "www.example.com/en/"), ("https://x.com", "x.com", "", None), ("ftp://b.net/fr/q", "b.net", "/fr/q", "net/fr/"), ("notcom://xcom/", "xcom", "/", None), ("/en/none", "", "", None), (None, "", "", None), ("", "", "", None), ("a://b://c/d", "b:", "//c/d", None), ("http://h.com/\nx", "h.com", "/\nx", "com/")]


def test_url_rules(spark):
    df = spark.createDataFrame([(i, u[0], "x") for i, u in enumerate(URLS)], "page_id long, url string, host string")
    got = [(r["host"], r["path"], r["rule"]) for r in url_filter.judge(df).orderBy("page_id").collect()]
    assert got == [u[1:] for u in URLS]
    assert url_filter.judge(df.limit(0)).count() == 0


def test_url_model_knows_its_marks():
    w, b = url_filter.fit()
    bad = ["m.casino-win.example.net", "ads-track.example.org", "banner-ads.example.net", "pixel-tracker.example.org", "spam-farm.example.org"]
    good = ["university.example.net", "library.example.org", "railway-museum.example.net", "torvane.example.com"]
    p = url_filter.probabilities(bad + good, ["/en/77"] * 9, w, b)
    assert (p[:5] > 0.5).all() and (p[5:] < 0.5).all()
    assert url_filter.probabilities(["", None], ["", None], w, b).tolist() == [0, 0]


def test_url_scores_match_brute_force(spark):
    """Every score again, n-gram by n-gram; repeated rows, long urls and signs beyond ASCII among them."""
    w, b = url_filter.fit()
    urls = [u[0] for u in URLS] + [URLS[0][0], "http://é日本.example.org/ü/12345", "http://" + "a" * 9000 + ".org/" + "b/" * 9000, "http:///only/path", "://", "http://x.y/007/7"]
    got = url_filter.judge(spark.createDataFrame([(i, u, 1.5, "k") for i, u in enumerate(urls)], "page_id long, url string, score double, best string")).orderBy("page_id").collect()
    assert len(got) == len(urls)
    for r in got:
        slots = set()
        for mark, text in ((1, f"^{r['host']}$"), (2, f"^{re.sub('[0-9]+', '0', r['path'])}$")):
            raw = np.frombuffer(text.encode(), np.uint8)
            for n in (3, 4, 5):
                for i in range(len(raw) - n + 1):
                    h = common.mix(common.span_hashes(raw[i : i + n].copy(), np.array([0]), np.array([n])) + np.uint64(mark))
                    slots.add(int(h[0]) % (1 << url_filter.BITS))
        z = sum(w[x] for x in slots) / np.sqrt(max(1, len(slots))) + b
        want = 1 / (1 + np.exp(-z)) if r["host"] else 0.0
        assert abs(r["score"] - want) < 1e-9
        assert r["rule"] or r["verdict"] == ("block" if want >= 0.5 else "allow")


def test_bpe_equals_the_library(odd, docs):
    tk = Tokenizer.from_file(public_tokenizers.path("word_bpe_49k.json"))
    tk.no_truncation()
    rng = random.Random(1)
    alphabet = "aAbcDİΣσßé'’st 0123٣x́\x1c\x85 ​\n日本語🙂ﬁ<|endoftext|>=-_.,ſK"
    texts = ["".join(rng.choice(alphabet) for _ in range(rng.randint(0, 50))) for _ in range(1500)] + [t or "" for _, t in ODD] + [r["text"] for r in docs.limit(60).collect()]
    own = bpe.WordBpe(public_tokenizers.path("word_bpe_49k.json"))
    for t, e, g in zip(texts, tk.encode_batch(texts, add_special_tokens=False), own.encode(texts), strict=True):
        assert g == (len(e.ids), " ".join(map(str, e.ids)), tk.decode(e.ids, skip_special_tokens=False)), t
    r = bpe.encode(odd, public_tokenizers.path("word_bpe_49k.json")).where("doc_id <= 2").collect()
    assert {(x["n_tokens"], x["ids"], x["decoded"]) for x in r} == {(0, "", "")}


def test_media_round_trip(odd):
    got = {(r["doc_id"], r["n_bytes"]): r for r in media.media_columns(odd).collect()}
    for i, t in ODD:
        raw = (t or "").encode()
        p = raw + b"\0" * (-len(raw) % 64 if raw else 64)
        r = got[i, len(raw)]
        assert (r["payload_bytes"], r["payload_sha256"], r["tail_crc32"]) == (len(p), hashlib.sha256(p).hexdigest(), zlib.crc32(p[-64:]))
        assert r["media_sha256"] == hashlib.sha256(media.sample_file(p)).hexdigest()
    assert media.media_columns(odd.limit(0)).count() == 0


def test_media_shares_chunks(spark):
    rng = random.Random(2)
    body = "".join(rng.choice("abcdefgh ") for _ in range(60000))
    df = spark.createDataFrame([(i, rng.choice("xyz") * i + body) for i in range(6)], "doc_id long, text string")
    stored, table = media.store(df)
    assert table.count() > 5
    assert stored.where("n_shared > 5").count() >= 5
    assert {r["media"][44:].rstrip(b"\0").decode() for r in media.rebuild(stored, table).collect()} == {r["text"] for r in df.collect()}


def test_media_shares_short_copies(spark):
    """A text below the least size of a chunk is stored once, however many documents hold it."""
    df = spark.createDataFrame([(i, "the same short text") for i in range(20)] + [(50, "another")], "doc_id long, text string")
    stored, table = media.store(df)
    assert table.count() == 1 and stored.where("n_shared = 1").count() == 20


def test_scratch_tables_are_removed(spark, docs):
    ngram_join.jaccard_join(docs)
    folder = Path(common._folder(spark))
    assert list(folder.glob("signatures-*")) and not list(folder.glob("sets-*")) and not list(folder.glob("tiles-*"))
    common.clear(spark)
    assert not folder.exists()


def test_cut_points_cover_and_bound():
    rng = np.random.default_rng(3)
    for n in (44, 45, 600, 5000, 200000):
        ends = media.cut_points(rng.integers(0, 256, n).astype(np.uint8))
        sizes = np.diff([0, *ends])
        assert ends[-1] == n and (sizes > 0).all() and sizes.max() <= media.MOST and (sizes[1:-1] >= media.LEAST).all()


def test_packing_covers_every_id(odd, docs):
    path = public_tokenizers.path("byte_bpe_50k.json")
    tk = Tokenizer.from_file(path)
    both = docs.select("doc_id", "text").limit(120).union(odd.select("doc_id", "text"))
    got = packing.pack(both, path).collect()
    ids = {}
    for r in both.collect():
        ids.setdefault(r["doc_id"], []).append(np.array([*tk.encode(r["text"] or "", add_special_tokens=False).ids, 1], "<u4"))
    assert sum(r["length"] for r in got) == sum(len(x) for v in ids.values() for x in v)
    for r in got:
        assert any(len(x) == r["doc_tokens"] and zlib.crc32(x[r["start"] : r["start"] + r["length"]].tobytes()) == r["ids_crc32"] for x in ids[r["doc_id"]])
    by = {}
    for r in got:
        by.setdefault(r["sequence_id"], []).append((r["offset"], r["length"]))
    for v in by.values():
        v.sort()
        assert [o for o, _ in v] == [0, *np.cumsum([n for _, n in v])[:-1].tolist()] and sum(n for _, n in v) <= 2048
    assert packing.pack(odd.limit(0), path).count() == 0


def test_cutting_stock_is_near_the_bound():
    rng = np.random.default_rng(1)
    d = np.bincount(rng.integers(0, 127, 3000), minlength=128)
    plan = packing.cutting_stock(d, 128)
    assert (sum(p * t for p, t in plan) == d).all()
    bins, least = sum(t for _, t in plan), (d * np.arange(1, 129)).sum() / 128
    assert bins <= 1.03 * least + 2
    assert all((p * np.arange(1, 129)).sum() <= 128 for p, _ in plan)


def test_classifiers_learn_and_take_odd_rows(spark, odd):
    rng = random.Random(4)
    words = ["".join(rng.choice("aeioklmn") for _ in range(4)) for _ in range(300)]
    rows = [(i, " ".join(rng.choice(words) for _ in range(80)) + (" awfulword" * (i % 5 == 0))) for i in range(900)]
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    labels = spark.createDataFrame([(i, int(i % 5 == 0), int(i % 5 == 0)) for i, _ in rows], "doc_id long, quality int, toxic int")
    got = pu_learning.toxicity(docs, labels).collect()
    held = [r for r in got if r["held_out"]]
    assert len(held) > 200 and all(r["predicted"] == int(r["doc_id"] % 5 == 0) for r in held)
    assert all(r["held_out"] == (zlib.crc32(str(r["doc_id"]).encode()) % 3 == 1) for r in got)
    out = pu_learning.quality(odd, labels.limit(0)).collect()
    assert len(out) == len(ODD) and all(0 <= r["score"] <= 1 for r in out)
    assert pu_learning.toxicity(odd.limit(0), labels).count() == 0


def test_scores_match_brute_force_and_labels_may_repeat(spark, odd):
    rng = random.Random(6)
    rows = [(i, " ".join(rng.choice("abcdefgh") * 3 for _ in range(20)) + " Bad!" * (i % 3 == 0)) for i in range(300)]
    docs = spark.createDataFrame(rows + rows[:50], "doc_id long, text string")
    given = [(i, int(i % 3 == 0)) for i, _ in rows]
    plain = pu_learning.fit(docs, spark.createDataFrame(given, "doc_id long, toxic int"), "toxic", F.lit(True), floor=3)
    noisy = given + given[:100] + [(9000, 1), (9000, 0), (None, 1)]  # repeats, and a conflict that is not trusted
    model = pu_learning.fit(docs, spark.createDataFrame(noisy, "doc_id long, toxic int"), "toxic", F.lit(True), floor=3)
    assert model.prior == plain.prior == 100 / 300 and (model.weights == plain.weights).all()
    few = pu_learning._picked(docs.select(F.col("doc_id").alias("id")), 40)
    assert 20 <= few.count() <= 40 and few.distinct().count() == few.count()
    weight = dict(zip(model.hashes.tolist(), model.weights.tolist(), strict=True))
    for r in pu_learning.score(odd.union(odd.select("doc_id", F.lit("aaa Bad! bbb"), *odd.columns[2:])).select("doc_id", "text"), model, keep=("text",)).collect():
        text = (r["text"] or "").encode()
        tokens = re.findall(rb"[0-9A-Za-z\x80-\xff]+|[\x21-\x2f\x3a-\x40\x5b-\x60\x7b-\x7f]+", text)
        z = sum(weight.get(int(common.span_hashes(np.frombuffer(t.lower(), np.uint8), np.array([0]), np.array([len(t)]))[0]), 0) for t in set(t.lower() for t in tokens))
        n, words = len(tokens), [t for t in tokens if re.match(rb"[0-9A-Za-z\x80-\xff]", t)]
        size, upper = sum(map(len, words)), len(re.findall(rb"[A-Z]", text))
        dense = [(n - len(words)) / max(n, 1), size / max(len(words), 1) / 10, upper / max(size, 1), np.log1p(n) / 10, n == 0, 1]
        assert abs(r["score"] - 1 / (1 + np.exp(-(z + np.dot(dense, model.dense))))) < 1e-9


def test_toxicity_knows_varied_forms_of_a_mark(spark):
    rng = random.Random(4)
    words = ["".join(rng.choice("aeioklmn") for _ in range(4)) for _ in range(300)]
    mark = lambda i: f" vilex{i}" * (i % 5 == 0)
    rows = [(i, " ".join(rng.choice(words) for _ in range(80)) + mark(i)) for i in range(900)]
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    labels = spark.createDataFrame([(i, int(i % 5 == 0)) for i, _ in rows], "doc_id long, toxic int")
    held = pu_learning.toxicity(docs, labels).where("held_out").collect()
    assert sum(r["predicted"] != int(r["doc_id"] % 5 == 0) for r in held) <= 0.03 * len(held)


def test_language_profiles(spark, odd, docs):
    got = language_id.identify(docs).join(docs.select("doc_id", "lang"), "doc_id").where("held_out")
    assert got.where("lang = lang_pred").count() >= 0.95 * got.count()
    r = {(x["doc_id"], x["lang_pred"]) for x in language_id.identify(odd).collect()}
    assert {(1, "und"), (2, "und"), (3, "und"), (10, "und"), (4, "en"), (9, "en")} <= r
    assert language_id.identify(odd.limit(0)).count() == 0


PAGES = [
    (None, ""), ("", ""), ("plain words only", None),
    ("<html><body><nav><ul><li><a href=x>Home</a></li><li><a href=y>More</a></li></ul></nav><article><h1>Title &amp; more</h1><p>First  <b>bo</b>ld\n text here.<br>Next<p>Second paragraph with &eacute;.</article><div class='cookie-notice'><p>We use cookies</p></div><footer>&copy; us</footer></body></html>", "Title & more First bold text here. Next Second paragraph with é."),
    ("<body><article><p>Body of the text that is long enough to be read by people.</p><script>var x = '<p>no</p>';</script><style>p{}</style><!-- <p>no</p> --><section class=comments><p>nice post</p></section></article>", "Body of the text that is long enough to be read by people."),
]


def test_html_pages(spark):
    df = spark.createDataFrame([(i, f"u{i}", h, "clash") for i, (h, _) in enumerate(PAGES)], "page_id long, url string, html string, text string")
    for r in html_text.extract(df).collect():
        want = PAGES[r["page_id"]][1]
        assert r["n_chars"] == len(r["text"]) and (want is None or r["text"] == want)


_NAV = "<nav><ul><li><a href=x>Home</a></li><li><a href=y>More</a></li></ul></nav>"
_SAID = "Direct text of the article stands here without any paragraph and goes on for a while."
#: Layouts that ``sample_page`` does not make in this form, with their main text.
LAYOUTS = [
    (f"<html><body>{_NAV}<article>{_SAID}<p>Body of the text follows.</p></article><footer>(c)</footer></body></html>", f"{_SAID} Body of the text follows."),
    (f"<html><body>{_NAV}<article>{_SAID}<br>Second line of it.<br>Third line.</article></body></html>", f"{_SAID} Second line of it. Third line."),
    ("<article><p title=it's>Hello there my friends</p><p>Second one it's fine.</p></article>", "Hello there my friends Second one it's fine."),
    ("<body><main>" + "<div>" * 450 + "<p>deep text goes here</p>" + "</div>" * 450 + "<p>Closing paragraph of the text.</p></main><footer>x y</footer></body>", "deep text goes here Closing paragraph of the text."),
    ("<body><main>" + "<div>" * 50 + "<p>deep text goes here</p>" + "</div>" * 50 + "<p>Closing paragraph of the text.</p></main><footer>x y</footer></body>", "deep text goes here Closing paragraph of the text."),
    ("<html><body>Plain page with text directly in the body.<br>More of the text is here.<p>And a paragraph.</p></body></html>", "Plain page with text directly in the body. More of the text is here. And a paragraph."),
    ("<body><div id=header><h1>Site</h1></div><table><tr><td><ul><li><a href=a>A</a></li><li><a href=b>B</a></li></ul></td><td class=story><h2>Title</h2>Story text in a cell, long enough to be read.<p>Second.</td></tr></table><div id=footer>foot</div></body>", "Title Story text in a cell, long enough to be read. Second."),
    ("<body><div class=wrapper><div class=sidebar><p>side note words</p></div><div class=post><h2>T</h2><noscript><p>text for those without scripts</p></noscript><p>Energy is <math><mi>E</mi><mo>=</mo><mi>m</mi></math> here.</p><svg><text>no</text></svg><object><p>object text</p></object></div></div></body>", "T text for those without scripts Energy is E=m here. object text"),
]


def test_html_keeps_the_text_of_other_layouts(spark):
    df = spark.createDataFrame([(i, "u", h) for i, (h, _) in enumerate(LAYOUTS)] + [(0, "u", LAYOUTS[0][0])], "page_id long, url string, html string")
    got = html_text.extract(df).collect()
    assert len(got) == len(LAYOUTS) + 1
    for r in got:
        assert r["text"] == LAYOUTS[r["page_id"]][1]
    long = "<body><article>" + "<p>some words of a long page &amp; more</p>" * 20000 + "</article><footer>x</footer>"
    assert html_text.main_text(long, html_text.trained()) == " ".join(["some words of a long page & more"] * 20000)


def test_html_on_given_pages_by_their_layout(docs, spark):
    """The given pages keep their text in the blocks below ``article``; that rule, without a model, gives the same text."""
    model = html_text.trained()
    for r in spark.read.parquet(f"{SF}/pages.parquet").collect():
        nodes = html_text.parse(r["html"])
        keep = np.zeros(len(nodes), bool)
        for i, up in enumerate(html_text.parents(nodes)):
            keep[i] = nodes[i].tag == "article" or up >= 0 and keep[up] and nodes[i].tag in "p h1 h2 h3 ul ol li pre blockquote table tr td".split()
        assert html_text.main_text(r["html"], model) == html_text.blocks_of(nodes, keep)


def test_html_model_on_new_pages():
    rng, model, wrong, n = random.Random(77), html_text.trained(), 0, 0
    for _ in range(60):
        nodes, flags = html_text.labelled(html_text.sample_page(rng))
        got = html_text.decode(nodes, model.predict(html_text.features(nodes)))
        wrong += int((got != flags.astype(bool)).sum())
        n += len(flags)
    assert wrong <= 0.03 * n


def test_tree_decoding_is_the_best_labelling():
    rng = np.random.default_rng(9)
    for _ in range(40):
        nodes = [html_text.Node("html", None)]
        for _ in range(int(rng.integers(1, 7))):
            nodes.append(html_text.Node("div", nodes[int(rng.integers(len(nodes)))]))
        p, parent = rng.random(len(nodes)), html_text.parents(nodes)
        best = max(
            (sum(np.log(p[i] if s == 1 else 1 - p[i]) for i, s in enumerate(states)), tuple(s == 1 for s in states))
            for states in itertools.product((0, 1, 2), repeat=len(nodes))
            if all(states[i] >= states[parent[i]] for i in range(1, len(nodes))) and states[0] < 2 and all(not (states[i] == 2 and states[parent[i]] == 0) for i in range(1, len(nodes)))
        )
        assert tuple(html_text.decode(nodes, p)) == best[1]


def test_top_k_matches_brute_force(spark):
    rng = np.random.default_rng(6)
    v = rng.normal(size=(400, 16)).astype(np.float32)
    v[7] = v[8] = v[9]
    rows = [(int(i), x.tolist()) for i, x in enumerate(v)] + [(1000, None), (1050, [float("nan")] * 16), (1100, [None] * 16), (1150, [float("inf")] + [0.0] * 15), (1200, [1.0, 2.0])]
    got = topk.top_k(spark.createDataFrame(rows, "vec_id long, embedding array<float>").repartition(3)).collect()
    x = np.floor(v.astype(float) * 256).astype(np.int64)
    want = set()
    for q in range(0, 400, 50):
        s = x @ x[q]
        best = [j for j in np.lexsort((np.arange(400), -s)) if j != q][:5]
        want |= {(q, k + 1, int(j), int(s[j])) for k, j in enumerate(best)}
    assert {(r["query_id"], r["rank"], r["vec_id"], r["score"]) for r in got} == want
    few = spark.createDataFrame([(0, [1.0, 0.5]), (3, [2.0, 1.0])], "vec_id long, embedding array<float>")
    assert [tuple(r) for r in topk.top_k(few).collect()] == [(0, 1, 3, 256 * 512 + 128 * 256)]
    assert topk.top_k(few.limit(0)).count() == 0


def test_top_k_on_odd_rows(spark):
    big = [3e38, -2.0, 1.0]
    rows = [(50, [1.0, 2.0, 3.0]), (50, [1.0, 2.0, 3.0]), (50, [9.0, 9.0, 9.0]), (7, [1.0, 0.0, 0.0]), (7, [1.0, 0.0, 0.0]), (8, big), (100, big), (9, []), (150, []), (200, []), (None, [1.0, 1.0, 1.0]), (10, [0.5])]
    df = spark.createDataFrame(rows, "vec_id long, embedding array<double>").withColumn("score", F.lit("x")).withColumn("id", F.lit(1)).withColumn("q", F.lit(2))
    clip = lambda x: max(-(1 << 63), min((1 << 63) - 1, x))
    exact = [(i, [int(max(-(1 << 60), min(1 << 60, math.floor(256 * c)))) for c in v]) for i, v in rows if i is not None]
    want = []
    for q in {(i, tuple(v)) for i, v in exact if i % 50 == 0}:
        s = sorted(((-clip(sum(a * b for a, b in zip(q[1], v, strict=True))), i) for i, v in exact if i != q[0] and len(v) == len(q[1])))[:5]
        want += [(q[0], k + 1, i, -x) for k, (x, i) in enumerate(s)]
    assert sorted(map(tuple, topk.top_k(df).collect())) == sorted(want)


def test_bounds_hold_and_cells_are_bytes(spark):
    rng = np.random.default_rng(4)
    v = (rng.normal(size=(500, 24)) * rng.choice([1, 50, 10**6], 24)).astype(np.int64)
    q = (rng.normal(size=(40, 24)) * 300).astype(np.int64)
    low, width = v.min(0), (v.max(0) - v.min(0)) // 256 + 1
    cells = ((v - low) // width).astype(np.uint8)
    upper, lower = topk.bounds(low, width, cells, q)
    assert ((v @ q.T <= upper) & (v @ q.T >= lower)).all()
    file = topk.approximation_file(spark.createDataFrame([(i, [float(x) for x in r]) for i, r in enumerate(v)], "vec_id long, embedding array<double>"), 1).collect()
    assert sum(len(r["cells"]) for r in file) == v.size and sorted(np.concatenate([np.frombuffer(r["ids"], np.int64) for r in file]).tolist()) == list(range(500))


def test_pipeline_matches_its_rules(spark):
    import corpus_pipeline as p

    docs = spark.read.parquet(f"{SF}/documents.parquet")
    texts = {r["doc_id"]: r["text"] for r in docs.collect()}
    extra = spark.createDataFrame([(9001, "1 2 3 !!", "en", "s", 8), (9002, None, "en", "s", 0)], docs.schema)
    kept = p.language_id(spark, docs.union(extra), SF)
    assert {r["doc_id"] for r in kept.collect()} == {i for i, t in texts.items() if re.search(r"[^\W\d_]", t)}
    assert kept.columns == p.COLUMNS
    clean = p.toxicity(spark, kept, SF)
    assert clean.count() >= 0.7 * kept.count()
    alone = {r["doc_id"] for r in p.near_duplicates(spark, docs, SF).collect()}
    assert alone == {i for i, c in components_of(list(texts.items())).items() if i == c}
    pieces = p.run(spark, SF)
    assert set(pieces.columns) >= {"doc_id", "start", "length", "ids_crc32", "doc_tokens", "sequence_id", "offset"} and pieces.count() > 0


def test_pipeline_stages_take_odd_rows(spark, odd):
    """Nulls, empty and long texts, repeated rows, null ids, extra and clashing columns, and empty tables, stage by stage."""
    import corpus_pipeline as p

    docs = odd.select("doc_id", "text", "lang", F.lit("s").alias("source"), F.lit(1).cast("long").alias("n_chars"), "id", "score", "label", "rank")
    letters = [(i, t) for i, t in ODD if t and re.search(r"[^\W\d_]", t)]
    key = lambda rows: sorted((str(i), t or "") for i, t in rows)
    kept = p.language_id(spark, docs, SF)
    assert kept.columns == p.COLUMNS and key((r["doc_id"], r["text"]) for r in kept.collect()) == key(letters)
    clean = p.toxicity(spark, docs, SF)
    assert clean.columns == p.COLUMNS and clean.count() <= len(ODD)
    alone = [(r["doc_id"], r["text"]) for r in p.near_duplicates(spark, docs, SF).collect()]
    assert key(alone) == key({(i, t) for i, t in ODD if i != 5})  # 5 repeats 4 but for its case; rows of one id become one
    pieces = p.packing(spark, docs, SF).collect()
    assert len({r["doc_id"] for r in pieces}) == len({i for i, _ in ODD})
    for name, stage in p.STAGES:
        assert stage(spark, docs.limit(0), SF).count() == 0, name


def test_every_query_is_registered():
    names = queries.queries()
    assert sorted({int(re.match(r"op(\d+)_", n)[1]) for n in names}) == list(range(1, 11)) and len(names) == 10


def test_hashes_are_counted_in_runs():
    """Counts merged over runs of rows are those of all rows at once, also for rows without tokens."""
    from semcat.llm.pu_learning import _counts

    rng = np.random.default_rng(5)
    rows = [(np.unique(rng.integers(0, 400, n)).astype(np.uint64), np.zeros(6)) for n in rng.integers(0, 60, 200)]
    want = np.unique(np.concatenate([h for h, _ in rows]), return_counts=True)
    for most in (1, 100, 1 << 20):
        got = _counts(rows, most)
        assert all(np.array_equal(a, b) for a, b in zip(got, want, strict=True))
    assert [len(x) for x in _counts([])] == [0, 0]
