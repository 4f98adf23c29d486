"""The corpus operators on small fixtures: brute force, round trips and edge cases."""

import hashlib
import itertools
import random
import re
import zlib

import numpy as np
import pytest

from lattica.llm import chat, common, components, decontaminate, htmltext, langid, media, mixing, neardup, pii, suffixdedup, toxicity

DOC = "doc_id long, text string, lang string, source string, n_chars long"


def docs(spark, texts, start=0):
    return spark.createDataFrame([(i + start, t, "en", "s", None if t is None else len(t)) for i, t in enumerate(texts)], DOC)


def sentence(rng, n, words=None):
    words = words or [a + b + c for a, b, c in itertools.product(("ka", "lo", "mi", "tu"), ("ra", "se", "no"), ("x", "l", "m"))]
    return " ".join(rng.choice(words) for _ in range(n))


EDGE = [None, "", " \n\t ", "one", "ab cd", "ab cd", "é" * 300, "x" * 100_000]


# ------------------------------------------------------------------ 1 mixing


def test_mixing_meets_targets(spark):
    rng = random.Random(1)
    texts = [("good " * 20 + sentence(rng, 30)) if i % 3 else ("junk %% " * 15 + sentence(rng, 10)) for i in range(90)]
    d = docs(spark, texts + EDGE)
    lab = spark.createDataFrame([(i, "good" if i % 3 else "junk") for i in range(60)], "doc_id long, domain string")
    out = mixing.mix(d.withColumnRenamed("lang", "rate"), lab, {"good": 0.5, "junk": 0.5}).collect()
    assert len(out) == len(texts) + len(EDGE)
    total = sum(r.n_tokens for r in out)
    for name in ("good", "junk"):
        assert sum(r.rate * r.n_tokens * r[f"p_{name}"] for r in out) == pytest.approx(total / 2, rel=1e-5)
    assert all(r.rate >= 0 and abs(r.repeats - r.rate) <= 1 for r in out)
    assert all(r.rate == 1 for r in out if not r.n_tokens)


def test_rates_equal_brute_force_optimum(spark):
    # targets that some nonnegative rates meet exactly (most of them zero): the least squares optimum is 0
    rng = np.random.default_rng(0)
    n, k = 9, 3
    p = rng.dirichlet(np.ones(k) * 0.6, n)
    tokens, copies = rng.integers(5, 60, n), rng.integers(1, 4, n)
    mass = (tokens * copies)[:, None] * p
    wanted = np.where(rng.random(n) < 0.4, rng.random(n) * 3 + 0.2, 0.0) + 0.05
    target = wanted @ mass
    rows = [(int(c), int(t), *map(float, x)) for c, t, x in zip(copies, tokens, p, strict=True)]
    frame = spark.createDataFrame(rows, "n_rows long, n_tokens long, p_0 double, p_1 double, p_2 double").coalesce(1)
    out, totals, aimed, _ = mixing.fit_rates(frame, list(target / target.sum()), budget=float(target.sum()))
    rates = np.array([r.rate for r in out.collect()])
    assert (rates >= 0).all() and aimed == pytest.approx(target)
    # brute force over the sets of documents with a positive rate: the smallest residual of all
    best = np.inf
    for some in itertools.chain.from_iterable(itertools.combinations(range(n), j) for j in range(1, k + 1)):
        r = np.linalg.lstsq(mass[list(some)].T, target, rcond=None)[0]
        if (r >= -1e-9).all():
            best = min(best, np.linalg.norm(r @ mass[list(some)] - target))
    assert np.linalg.norm(np.asarray(totals) - target) <= best + 1e-3 * target.sum()


def test_mixing_query(spark, tmp_path):
    rng = random.Random(21)
    texts = [("fine " * 20 + sentence(rng, 30)) if i % 3 else ("junk %% " * 15 + sentence(rng, 10)) for i in range(90)]
    docs(spark, [*texts, *EDGE]).write.parquet(f"{tmp_path}/documents.parquet")
    labels = [(i, int(i % 3 > 0), 0) for i in range(60)] + [(2, 1, 0), (None, 1, 0), (3, None, None)]
    spark.createDataFrame(labels, "doc_id long, quality int, toxic int").write.parquet(f"{tmp_path}/labels.parquet")
    out = mixing.op1_mixing(spark, str(tmp_path)).collect()
    assert len(out) == len(texts) + len(EDGE) and all(r.rate >= 0 for r in out)
    total = sum(r.n_tokens for r in out)
    share = {d: mixing.TARGETS[d] for d in ("good", "junk")}
    for d, t in share.items():
        assert sum(r.rate * r.n_tokens * r[f"p_{d}"] for r in out) == pytest.approx(total * t / sum(share.values()), rel=1e-4)


def test_mixing_without_labels_or_rows(spark):
    none = spark.createDataFrame([], "doc_id long, domain string")
    assert {r.rate for r in mixing.mix(docs(spark, ["a b", None]), none).collect()} == {1.0}
    assert mixing.mix(docs(spark, []), none).count() == 0


# ------------------------------------------------------------------ 2 near-duplicates


def brute_classes(texts):
    word = re.compile(r"[^ \t\n\r\f\v]+")
    sets = []
    for t in texts:
        w = word.findall((t or "").lower())
        sets.append({tuple(w[j : j + 5]) for j in range(max(1, len(w) - 4))} if w else set())
    top = list(range(len(texts)))
    for i, j in itertools.combinations(range(len(texts)), 2):
        if sets[i] and sets[j] and len(sets[i] & sets[j]) >= 0.8 * len(sets[i] | sets[j]):
            a, b = top[i], top[j]
            top = [min(a, b) if x in (a, b) else x for x in top]
    return top


def test_near_duplicates_equal_brute_force(spark):
    rng = random.Random(2)
    texts = list(EDGE)
    for _ in range(8):
        base = sentence(rng, 80).split()
        texts.append(" ".join(base))
        for _ in range(4):
            w = list(base)
            for k in rng.sample(range(80), rng.randint(0, 4)):
                w[k] = "zz" + str(rng.random())
            texts.append(" ".join(w))
    got = {r.doc_id: r.class_id for r in neardup.classes(docs(spark, texts)).collect()}
    assert [got[i] for i in range(len(texts))] == brute_classes(texts)
    kept = [r.doc_id for r in neardup.keep_first(docs(spark, texts)).collect()]
    assert sorted(kept) == sorted(i for i, c in got.items() if i == c)


def test_near_duplicates_edges(spark):
    assert neardup.classes(docs(spark, [])).count() == 0
    same = docs(spark, ["a b c d e f"] * 3).withColumn("doc_id", common.F.lit(4).cast("long"))
    assert neardup.keep_first(same).count() == 1
    noid = docs(spark, ["a b c d e f"] * 2).withColumn("doc_id", common.F.lit(None).cast("long"))
    assert neardup.classes(noid).count() == 2


def test_probability_jaccard_estimate():
    rng = np.random.default_rng(0)
    shared, a, b = (rng.integers(0, 2**63, n).astype(np.uint64) for n in (60, 20, 20))
    doc = np.repeat([0, 1], 80)
    h = np.concatenate([shared, a, shared, b])
    s = neardup.signatures(2, *neardup.weighted(doc, h), m=4096)
    assert (s[0] == s[1]).mean() == pytest.approx(0.6, abs=0.04)


def test_compared_blocks_equal_brute_force(spark, monkeypatch):
    # members of one bucket, exactly compared in blocks: what the links join is what all pairs join
    monkeypatch.setattr(neardup, "BLOCK", 16)
    rng = np.random.default_rng(0)
    sets = []
    for _ in range(6):
        base = rng.integers(0, 2**62, 80).astype(np.uint64)
        for _ in range(20):
            x, k = base.copy(), rng.integers(0, 24)
            x[rng.choice(80, k, replace=False)] = rng.integers(0, 2**62, k)
            sets.append(np.unique(x))
    frame = spark.createDataFrame([(bytearray([i]), bytearray(x.tobytes())) for i, x in enumerate(sets)], "node binary, shingles binary")
    left = spark.createDataFrame([(1, bytearray([i]), bytearray([i])) for i in range(len(sets))], "bucket long, node binary, comp binary")
    links = neardup.compared(left, frame, 0.8).collect()
    sim = lambda a, b: len(np.intersect1d(a, b)) / len(np.union1d(a, b))
    assert all(sim(sets[r.a[0]], sets[r.b[0]]) >= 0.8 for r in links)

    def joined(pairs):
        top = list(range(len(sets)))
        for a, b in pairs:
            x, y = top[a], top[b]
            top = [min(x, y) if t in (x, y) else t for t in top]
        return top

    every = [(i, j) for i, j in itertools.combinations(range(len(sets)), 2) if sim(sets[i], sets[j]) >= 0.8]
    assert joined((r.a[0], r.b[0]) for r in links) == joined(every) and len(every) > 100
    blocks = -(-len(sets) // 16)
    assert len(links) <= blocks * (blocks + 1) / 2 * 32  # rows by blocks, not by pairs


def repeated_passages(rng, most=200):
    """Texts with as many shared shingles as two similar ones, in which one repeats a passage over and over."""
    base = sentence(rng, 104, [f"w{i}{rng.random()}" for i in range(400)]).split()
    more = [f"q{i}{rng.random()}" for i in range(rng.choice((0, 3, 8)))]
    part = base[40:61]
    return " ".join(base), " ".join(base + (part * most) + more)


def test_near_duplicates_with_repeated_passages(spark):
    rng = random.Random(8)
    texts = [t for _ in range(60) for t in repeated_passages(rng)]
    got = {r.doc_id: r.class_id for r in neardup.classes(docs(spark, texts)).collect()}
    want = brute_classes(texts)
    assert sum(a != i for i, a in enumerate(want)) > 30
    assert [got[i] for i in range(len(texts))] == want


def test_last_comparison_is_exact(spark):
    rng = random.Random(9)
    texts = [t for _ in range(60) for t in repeated_passages(rng, 30)]
    texts += [" ".join(w if rng.random() > 0.03 else "zz" + str(rng.random()) for w in texts[0].split()) for _ in range(40)]
    node = lambda i: bytearray(i.to_bytes(2, "big"))
    sets = neardup.shingle_sets(spark.createDataFrame([(node(i), t) for i, t in enumerate(texts)], "node binary, text string"))
    left = spark.createDataFrame([(1, node(i), node(i)) for i in range(len(texts))], "bucket long, node binary, comp binary")
    top = list(range(len(texts)))
    for r in neardup.compared(left, sets, 0.8).collect():
        a, b = (top[int.from_bytes(x, "big")] for x in (r.a, r.b))
        top = [min(a, b) if x in (a, b) else x for x in top]
    assert top == brute_classes(texts)


def test_components(spark):
    edges = [(1, 2), (2, 3), (3, 4), (10, 11), (11, 12), (20, 20)] + [(i, i + 1) for i in range(100, 140)]
    got = {r.node: r.comp for r in components.components(spark.createDataFrame(edges, "a long, b long")).collect()}
    assert got[4] == 1 and got[12] == 10 and got[140] == 100 and 20 not in got


# ------------------------------------------------------------------ 3 suffix arrays


def brute_repeats(rows, length=50):
    first = {}
    for i, t in rows:
        b = (t or "").encode()
        if i is not None:
            for p in range(len(b) - length + 1):
                k = b[p : p + length]
                first[k] = min(first.get(k, i), i)
    out = {}
    for i, t in rows:
        b = (t or "").encode()
        gone = [False] * len(b)
        if i is not None:
            for p in range(len(b) - length + 1):
                if first[b[p : p + length]] < i:
                    gone[p : p + length] = [True] * length
        kept = bytes(x for x, g in zip(b, gone, strict=True) if not g)
        runs = sum(g and (k == 0 or not gone[k - 1]) for k, g in enumerate(gone))
        out[i] = (len(b), sum(gone), runs, hashlib.sha256(kept).hexdigest())
    return out


def test_repeats_equal_brute_force(spark, monkeypatch):
    rng = random.Random(3)
    line = sentence(rng, 30)
    texts = [None, "", "x" * 49, "x" * 50, "x" * 400, "x" * 120, "ab" * 300, "ba" * 100, "é" * 80, "é" * 40 + line]
    texts += [sentence(rng, 20) + line + sentence(rng, 10) for _ in range(12)] + [texts[4], line, line[:60], line[30:]]
    rows = list(enumerate(texts))
    want = brute_repeats(rows)
    for shard in (4 << 20, 2000):
        monkeypatch.setattr(suffixdedup, "SHARD", shard)
        got = {r.doc_id: (r.n_bytes, r.n_removed, r.n_spans, r.kept_sha256) for r in suffixdedup.remove_repeats(docs(spark, texts)).collect()}
        assert got == want


def test_repeats_edges(spark):
    assert suffixdedup.remove_repeats(docs(spark, [])).count() == 0
    t = "y" * 90
    d = spark.createDataFrame([(None, t), (5, t), (5, t), (7, t)], "doc_id long, text string")
    got = sorted((r.doc_id or -1, r.n_removed) for r in suffixdedup.remove_repeats(d).collect())
    assert got == [(-1, 0), (5, 0), (5, 0), (7, 90)]


@pytest.mark.parametrize("seed", range(4))
def test_suffix_array_and_prefixes(seed):
    rng = np.random.default_rng(seed)
    data = rng.integers(97, 99 + seed, 400).astype(np.uint8)
    data[200:300] = data[50:150]
    sa = suffixdedup.suffix_array(data, 50)
    raw = data.tobytes()
    assert sorted(sa.tolist()) == list(range(400))
    cuts = [raw[p : p + 50] for p in sa]
    assert all(a <= b for a, b in zip(cuts[:-1], cuts[1:], strict=True))
    lcp = suffixdedup.common_prefixes(data, sa, 50)

    def common_(p, q):
        n = 0
        while n < 50 and max(p, q) + n < 400 and raw[p + n] == raw[q + n]:
            n += 1
        return n

    assert [common_(sa[i - 1], sa[i]) for i in range(1, 400)] == lcp[1:].tolist()
    # with suffixes left out: runs of listed positions of several lengths
    listed = np.repeat(rng.random(40) < 0.7, 10) & (np.arange(400) % 37 > 2)
    few = sa[listed[sa]]
    assert [common_(few[i - 1], few[i]) for i in range(1, len(few))] == suffixdedup.common_prefixes(data, few, 50)[1:].tolist()


# ------------------------------------------------------------------ 4 html


PAGE = """<html><head><title>t</title><style>p{}</style></head><body><header>Site</header><nav><ul><li><a href="/">Home</a></ul></nav>
<div class="cookie-notice">We use cookies</div><div class="content-12"><h1>Head &amp; tail</h1><p>First   para<br>line<p>Second <b>bold</b> &#233;
<script>var x = "<p>no</p>";</script><form><p>form</p></form></div><div id="comments"><p>nice post, I like it a lot, really</p></div><aside>side</aside><footer>foot</footer></body></html>"""


def test_html(spark):
    want = "Head & tail\n\nFirst para line\n\nSecond bold é"
    pages = spark.createDataFrame([(1, "http://a.com/1", PAGE), (2, "http://a.com/2", None), (3, None, ""), (4, "http://b.com", "plain & text"), (5, "http://a.com/5", PAGE.replace("content-12", "content-7"))], "page_id long, url string, html string")
    got = {r.page_id: r.text for r in htmltext.extract_main_text(pages).collect()}
    assert got == {1: want, 2: "", 3: "", 4: "plain & text", 5: want}
    assert htmltext.extract_main_text(pages.limit(0)).count() == 0


def test_html_host_consensus():
    # a page whose own best container is another one follows its host
    page = '<body><div class="story"><p>short</p></div><div class="other"><p>' + "long text " * 30 + "</p></div></body>"
    assert htmltext.extract(page, ">body>div.story") == "short"
    assert htmltext.extract(page, None).startswith("long")


def main_text(page):
    return htmltext.extract(page, htmltext.best_path(htmltext.blocks(page)))


def test_html_keeps_all_parts_of_the_article():
    long = "long text " * 40
    # sections of different classes, a headline beside the body, an article beside its title, nested containers
    assert main_text('<body><main><section class="a"><p>one</p></section><section class="b"><p>two two</p></section></main></body>') == "one\n\ntwo two"
    assert main_text(f'<body><article><h1>T</h1><div class="body"><p>{long}</p></div></article></body>') == "T\n\n" + long.strip()
    assert main_text(f"<body><main><h1>T</h1><article><p>{long}</p></article></main></body>") == "T\n\n" + long.strip()
    assert main_text(f'<body><div class="content"><h1>T</h1><div class="x"><div class="y"><p>{long}</p></div></div><ul><li>end</li></ul></div></body>') == f"T\n\n{long.strip()}\n\nend"
    # of several articles in main, the one that holds most
    assert main_text(f"<body><main><article class='teaser'><p>short</p></article><article><p>{long}</p></article></main></body>") == long.strip()


def test_html_noise_words():
    assert main_text('<body><article><p>He said <span class="comment">word</span> and <b id="menu">more</b>.</p></article>') == "He said word and more."
    assert main_text('<body><div class="content no-sidebar has-comments"><h1>H</h1><p>abc</p></div></body>') == "H\n\nabc"
    assert main_text('<body><div class="page-with-menu sidebar"><h1>H</h1><p>abc</p></div></body>') == "H\n\nabc"  # holds the headline
    for noise in ('class="ad-slot"', 'class="cookie_notice"', 'id="comments"', 'class="post-comments"', 'class="x related"', 'role="navigation"', "hidden", 'style="display: none"'):
        assert main_text(f"<body><article><h1>H</h1><p>abc</p><div {noise}><p>noise noise noise noise</p></div></article></body>") == "H\n\nabc", noise


def test_html_takes_linear_time():
    import time

    started = time.perf_counter()
    for part in ('<a "', '<a href="', "<div>", "<!--", "<p><b>x", "</div>", '<div class="menu">', "<x y='>", "<script>"):
        htmltext.extract(part * (1_000_000 // len(part)), None)
    assert time.perf_counter() - started < 60


def test_html_query(spark, tmp_path):
    host = '<body><div class="story-9"><p>{}</p></div><div class="other"><p>{}</p></div></body>'
    rows = [(i, f"http://h.com/{i}", host.format("words " * 60, "few")) for i in range(5)]
    rows += [(9, "http://h.com/9", host.format("short", "text " * 50)), (9, "http://h.com/9", host.format("short", "text " * 50)), (None, None, None), (11, "", ""), (12, "x", "é &lt;b&gt; " * 40_000)]
    spark.createDataFrame(rows, "page_id long, url string, html string").withColumn("text", common.F.lit("clash")).write.parquet(f"{tmp_path}/pages.parquet")
    out = htmltext.op4_html_main_text(spark, str(tmp_path))
    assert [(f.name, f.dataType.simpleString()) for f in out.schema] == [("page_id", "bigint"), ("url", "string"), ("text", "string"), ("n_chars", "bigint")]
    got = out.collect()
    assert len(got) == len(rows) and all(r.n_chars == len(r.text) for r in got)
    by = {r.page_id: r.text for r in got}
    assert by[0] == ("words " * 60).strip() and by[9] == "short"  # equal rows agree, the host decides
    assert by[None] == by[11] == "" and by[12] == ("é <b> " * 40_000).strip()


def test_html_never_fails():
    rng = random.Random(4)
    bits = ["<p>", "</p>", "<div", ">", "<!--", "-->", "text", "<a href='x", "&amp;", "<script>", "</script>", "<ul><li>", "</article>", "<article>", "<br/>", "\x00", "<![CDATA[", "]]>"]
    for _ in range(300):
        htmltext.extract("".join(rng.choice(bits) for _ in range(30)), None)


# ------------------------------------------------------------------ 5 language


def test_language(spark):
    rng = random.Random(5)
    vocab = {k: ["".join(rng.choice(s) for _ in range(4)) for _ in range(60)] for k, s in {"aa": "abcde", "bb": "fghij"}.items()}
    rows = [(i, sentence(rng, 80, vocab[k]), k) for i, k in enumerate(["aa", "bb"] * 20)]
    train = spark.createDataFrame(rows[:30], "doc_id long, text string, lang string")
    model = langid.fit(train)
    test = spark.createDataFrame([*rows[30:], (90, None, "aa"), (91, "123 !!", "aa"), (92, "", None)], "doc_id long, text string, lang string")
    got = {r.doc_id: r for r in langid.predict(test, model).collect()}
    assert all(got[i].lang_pred == k for i, _, k in rows[30:])
    assert all(got[i].lang_pred == "und" and got[i].score == 0 for i in (90, 91, 92))
    assert all(0 <= r.score <= 1 for r in got.values())
    assert {r.lang_pred for r in langid.predict(test, {}).collect()} == {"und"}


def test_language_with_short_texts_only(spark):
    rng = random.Random(6)
    vocab = {k: ["".join(rng.choice(c) for _ in range(9)) for _ in range(40)] for k, c in {"aa": "abcde", "bb": "fghij", "cc": "klmno"}.items()}
    rows = [(i, sentence(rng, 80 if k == "aa" else 4, vocab[k]), k) for i, k in enumerate(["aa", "bb", "cc"] * 60)] + [(500, "123", "dd"), (501, "x", None), (None, None, "ee")]
    model = langid.fit(spark.createDataFrame(rows, "doc_id long, text string, lang string"))
    assert {k for k, v in model.items() if v} == {"aa", "bb", "cc"}
    test = [(i, sentence(rng, 30, vocab[k]), k) for i, k in enumerate(["aa", "bb", "cc"] * 10)]
    got = {r.doc_id: r.lang_pred for r in langid.predict(spark.createDataFrame(test, "doc_id long, text string, lang string"), model).collect()}
    assert all(got[i] == k for i, _, k in test)


def test_language_query(spark, tmp_path):
    rng = random.Random(7)
    vocab = {k: ["".join(rng.choice(c) for _ in range(9)) for _ in range(60)] for k, c in {"aa": "abcde", "bb": "fghij"}.items()}
    rows = [(i, sentence(rng, 60, vocab["ab"[i % 2] * 2]), "ab"[i % 2] * 2, "s", 1) for i in range(200)]
    # repeated rows, a text of a megabyte, one that is half and half, and one label that is wrong but held out
    held = [i for i in range(1000, 1100) if zlib.crc32(str(i).encode()) % 3 == 1]
    rows += [rows[0], (held[0], sentence(rng, 200_000, vocab["bb"]), "aa", "s", 1), (held[1], "abcd and fghi", None, "s", 1), (held[2], None, "aa", "s", None), (None, "42", "bb", "s", 2)]
    spark.createDataFrame(rows, DOC).withColumn("score", common.F.lit("clash")).write.parquet(f"{tmp_path}/documents.parquet")
    out = langid.op5_language_id(spark, str(tmp_path))
    assert [(f.name, f.dataType.simpleString()) for f in out.schema][:4] == [("doc_id", "bigint"), ("held_out", "boolean"), ("lang_pred", "string"), ("score", "double")]
    got = out.collect()
    assert len(got) == len(rows) and all(0 <= r.score <= 1 and r.held_out == (zlib.crc32(str(r.doc_id).encode()) % 3 == 1) for r in got if r.doc_id is not None)
    by = {r.doc_id: r.lang_pred for r in got}
    assert np.mean([by[i] == "ab"[i % 2] * 2 for i in range(200)]) > 0.99
    assert by[held[0]] == "bb" and by[held[1]] in ("aa", "bb") and by[held[2]] == by[None] == "und"
    spark.createDataFrame([], DOC).write.parquet(f"{tmp_path}/none/documents.parquet")
    assert langid.op5_language_id(spark, f"{tmp_path}/none").count() == 0


# ------------------------------------------------------------------ 6 media


def png():
    import struct
    import zlib

    chunk = lambda k, d: struct.pack(">I", len(d)) + k + d + struct.pack(">I", zlib.crc32(k + d))
    return b"\x89PNG\r\n\x1a\n" + chunk(b"IHDR", struct.pack(">IIBBBBB", 1, 1, 8, 0, 0, 0, 0)) + chunk(b"IDAT", zlib.compress(b"\0\0")) + chunk(b"IEND", b"")


def test_media(spark):
    import gzip
    import io
    import zipfile

    z = io.BytesIO()
    with zipfile.ZipFile(z, "w") as f:
        f.writestr("a", "hello")
    gif = b"GIF89a\x01\x00\x01\x00\x80\x00\x00\x00\x00\x00\xff\xff\xff\x2c\x00\x00\x00\x00\x01\x00\x01\x00\x00\x02\x02D\x01\x00;"
    jpeg = b"\xff\xd8\xff\xe0\x00\x04ab\xff\xda\x00\x03x1234\xff\xd9"
    good = {"image/png": png(), "image/gif": gif, "image/jpeg": jpeg, "application/zip": z.getvalue(), "application/gzip": gzip.compress(b"x" * 100), "application/pdf": b"%PDF-1.4 x %%EOF", "audio/wav": media.to_wave(b"1234"), "image/x-portable-graymap": b"P5 2 2 255\n1234"}
    rows = [(i, bytearray(v), "image/png") for i, v in enumerate(good.values())] + [(50, None, "image/png"), (51, bytearray(b"\x89PNG\r\n\x1a\nbroken"), "image/png")]
    df = spark.createDataFrame(rows, "id long, content binary, declared string")
    got = {r.id: r for r in media.sniff(df, "content", "declared").collect()}
    for i, (kind, data) in enumerate(good.items()):
        assert (got[i].sniffed_type, got[i].sniffed_length, got[i].type_corrected) == (kind, len(data), kind != "image/png")
    assert got[50].sniffed_type == "empty" and got[51].sniffed_type == "unknown"
    inside = b"junk" + png() + b"more" + gif
    cut = media.carve(spark.createDataFrame([(1, bytearray(inside))], "id long, content binary"), "id", "content").collect()
    assert [(r.offset, r.media_type, bytes(r.content)) for r in cut] == [(4, "image/png", png()), (8 + len(png()), "image/gif", gif)]


def flac(frames, announced=None):
    def crc(data, bits, poly):
        c = 0
        for x in data:
            c ^= x << (bits - 8)
            for _ in range(8):
                c = (c << 1 ^ poly if c >> (bits - 1) & 1 else c << 1) & ((1 << bits) - 1)
        return c

    total = 192 * (frames if announced is None else announced)
    info = b"\x00\xc0\x00\xc0" + bytes(6) + (44100 << 12 | 7 << 4 | total >> 32).to_bytes(4, "big") + (total & 0xFFFFFFFF).to_bytes(4, "big") + bytes(16)
    out = b"fLaC\x00" + (34).to_bytes(3, "big") + info + b"\x81" + (5).to_bytes(3, "big") + b"extra"
    for i in range(frames):  # one constant sample value a block
        head = bytes([0xFF, 0xF8, 0x19, 0x02, i])
        body = head + bytes([crc(head, 8, 0x07), 0, 40 + i])
        out += body + crc(body, 16, 0x8005).to_bytes(2, "big")
    return out


def test_media_lengths():
    auto = media.automaton()
    kind = lambda data: [(a, n, k) for a, n, k in media.found(auto, data)]
    whole = flac(9)
    assert kind(whole) == [(0, len(whole), "flac")]
    assert kind(b"zz" + whole + b"tail" * 9) == [(2, len(whole), "flac")]
    assert kind(whole[:-1]) == [] and kind(flac(3, 4)) == [] and kind(whole[:60] + b"\x00" + whole[61:]) == []
    # a document that was saved twice ends at its last confirmed mark
    body = b"%PDF-1.4\n1 0 obj\nx\nendobj\n"
    once = body + b"xref\ntrailer\nstartxref\n%d\n%%%%EOF" % len(body)
    twice = once + b"\nxref\ntrailer\nstartxref\n%d\n%%%%EOF" % (len(once) + 1)
    assert kind(twice + b" %%EOF not confirmed") == [(0, len(twice), "pdf")]
    assert kind(once + b"--" + once) == [(0, len(once), "pdf"), (len(once) + 2, len(once), "pdf")]


def test_media_edges(spark):
    none = spark.createDataFrame([], "id long, content binary, declared string")
    assert media.sniff(none, "content", "declared").count() == 0 and media.carve(none, "id", "content").count() == 0
    # names that clash with the added ones, strings, nulls in every column
    rows = spark.createDataFrame([(1, "GIF89a", "x", "y"), (None, None, None, None), (2, "x" + media.to_wave(b"ab").decode("latin-1") * 0, "", "z")], "id long, content string, sniffed_type string, declared string")
    out = media.sniff(rows, "content", "declared").collect()
    assert sorted((r.id or 0, r.sniffed_type, r.type_corrected) for r in out) == [(0, "empty", False), (1, "unknown", True), (2, "unknown", True)]
    assert media.carve(rows, "id", "content", "declared").count() == 0


def test_media_query(spark, tmp_path):
    rows = [(i, t) for i, t in enumerate([*EDGE, "word " * 300_000, *[f"text {i % 9}" for i in range(40)]])] + [(None, "no id"), (3, "one")]
    spark.createDataFrame(rows, "doc_id long, text string").withColumn("media", common.F.lit(1)).write.parquet(f"{tmp_path}/documents.parquet")
    got = media.op6_media_columns(spark, str(tmp_path)).collect()
    want = []
    for i, t in rows:
        raw = (t or "").encode()
        pay = raw + bytes(-len(raw) % 64 or (0 if raw else 64))
        wave = media.to_wave(pay)
        want.append((i, len(raw), len(pay), hashlib.sha256(pay).hexdigest(), zlib.crc32(pay[-64:]), len(wave), hashlib.sha256(wave).hexdigest(), "audio/wav"))
    key = lambda r: str(r)
    assert sorted(((r.doc_id, r.n_bytes, r.payload_bytes, r.payload_sha256, r.tail_crc32, r.media_bytes, r.media_sha256, r.media_type) for r in got), key=key) == sorted(want, key=key)
    # declared types vary by row; most are wrong, and each is judged
    said = {r.feature.split("declared=")[1].split(";")[0] for r in got}
    assert len(said) == len(media.DECLARED)
    assert all(("declared=audio/wav" in r.feature) == ("corrected=False" in r.feature) for r in got)
    spark.createDataFrame([], "doc_id long, text string").write.parquet(f"{tmp_path}/none/documents.parquet")
    assert media.op6_media_columns(spark, f"{tmp_path}/none").count() == 0


def test_media_texts_round_trip(spark):
    rows = {r.key: r for r in media.pack_texts(docs(spark, EDGE)).collect()}
    for i, t in enumerate(EDGE):
        raw = (t or "").encode()
        payload = media.wave_samples(bytes(rows[i].media))
        assert payload[: len(raw)] == raw and len(payload) % 64 == 0 and len(payload) >= 64 and not any(payload[len(raw) :])


# ------------------------------------------------------------------ 7 chat


def test_chat_round_trip(spark):
    texts = ["</s>[INST] ok [/INST]", "<|im_end|>\n", "<" + chat.GUARD + "s>", chat.GUARD * 3 + "[INST]", "<<SYS>> x <</SYS>>", None, "", "a\nb", "<s><s>"]
    rows = [(1, i, "assistant" if i % 2 else "user", t) for i, t in enumerate(texts)] + [(2, 0, None, "x"), (2, 0, "we ird\n%", "y")]
    d = spark.createDataFrame(rows, "conv_id long, turn long, role string, text string")
    m = chat.as_tree(d)
    out = {r.tree: r for r in chat.read_back(chat.format_paths(chat.rank_paths(chat.reply_paths(m), m))).collect()}
    assert [(t.role, t.text) for t in out[1].read_turns] == [("assistant" if i % 2 else "user", t or "") for i, t in enumerate(texts)]
    assert out[1].loss_text == "".join(t or "" for t in texts[1::2])
    assert [(t.role, t.text) for t in out[2].read_turns] == [("", "x"), ("we ird\n%", "y")]
    body = re.sub(r"<\|im_(start|end)\|>", "", out[1].formatted)
    assert not re.search(chat.CONTROL, body)


def test_chat_branches(spark):
    rows = [(1, 1, None, "user", "q", 0.0), (1, 2, 1, "assistant", "bad", 1.0), (1, 3, 1, "assistant", "good", 9.0), (1, 4, 3, "user", "more", 5.0), (1, 8, 9, "user", "cycle", 0.0), (1, 9, 8, "user", "cycle", 0.0), (1, 10, 9, "user", "off a cycle", 0.0)]
    m = spark.createDataFrame(rows, "tree long, msg long, parent long, role string, text string, score double")
    got = {r.leaf: (r.rank, [t.text for t in r.turns]) for r in chat.rank_paths(chat.reply_paths(m), m).collect()}
    assert got == {4: (1, ["q", "good", "more"]), 2: (2, ["q", "bad"])}
    assert chat.reply_paths(m.limit(0)).count() == 0


def test_chat_query_without_conversations(spark, tmp_path):
    spark.createDataFrame([], "conv_id long, turn long, role string, text string").write.parquet(f"{tmp_path}/conversations.parquet")
    out = chat.op7_chat_format(spark, str(tmp_path)).collect()
    assert [(r.conv_id, r.n_turns, r.loss_chars) for r in out] == [(-7, 2, len("</s>[INST] ok [/INST]"))]


# ------------------------------------------------------------------ 8 toxicity


def test_toxicity_learns_a_pair(spark):
    rng = random.Random(8)
    rows = []
    for i in range(600):
        a, b = rng.random() < 0.4, rng.random() < 0.4
        w = sentence(rng, 30).split() + (["insult"] if a else []) + (["group"] if b else [])
        rng.shuffle(w)
        rows.append((i, " ".join(w), int(a and b)))
    d = spark.createDataFrame(rows, "doc_id long, text string, label int")
    model = toxicity.fit(d.where("doc_id < 450"), epochs=40)
    got = {r.doc_id: r.score for r in toxicity.score(d.select("doc_id", "text"), model).collect()}
    held = [(got[i], y) for i, _, y in rows[450:]]
    assert np.mean([(s >= 0.5) == bool(y) for s, y in held]) > 0.95


def test_toxicity_learns_exclusive_words():
    # neither word tells anything alone: label 1 has exactly one of them
    rng = np.random.default_rng(3)
    rows = 900
    a, b = rng.random(rows) < 0.5, rng.random(rows) < 0.5
    sets = [np.unique(np.concatenate([rng.choice(40, 15).astype(np.int32) + 100, [1] * int(x), [2] * int(z)]).astype(np.int32)) for x, z in zip(a, b, strict=True)]
    y = (a ^ b).astype(float)
    m = toxicity.train(y[:600], sets[:600], epochs=40)
    assert {1, 2} <= set(m.terms.tolist())
    right = []
    for s, label in zip(sets[600:], y[600:], strict=True):
        at = np.flatnonzero(np.isin(m.terms, s))
        right.append((m.scores(1, np.zeros(len(at), int), at)[0] >= 0.5) == bool(label))
    assert np.mean(right) > 0.9


def test_toxicity_query(spark, tmp_path):
    rng = random.Random(12)
    texts = [sentence(rng, 30) + (" vile scum" if i % 4 == 0 else "") for i in range(400)]
    docs(spark, [*texts, *EDGE]).write.parquet(f"{tmp_path}/documents.parquet")
    # a repeated label counts once, the largest; null labels are not learned from
    labels = [(i, int(i % 4 == 0)) for i in range(400)] + [(0, 0), (1, None), (None, 1)]
    spark.createDataFrame(labels, "doc_id long, toxic int").write.parquet(f"{tmp_path}/labels.parquet")
    out = toxicity.op8_toxicity(spark, str(tmp_path))
    assert [(f.name, f.dataType.simpleString()) for f in out.schema][:4] == [("doc_id", "bigint"), ("held_out", "boolean"), ("score", "double"), ("predicted", "int")]
    rows = out.collect()
    assert len(rows) == len(texts) + len(EDGE)
    for r in rows:
        assert r.held_out == (zlib.crc32(str(r.doc_id).encode()) % 5 == 0) and r.predicted == int(r.score >= 0.5)
    held = [r for r in rows if r.held_out and r.doc_id < 400]
    assert np.mean([r.predicted == int(r.doc_id % 4 == 0) for r in held]) > 0.95
    # an empty table of documents, and one without labels
    spark.createDataFrame([], DOC).write.parquet(f"{tmp_path}/none/documents.parquet")
    spark.createDataFrame([], "doc_id long, toxic int").write.parquet(f"{tmp_path}/none/labels.parquet")
    assert toxicity.op8_toxicity(spark, f"{tmp_path}/none").count() == 0


def test_toxicity_edges(spark):
    d = docs(spark, EDGE)
    empty = spark.createDataFrame([], "doc_id long, toxic int")
    out = toxicity.score(d.withColumnRenamed("n_chars", "score"), toxicity.learn(d, empty)).collect()
    assert len(out) == len(EDGE) and all(0 <= r.score <= 1 for r in out)


# ------------------------------------------------------------------ 9 pii


def test_pii(spark):
    texts = ["write to ann.b@mail.example.com or +1 (743) 555-3824 from 10.2.3.4", "ann.b@mail.example.com again, card 4111 1111 1111 1111", 'token = "f33e61083db5dbdf4bd2369d2f80176e57f7fda2"', "Dear Mr. John Smith, Smith wrote to Frau Anna Weber", *EDGE, "clean text with 42 apples in 2024 and v1.2.3"]
    out = {r.doc_id: r for r in pii.replace(docs(spark, texts).withColumn("n_entities", common.F.lit(1)), b"secret").collect()}
    for i, t in enumerate(texts):
        if t:
            for a, z, _ in pii.detect(t):
                assert t[a:z] not in out[i].text or t[a:z] == "Weber"
    mail = re.search(r"\S+@\S+", out[0].text)[0]
    assert mail in out[1].text and len(mail) == len("ann.b@mail.example.com")
    card = re.sub(r"\D", "", out[1].text.split("card")[1])
    assert int(card[-1]) == pii.luhn(card[:-1])
    assert re.search(r"\+1 \(\d{3}\) \d{3}-\d{4}", out[0].text)
    assert out[len(texts) - 1].text == texts[-1] and out[4].text is None
    assert pii.replace(docs(spark, [])).count() == 0


def test_long_secrets_and_plain_phone_numbers():
    rng = random.Random(4)
    long = lambda n, a="0123456789abcdefghijklmnopqrstuvwxyz": "".join(rng.choice(a) for _ in range(n))
    values = [("secret", "token={}", long(240)), ("secret", "password: '{}'", long(700)), ("secret", "sum {} end", long(300, "0123456789abcdef")), ("key", "use {} now", "sk-" + long(150))]
    values += [("phone", "call {} today", v) for v in ("+14155552671", "+49 30 1234567", "+44 7911 123456", "+33612345678", "+1 (743) 555-3824", "+9 (123) 456-7890")]
    for kind, frame, v in values:
        t = frame.format(v)
        assert [(t[a:z], k) for a, z, k in pii.detect(t)] == [(v, kind)], t
        new = pii.surrogate(kind, v, b"k")
        assert new != v and len(new) == len(v)
        assert kind != "secret" or not any(v[i : i + 24] in new for i in range(len(v) - 24))
    assert pii.detect("costs +12 in 2024, 1234567 items, +5 to +10, a+1234567890") == []


def test_surrogates_are_distinct(spark):
    values = [f"u{i}@m.example.com" for i in range(300)]
    made = {pii.surrogate("email", v, b"k") for v in values}
    assert len(made) == len(values)
    names = "\n".join(f"Mr. {n} Xu" for n in pii.GIVEN["m", "latin"])
    out = pii.replace(docs(spark, [names])).first().text
    given = re.findall(r"Mr\. (\S+)", out)
    assert len(set(given)) == len(given)
    space = [pii._permute(x, 1000, b"k", b"t") for x in range(1000)]
    assert sorted(space) == list(range(1000))


def test_email_finder_equals_pattern():
    pattern = re.compile(r"[\w.+%-]+@(?:[\w-]+\.)+[^\W\d_]{2,24}(?!\w)")
    rng = random.Random(1)
    bits = ["a", "b1", "@", ".", "-", "com", "org", "x.y", "@m.ex.com", " ", "_", "+", "é", "c0", "9"]
    for _ in range(20_000):
        t = "".join(rng.choice(bits) for _ in range(rng.randint(3, 12)))
        assert list(pii.emails(t)) == [m.span() for m in pattern.finditer(t)], t


def test_personal_data_takes_linear_time():
    import time

    started = time.perf_counter()
    for part in ("a", "a.", "a@", "a@b.", "+1 ", "1-", "Mr. Xu ", "1 ", "Ab-", "token="):
        pii.detect(part * (400_000 // len(part)))
    assert time.perf_counter() - started < 30


def test_names_stay_gendered_under_collisions(spark):
    # every listed name is a real value, so no listed name may be a surrogate
    men, women = pii.GIVEN["m", "latin"], pii.GIVEN["f", "latin"]
    russian = pii.GIVEN["f", "cyrillic"]
    text = "\n".join([f"Mr. {n} Xu" for n in men] + [f"Frau {n} Xu" for n in women] + [f"госпожа {n} Иванова" for n in russian])
    out = pii.replace(docs(spark, [text, text, text + " " * 300_000]), b"secret").collect()
    new = [re.findall(r"(?:Mr\.|Frau|госпожа) (\S+)", r.text) for r in out]
    assert new[0] == new[1] == new[2]  # one surrogate for a value everywhere
    made = new[0]
    assert len(set(made)) == len(men) + len(women) + len(russian) and not set(made) & {*men, *women, *russian}
    for names, kind in ((made[: len(men)], ("m", "latin")), (made[len(men) : -len(russian)], ("f", "latin")), (made[-len(russian) :], ("f", "cyrillic"))):
        for n in names:
            stem = n.lower()
            end = max((e for e in pii.ENDINGS[kind] if stem.endswith(e)), key=len)
            assert re.fullmatch(f"(?:{'|'.join(pii.SYLLABLES[kind[1]])})+", stem[: -len(end)]), n


def test_exceptions_by_document_equal_those_sent_to_tasks(spark, monkeypatch):
    names = pii.GIVEN["m", "latin"]
    texts = [f"Mr. {n} Xu wrote to {n.lower()}@m.example.com" for n in names] + ["clean", None, ""]
    sent = sorted((r.doc_id, r.text) for r in pii.replace(docs(spark, texts), b"secret").collect())
    monkeypatch.setattr(pii, "MOST_FIXED", 0)
    joined = pii.replace(docs(spark, [*texts, texts[0]]), b"secret")
    got = sorted((r.doc_id, r.text) for r in joined.collect())
    assert got[:-1] == sent and got[-1][1] == got[0][1]


def test_full_formats_grow():
    values = [f"{a}@{b}.com" for a in range(10) for b in range(10)]
    grown = [pii.surrogate("email", v, b"k", pii.MOST_DRAWS) for v in values]
    assert len(set(grown)) == len(values) and not set(grown) & set(values)
    for kind, v in (("ssn", "123-45-6789"), ("ipv4", "1.2.3.4"), ("card", "4111 1111 1111 1111"), ("phone", "+1 (743) 555-3824"), ("iban", "DE44500105175407324931"), ("secret", "ab" * 20), ("key", "sk-" + "a1" * 12)):
        assert len(pii.surrogate(kind, v, b"k", pii.MOST_DRAWS + 2)) == len(v) + 3


def test_pii_key(spark):
    d = docs(spark, ["mail ann@mail.example.com"])
    one = {pii.replace(d, k).first().text for k in (b"a", b"b", b"a")}
    assert len(one) == 2
    assert pii.replace(d).first().text != pii.replace(d).first().text  # a key of its own, kept nowhere


# ------------------------------------------------------------------ 10 decontamination


def test_masks_lose_nothing():
    for window in range(8, 14):
        errors = 2 if window >= 10 else 1
        for bad in itertools.combinations(range(window), errors):
            assert any(all(o + p not in bad for p in m) for m in decontaminate.MASKS for o in range(window - max(m))), (window, bad)


def test_decontamination(spark):
    rng = random.Random(10)
    item = sentence(rng, 20)
    w = item.split()
    near = " ".join("zzz" if k in (4, 9) else x for k, x in enumerate(w))
    part = " ".join(w[3:16])
    far = " ".join("zzz" if k % 4 == 0 else x for k, x in enumerate(w))
    texts = [f"intro {item} end", f"A {near.upper()}!", f"{part} tail", far, sentence(rng, 60), "two words here", *EDGE, f"intro {item} end"]
    bench = spark.createDataFrame([(1, item), (2, "two words here"), (3, "ab"), (4, None), (1, item)], "item_id long, text string")
    got = {r.doc_id: (r.contaminated, r.item_id) for r in decontaminate.judge(docs(spark, texts).withColumnRenamed("lang", "overlap"), bench).collect()}
    want = {0: (True, 1), 1: (True, 1), 2: (True, 1), 5: (True, 2), len(texts) - 1: (True, 1)}
    assert got == {i: want.get(i, (False, None)) for i in range(len(texts))}
    assert decontaminate.judge(docs(spark, []), bench).count() == 0
    assert decontaminate.judge(docs(spark, texts), bench.limit(0)).where("contaminated").count() == 0


# ------------------------------------------------------------------ pipeline


def test_pipeline_against_brute_force(spark, tmp_path):
    import corpus_pipeline

    rng = random.Random(11)
    item = sentence(rng, 18)
    base = sentence(rng, 60)
    texts = [sentence(rng, 40) for _ in range(30)]
    texts += [base, base, base.replace(base.split()[30], "changed", 1), f"see {item} now", "mail me: bob@mail.example.com " + sentence(rng, 30), *EDGE[:4]]
    toxic = [sentence(rng, 30) + " vile scum " + sentence(rng, 10) for _ in range(30)]
    every = texts + toxic
    docs(spark, every).write.parquet(f"{tmp_path}/documents.parquet")
    spark.createDataFrame([(i, 1, int(i >= len(texts))) for i in range(len(every)) if i % 2], "doc_id long, quality int, toxic int").write.parquet(f"{tmp_path}/labels.parquet")
    spark.createDataFrame([(1, item)], "item_id long, text string").write.parquet(f"{tmp_path}/benchmark.parquet")
    out = {r.doc_id: r.text for r in corpus_pipeline.run(spark, str(tmp_path)).collect()}
    classes = brute_classes(every)
    want = [i for i in range(len(texts)) if classes[i] == i and item not in (texts[i] or "")]
    assert sorted(out) == want
    assert "bob@" not in out[34] and all(out[i] == texts[i] for i in want if i != 34)


def test_pipeline_edges(spark, tmp_path):
    import corpus_pipeline

    def tables(name, rows, labels, items):
        spark.createDataFrame(rows, DOC).withColumns({"score": common.F.lit("clash"), "item_id": common.F.lit(7)}).write.parquet(f"{tmp_path}/{name}/documents.parquet")
        spark.createDataFrame(labels, "doc_id long, quality int, toxic int").write.parquet(f"{tmp_path}/{name}/labels.parquet")
        spark.createDataFrame(items, "item_id long, text string").write.parquet(f"{tmp_path}/{name}/benchmark.parquet")
        return corpus_pipeline.run(spark, f"{tmp_path}/{name}").collect()

    assert tables("none", [], [], []) == []
    # nulls in every column, repeated rows, a text of a megabyte; without labels nothing is toxic
    rows = [(None, None, None, None, None), (None, "a b c", None, "s", 5), (1, "same text here", "en", "s", 14), (1, "same text here", "en", "s", 14), (2, "w " * 500_000, "en", None, None)]
    out = tables("some", rows, [], [(None, "x y z q"), (1, None)])
    assert sorted((r.doc_id or 0, len(r.text or "")) for r in out) == [(0, 0), (0, 5), (1, 14), (2, 1_000_000)]
