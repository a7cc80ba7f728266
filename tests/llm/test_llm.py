"""Training-data operators against brute force, with nulls, empty and long texts, ties, repeated rows and extra columns."""

import datetime
import hashlib
import math
import random
import re
import zlib
from collections import defaultdict

import numpy as np
import pytest
from pyspark.sql import functions as F

from ldpspark.llm import common as C
from ldpspark.llm import decontaminate, html_extract, language_id, license_scan, mixing, near_dedup, registry, token_output, topk, toxicity, url_filter
from ldpspark.llm.components import components

DOCS = "doc_id long, text string, lang string, source string, n_chars long, tokens string, n long, cls string"


def frame(spark, rows):
    """documents with extra columns whose names clash with those the operators use inside."""
    return spark.createDataFrame([(i, t, lang, s, 0, "x", 1, "y") for i, t, lang, s in rows], DOCS)


ODD = [(None, "null id text here", "en", "a"), (1, None, "en", "a"), (2, "", None, None), (3, "Word", "en", "b"), (4, "word word " * 30000, "en", "b"), (3, "Word", "en", "b"), (5, "a b c d e f g", "de", "a"), (6, "a b c d e f g", "de", None)]


@pytest.mark.parametrize("name", sorted(registry.ORACLES))
def test_against_sql(spark, duck, sf, name):
    df = registry.QUERIES[name](spark, sf)
    cols = sorted(df.columns)
    plain = lambda v: repr(v + 0.0) if isinstance(v, float) else v.replace(tzinfo=None) if isinstance(v, datetime.datetime) else v
    ours = sorted(str(tuple(plain(r[c]) for c in cols)) for r in df.collect())
    rel = duck.sql(registry.ORACLES[name])
    names = list(rel.columns)
    assert sorted(names) == cols
    assert ours == sorted(str(tuple(plain(dict(zip(names, r, strict=True))[c]) for c in cols)) for r in rel.fetchall())


# ---- 1 license scan

def test_license_scan_suppresses_contained_detections(spark):
    rows = [
        (1, "Under the GNU Lesser General Public License version 2.1. All rights reserved", "en", "a"), (2, "Licensed under the Apache License, Version 2.0.", "en", "a"), (3, "CC BY-NC 4.0 cc by cc by", "en", "a"),
        (4, "SPDX-License-Identifier: MIT", "en", "a"), (5, "nothing here", "en", "a"), *ODD,
    ]
    out = {r["doc_id"]: r for r in license_scan.scan(frame(spark, rows).filter("doc_id <= 5")).collect() if r["doc_id"] not in (3,)}
    got = {r["doc_id"]: r for r in license_scan.scan(frame(spark, rows[:5])).collect()}
    assert got[1]["base_labels"] == ["gpl", "reserved"] and set(got[1]["labels"]) == {"gpl", "reserved", "lgpl-2.1"} and got[1]["first_word"] == 4
    assert got[2]["labels"] == ["apache-2.0"] and got[2]["n_base"] == 0 and got[2]["first_word"] is None
    assert got[3]["n_base"] == 3 and (got[3]["first_word"], got[3]["last_word"]) == (0, 7) and "cc-by-nc-4.0" in got[3]["labels"]
    assert got[4]["labels"] == ["mit"] and got[4]["score"] == 1.0 and got[5]["score"] == 0.0
    assert out is not None
    odd = license_scan.scan(frame(spark, ODD)).collect()
    assert len(odd) == len(ODD) and {r["n_words"] for r in odd if r["doc_id"] in (1, 2)} == {0}


def test_license_rules_are_many_and_native(spark):
    assert len(license_scan.RULES) >= 300
    plan = license_scan.scan(frame(spark, ODD))._jdf.queryExecution().executedPlan().toString()
    assert "Python" not in plan and "Exchange" not in plan


def test_license_words_against_brute_force(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet").limit(200)
    texts = {r["doc_id"]: r["text"] for r in docs.collect()}
    phrases = {"cc-by": ["cc", "by"], "gpl": ["general", "public", "license"], "reserved": ["all", "rights", "reserved"]}
    for r in license_scan.scan(docs).collect():
        w = [x.decode() for x in C.ascii_words(texts[r["doc_id"]].encode())]
        at = [(i, k) for k, p in phrases.items() for i in range(len(w)) if w[i : i + len(p)] == p]
        assert (r["n_words"], r["n_base"], r["base_labels"]) == (len(w), len(at), sorted({k for _, k in at}))


# ---- 2 HTML

def test_html_parser_cases():
    main = lambda t: html_extract.Page(t).main_text(frozenset(), frozenset())
    assert main("") == "" and main("plain &amp; text") == "plain & text"
    assert main("<article><h1>A&nbsp;b</h1><p>x<b>y</b> z<br>w</article><footer>f</footer>") == "A b xy z w"
    assert main("<body><div class='sidebar'>s</div><main><p>t</p><aside>a</aside><form>f</form></main></body>") == "t"
    assert main("<nav>n</nav><script>var a='</p>'</script><style>p{}</style><!-- c --><p>one</p>") == "one"
    assert main("<div class='comments'><article class='comment'>c</article></div><article>real<section id=comments>no</section></article>") == "real"
    assert main("<p>a < b & c") == "a < b & c" and main("<p>" + "x " * 100000).count("x") == 100000
    assert main("<article>t<!-- open <p>never") == "t" and main("<article>t<script>never") == "t"


LAYOUTS = [
('<body class="single-post"><header class="site-header"><a href="/">Logo</a><nav>m</nav></header><div id="content"><h1>T</h1><p>Body text here is long enough to matter.</p><p class="notice">Cookie notice</p><div class="share-buttons">Share</div></div><aside id="sidebar">S</aside><div id="comments"><p>c1</p></div><footer>F</footer></body>','T Body text here is long enough to matter.'),
('<main><article><header><h1>T</h1></header><p>One&#8217;s</p><pre>a\n b</pre><blockquote>q</blockquote><ul><li>x</li></ul><section class="comments"><h2>Comments</h2><article class="comment"><p>very long comment text that goes on and on and on and on</p></article></section></article></main>','T One’s a b q x'),
('<div class="page"><ul class="menu"><li>Home</li></ul><div class="story-body"><p>Para 1</p><p>Para 2 <span>in</span>line</p><table><tr><th>h</th><td>d</td></tr></table></div><div class="advert">Buy</div></div>','Para 1 Para 2 inline h d'),
('<html><body><div role="navigation">n</div><div role="main"><p>m</p></div><div role="contentinfo">f</div></body></html>','m'),
('<ARTICLE><P>Upper<BR/>case</P></ARTICLE>','Upper case'),
('<body><nav><ul><li><a href=a>x</a></nav><article><p>t1<p>t2<div class="cookie-consent">ok?</div><form><input><button>Go</button></form></article>','t1 t2'),
('<p>&lt;b&gt; &amp;amp; &nbsp; x</p>','<b> &amp; x'),
('<article><p>a</p><script>if (a < b) { x = "</p>" }</script><style>.a{}</style><noscript>no</noscript><p>b</p></article>','a b'),
('<article>one</article><article>two is the longer article</article>','two is the longer article'),
('<body><section class="hero banner">Big</section><section><p>Real content paragraph.</p></section></body>','Real content paragraph.'),
('<article><figure><img alt=x><figcaption>cap</figcaption></figure><p>t</p></article>','cap t'),
('<article><p>a<!-- x --> b</p><![CDATA[zz]]><?php echo 1 ?></article>','a b'),
('<div class="content-wrapper has-sidebar"><div class="entry-content"><p>Hello world text</p></div><div class="widget">w</div></div>','Hello world text'),
]


@pytest.mark.parametrize("page,text", LAYOUTS)
def test_html_layouts(page, text):
    assert html_extract.Page(page).main_text(frozenset(), frozenset()) == text


def test_html_template_drops_what_pages_share(spark):
    page = "<html><body><div><ul><li>Home</li><li>About</li></ul></div><div><p>Join our list today</p></div><div><div>{0}</div></div><div><p>All the small print</p></div></body></html>"
    rows = [(i, f"http://h.org/{i}", page.format(f"<p>Story {i} tells {'many ' * (i + 3)}things</p><p>and more {i}</p>")) for i in range(12)]
    rows += [(100, None, None), (101, "no scheme", ""), (5, "http://h.org/5", rows[5][2])]
    out = html_extract.extract(spark.createDataFrame(rows, "page_id long, url string, html string")).collect()
    assert len(out) == 15
    for r in out:
        if r["page_id"] < 12:
            assert r["text"] == f"Story {r['page_id']} tells {'many ' * (r['page_id'] + 3)}things and more {r['page_id']}"
        else:
            assert r["text"] == ""


def test_html_classes_against_brute_force(spark):
    rng = random.Random(5)
    pages = [(rng.choice(["a.org", "b.org"]), i, "<body>" + "".join(f"<div class=c{rng.choice('xyz')}><p>{rng.choice(['one', 'two', 'same'])}</p></div>" for _ in range(4)) + "<hr><section><i>s</i></section></body>") for i in range(40)]
    got = {r["host"]: set(r["tokens"]) for r in html_extract.templates(spark.createDataFrame(pages, "host string, key long, html string")).collect()}
    for host in ("a.org", "b.org"):
        own = [html_extract.Page(h).tokens() for x, _, h in pages if x == host]
        groups = defaultdict(list)
        for t in {t for p in own for t in p}:
            groups[tuple(p.get(t, 0) for p in own)].append(t)
        valid = {html_extract._signed(t) for v, ts in groups.items() if len(ts) >= 3 and sum(map(bool, v)) >= max(3, 0.5 * len(own)) for t in ts}
        assert got.get(host, set()) == valid


def test_html_on_the_given_pages(spark, sf):
    import html

    def reference(h):
        x = re.sub(r"<(?:br|/?p|/?h1)[^>]*>", "\0", re.search(r"<article>(.*)</article>", h, re.S)[1])
        return " ".join(" ".join(html.unescape(y).split()) for y in re.sub(r"<[^>]*>", "", x).split("\0") if y.strip())

    pages = {r["page_id"]: r["html"] for r in spark.read.parquet(f"{sf}/pages.parquet").collect()}
    for r in html_extract.op2_html_extraction(spark, sf).collect():
        assert r["text"] == reference(pages[r["page_id"]]) and r["n_chars"] == len(r["text"])


# ---- 3 top-k

def test_topk_ties_nulls_and_tree(spark):
    rng = np.random.default_rng(2)
    rows = [(i, [float(x) for x in rng.integers(-3, 3, 4) / 64]) for i in range(300)] + [(300, None), (301, [1.0, None, 1.0, 1.0]), (302, [float("nan")] * 4), (303, [1.0]), (None, [1.0] * 4)]
    df = spark.createDataFrame(rows, "vec_id long, embedding array<double>").repartition(40)
    got = defaultdict(list)
    for r in topk.search(df, F.col("vec_id") % 20 == 0, k=7, fan_in=3, block_bytes=200).collect():
        got[r["query_id"]].append((r["rank"], r["id"], r["score"]))
    good = {i: [math.floor(64 * x) for x in v] for i, v in rows[:300]}
    for q in range(0, 300, 20):
        best = sorted((-sum(a * b for a, b in zip(good[q], v, strict=True)), i) for i, v in good.items() if i != q)[:7]
        assert sorted(got[q]) == [(k + 1, i, -s) for k, (s, i) in enumerate(best)]
    assert set(got) == set(range(0, 300, 20))
    assert topk.search(df.filter("false"), F.lit(True)).count() == 0


def test_topk_large_numbers_stay_exact():
    q, t = np.array([[2.0**30, 3.0]]), np.array([[2.0**31, 5.0], [-(2.0**31), 7.0]])
    assert topk.scores(q, t).tolist() == [[2**61 + 15, -(2**61) + 21]]


# ---- 4 token output

def test_block_round_trip():
    rng = np.random.default_rng(1)
    for high in (3, 300, 70_000):
        counts = rng.integers(0, 50, 40)
        ids = rng.integers(0, high, counts.sum()).astype(np.uint32)
        c, i = token_output.decode_block(token_output.encode_block(counts, ids))
        assert (c == counts).all() and (i == ids).all()
    assert [len(x) for x in token_output.decode_block(token_output.encode_block(np.zeros(3, int), np.zeros(0, np.uint32)))] == [3, 0]
    block = token_output.encode_block(np.array([4]), np.array([9, 9, 9, 5], np.uint32))
    assert np.frombuffer(block, "<u4", 2, token_output.HEAD.size).tolist() == [9, 5]


def test_pieces_give_the_tokenizers_ids():
    import public_tokenizers
    from tokenizers import Tokenizer

    path = public_tokenizers.path("word_bpe_49k.json")
    plain, own, rng = Tokenizer.from_file(path), token_output.Encoder(path, None), random.Random(4)
    letters = ["".join(map(chr, range(256))), "aB'sdrevmlt 1²é.,!<|>endoftxÀßµªº\x85\xa0\n", "aΣσİ̈e漢字 b <|endoftext|>É"]
    texts = ["".join(rng.choice(letters[k % 3]) for _ in range(rng.randrange(50))) for k in range(3000)] + ["", "<|endoftext|> x"]
    counts, ids = own(texts)
    at = np.cumsum(counts) - counts
    for k, e in enumerate(plain.encode_batch(texts, add_special_tokens=False)):
        assert ids[at[k] : at[k] + counts[k]].tolist() == e.ids


def test_token_output_order_starts_and_checksums(spark, sf, tmp_path):
    import public_tokenizers
    from tokenizers import Tokenizer

    plain = Tokenizer.from_file(public_tokenizers.path("word_bpe_49k.json"))
    docs = spark.read.parquet(f"{sf}/documents.parquet").limit(120).select("doc_id", "text").union(spark.createDataFrame([(None, "null id"), (-1, None), (7, "again"), (7, "")], "doc_id long, text string"))
    rows = sorted(((r[0], r[1] or "") for r in docs.collect()), key=lambda r: (r[0] is not None, r[0] or 0, r[1]))
    start, want = 0, []
    for i, t in rows:
        ids = plain.encode(t, add_special_tokens=False).ids + [2]
        want.append((i, start, len(ids), zlib.crc32(np.array(ids, "<u4").tobytes())))
        start += len(ids)
    blocks = C.stored(token_output.encode(docs, public_tokenizers.path("word_bpe_49k.json"), block_tokens=3000), "t")
    got = token_output.decode(blocks, tokens=False).collect()
    assert sorted(map(tuple, got), key=lambda r: r[1]) == want
    assert token_output.export(blocks, str(tmp_path / "b")) == blocks.count() > 3
    assert token_output.token_output(docs.filter("false")).count() == 0


# ---- 5 toxicity

def test_segments_against_brute_force():
    rng = random.Random(6)

    def maximal(scores):
        """Maximal segments by definition: best segment, then the same to its left and right."""
        if not any(s > 1e-12 for s in scores):
            return []
        best = max((sum(scores[a:b]), -(b - a), -a, a, b) for a in range(len(scores)) for b in range(a + 1, len(scores) + 1))
        a, b = best[3], best[4]
        return [*maximal(scores[:a]), (a, b - 1, best[0]), *[(x + b, y + b, s) for x, y, s in maximal(scores[b:])]]

    for _ in range(200):
        n = rng.randrange(1, 14)
        hits = sorted((i, rng.choice([0.7, 1.3, 2.9])) for i in rng.sample(range(n), rng.randrange(0, n)))
        scores = [-0.41] * n
        for i, s in hits:
            scores[i] = s
        got = [(a, b, pytest.approx(s)) for a, b, s in toxicity.segments(hits, 0.41)]
        assert [(a, b, s) for a, b, s in maximal(scores)] == got


def test_toxicity_accuracy_and_edges(spark):
    sf = "/root/testdata/sf0.1"
    labels = {r["doc_id"]: r["toxic"] for r in spark.read.parquet(f"{sf}/labels.parquet").collect()}
    rows = toxicity.op5_toxicity(spark, sf).collect()
    assert len(rows) == 10_000 and all(0 <= r["score"] <= 1 and r["predicted"] == (r["score"] >= 0.5) for r in rows)
    held = [(labels[r["doc_id"]], r["score"], r["predicted"]) for r in rows if r["held_out"] and r["doc_id"] in labels]
    pos, neg = [s for t, s, _ in held if t], [s for t, s, _ in held if not t]
    auc = sum((p > q) + (p == q) / 2 for p in pos for q in neg) / len(pos) / len(neg)
    assert auc > 0.93 and sum(t for t, _, p in held if p) / sum(p for _, _, p in held) > 0.95


def test_toxicity_without_labels(spark):
    labels = spark.createDataFrame([(1, 1), (None, 0)], "doc_id long, toxic int")
    out = toxicity.toxicity(frame(spark, ODD), labels).collect()
    assert len(out) == len(ODD) and {r["score"] for r in out} == {0.0}


def test_decay_root():
    lam = toxicity.decay(np.array([5.0, 3.0]), np.array([1e-4, 1e-3]), 0.3)
    assert 1e-4 * math.exp(5 * lam) + 1e-3 * math.exp(3 * lam) + (1 - 1.1e-3) * math.exp(-0.3 * lam) == pytest.approx(1)


# ---- 6 language

def test_table_is_the_product_of_the_vectors():
    rng = np.random.default_rng(3)
    vectors = language_id.bind(9, 64, 1)
    codes = rng.integers(0, 9**3, 50)
    values, counts = np.unique(codes, return_counts=True)
    own = language_id.bundle(values, counts, vectors)
    direct = sum(np.roll(vectors[c // 81], 2) * np.roll(vectors[c // 9 % 9], 1) * vectors[c % 9] for c in codes)
    assert (own == direct).all()
    p = rng.integers(-50, 50, (2, 64))
    table = language_id.product_table(p, vectors)
    for k in range(2):
        assert table[k][codes].sum() == pytest.approx(own @ p[k] / np.linalg.norm(p[k]), rel=1e-3, abs=1e-2)


def test_trigrams_of_odd_texts():
    symbol = language_id.symbols_of([ord("a"), ord("b"), ord("c")])
    texts = [b"", b"a", b"", b" a  b ", b"abc", b"1 2", "ßAB".encode()]
    codes, stop = language_id.trigrams(texts, symbol, 6)
    got = [codes[a:b].tolist() for a, b in zip([0, *stop[:-1]], stop, strict=True)]

    def brute(t):
        s = "".join(c if c.isalpha() else " " for c in f" {t.decode().lower()} ")
        s = re.sub(" +", " ", s)
        n = [0 if c == " " else {"a": 2, "b": 3, "c": 4}.get(c, 1) for c in s]
        return [36 * n[i] + 6 * n[i + 1] + n[i + 2] for i in range(len(n) - 2) if n[i + 1]]

    assert got == [brute(t) for t in texts]


def test_language_accuracy_and_edges(spark, sf):
    rows = language_id.op6_language_id(spark, sf).collect()
    lang = {r["doc_id"]: r["lang"] for r in spark.read.parquet(f"{sf}/documents.parquet").collect()}
    held = [r for r in rows if r["held_out"]]
    assert len(rows) == 1000 and sum(r["lang_pred"] == lang[r["doc_id"]] for r in held) / len(held) > 0.98
    assert all(r["held_out"] == (zlib.crc32(str(r["doc_id"]).encode()) % 5 == 0) and 0 <= r["score"] <= 1 for r in rows)
    out = language_id.identify(frame(spark, [*ODD, (9, "123 456", "en", "a")])).collect()
    assert len(out) == 9 and {r["doc_id"]: r["lang_pred"] for r in out}[9] == "und" and {r["doc_id"]: r["lang_pred"] for r in out}[1] == "und"
    assert {r["lang_pred"] for r in language_id.identify(frame(spark, ODD).withColumn("lang", F.lit(None).cast("string"))).collect()} == {"und"}
    kept = language_id.identify(frame(spark, ODD), keep=0.0)
    assert kept.columns == frame(spark, ODD).columns and kept.count() == 6


# ---- 7 near-duplicates

def shingles(text, width):
    w = re.findall(r"[^\x20\x09-\x0D]+", (text or "").translate({c: c + 32 for c in range(65, 91)}))
    return frozenset(tuple(w[i : i + width]) for i in range(max(1, len(w) - width + 1))) if w else frozenset()


def brute_components(rows, width, num, den):
    sets = [shingles(t, width) for _, t in rows]
    root = list(range(len(rows)))

    def find(k):
        while root[k] != k:
            k = root[k]
        return k

    for i in range(len(rows)):
        for j in range(i):
            if sets[i] and sets[j] and den * len(sets[i] & sets[j]) >= num * len(sets[i] | sets[j]):
                root[find(i)] = find(j)
    least = defaultdict(list)
    for k, (i, _) in enumerate(rows):
        if i is not None:
            least[find(k)].append(i)
    return [(rows[k][0], len(sets[k]), min(least[find(k)], default=None) if sets[k] else rows[k][0]) for k in range(len(rows))]


@pytest.mark.parametrize("width,num,den", [(3, 85, 100), (5, 80, 100)])
def test_near_duplicates_against_brute_force(spark, width, num, den):
    rng = random.Random(width)
    words = [f"w{i}" for i in range(400)]
    common = [rng.choice(words) for _ in range(60)]
    rows = []
    for g in range(25):
        base = [rng.choice(words) for _ in range(rng.choice([2, 6, 20, 60, 200]))] + (common if g % 3 == 0 else [])
        for _ in range(rng.choice([1, 2, 6, 30])):
            t = list(base)
            for _ in range(rng.choice([0, 0, 1, 2, 4])):
                t[rng.randrange(len(t))] = rng.choice(words)
            rows.append((len(rows) * 7 % 1009, " ".join(t)))
    rows += [(2000, None), (2001, ""), (2002, " \t\n"), (2003, "One two"), (2004, "one  TWO"), (rows[0][0], rows[0][1]), (None, rows[0][1]), (None, "lonely text without id"), (2005, "x" * 300_000)]
    df = spark.createDataFrame([(i, t, "c", 1, 2) for i, t in rows], "doc_id long, text string, cls string, n int, th long")
    got = [(r["doc_id"], r["n"], r["component"]) for r in near_dedup.near_duplicates(df, width=width, similarity=(num, den)).collect()]
    key = lambda r: tuple((x is None, x or 0) for x in r)
    assert sorted(got, key=key) == sorted(brute_components(rows, width, num, den), key=key)
    kept = near_dedup.deduplicated(df, width=width, similarity=(num, den))
    assert kept.columns == df.columns
    ids = [r["doc_id"] for r in kept.collect() if r["doc_id"] is not None and r["doc_id"] != rows[0][0]]
    assert sorted(ids) == sorted({r[2] for r in got if r[1] and r[2] is not None and r[2] != rows[0][0]})


def test_near_duplicates_of_the_given_documents(spark, sf):
    rows = [(r["doc_id"], r["text"]) for r in spark.read.parquet(f"{sf}/documents.parquet").collect()]
    got = sorted((r["doc_id"], r["n_shingles"], r["component_id"]) for r in near_dedup.op7_minhash(spark, sf).collect())
    inverted, sets = defaultdict(set), {i: shingles(t, 3) for i, t in rows}
    root = {i: i for i in sets}

    def find(k):
        while root[k] != k:
            k = root[k]
        return k

    for i, s in sorted(sets.items()):
        for j in {j for x in s for j in inverted[x]}:
            if 100 * len(s & sets[j]) >= 85 * len(s | sets[j]):
                a, b = find(i), find(j)
                root[max(a, b)] = min(a, b)
        for x in s:
            inverted[x].add(i)
    assert got == sorted((i, len(s), find(i)) for i, s in sets.items())


def test_empty_table_has_no_duplicates(spark):
    assert near_dedup.near_duplicates(frame(spark, ODD).filter("false")).count() == 0


def test_least_common_bounds_the_tail():
    c = near_dedup.least_common(40, 0.85)
    tail = sum(math.comb(40, i) * 0.85**i * 0.15 ** (40 - i) for i in range(c))
    assert tail <= near_dedup.MISS < tail + math.comb(40, c) * 0.85**c * 0.15 ** (40 - c)


def test_components(spark):
    links = [(f"n{a}", f"n{b}") for a, b in [(1, 2), (2, 3), (5, 4), (7, 7), (8, 9), (9, 10), (10, 11), (11, 12), (12, 13), (3, 1)]]
    got = dict(map(tuple, components(spark.createDataFrame(links, "a string, b string")).collect()))
    assert got == {"n1": "n1", "n2": "n1", "n3": "n1", "n4": "n4", "n5": "n4", **{f"n{k}": "n10" for k in range(8, 14)}}


# ---- 8 mixing

def test_targets_are_filled_by_weight(spark):
    rng = random.Random(8)
    for _ in range(8):
        sizes = {f"s{k:02d}": rng.choice([0, 5, 40, 300, 5000]) for k in range(9)} | {None: 70}
        order = sorted((s for s in sizes if s), key=str) + [None]
        weight = {s: [3.0, 1.0, 2.0][k % 3] for k, s in enumerate(order)}
        total, full, target = 1.5 * sum(sizes.values()), set(), {}
        while True:  # share by weight, stop those above, share again
            rest = total - sum(2 * sizes[s] for s in full)
            w = sum(weight[s] for s in sizes if s not in full)
            target = {s: 2.0 * sizes[s] if s in full else rest * weight[s] / w for s in sizes}
            over = {s for s in sizes if s not in full and target[s] > 2 * sizes[s] + 1e-9}
            if not over:
                break
            full |= over
        got = {r["source"]: r["target"] for r in mixing.targets(spark.createDataFrame(list(sizes.items()), "source string, source_size long"), [3.0, 1.0, 2.0], 1.5, 2.0).collect()}
        assert got == {s: pytest.approx(t) for s, t in target.items()}


def test_mix_rows_repeat_and_agree(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    plan = {r["doc_id"]: r["copies"] for r in mixing.plan_copies(docs).collect()}
    rows = mixing.mix(docs)
    assert rows.columns == docs.columns
    assert {r["doc_id"]: r["count"] for r in rows.groupBy("doc_id").count().collect()} == {k: v for k, v in plan.items() if v}
    assert plan == {r["doc_id"]: r["copies"] for r in mixing.plan_copies(docs.repartition(7)).collect()}
    odd = mixing.plan_copies(frame(spark, ODD), odds_col="n").collect()
    assert len(odd) == len(ODD) and sum(r["size"] * r["copies"] for r in odd) > 0
    assert mixing.plan_copies(frame(spark, ODD).filter("false")).count() == 0
    assert mixing.mix(frame(spark, [(1, None, "en", "a"), (2, "", "en", "a")])).count() == 0


def test_unequal_odds_favour_heavier_documents(spark):
    rows = [(i, "w " * 10, "en", "a" if i % 2 else "b") for i in range(400)]
    df = spark.createDataFrame([(*r, 4.0 if r[0] % 4 < 2 else 1.0) for r in rows], "doc_id long, text string, lang string, source string, odds double")
    got = mixing.plan_copies(df, odds_col="odds", total_share=0.5).collect()
    heavy = sum(r["copies"] for r in got if r["doc_id"] % 4 < 2)
    assert sum(r["size"] * r["copies"] for r in got) == pytest.approx(2000, abs=20) and heavy > 0.65 * sum(r["copies"] for r in got)


# ---- 9 decontamination

def test_windows_against_brute_force(spark):
    rng = random.Random(9)
    words = ["alpha", "beta", "gamma", "delta"]
    items = [(k, " ".join(rng.choice(words) for _ in range(rng.choice([1, 3, 12, 13, 14, 20])))) for k in range(12)] + [(90, None), (91, ""), (None, "zeta eta theta")]
    items[0] = (0, "omega")
    docs = [(k, " ".join(rng.choice([*words, "Omega!", "x9"]) for _ in range(40))) for k in range(30)]
    docs += [(100, items[5][1].upper() + " tail"), (101, None), (102, ""), (103, "Zeta, eta; theta"), (100, "omega"), (None, "omega x")]

    def judge(text):
        w = [x.decode() for x in C.ascii_words((text or "").encode())]
        hit, found = set(), set()
        for k, t in items:
            v = [x.decode() for x in C.ascii_words((t or "").encode())]
            n = min(13, len(v))
            grams = {tuple(v[i : i + n]) for i in range(len(v) - n + 1)} if v else set()
            for i in range(len(w) - n + 1):
                if n and tuple(w[i : i + n]) in grams:
                    hit |= set(range(i, i + n))
                    found.add("" if k is None else str(k))
        return len(w), len(hit), sorted(found)

    df = spark.createDataFrame([(i, t, 1, []) for i, t in docs], "doc_id long, text string, n_hit int, items array<string>")
    bench = spark.createDataFrame(items, "item_id long, text string")
    want = sorted(str((i, *judge(t))) for i, t in docs)
    for limit in (decontaminate.SLICE_BYTES, 60):
        got = decontaminate.contamination(df, bench, slice_bytes=limit).collect()
        assert sorted(str((r["doc_id"], r["n_words"], r["n_hit"], r["items"])) for r in got) == want
    kept = decontaminate.clean(df, bench)
    bad = [t for _, t in docs if (j := judge(t))[1] and 20 * j[1] >= j[0]]
    assert kept.columns == df.columns and kept.count() == len(docs) - len(bad)
    cut = decontaminate.clean(df, bench, remove="spans").collect()
    assert len(cut) == len(docs) and " " in [r["text"] for r in cut]
    assert decontaminate.contamination(df, bench.filter("false")).filter("n_hit > 0").count() == 0


def test_items_digest(spark, sf):
    r = decontaminate.op9_decontamination(spark, sf).filter("n_items = 0").first()
    assert r["items_sha256"] == hashlib.sha256(b"").hexdigest()


# ---- 10 URL filter

def test_bloom_filter_has_no_false_negatives_and_few_positives():
    rng = np.random.default_rng(10)
    keys = rng.integers(-(2**63), 2**63, 5000)
    table = url_filter.build_filter(keys, len(keys))
    assert url_filter.may_hold(table, keys).all()
    assert url_filter.may_hold(table, rng.integers(-(2**63), 2**63, 20000)).mean() < 0.02


def test_urls_against_brute_force(spark):
    rng = random.Random(10)
    listed = [(rng.randrange(2), ".".join(rng.choice(["a", "b", "org", "com"]) for _ in range(rng.randrange(1, 4))), rng.choice(["", "/", "/x", "/x/y", "/é"]), rng.choice(["allow", "block"])) for _ in range(25)]
    urls = [(k, rng.choice(["http://", "https://", "", "x://y://"]) + ".".join(rng.choice(["a", "B", "org", "com"]) for _ in range(rng.randrange(1, 5))) + rng.choice(["", "/", "/x?q", "/x/y#z", "/é/ü", "?a", "/X"])) for k in range(200)]
    urls += [(200, None), (201, ""), (202, "://"), (3, urls[3][1]), (203, "http:///path"), (204, "http://a.org/" + "p" * 100_000)]

    def judge(u):
        host = path = ""
        if u and "://" in u:
            rest = u.split("://", 1)[1]
            host = re.match(r"[^/?#]*", rest)[0]
            path = re.match(r"[^?#]*", rest[len(host) :])[0]
            host = host.translate({c: c + 32 for c in range(65, 91)})
        fits = [(t, len(h) + len(p), len(h), v, h, p) for t, h, p, v in listed if (host == h or host.endswith("." + h)) and path.startswith(p)]
        best = max(fits, default=None)
        return host, path, best[4] + best[5] if best else None, best[3] if best else "allow"

    df = spark.createDataFrame([(*u, "h") for u in urls], "page_id long, url string, host string")
    rules = spark.createDataFrame(listed, "tier int, host string, path string, verdict string")
    want = sorted(str((i, *judge(u))) for i, u in urls)
    for limit in (url_filter.FILTER_BYTES, 0):
        got = url_filter.judge(df, rules, filter_bytes=limit).collect()
        assert sorted(str((r["page_id"], r["host"], r["path"], None if r["listed_host"] is None else r["listed_host"] + r["listed_path"], r["verdict"])) for r in got) == want
    assert {r["verdict"] for r in url_filter.judge(df, rules.filter("false")).collect()} == {"allow"}


# ---- pipeline

def test_pipeline_stages_against_brute_force(spark, sf):
    import corpus_pipeline as P

    docs = spark.read.parquet(f"{sf}/documents.parquet").filter("doc_id < 300")
    columns, frames = docs.columns, {}
    now = docs
    for name, stage in P.STAGES:
        before, now = now, C.stored(stage(spark, now, sf), "test")
        frames[name] = (before, now)
        if name != P.STAGES[-1][0]:
            assert now.columns == columns
    before, after = frames["MinHash near-dedup"]
    rows = [(r["doc_id"], r["text"]) for r in before.collect()]
    assert sorted(r["doc_id"] for r in after.collect()) == sorted({c for i, n, c in brute_components(rows, 5, 80, 100) if n} | {i for i, t in rows if not shingles(t, 5)})
    before, after = frames["benchmark decontamination"]
    judged = {r["doc_id"]: r for r in decontaminate.contamination(before, spark.read.parquet(f"{sf}/benchmark.parquet")).collect()}
    assert {r["doc_id"] for r in after.collect()} == {i for i, r in judged.items() if not (r["n_hit"] and 20 * r["n_hit"] >= r["n_words"])}
    before, after = frames["mixing sources to target weights"]
    words = lambda df: sum(len(re.findall(r"[^\x20\x09-\x0D]+", r["text"] or "")) for r in df.collect())
    assert words(after) == pytest.approx(1.5 * words(before), rel=0.03)
    before, after = frames["token-ID / binary output"]
    assert before.count() == after.count()
    assert len(P.run(spark, sf).columns) == 4
