"""Each operator against brute force, and on nulls, empty and repeated rows, empty tables and clashing columns."""

import collections
import hashlib
import math
import random
import re
import zlib

import numpy as np
import pytest
from pyspark.sql import functions as F

from itemset_sieve.llm import ann, bpe, exact_dedup, html_extract, license_scan, mix, ngram_join, pitman_yor, quality_cnn, url_filter
from itemset_sieve.llm.common import ASCII_LOWER, components

WORD = re.compile(r"[^\x20\x09-\x0D]+")
TEXTS = [None, "", "   ", "One two three four five six", "one TWO three four five six", "É é", "a", "a", "word " * 3000, "x y z", "x y Z", "ok", None]


@pytest.fixture(scope="module")
def docs(spark):
    rows = [(i, t, None if i % 4 == 0 else f"s{i % 3}", "clash") for i, t in enumerate(TEXTS)]
    return spark.createDataFrame(rows, "doc_id long, text string, source string, recipe string")


@pytest.fixture(scope="module")
def none(docs):
    return docs.where("doc_id < 0")


def words(t):
    return WORD.findall((t or "").translate(ASCII_LOWER))


# Licenses.


def test_licenses_are_stated_and_inherited(spark):
    files = {
        "LICENSE": "Released under the MIT License.", "src/a.py": "print(1)", "src/b.py": "# Licensed under the Apache License, Version 2.0.\nprint(2)", "src/lib/COPYING": "GNU General Public License\nVersion 3, 29 June 2007\nEveryone is permitted to copy and distribute verbatim copies of this license document",
        "src/lib/x/y.c": "int main;", "src/lib/n.txt": None, "src/lib2/z.c": "the river license of nothing much in a long sentence about rivers", "doc/t.txt": "story words. Licensed under CC BY-NC 4.0.",
    }
    df = spark.createDataFrame([*files.items(), (None, "All rights reserved."), (None, "x")], "path string, text string")
    got = {r.path: (r.own_license, r.license, r.licensed_by) for r in license_scan.scan(df).where("path is not null").collect()}
    assert got["src/a.py"] == (None, "mit", "") and got["src/b.py"] == ("apache-2.0", "apache-2.0", "src/b.py")
    assert got["src/lib/x/y.c"] == got["src/lib/n.txt"] == (None, "gpl-3.0", "src/lib")
    assert got["src/lib2/z.c"] == (None, "mit", "") and got["doc/t.txt"][0] == "cc-by-nc-4.0"
    assert license_scan.scan(df).count() == len(files) + 2 and license_scan.scan(df.where("path = 'none'")).count() == 0


def test_licence_files_of_any_length_govern(spark):
    rows = [("a/1.txt", "Released under the MIT License.\n" * 4000), ("a/2.txt", "words"), ("b/1.txt", "Released under the MIT License.\n" * 10), ("b/2.txt", "words")]
    got = {r.path: (r.license, r.licensed_by) for r in license_scan.scan(spark.createDataFrame(rows, "path string, text string")).collect()}
    assert len(rows[0][1]) > 100_000 and got["a/2.txt"] == ("mit", "a") and got["b/2.txt"] == ("mit", "b")


def test_sparse_cosine_equals_the_dense_one():
    m = license_scan.Matcher(50, {t: 3 for x in license_scan.TEMPLATES.values() for y in x for t in license_scan.terms(y.encode())})
    text = b"Released under the MIT license, of course"
    v, n = m.vector(license_scan.terms(text))
    dense = []
    for name, texts in license_scan.TEMPLATES.items():
        for x in texts:
            u, k = m.vector(license_scan.terms(x.encode()))
            dense.append((sum(w * u.get(t, 0) for t, w in v.items()) / (n * k), name))
    name, score = m.best(text)
    assert name == max(dense)[1] == "mit" and abs(score - max(dense)[0]) < 1e-8


# Exact dedup.


def test_exact_groups(docs, none):
    rows = exact_dedup.exact_groups(docs).collect()
    norm = {i: (t or "").translate(ASCII_LOWER) for i, t in enumerate(TEXTS)}
    for r in rows:
        same = [i for i, t in norm.items() if t == norm[r.doc_id]]
        assert (r.keep_id, r.group_size, r.kept) == (max(same), len(same), r.doc_id == max(same))
        assert r.text_sha256 == hashlib.sha256(norm[r.doc_id].encode()).hexdigest()
    assert len(rows) == len(TEXTS) and exact_dedup.exact_groups(none).count() == 0


def test_chunks_join_to_the_text_and_follow_its_content(spark):
    rng = random.Random(1)
    text = " ".join("".join(rng.choice("abcdefghiklmnorstu") for _ in range(rng.randrange(1, 9))) for _ in range(40_000))
    df = spark.createDataFrame([(text,), ("put in front, " + text,), ("",)], "t string").select(exact_dedup.chunks(F.col("t")).alias("c"))
    a, b, c = (r.c for r in df.collect())
    assert "".join(a) == text and c == [] and max(map(len, a)) <= exact_dedup.CHUNK_MAX
    assert len(set(a) & set(b)) > 0.8 * len(a)


def test_clashing_digests_do_not_join_texts(spark):
    df = spark.createDataFrame([(1, "abc"), (2, "abd"), (3, "ABC"), (4, "")], "doc_id long, text string")
    weak = exact_dedup.exact_groups(df, digest=lambda c: F.substring(c, 1, 2))
    assert {r.doc_id: (r.keep_id, r.group_size) for r in weak.collect()} == {1: (3, 2), 2: (2, 1), 3: (3, 2), 4: (4, 1)}


def test_repeated_rows_do_not_lengthen_recipes_where_digests_clash(spark):
    df = spark.createDataFrame([(1, "abc", 0), (1, "abc", 1), (3, "ABC", 2), (4, "abd", 3)], "doc_id long, text string, recipe long")
    weak = exact_dedup.exact_groups(df, digest=lambda c: F.substring(c, 1, 2)).collect()
    assert sorted((r.doc_id, r.keep_id, r.group_size) for r in weak) == [(1, 3, 3), (1, 3, 3), (3, 3, 3), (4, 4, 1)]


def test_dedup_plan_is_native(docs):
    plan = exact_dedup.exact_groups(docs)._jdf.queryExecution().executedPlan().toString()
    assert not re.search("Python|Pandas|Arrow", plan)


def test_mix_leaves_clashing_columns_alone(spark):
    rows = [(i, f"s{i % 2}", "a b c", 7, 8, 9) for i in range(40)]
    df = spark.createDataFrame(rows, "doc_id long, source string, text string, size long, target int, taken int")
    plain = {r.doc_id: (r.size, r.copies) for r in mix.mix(df.select("doc_id", "source", "text")).collect()}
    got = mix.mix(df, prefix="m_").collect()
    assert all((r.size, r.target, r.taken) == (7, 8, 9) and (r.m_size, r.m_copies) == plain[r.doc_id] for r in got) and len(got) == 40
    assert {r.doc_id: (r.size, r.copies) for r in mix.mix(df).collect()} == plain


# HTML.

PAGE = """<html><head><title>T</title><style>p{}</style><script>var t="</p>";</script></head><body><header>Site</header><nav><a href=/x>Menu</a></nav>
<div class="cookie-notice">We use cookies</div><article><h1>Head &amp; line</h1><p>One <b>two</b>
 three<p>Four<br>five</p><aside>Related</aside><form>Mail <input></form></article><div id="comments"><p>Nice!</p></div><footer>&copy; me</footer>"""


def test_article_is_taken_whole_and_alone():
    assert html_extract.main_text(PAGE) == ["Head & line", "One two three", "Four five"]
    assert html_extract.main_text("") == [] and html_extract.main_text("<p>a<!-- <p>b") == ["a"]
    assert html_extract.main_text("<p>a &lt;b&gt; c</p></div></p><p>d") == ["a <b> c", "d"]


def test_wrapper_tells_template_from_slots(spark):
    page = "<body><div><p>Welcome to the site</p></div><div><p>{}</p><p>{}</p></div><div><span>All rights</span></div></body>"
    rows = [(i, f"http://h.example.com/{i}", page.format(f"text {i}", f"more {i * i}")) for i in range(6)] + [(9, None, None), (10, "http://x/", "<p>alone")]
    df = spark.createDataFrame(rows, "page_id long, url string, html string")
    got = {r.page_id: (r.text, r.n_chars) for r in html_extract.extracted(df).collect()}
    assert got[3] == ("text 3\n\nmore 9", 14) and got[9] == ("", 0) and got[10] == ("alone", 5)
    assert html_extract.extracted(df.where("page_id < 0")).count() == 0


def test_pages_that_are_all_alike_keep_their_text(spark):
    df = spark.createDataFrame([(i, "http://h/a", "<body><p>same</p></body>") for i in range(5)], "page_id long, url string, html string")
    assert {r.text for r in html_extract.extracted(df).collect()} == {"same"}


def test_constant_blocks_beside_varying_ones_are_template(spark):
    page = "<body><p>Site notice</p>{}<p>Imprint</p>{}</body>"
    more = "".join(f"<div>Box {k}</div><div>{{0}} in {k}</div>" for k in range(12))
    rows = [(i, f"http://h.example.com/{i}", page.format("".join(f"<p>text {i} {j}</p>" for j in range(1 + i % 3)), more.format(f"page {i}"))) for i in range(9)]
    df = spark.createDataFrame(rows, "page_id long, url string, html string")
    got = {r.page_id: r.text.split("\n\n") for r in html_extract.extracted(df).collect()}
    assert got == {i: [*(f"text {i} {j}" for j in range(1 + i % 3)), *(f"page {i} in {k}" for k in range(12))] for i in range(9)}


def test_wrapper_decides_inside_articles_and_copies_count_once(spark):
    page = "<body><{0}><p>Subscribers read on</p><p>text {1}</p><section><p>more {1}</p><p>Printed in Ulm</p></section></{0}><p>Imprint</p></body>"
    rows = [(i, f"http://{tag}.example.com/{i}", page.format(tag, f"{i} of {tag}")) for i, tag in enumerate(["article", "main"] * 6)]
    copy = "<body><article><p>one</p><p>two</p></article><p>{}</p></body>"
    rows += [(100 + i, f"http://copies.example.com/{i}", copy.format(i)) for i in range(9)]
    rows += [(200 + i, "http://near.example.com/", f"<article><p>one</p><p>own {i}</p></article>") for i in range(4)]
    rows += [(300 + i, "http://near.example.com/", f"<article><p>story {i}</p><p>end {i}</p></article>") for i in range(9)]
    df = spark.createDataFrame(rows, "page_id long, url string, html string")
    got = {r.page_id: r.text.split("\n\n") for r in html_extract.extracted(df).collect()}
    assert all(got[i] == [f"text {i} of {tag}", f"more {i} of {tag}"] for i, tag in enumerate(["article", "main"] * 6))
    assert all(got[100 + i] == ["one", "two"] for i in range(9)) and all(got[200 + i] == ["one", f"own {i}"] for i in range(4))


def test_tree_matching_keeps_order():
    a, b = ["r", 1, "", [["x", 1, "1", []], ["y", 1, "2", []], ["z", 1, "3", []]]], ["r", 1, "", [["y", 1, "2", []], ["x", 1, "9", []], ["z", 1, "4", []]]]
    m = html_extract.merge(a, b)
    assert html_extract.size_of_match(a, b) == 3 and sum(c[1] for c in m[3]) == 6
    assert [c[2] for c in m[3] if c[0] == "z"] == [""]


def test_deep_and_broken_pages_are_read_in_linear_time():
    import time

    began = time.time()
    deep = html_extract.blocks("<div>" * 5000 + "a" + "</div>" * 5000)
    w = html_extract.merge(html_extract.tree(deep), html_extract.grown(html_extract.flat(html_extract.tree(deep))))
    assert html_extract.template(w, 1) == ["div " + html_extract.mark("a")]
    rng = random.Random(1)
    page = lambda d: "".join("<div>" + "<p>x" * rng.randrange(3) for _ in range(d)) + "</div>" * d
    a, b = (html_extract.tree(html_extract.blocks(page(200))) for _ in "ab")
    assert html_extract.size_of_match(a, b) > 200
    for broken in ('<a href="' + "<x " * 50_000, "</ " * 50_000, "<a '" * 30_000 + '<b "' * 30_000):
        html_extract.blocks(broken)
    assert html_extract.main_text("<div <p>x") == ["x"] and time.time() - began < 20


def test_pages_of_ever_new_shapes_do_not_add_up():
    w = html_extract.tree(html_extract.blocks("<p>Notice</p><i>x"))
    for i in range(600):
        w = html_extract.thinned(html_extract.merge(w, html_extract.tree(html_extract.blocks(f"<p>Notice</p><div class=c{i}><p>{i}</div>"))), 200)
    assert sum(1 for _ in html_extract.nodes_of(w)) < 300 and html_extract.template(w) == ["p " + html_extract.mark("Notice")]


def test_template_of_rare_sections_is_found_on_hosts_of_many_shapes(spark):
    new = lambda i: "".join(f"<div class=c{i}x{k}><p>only {i} {k}</p><p>b</p></div>" for k in range(20))
    rare = lambda i: f"<div class=special><p>The same words</p><p>own {i}</p></div>" if i % 12 == 0 else ""
    df = spark.createDataFrame([(i, "http://h/", f"<body>{rare(i)}{new(i)}</body>") for i in range(144)], "page_id long, url string, html string")
    got = {r.page_id: r.text for r in html_extract.extracted(df.coalesce(1)).collect()}
    assert all("only 24 3" in got[i] for i in (24,)) and "own 24" in got[24]
    assert not any("The same words" in x for x in got.values())


def test_extraction_ignores_repeats_and_clashing_columns(spark):
    page = "<body><p>Welcome</p><p>{}</p></body>"
    rows = [(i % 5, "http://h/", page.format(i % 5), "x", "y", 1) for i in range(20)]
    df = spark.createDataFrame(rows, "page_id long, url string, html string, host string, fixed string, n_chars long")
    got = html_extract.extracted(df).collect()
    assert len(got) == 20 and all(r.text == str(r.page_id) for r in got)


# Language model.


def base_scores(texts):
    tokens = {i: words(t) + [None] for i, t in texts.items()}
    out = {i: zlib.crc32(str(i).encode()) % 7 == 2 for i in tokens}
    c = collections.Counter(w for i, x in tokens.items() if not out[i] for w in x)
    n, v = sum(c.values()), len(c)
    return {i: (out[i], len(x), sum(c[w] > 0 for w in x), n, sum(math.log10((c[w] + 1) / (n + v + 1)) for w in x)) for i, x in tokens.items()}


def test_base_score_and_counts(docs, none):
    want = base_scores(dict(enumerate(TEXTS)))
    for r in pitman_yor.scored(docs.select("doc_id", "text")).collect():
        assert (r.held_out, r.n_tokens, r.n_known, r.train_tokens) == want[r.doc_id][:4]
        assert abs(r.base_score - want[r.doc_id][4]) < 1e-6 and -1e6 < r.score < 0
    assert pitman_yor.scored(none).count() == 0


def test_model_beats_its_base_on_held_out_text_and_repeats(spark):
    rng = random.Random(3)
    follow = {w: [f"w{rng.randrange(60)}" for _ in range(3)] for w in (f"w{i}" for i in range(60))}
    texts = {}
    for i in range(400):
        w, out = "w0", []
        for _ in range(60):
            w = rng.choice(follow[w])
            out.append(w)
        texts[i] = " ".join(out)
    df = spark.createDataFrame(list(texts.items()), "doc_id long, text string")
    one, two = (sorted(map(tuple, pitman_yor.scored(x).collect())) for x in (df, df))
    held = [r for r in one if r[1]]
    assert one == two and sum(r[6] for r in held) > 0.6 * sum(r[5] for r in held)


def seats_of(model):
    """Customers, tables and parent probabilities by context and word, of a model whose chunks are read whole."""
    rows = {r["chunk"]: r.asDict() for r in model.dishes.collect()}
    seats = {}
    for r in model.seats().collect():
        seats.setdefault(r["chunk"], []).append(r.asDict())
    import pyarrow as pa

    out = {}
    for k, row in rows.items():
        x, seen = pitman_yor.Dishes(row), pitman_yor.Seats(pa.Table.from_pylist(seats[k]))
        parent = model.up.probability(*seen.parents())
        for i in range(len(x.c)):
            out[int(x.names[x.ctx[i]]), int(x.words[x.word[i]])] = (int(x.c[i]), int(seen.now[i]), float(parent[x.word[i]]))
    return out


TALK = [" ".join(f"w{(i * i + 3 * j * (1 + i % 3)) % 17}" for j in range(40)) for i in range(60)]


@pytest.mark.parametrize("chunk", [10_000, 150])
def test_probabilities_sum_to_one_in_every_context_after_every_sweep(spark, chunk):
    df = spark.createDataFrame(list(enumerate(TALK)), "doc_id long, text string")
    model = pitman_yor.Model(df, chunk)
    assert (len(model.deal.names) > 3) == (chunk == 150)  # with small chunks contexts are dealt to several
    for sweep in range(3):
        got = seats_of(model)
        parent = {w: p for (_, w), (_, _, p) in got.items()}
        unknown = float(model.up.probability(np.zeros(1), np.zeros(1))[0])
        known = {w for (_, w), (c, _, _) in got.items() if c}
        assert len(known) == model.up.vocabulary and abs(sum(parent[w] for w in known) + unknown - 1) < 1e-9
        assert sum(t for _, t, _ in got.values()) == model.up.customers
        for u in {u for u, _ in got}:
            own = {w: x for (v, w), x in got.items() if v == u}
            customers, opened = sum(x[0] for x in own.values()), sum(x[1] for x in own.values())
            p = sum(float(pitman_yor.predictive(own.get(w, (0,))[0], own.get(w, (0, 0))[1], customers, opened, parent[w])) for w in known)
            assert abs(p + float(pitman_yor.predictive(0, 0, customers, opened, unknown)) - 1) < 1e-9
        model.step(keep=False)


def brute_scores(texts, sweeps=120, burn=40, seed=1):
    """Sequential Gibbs over customers and tables, one at a time, on real seating arrangements."""
    rng = random.Random(seed)
    d2, t2, d1, t1 = pitman_yor.D2, pitman_yor.T2, pitman_yor.D1, pitman_yor.T1
    docs = {i: [None, *words(t), None] for i, t in texts.items()}
    out = {i: zlib.crc32(str(i).encode()) % 7 == 2 for i in docs}
    pairs = [(a, b) for i, x in docs.items() if not out[i] for a, b in zip(x, x[1:])]
    v = len({b for _, b in pairs})
    low, top = collections.defaultdict(list), collections.defaultdict(list)  # sizes of tables by (context, dish), and by dish
    count, opened = collections.Counter(), collections.Counter()

    def parent(w):
        n, t = sum(map(sum, top.values())), sum(map(len, top.values()))
        return (sum(top[w]) - d1 * len(top[w]) + (t1 + d1 * t) / (v + 1)) / (t1 + n)

    def put(tables, d, new):
        at = rng.choices(range(len(tables) + 1), [n - d for n in tables] + [new])[0]
        if at == len(tables):
            tables.append(0)
        tables[at] += 1
        return tables[at] == 1

    def take(tables):
        at = rng.choices(range(len(tables)), tables)[0]
        tables[at] -= 1
        if not tables[at]:
            del tables[at]
            return True
        return False

    def sit(u, w):
        if put(low[u, w], d2, (t2 + d2 * opened[u]) * parent(w)):
            opened[u] += 1
            put(top[w], d1, (t1 + d1 * sum(map(len, top.values()))) / (v + 1))
        count[u] += 1

    for u, w in pairs:
        sit(u, w)
    probability = collections.Counter()
    asked = {(a, b) for x in docs.values() for a, b in zip(x, x[1:])}
    for k in range(sweeps):
        for u, w in pairs:
            if take(low[u, w]):
                opened[u] -= 1
                take(top[w])
            count[u] -= 1
            sit(u, w)
        if k >= burn:
            for u, w in asked:
                probability[u, w] += (sum(low[u, w]) - d2 * len(low[u, w]) + (t2 + d2 * opened[u]) * parent(w)) / (t2 + count[u]) / (sweeps - burn)
    return {i: (out[i], sum(math.log10(probability[a, b]) for a, b in zip(x, x[1:]))) for i, x in docs.items()}


def test_scores_agree_with_a_sampler_of_single_customers(spark):
    texts = dict(enumerate(x[:60] for x in TALK[:30]))
    want = brute_scores(texts)
    for chunk in (10_000, 60):
        got = {r.doc_id: (r.held_out, r.score) for r in pitman_yor.scored(spark.createDataFrame(list(texts.items()), "doc_id long, text string"), chunk).collect()}
        for held in (True, False):
            a, b = (sum(x[1] for x in of.values() if x[0] == held) for of in (got, want))
            assert abs(a / b - 1) < 0.02


def test_null_ids_repeated_rows_and_long_texts_are_scored(spark):
    long = "a b " * 1_200_000  # more than one piece and more than one block
    rows = [(None, "a b", 1), (1, "a b", 2), (1, "a b", 3), (2, long, 4), (3, None, 5)]
    got = pitman_yor.scored(spark.createDataFrame(rows, "doc_id long, text string, score long")).collect()
    n = {None: 3, 1: 3, 2: 2_400_001, 3: 1}
    learnt = sum(n[r[0]] for r in rows if r[0] is None or zlib.crc32(str(r[0]).encode()) % 7 != 2)
    assert learnt > 2_400_000 and sorted((r.doc_id or 0, r.n_tokens, r.n_known, r.train_tokens) for r in got) == [(i or 0, n[i], n[i], learnt) for i in (None, 1, 1, 2, 3)]
    one = next(r for r in got if r.doc_id == 2)
    assert one.score > -0.01 * one.n_tokens > one.base_score


def test_perplexity_is_lower_than_that_of_the_base(spark):
    r = pitman_yor.perplexity(pitman_yor.scored(spark.createDataFrame(list(enumerate(TALK)), "doc_id long, text string"))).collect()
    assert {x.held_out for x in r} == {True, False} and all(1 < x.perplexity < x.base_perplexity for x in r)


def test_table_counts_follow_their_conditional():
    s, rng = pitman_yor.stirling(0.5), np.random.default_rng(1)
    c = np.full(40_000, 3)
    t = pitman_yor.tables(c, np.full(len(c), np.log(0.6)), 0.5, s, rng)
    weight = np.exp(s[3, 1:4]) * 0.6 ** np.arange(1, 4)
    assert np.allclose(np.exp(s[3, 1:4]), [0.5 * 1.5, 3 * 0.5, 1]) and np.abs(np.bincount(t, minlength=4)[1:4] / len(t) - weight / weight.sum()).max() < 0.01


@pytest.mark.parametrize("d", [0.6, 0.75])
@pytest.mark.parametrize("a", [1e-4, 0.05, 1.0, 8.0, 60.0, 400.0])
def test_the_limit_law_of_table_counts_meets_the_exact_one(d, a):
    n = pitman_yor.EXACT
    w = pitman_yor.stirling(d)[n, 1:] + np.log(a) * np.arange(1, n + 1)
    p = np.exp(w - w.max()) / np.exp(w - w.max()).sum()
    mean = p @ np.arange(1, n + 1)
    spread = math.sqrt(p @ np.arange(1, n + 1) ** 2 - mean**2)
    t = pitman_yor.many_tables(np.full(20_000, n), np.full(20_000, a), d, np.random.default_rng(3))
    assert abs(t.mean() - mean) < 0.06 * mean + 0.2 and abs(t.std() - spread) < 0.25 * spread + 0.3


# BPE.


@pytest.fixture(scope="module")
def codec():
    import public_tokenizers as p

    return bpe.Codec(bpe.read_ranks(p.path("byte_bpe_50k.tiktoken")), p.PATTERN)


@pytest.fixture(scope="module")
def reference():
    import public_tokenizers as p
    import tiktoken

    return tiktoken.Encoding("own", pat_str=p.PATTERN, mergeable_ranks=bpe.read_ranks(p.path("byte_bpe_50k.tiktoken")), special_tokens={})


def test_encoding_equals_the_reference_library(codec, reference):
    rng = random.Random(5)
    parts = ["a", "the", " ", "  ", "\n", "\t ", "\r\n", "é", "'s", "'re", "12", "_!", "\x1c", "\x85", " ", "日本", "\U0001f600", "aaaa", "<|endoftext|>"]
    for _ in range(1500):
        s = "".join(rng.choice(parts) for _ in range(rng.randrange(30)))
        ids = codec.encode(s)
        assert ids == reference.encode_ordinary(s) and codec.decode(ids).decode() == s
    long = "abcdefgh" * 4000
    assert codec.decode(codec.encode(long)).decode() == long


def test_appends_and_edits_redo_little(codec, reference):
    rng = random.Random(6)
    for _ in range(200):
        s = "".join(rng.choice("abcdetion") for _ in range(rng.randrange(80)))
        a = rng.randrange(len(s) + 1)
        b = rng.randrange(a, len(s) + 1)
        t = bpe.PrefixTable(codec, s.encode())
        t.edit(a, b, b"tio")
        t.append(b"ness")
        want = (s[:a] + "tio" + s[b:] + "ness").encode()
        assert t.ids() == bpe.PrefixTable(codec, want).ids() == reference._core_bpe.encode_single_piece(want)
    t = bpe.PrefixTable(codec, b"abcdetion" * 500)
    assert t.edit(10, 11, b"x") < 600


def test_encoded_frames(docs, none, reference):
    import public_tokenizers as p

    args = (p.path("byte_bpe_50k.tiktoken"), p.PATTERN)
    for r in bpe.encoded(docs, *args).collect():
        text = TEXTS[r.doc_id] or ""
        assert (r.ids, r.n_tokens, bytes(r.decoded)) == (reference.encode_ordinary(text), len(r.ids), text.encode())
    for r in bpe.encoded(docs, *args, digests=True).collect():
        ids = reference.encode_ordinary(TEXTS[r.doc_id] or "")
        assert r.ids_sha256 == hashlib.sha256(" ".join(map(str, ids)).encode()).hexdigest()
    assert bpe.encoded(none, *args).count() == 0


# Mixing.


def test_mix_meets_its_targets(spark):
    rng = random.Random(2)
    rows = [(i, rng.choice(["a", "b", "b", "b", "b", "c", None]), "w " * rng.randrange(200)) for i in range(4000)]
    df = spark.createDataFrame(rows, "doc_id long, source string, text string")
    out = mix.mix(df).collect()
    by = collections.defaultdict(lambda: [0, 0, 0])
    for r in out:
        assert r.taken <= 3 * r.size and r.taken % max(r.size, 1) == 0
        by[r.source][0] += r.taken
        by[r.source][1], by[r.source][2] = r.target, r.source_size
    total = sum(x[2] for x in by.values())
    assert abs(sum(x[1] for x in by.values()) - total) < 1e-6 * total
    for taken, target, size in by.values():
        assert target <= 3 * size + 1e-9 and abs(taken - target) < 0.02 * target + 400
    assert sorted(map(repr, out)) == sorted(map(repr, mix.mix(df.repartition(7)).collect()))


def test_targets_reshare_what_full_sources_cannot_take(spark):
    sizes = spark.createDataFrame([("a", 10), ("b", 10), ("c", 980), (None, 0)], "source string, source_size long")
    got = {r.source: r.target for r in mix.targets(sizes).collect()}
    assert got["a"] == 30 and got["b"] == 30 and got[None] == 0 and abs(got["c"] - 940) < 1e-9


def test_mix_edge_cases(docs, none):
    out = {r.doc_id: r for r in mix.mix(docs).collect()}
    assert len(out) == len(TEXTS) and out[0].size == 0 and out[8].size == 3000 and out[8].recipe == "clash"
    assert mix.mix(none).count() == 0


# Quality.


def test_classifier_learns_and_covers_whole_texts(spark):
    rng = random.Random(4)
    clean = lambda: " ".join(rng.choice(["the", "river", "of", "stone", "and", "light"]) for _ in range(rng.randrange(20, 400)))
    rows, labels = [], []
    for i in range(300):
        good = i % 3 != 0
        rows.append((i, clean() if good else clean() + " ### $$$ !!!"))
        labels.append((i, int(good)))
    rows += [(1000, None), (1001, ""), (1002, clean() * 30 + " $$$ ### !!!")]
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    got = {r.doc_id: r for r in quality_cnn.judged(docs, spark.createDataFrame([*labels, (5, 0), (7, None)], "doc_id long, quality int")).collect()}
    held = [i for i, _ in labels if zlib.crc32(str(i).encode()) % 3 == 1]
    assert np.mean([got[i].predicted == dict(labels)[i] for i in held]) > 0.95 and all(got[i].held_out for i in held)
    assert got[1002].predicted == 0 and 0 <= got[1000].score <= 1 and got[1000].score == got[1001].score


def test_padding_covers_every_byte():
    for n in (0, 1, 7, 8, 9, 12, 100, 101):
        x = quality_cnn.padded(bytes(range(1, 2)) * n)
        assert len(x) >= max(n, quality_cnn.WIDTH) and (len(x) - quality_cnn.WIDTH) % quality_cnn.STRIDE == 0


def test_without_labels_scores_are_undecided(docs, spark):
    got = quality_cnn.judged(docs, spark.createDataFrame([], "doc_id long, quality int")).collect()
    assert len(got) == len(TEXTS) and {r.score for r in got} == {0.5}


# URLs.


def test_rules_hosts_and_paths(spark):
    urls = {
        "http://a.COM/en/1": ("a.com", "/en/1", "com/en/", "block"), "https://example.com/en/7x?q#f": ("example.com", "/en/7x", "example.com/en/7", "allow"), "http://x.net/de/": ("x.net", "/de/", "net/de/", "allow"),
        "http://sub.example.net/de/81": ("sub.example.net", "/de/81", "example.net/de/8", "block"), "http://acom/en/": ("acom", "/en/", None, "allow"), "http://q.org?x=/es/": ("q.org", "", None, "allow"),
        "nothing": ("", "", None, "allow"), None: ("", "", None, "allow"), "http://casino-pills.example.org/de/5": ("casino-pills.example.org", "/de/5", None, "block"),
    }
    df = spark.createDataFrame(list(enumerate(urls)), "page_id long, url string")
    got = {r.page_id: (r.host, r.path, r.rule, r.verdict) for r in url_filter.judged(df).collect()}
    assert got == dict(enumerate(urls.values()))
    assert url_filter.judged(df.where("page_id < 0")).count() == 0


def test_url_model_holds_on_urls_it_has_not_seen(spark):
    rows = url_filter.labelled()
    odds, unwanted = url_filter.held_out(rows), np.array([r[2] == 1 for r in rows])
    assert 150 <= len(rows) <= 200 and np.mean([(odds[unwanted] > x).mean() for x in odds[~unwanted]]) > 0.85
    shift = np.quantile(odds[~unwanted], 1 - url_filter.WRONG)
    assert (odds[unwanted] > shift).mean() > 0.5
    df = spark.createDataFrame([(1, "http://x.org/es/", "a", "b"), (1, "http://x.org/es/", "a", "b")], "page_id long, url string, host string, score string")
    assert [(r.page_id, r.verdict) for r in url_filter.judged(df).collect()] == [(1, "block")] * 2


# Nearest neighbours.


def test_recall_scores_and_ties(spark):
    rng = np.random.default_rng(1)
    x = rng.normal(size=(3000, 32))
    x[2000:2400] = x[0]  # one vector many times
    rows = [(i, [float(v) for v in r]) for i, r in enumerate(x)] + [(5000, None), (5050, [0.0] * 32), (5100, [1.0] * 31 + [None]), (5150, [float("nan")] * 32), (5200, [1.0])]
    got = collections.defaultdict(list)
    for r in ann.nearest(spark.createDataFrame(rows, "vec_id long, embedding array<double>")).collect():
        got[r.query_id].append((r.rank, r.vec_id, r.score))
    assert set(got) == set(range(0, 3000, 50))
    u, hit = x / np.linalg.norm(x, axis=1, keepdims=True), 0
    for q, found in got.items():
        s = u @ u[q]
        s[q] = -9
        want = np.lexsort((np.arange(3000), -np.round(s, 12)))[:5]
        hit += len(set(want) & {v for _, v, _ in found})
        for k, (rank, v, score) in enumerate(sorted(found)):
            assert rank == k + 1 and abs(score - s[v]) < 1e-12
    assert hit / (5 * len(got)) >= 0.9
    assert [v for _, v, _ in sorted(got[0])] == [2000, 2001, 2002, 2003, 2004]


def test_grouped_vectors_are_found_in_few_leaves_and_all_leaves_are_exact(spark):
    rng = np.random.default_rng(2)
    x = np.repeat(rng.normal(size=(300, 16)), 20, 0) + 0.1 * rng.normal(size=(6000, 16))
    df = spark.createDataFrame([(i, [float(v) for v in r], 1) for i, r in enumerate(x)], "vec_id long, embedding array<double>, score int")
    u = x / np.linalg.norm(x, axis=1, keepdims=True)
    want = {}
    for q in range(0, 6000, 50):
        s = u @ u[q]
        s[q] = -9
        want[q] = set(np.argsort(-s)[:5].tolist())
    for target, least in ((0.96, 0.9), (1.0, 1.0)):
        got = collections.defaultdict(set)
        for r in ann.nearest(df, target=target).collect():
            got[r.query_id].add(r.vec_id)
        assert sum(len(want[q] & got[q]) for q in want) >= least * 5 * len(want)
    forest, ids = ann.Forest(u, 8, 6), np.arange(0, 6000, 97)
    pops = ann.probed(df.select(F.col("vec_id").alias("id"), F.col("embedding").alias("v")), forest, ids, x[ids], 5, 0.96)
    assert pops < 0.05 * forest.trees * forest.leaves


def test_few_or_no_candidates(spark):
    df = spark.createDataFrame([(0, [1.0, 0.0]), (1, [0.0, 1.0]), (2, [1.0, 1.0])], "vec_id long, embedding array<float>")
    assert sorted((r.rank, r.vec_id) for r in ann.nearest(df).collect()) == [(1, 2), (2, 1)]
    assert ann.nearest(df.where("vec_id < 0")).count() == 0


# Near duplicates.


def brute(texts, size=5, percent=75):
    sets = {}
    for i, t in texts.items():
        w = words(t)
        sets[i] = {tuple(w[j : j + size]) for j in range(len(w) - size + 1)} if len(w) >= size else ({tuple(w)} if w else set())
    comp = {i: i for i in texts}
    ids = sorted(texts)
    for _ in ids:
        changed = False
        for a in ids:
            for b in ids:
                if a < b and sets[a] and comp[a] != comp[b] and 100 * len(sets[a] & sets[b]) >= percent * len(sets[a] | sets[b]):
                    comp[a] = comp[b] = min(comp[a], comp[b])
                    changed = True
        if not changed:
            break
    return {i: (len(sets[i]), comp[i]) for i in texts}


def made_texts(seed, n=120):
    rng = random.Random(seed)
    vocab = [f"v{i}" for i in range(400)]
    passage = [rng.choice(vocab) for _ in range(60)]
    base = [[rng.choice(vocab) for _ in range(rng.randrange(4, 220))] for _ in range(12)]
    out = {}
    for i in range(n):
        w = list(rng.choice(base))
        for _ in range(rng.choice([0, 0, 1, 2, 5, 9])):
            w[rng.randrange(len(w))] = rng.choice(vocab)
        if rng.random() < 0.3:
            w = [rng.choice(vocab) for _ in range(rng.randrange(3, 200))]
        if rng.random() < 0.4:
            w[rng.randrange(len(w)) : 0] = passage
        out[i] = " ".join(w)
    return out


@pytest.mark.parametrize(("seed", "crowd"), [(1, 24), (2, 2), (3, 3)])
def test_components_equal_brute_force(spark, monkeypatch, seed, crowd):
    monkeypatch.setattr(ngram_join, "CROWD", crowd)  # small, so that groups do leave buckets
    texts = made_texts(seed)
    df = spark.createDataFrame(list(texts.items()), "doc_id long, text string")
    got = {r.doc_id: (r.n_shingles, r.component_id) for r in ngram_join.near_duplicates(df).collect()}
    assert got == brute(texts)


def test_near_duplicate_edge_cases(docs, none, spark):
    got = {r.doc_id: (r.n_shingles, r.component_id) for r in ngram_join.near_duplicates(docs).collect()}
    assert got == brute(dict(enumerate(TEXTS)))
    assert ngram_join.near_duplicates(none).count() == 0
    twice = docs.union(docs)
    assert ngram_join.near_duplicates(twice).count() == 2 * len(TEXTS)


def test_prefixes_of_similar_sets_share_what_they_must():
    rng = random.Random(8)
    for _ in range(2000):
        n = rng.randrange(1, 300)
        m = rng.randrange(-(-75 * n // 100), n + 1)
        extra = rng.randrange(0, n)
        x, y = set(range(n)), set(range(n - m, n)) | set(range(1000, 1000 + extra))
        if 100 * len(x & y) < 75 * len(x | y):
            continue
        order = {v: rng.random() for v in x | y}
        px, py = (set(sorted(s, key=order.get)[: ngram_join.prefix_length(len(s))]) for s in (x, y))
        assert len(px & py) >= min(ngram_join.share_of(len(x)), ngram_join.share_of(len(y)))


def test_connected_components(spark):
    edges = [(i, i + 1) for i in range(10, 60)] + [(5, 100), (100, 7), (8, 8), (5, 100)]
    got = {r.node: r.component for r in components(spark.createDataFrame(edges, "a long, b long")).collect()}
    assert got == {**{i: 10 for i in range(10, 61)}, 5: 5, 7: 5, 100: 5, 8: 8}
    assert components(spark.createDataFrame([], "a long, b long")).count() == 0


def test_texts_that_share_common_words_alone_hardly_meet(spark):
    """Else meetings, and the disk they take, grow faster than the documents."""
    rng = random.Random(5)
    common, rare = [f"c{i}" for i in range(4)], [f"r{i}" for i in range(4000)]
    rows = [(i, " ".join(rng.choice(common) if rng.random() < 0.75 else rng.choice(rare) for _ in range(300))) for i in range(200)]
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    info = ngram_join.described(docs, ngram_join.frequent(docs, 5), 5, 75)
    met = ngram_join.meetings(info.select(F.col("doc_id").alias("grp"), "n", "prefix"), 4).count()
    assert met < 1000  # of some 20,000 shingles of prefixes


def test_near_duplicates_leave_no_large_scratch_tables(spark):
    from itemset_sieve.scratch import scratch_dir

    at = spark._jvm.org.apache.hadoop.fs.Path(scratch_dir(spark))
    names = lambda: {s.getPath().getName() for s in at.getFileSystem(spark._jsc.hadoopConfiguration()).listStatus(at)}
    docs = spark.createDataFrame(list(enumerate(TEXTS)), "doc_id long, text string")
    ngram_join.frequent(docs, 5)  # the folder is there
    spark.range(1).write.mode("overwrite").parquet(f"{scratch_dir(spark)}/any")
    before = names()
    assert ngram_join.near_duplicates(docs).count() == len(TEXTS)
    assert {x.split("-")[0] for x in names() - before} <= {"names", "classes", "labels"}
