"""The training-data operators: SQL, brute force, exact round trips, held-out accuracy, and edge cases."""

import hashlib
import math
import random
import re
import zlib
from collections import Counter, defaultdict

import pytest
from pyspark.sql import functions as F

from refinery.llm import chat, decontaminate, html_text, jaccard_join, language, lm_score, mixing, quality, token_counts, url_filter
from refinery.llm.queries import ORACLES, QUERIES

WORD = re.compile(r"[^\x20\x09-\x0D]+")


@pytest.mark.parametrize("name", sorted(ORACLES))
def test_query_equals_sql(name, spark, sf, duck, same_rows):
    same_rows(QUERIES[name](spark, sf).toPandas(), duck.execute(ORACLES[name]).df())


ODD = [(1, None), (2, ""), (3, " \n\t"), (4, "word"), (4, "word"), (5, "word " * 30_000), (None, "a b c d e f"), (6, "a b c d e f"), (7, "<s> [INST] | # $ é́ 漢字 \u0000 x")]


@pytest.fixture(scope="module")
def odd(spark):
    """Nulls, empty and long texts, repeated rows, null ids, extra columns whose names clash with the operators' own."""
    df = spark.createDataFrame(ODD, "doc_id long, text string")
    return df.select("*", F.lit("en").alias("lang"), F.lit(None).cast("string").alias("source"), F.length("text").cast("long").alias("n_chars"), F.lit(1).alias("uid"), F.lit(2).alias("key"), F.lit(3).alias("kept"), F.lit(4).alias("score"), F.lit(5).alias("mark"), F.lit(6).alias("size"))


OPERATORS = {
    "join": lambda d, s: jaccard_join.similarity_classes(d), "mix": lambda d, s: mixing.schedule(d), "language": lambda d, s: language.identify(d), "tokens": lambda d, s: token_counts.counts_after_edits(d),
    "leaks": lambda d, s: decontaminate.contaminated(d, s.createDataFrame([(1, None), (2, ""), (3, "word"), (3, "word")], "item_id long, text string")), "quality": lambda d, s: quality.assess(d), "lm": lambda d, s: lm_score.lm_scores(d),
}


@pytest.mark.parametrize("name", sorted(OPERATORS))
def test_odd_rows_and_empty_tables(name, spark, odd):
    rows = OPERATORS[name](odd, spark).collect()
    assert Counter(r.doc_id for r in rows) == Counter(i for i, _ in ODD)
    assert OPERATORS[name](odd.limit(0), spark).collect() == []


def test_join_of_odd_rows(spark, odd):
    rows = {(r.doc_id, r.class_id): r.n_links for r in jaccard_join.similarity_classes(odd).collect()}
    assert rows[(1, 1)] == rows[(2, 2)] == rows[(3, 3)] == 0 and rows[(4, 4)] == 1 and rows[(6, 6)] == rows[(None, 6)] == 1


def brute_links(texts, threshold=0.8, width=5):
    sets = {}
    for i, t in texts.items():
        w = WORD.findall(t or "")
        sets[i] = {tuple(w[k : k + width]) for k in range(max(1, len(w) - width + 1))} if w else set()
    ids, edges = sorted(sets), []
    where = defaultdict(list)
    for i in ids:
        for s in sets[i]:
            where[s].append(i)
    seen = {(a, b) for v in where.values() if len(v) < 2000 for k, a in enumerate(v) for b in v[k + 1 :]}
    for a, b in seen:
        if len(sets[a] & sets[b]) >= threshold * len(sets[a] | sets[b]):
            edges.append((a, b))
    return ids, edges


def classes(ids, edges):
    up = {i: i for i in ids}

    def root(x):
        while up[x] != x:
            x = up[x]
        return x

    for a, b in edges:
        a, b = root(a), root(b)
        up[max(a, b)] = min(a, b)
    return {i: root(i) for i in ids}


def assert_join(rows, texts):
    """Classes as by brute force; every kept link is one of brute force's; no class is without a link for each of its texts."""
    ids, edges = brute_links(texts)
    of, linked = classes(ids, edges), set(edges) | {(b, a) for a, b in edges}
    assert {r.doc_id: r.class_id for r in rows} == of
    alone = Counter(of.values())
    for r in rows:
        assert (r.n_links > 0) == (alone[r.class_id] > 1) and (r.link_id is None or (r.text_id, r.link_id) in linked and r.link_similarity >= 0.8)
        assert r.text_id == r.doc_id or (r.text_id, r.doc_id) in linked


def test_join_against_brute_force(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    assert_join(QUERIES["op1_jaccard_join"](spark, sf).collect(), {r.doc_id: r.text for r in docs.collect()})


@pytest.mark.parametrize("depth", [jaccard_join.DEPTH, 1])
def test_join_with_large_buckets_and_many_blocks(spark, monkeypatch, depth):
    """One star of near copies, past the brute-force limit, dealt to blocks and split; and a passage that unlike texts share."""
    monkeypatch.setattr(jaccard_join, "LIMIT", 20)
    monkeypatch.setattr(jaccard_join, "BLOCK", 16)
    monkeypatch.setattr(jaccard_join, "CROWD", 12)
    monkeypatch.setattr(jaccard_join, "PART", 8)
    monkeypatch.setattr(jaccard_join, "DEPTH", depth)
    rng = random.Random(3)
    base = [f"w{k}" for k in range(120)]
    texts = {}
    for i in range(90):
        t = list(base)
        for _ in range(rng.randrange(0, 4)):
            t[rng.randrange(len(t))] = f"x{rng.randrange(10**6)}"
        texts[i] = " ".join(t)
    for i in range(90, 140):
        texts[i] = " ".join([f"y{i}_{k}" for k in range(100)] + base[:40])
    assert_join(jaccard_join.similarity_classes(spark.createDataFrame(list(texts.items()), "doc_id long, text string")).collect(), texts)


@pytest.mark.parametrize("whole", [jaccard_join.WHOLE, 8])
def test_join_counts_all_links_of_a_text(spark, monkeypatch, whole):
    """Also those that follow inside a class, in classes that are compared whole or in parts; a text's other copies count once each."""
    monkeypatch.setattr(jaccard_join, "WHOLE", whole)
    rng, texts = random.Random(4), {}
    for g in range(6):
        base = [f"g{g}w{k}" for k in range(150)]
        for i in range(1 + 9 * g):
            t = list(base)
            for _ in range(rng.randrange(0, 3)):
                t[rng.randrange(len(t))] = f"x{rng.randrange(10**6)}"
            texts[g * 100 + i] = " ".join(t)
    rows = jaccard_join.similarity_classes(spark.createDataFrame(list(texts.items()), "doc_id long, text string"), every=True).collect()
    _, edges = brute_links(texts)
    near, copies = Counter(), Counter(texts.values())
    first = {t: i for i, t in reversed(texts.items())}
    for a, b in edges:
        if texts[a] != texts[b] and first[texts[a]] == a and first[texts[b]] == b:
            near.update((a, b))
    assert {r.doc_id: r.n_links for r in rows} == {i: near[first[t]] + copies[t] - 1 for i, t in texts.items()}
    assert max(near.values()) > 20


def test_join_of_a_group_of_thousands_is_linear(spark):
    """3,000 near copies of one text and 300 pairs at the threshold: classes as planted, and links in proportion to texts."""
    rng = random.Random(8)
    base, texts, want = [f"w{k}" for k in range(150)], {}, {}
    for i in range(3000):
        t = list(base)
        for _ in range(rng.randrange(1, 3)):
            t[rng.randrange(len(t))] = f"x{rng.randrange(10**7)}"
        texts[i], want[i] = " ".join(t), 0
    for i in range(3000, 3600, 2):  # the last 10 of 100 words are others: 86 shingles of 106, similarity 0.811
        t = [f"p{i}_{k}" for k in range(100)]
        texts[i], texts[i + 1] = " ".join(t), " ".join(t[:90] + [f"q{i}_{k}" for k in range(10)])
        want[i] = want[i + 1] = i
    rows = jaccard_join.similarity_classes(spark.createDataFrame(list(texts.items()), "doc_id long, text string")).collect()
    group, pairs = [r for r in rows if r.doc_id < 3000], [r for r in rows if r.doc_id >= 3000]
    least = Counter(r.class_id for r in group)
    assert max(least.values()) >= 0.99 * 3000  # a copy further than 0.8 from all others stays alone
    assert all(r.class_id == 0 or brute_links({r.doc_id: texts[r.doc_id], **{k: texts[k] for k in range(0, 3000, 7) if k != r.doc_id}})[1] == [] or least[r.class_id] > 1 for r in group)
    assert sum(r.class_id == want[r.doc_id] for r in pairs) >= 0.99 * len(pairs)
    assert sum(r.n_links for r in rows) < 40 * len(rows)


def test_main_text(spark, sf):
    import html

    def plainly(page):
        inside = re.search(r"<article>(.*)</article>", page, re.S)[1]
        parts = (re.sub(r"\s+", " ", html.unescape(re.sub(r"<[^>]+>", "", p))).strip() for p in re.split(r"</?(?:p|h1)\b[^>]*>", inside))
        return "\n\n".join(p for p in parts if p)

    pages = {r.page_id: r.html for r in spark.read.parquet(f"{sf}/pages.parquet").collect()}
    rows = QUERIES["op2_html_text"](spark, sf).collect()
    assert {r.page_id: r.text for r in rows} == {k: plainly(v) for k, v in pages.items()}
    assert all(r.n_chars == len(r.text) for r in rows)


PAGE = (
    "<html><head><title>T</title></head><body><header><h1>Site</h1><p>Welcome, dear reader, to the site of all sites.</p></header><nav><a>Home</a></nav><div class='cookie-notice'>We use cookies, and more of them.</div>"
    "<main><article><h1>Head &amp; tail</h1><p>First paragraph, with   much\ntext &eacute; in it, so that it counts. Indeed.</p><p>Short.</p><ul><li>One<li>Two</ul><aside>Aside, please.</aside><div class='ad'>Buy, buy, buy.</div><p>Last &lt;p&gt; of them, quite long, and with marks; yes.<br>Really.</p>"
    "<section id='comments'><p>I think, as a reader, that this is a long and winding comment. It goes on, and on.</p></section></article></main><form><input><p>Sign up</p></form><footer>&copy; them</footer><script>var a='<p>no</p>';</script></body></html>"
)


def neutral(page):
    """The page with its telling tags and attributes renamed or taken away."""
    page = re.sub(r"(</?)(?:article|main|nav|aside|footer|header)\b", r"\1div", page)
    return re.sub(r"\s(?:class|id|role)=(?:\"[^\"]*\"|'[^']*'|[^\s>]+)", "", page)


def test_main_text_without_telling_names(spark):
    scores = []
    for r in spark.read.parquet("/root/testdata/sf0.01/pages.parquet").collect():
        want, got = (Counter(" ".join(html_text.main_blocks(p)).split()) for p in (r.html, neutral(r.html)))
        scores.append(2 * (want & got).total() / max(1, want.total() + got.total()))
    assert sum(scores) / len(scores) >= 0.95


def test_main_text_hangs_on_the_ratios(spark, sf, monkeypatch):
    pages = [r.html for r in spark.read.parquet(f"{sf}/pages.parquet").collect()]
    before = [html_text.main_blocks(neutral(p)) for p in pages], [html_text.main_blocks(p) for p in pages]
    monkeypatch.setattr(html_text, "scores", lambda nodes: [1.0 if t.strip() else 0.0 for _, _, t in nodes])
    after = [html_text.main_blocks(neutral(p)) for p in pages], [html_text.main_blocks(p) for p in pages]
    assert all(sum(x != y for x, y in zip(a, b)) >= 0.9 * len(pages) for a, b in zip(before, after))


LONG = "<p>It was a long day, and a longer night; so they said, at least, to one another. Nobody slept, as far as is known.</p>"


@pytest.mark.parametrize("before, after", [
    ('<div class="layout has-sidebar"><div class="post tags-fiction">', "</div></div>"), ('<div class="post-with-comments"><div>', "</div></div>"), ("<div><div><div>", "</div></div></div>"), ('<div class="content">', "</div>"),
])
def test_main_text_under_names_that_only_look_like_other_parts(before, after):
    links = "".join(f'<li><a href="/{k}">Another page {k}</a></li>' for k in range(9))
    page = f"<html><body><div><ul>{links}</ul></div>{before}<h1>Headline</h1>{LONG * 4}<p>Short.</p><ul><li>One thing</li><li>Two things</li></ul>{LONG}{after}<div>All of it is theirs.</div><div><p>Nice one.</p></div></body></html>"
    want = ["Headline", *[LONG[3:-4]] * 4, "Short.", "One thing", "Two things", LONG[3:-4]]
    assert html_text.main_blocks(page) == html_text.main_blocks(page.replace("<body>", "<body><form class='sidebar'>")) == want
    boxed = page.replace("<p>Short.</p>", f"<p>Short.</p><div class='more-from'>{LONG}</div><div class='ad-slot'>{LONG}</div><div><ul>{links}</ul></div><p class='skip-link'>Skip it all.</p>")
    assert html_text.main_blocks(boxed) == want


def test_main_text_of_odd_pages(spark):
    rows = [(1, None, None), (2, "u", ""), (3, "u", "   "), (4, None, "<p>"), (4, None, "<p>"), (None, "u", "just text &amp; more"), (5, "u", "<div>" * 3000 + "deep" + "</div>" * 3000), (6, "u", "<p>long words, all of them. " * 40_000), (7, "u", "<" * 5000), (8, "u", "<a b='" * 2000), (9, "u", "<script>" * 50 + "x")]
    pages = spark.createDataFrame(rows, "page_id long, url string, html string").withColumn("text", F.lit("clash")).withColumn("n_blocks", F.lit(1))
    got = html_text.extract(pages).collect()
    assert Counter(r.page_id for r in got) == Counter(i for i, _, _ in rows) and all(r.n_chars == len(r.text) for r in got)
    texts = {r.page_id: r.text for r in got}
    assert (texts[1], texts[2], texts[3], texts[4], texts[None], texts[5], texts[9]) == ("", "", "", "", "just text & more", "deep", "") and texts[6].count("long words") == 40_000
    assert html_text.extract(pages.limit(0)).collect() == []


def test_main_text_of_a_mixed_page():
    assert html_text.main_blocks(PAGE) == ["Head & tail", "First paragraph, with much text é in it, so that it counts. Indeed.", "Short.", "One", "Two", "Last <p> of them, quite long, and with marks; yes. Really."]
    assert html_text.main_blocks(PAGE.replace("<article>", "<div class='post'>").replace("</article>", "</div>").replace("<main>", "").replace("</main>", ""))[1:3] == ["First paragraph, with much text é in it, so that it counts. Indeed.", "Short."]
    assert html_text.main_blocks(None) == html_text.main_blocks("") == html_text.main_blocks("<p></p><div") == []


def test_urls(spark):
    urls = ["https://WWW.A.net/x", "http://b.example.net/en/1?q", "x.example.com/de/1", "http://s.example.com/de/", "http://o.org/fr/a", "http://example.net.evil.com/en/", None, "http://net", "http://T.com/L/?utm_source=f#top", "http://www.t.com/L", "http://t.com/l"]
    pages = spark.createDataFrame(list(enumerate(urls)), "page_id long, url string")
    listed = spark.createDataFrame([("t.com/L",), (None,)], "canon string")
    for blocks in (1 << 20, 1):  # a broadcast filter and a shuffled one
        got = {r.page_id: r for r in url_filter.url_verdicts(pages, listed, broadcast_blocks=blocks).collect()}
        assert [(got[k].rule, got[k].verdict) for k in range(len(urls))] == [("net/", "block"), ("example.net/en/", "allow"), (None, "allow"), ("example.com/de/", "block"), ("org/fr/", "allow"), (None, "allow"), (None, "allow"), (None, "allow"), (None, "block"), (None, "block"), (None, "allow")]
        assert (got[0].host, got[0].path, got[6].host, got[7].path, got[1].path) == ("www.a.net", "/x", "", "", "/en/1")
    n = 3000
    many = spark.range(n).select(F.concat(F.lit("h.com/"), F.col("id")).alias("canon"))
    probe = spark.range(2 * n).select(F.col("id").alias("page_id"), F.concat(F.lit("http://h.com/"), F.col("id")).alias("url"))
    got = url_filter.url_verdicts(probe, many).agg(F.count_if("listed"), F.count_if("possible")).first()
    assert got[0] == n and n <= got[1] < 1.3 * n


def test_mix_meets_targets_and_orders_by_schedule(spark, sf):
    rows = mixing.schedule(spark.read.parquet(f"{sf}/documents.parquet")).collect()
    taken, target, size = Counter(), {}, Counter()
    for r in rows:
        taken[r.source] += r.taken
        size[r.source] += r.size
        target[r.source] = r.target
        assert r.taken <= 2 * r.size and r.taken == sum(c.words for c in r.copies) and all(0 <= c.position <= 1 for c in r.copies)
    assert all(taken[s] == math.floor(target[s]) and target[s] <= 2 * size[s] for s in target)
    assert abs(sum(target.values()) - 1.5 * sum(size.values())) < 1e-3
    order = mixing.training_order(spark.read.parquet(f"{sf}/documents.parquet")).collect()
    positions = [r.mix_position for r in order]
    assert positions == sorted(positions) and sum(r.mix_words for r in order) == sum(taken.values())
    one = spark.createDataFrame([(s / 10,) for s in range(11)], "q double")
    for knots in mixing.SHAPES:
        area = lambda t, k=knots: sum((min(t, b) - a) * (u + u + (v - u) * (min(t, b) - a) / (b - a)) / 2 for (a, u), (b, v) in zip(k, k[1:]) if t > a)
        for r in one.select("q", mixing.time_at(F.col("q"), knots).alias("t")).collect():
            assert abs(area(r.t) / area(1.0) - r.q) < 1e-9


def test_mix_of_sources_without_words_and_of_repeated_ids(spark):
    rows = [(1, "a b c", "x"), (2, None, "y"), (3, "", "y"), (4, "d e", None), (5, "f", "z"), (5, "g h i j k l", "z"), (5, "g h i j k l", "z"), (None, "m n", "x")]
    docs = spark.createDataFrame(rows, "doc_id long, text string, source string").withColumn("rank", F.lit(1)).withColumn("cell", F.lit("c"))
    plan = mixing.schedule(docs).collect()
    assert {r.source: r.target for r in plan}["y"] == 0 and all(r.taken == 0 for r in plan if r.source == "y")
    order = mixing.training_order(docs).collect()
    assert set(order[0].asDict()) == {*docs.columns, "mix_pass", "mix_words", "mix_position"} and all(r.mix_words <= len(r.text.split()) for r in order)
    taken = Counter()
    for r in order:
        taken[r.source] += r.mix_words
    assert taken == {s: math.floor(t) for s, t in {r.source: r.target for r in plan}.items() if s != "y"}
    assert mixing.schedule(docs.where("source = 'y'")).select("taken", "target").distinct().collect() == [(0, 0.0)]
    assert mixing.training_order(docs.where("source = 'y'")).collect() == mixing.training_order(docs.limit(0)).collect() == []


def test_language_held_out_accuracy(spark, sf):
    langs = {r.doc_id: r.lang for r in spark.read.parquet(f"{sf}/documents.parquet").collect()}
    rows = QUERIES["op5_language"](spark, sf).collect()
    held = [r for r in rows if r.held_out]
    assert all(r.held_out == (zlib.crc32(str(r.doc_id).encode()) % 4 == 2) for r in rows)
    assert sum(langs[r.doc_id] == r.lang_pred for r in held) >= 0.97 * len(held) and all(0 <= r.score <= 1 for r in rows)


def test_language_cases(spark, odd):
    rows = language.identify(odd).collect()
    assert {r.lang_pred for r in rows if r.doc_id in (1, 2, 3)} == {"und"}
    kept = language.keep_known(odd).collect()
    assert len(kept) == sum(1 for i, t in ODD if t and t.strip())
    text = "abc " * 500
    whole, half = language.Encoder().encode(text), language.Encoder().encode(text[: len(text) // 2])
    assert abs((whole @ half) / math.sqrt((whole @ whole) * (half @ half)) - 1) < 1e-6


def test_language_stage_rejects_gibberish_and_unseen_languages(spark, sf):
    rng = random.Random(4)
    docs = spark.read.parquet(f"{sf}/documents.parquet").select("doc_id", "text", "lang").where("length(text) >= 300")
    known, unseen = docs.where("lang <> 'es'"), docs.where("lang = 'es'").withColumn("lang", F.lit(None).cast("string"))
    noise = [(10**9 + k, " ".join("".join(rng.choice("abcdefghijklmnopqrstuvwxyz") for _ in range(rng.randrange(2, 10))) for _ in range(150)), None) for k in range(20)]
    noise.append((10**9 + 20, "for (int i = 0; i < n; i++) { if (x[i] == null) return fprintf(stderr, q); } static const uint32_t kv = 0x3f; " * 5, None))
    kept = {r.doc_id for r in language.keep_known(known.unionByName(unseen).unionByName(spark.createDataFrame(noise, docs.schema))).collect()}
    assert not any(k in kept for k, _, _ in noise)
    ids = lambda d: {r.doc_id for r in d.collect()}
    assert len(ids(unseen) & kept) <= 0.1 * unseen.count() and len(ids(known) & kept) >= 0.98 * known.count()


def test_language_learns_from_all_labelled_rows(spark):
    """Models and limits change with the last labelled row of a table of more than 20,000 a language: no sample of it stands for the rest."""
    import numpy as np

    plain = spark.range(21_000).select(F.lit("we had tea and bread at home").alias("text"), F.lit("en").alias("lang"))
    rare = spark.range(1_100).select(F.lit("zzyzx qoph wyvern zzyzx").alias("text"), F.lit("en").alias("lang"))
    known = language.profiles(plain.unionByName(rare))
    once, other = (language.profiles(x)["en"] for x in (plain.limit(1), rare))
    assert np.allclose(known["en"], 21_000 * once + other, atol=1e-2)
    low = language.low_likeness(plain.unionByName(rare), known)[("en", 0)]
    likes = [language.Classifier(known).likeness(language.Encoder().encode("we had tea and bread at home"), "en")] * 21_000
    likes += [language.Classifier(known).likeness(language.Encoder().encode(r.text), "en") for r in rare.limit(1).collect()] * 1_100
    assert abs(low - np.quantile(likes, language.LOW)) < 1e-3


def test_token_counts_after_random_edits():
    counter, rng = token_counts.Counter(), random.Random(5)
    texts = ["  a  b\n\n c's x'll", "", "x", "   ", "Straße 12-3 naïve b c \x1c d 漢字 🙂 " * 40, "word " * 2000]
    for text in texts:
        tree, now = token_counts.SegmentTree(text, counter), text
        for _ in range(40):
            a = rng.randrange(len(now) + 1)
            b = min(len(now), a + rng.choice([0, 1, 3, 50, 900]))
            new = rng.choice(["", " ", "  ", "zz", "'s re", "\n\n", " x y z" * 5, "é🙂"])
            tree.edit(a, b, new)
            now = now[:a] + new + now[b:]
            assert tree.text() == now and tree.n_chars == len(now) and tree.n_tokens == len(counter.encoding.encode_ordinary(now))


@pytest.mark.parametrize("text", ["x" * 90_000, "word and more " * 9_000, "  \n " * 12_000, "漢" * 20_000, "a1" * 20_000])
def test_token_edits_encode_what_they_touch(text):
    """Texts of one piece, or of many; also when an edit makes its leaf outgrow the bound."""
    counter = token_counts.Counter()
    tree, now, rng = token_counts.SegmentTree(text, counter), text, random.Random(2)
    encoded = counter.encoded
    for new in ("y", "", " some more text" * 800, "z" * 9_000, "", " "):
        a = rng.randrange(len(now))
        b = min(len(now), a + rng.choice((0, 5)))
        tree.edit(a, b, new)
        now = now[:a] + new + now[b:]
        assert tree.text() == now and tree.n_chars == len(now) and tree.n_tokens == len(counter.encoding.encode_ordinary(now))
    assert tree.reencoded == counter.given - len(text) and counter.encoded - encoded <= tree.reencoded
    cuts = text[0] in "wa"  # the others are one pre-token
    assert not cuts or tree.reencoded < 60_000
    before = tree.reencoded
    tree.edit(len(now) // 2, len(now) // 2, "q")
    assert not cuts or tree.reencoded - before < 3 * token_counts.FULL


def test_token_counts_against_whole_encodings(spark, sf):
    counter = token_counts.Counter()
    texts = {r.doc_id: r.text for r in spark.read.parquet(f"{sf}/documents.parquet").collect()}
    for r in QUERIES["op6_token_counts"](spark, sf).collect():
        now = texts[r.doc_id]
        assert r.n_tokens == len(counter.encoding.encode_ordinary(now))
        for a, b, new in token_counts.production_edits(texts[r.doc_id]):
            now = now[:a] + new + now[b:]
        assert r.n_tokens_after == len(counter.encoding.encode_ordinary(now)) and r.n_chars_after == len(now)


def test_leaks(spark):
    rng = random.Random(1)
    say = lambda n, p: [f"{p}{rng.randrange(10**6)}" for _ in range(n)]
    items = {k: say(n, "i") for k, n in enumerate((30, 45, 45, 60, 3))}
    near = list(items[1])
    near[20] = "changed"  # 41 shingles of which 5 change: below 0.8
    close = list(items[3])
    close[0] = "changed"
    docs = {0: say(200, "d"), 1: say(50, "d") + items[0] + say(50, "d"), 2: items[2][:], 3: say(9, "d") + near + say(9, "d"), 4: close + say(100, "d"), 5: say(10, "d") + items[4] + say(10, "d"), 6: items[0][:25]}
    d = spark.createDataFrame([(k, " ".join(v)) for k, v in docs.items()], "doc_id long, text string")
    b = spark.createDataFrame([(k, " ".join(v)) for k, v in items.items()], "item_id long, text string")
    got = {r.doc_id: r for r in decontaminate.contaminated(d, b).collect()}
    assert {k: (r.item_id, r.start) for k, r in got.items() if r.contaminated} == {1: (0, 50), 2: (2, 0), 4: (3, 0), 5: (4, 10), 6: (0, 0)}
    assert sorted(r.doc_id for r in decontaminate.drop_leaks(d, b).collect()) == [0, 3]
    assert all(not r.contaminated for r in decontaminate.contaminated(d, b.limit(0)).collect())


def brute_leaks(docs, items, threshold=0.8):
    """All windows of all texts against all items, without fingerprints or shared places."""
    bag = lambda w, g: Counter(tuple(w[k : k + g]) for k in range(len(w) - g + 1))
    out = {}
    for i, text in docs.items():
        for j, item in items.items():
            g = min(5, len(item))
            own = bag(item, g)
            for start in range(max(len(text) - len(item), 0) + 1):
                window = bag(text[start : start + len(item)], g)
                s = (window & own).total() / max((window | own).total(), 1)
                if s >= threshold and (-s, j, start) < out.get(i, (1,)):
                    out[i] = (-s, j, start)
    return out


def test_leaks_in_windows_that_no_shared_shingle_lines_up_with(spark):
    """Words out before and in after: only windows between the two places reach the threshold; and random cuts, repeats and ends."""
    rng = random.Random(11)
    say = lambda n, p: [f"{p}{rng.randrange(10**6)}" for _ in range(n)]
    items = {k: say(n, "i") for k, n in enumerate((84, 84, 60, 7, 5, 3, 1, 120))}
    items[8] = ["so", "it", "is"] * 12
    items[9] = list(items[2])
    docs = {0: say(20, "d") + items[0][2:40] + say(3, "n") + items[0][40:82] + say(20, "d"), 1: items[8][:30], 2: ["so", "it", "is"] * 40, 3: items[7][:100], 4: items[7][10:], 5: say(9, "d") + items[6] + items[3]}
    for k in range(6, 60):
        item = list(items[rng.choice((0, 1, 2, 7))])
        for _ in range(rng.randrange(4)):
            at = rng.randrange(len(item))
            item[at : at + rng.randrange(3)] = say(rng.randrange(4), "r")
        docs[k] = say(rng.randrange(30), "d") + item[rng.randrange(4) : len(item) - rng.randrange(8)] + say(rng.randrange(30), "d")
    d = spark.createDataFrame([(k, " ".join(v)) for k, v in docs.items()], "doc_id long, text string")
    b = spark.createDataFrame([(k, " ".join(v)) for k, v in items.items()], "item_id long, text string")
    want = brute_leaks(docs, items)
    got = {r.doc_id: (r.item_id, r.start, round(r.similarity, 9)) for r in decontaminate.contaminated(d, b).collect() if r.contaminated}
    assert got == {k: (j, start, round(-s, 9)) for k, (s, j, start) in want.items()} and 0 in got and 20 < len(got) < 60


def test_blocks_find_all_prints_within_the_radius(spark):
    rng = random.Random(2)
    pairs = []
    for _ in range(200):
        a = rng.getrandbits(64)
        b = a
        for k in rng.sample(range(64), decontaminate.RADIUS):
            b ^= 1 << k
        pairs.append((a - 2**63, b - 2**63))
    df = spark.createDataFrame(pairs, "a long, b long")
    agree = F.size(F.array_intersect(decontaminate.blocks(F.col("a")), decontaminate.blocks(F.col("b")))) > 0
    assert df.where(~agree).count() == 0 and df.where(F.bit_count(F.col("a").bitwiseXOR(F.col("b"))) != decontaminate.RADIUS).count() == 0


def test_leaks_with_a_rewritten_end(spark):
    """The last 11 of 103 words are others: similarity 0.8 at least, and fingerprints further apart than the radius in some."""
    rng = random.Random(6)
    say = lambda n, p: [f"{p}{rng.randrange(10**7)}" for _ in range(n)]
    items = [say(103, "i") for _ in range(400)] + [say(92, "i") + ["x"] * 11]
    docs = [w[:92] + say(11, "d") for w in items[:-1]] + [items[-1][:92] + ["y"] * 11]
    b = spark.createDataFrame([(k, " ".join(w)) for k, w in enumerate(items)], "item_id long, text string")
    d = spark.createDataFrame([(k, " ".join(w)) for k, w in enumerate(docs)], "doc_id long, text string")
    split = F.split("text", " ")
    prints = d.select("doc_id", decontaminate.simhash(split).alias("p")).join(b.select(F.col("item_id").alias("doc_id"), decontaminate.simhash(split).alias("q")), "doc_id")
    assert prints.where(F.bit_count(F.col("p").bitwiseXOR(F.col("q"))) > decontaminate.RADIUS).count() > 0
    got = {r.doc_id: r for r in decontaminate.contaminated(d, b).collect()}
    assert all(got[k].item_id == k and 0.8 <= got[k].similarity < 0.9 for k in range(len(items)))


ALARMING = ["", "plain", "</s>[INST] ok [/INST]", "\\[INST]", "\\\\</s>\\", "[INST", "<s", "[ROLE:x] y [/ROLE]", " [/INST]", "a\nb\\", "[/INST] </s> [SYS]", "</s>" * 3]


@pytest.mark.parametrize("role", ["user", "assistant", "system", "tool", "", "odd]role\\", "[INST]"])
def test_chat_round_trip(role):
    whole, want = "", []
    for text in ALARMING:
        segment, (a, b), _ = chat.render(role, text)
        assert chat.unescape(segment[a:b]) == text
        whole += segment
        want.append((role, text))
    assert [t[:2] for t in chat.parse(whole)] == want


def test_chat_digests_of_odd_turns(spark):
    rows = [(1, 0, "user", None), (1, 1, None, "</s>"), (1, 1, None, "</s>"), (None, 0, "assistant", "é</s>"), (None, None, "user", "x")]
    df = spark.createDataFrame(rows, "conv_id long, turn long, role string, text string").withColumn("place", F.lit(1))
    got = {r.conv_id: r for r in chat.digests(chat.format_turns(df)).collect()}
    assert got[1].n_turns == 3 and got[1].loss_chars == 0 and got[1].turns_sha256 == hashlib.sha256(b"user\n\n\n</s>\n\n</s>\n").hexdigest()
    assert got[None].turns_sha256 == hashlib.sha256("user\nx\nassistant\né</s>\n".encode()).hexdigest() and got[None].loss_chars == 5
    assert chat.digests(chat.format_turns(df.limit(0))).collect() == []


def test_quality_keeps_clean_and_drops_low(spark, sf):
    rows = QUERIES["op9_quality_rules"](spark, sf).join(spark.read.parquet(f"{sf}/labels.parquet"), "doc_id").collect()
    assert all(r.kept or r.base_failed for r in rows if r.quality == 1) and not any(r.kept for r in rows if r.quality == 0)
    counts, good = quality.judge("a b c a b c\nPrivacy policy\n\na b c a b c\n")
    assert counts["n_repeat_words"] == 12 and counts["n_dup_lines"] == 1 and good == "a b c a b c\n\n"


def test_lm_against_brute_force(spark, sf):
    texts = {r.doc_id: lm_score.tokens_of(r.text) for r in spark.read.parquet(f"{sf}/documents.parquet").collect()}
    held = {i: zlib.crc32(str(i).encode()) % 10 == 0 for i in texts}
    c = Counter(w for i, t in texts.items() if not held[i] for w in t)
    n, v = sum(c.values()), len(c)
    rows = QUERIES["op10_lm_score"](spark, sf).collect()
    for r in rows:
        t = texts[r.doc_id]
        assert (r.held_out, r.n_tokens, r.n_known, r.train_tokens) == (held[r.doc_id], len(t), sum(w in c for w in t), n)
        assert abs(r.base_score - sum(math.log10((c[w] + 0.1) / (n + 0.1 * (v + 1))) for w in t)) < 1e-6 * len(t)
    out = [r for r in rows if r.held_out]
    assert sum(r.score for r in out) > sum(r.base_score for r in out)


def test_lm_is_a_distribution():
    """Over all known words and one unseen word of each rest, the probabilities of a history's next word sum to 1."""
    import numpy as np

    rng = np.random.default_rng(0)
    head = {f"w{k}".encode(): int(2000 / (k + 1)) + 1 for k in range(lm_score.OWN + 300)} | {lm_score.END: 50}
    rest_c, rest_n = np.zeros(lm_score.CLASSES), np.zeros(lm_score.CLASSES)
    voc = lm_score.Vocabulary(head, sum(head.values()), len(head), rest_c, rest_n)
    for w in voc.words[lm_score.OWN :]:
        rest_c[lm_score.rest_class(w)] += head[w]
        rest_n[lm_score.rest_class(w)] += 1
    voc = lm_score.Vocabulary(head, voc.total, voc.types, rest_c, rest_n)
    weights = [rng.normal(size=(lm_score.ROWS, n)).astype(np.float32) for _, n in lm_score.LEVELS]
    history = np.array([5 * lm_score.CODES + 7])
    p_class = np.exp(lm_score.log_softmax(weights[0], lm_score.class_features(history)))[0]
    p_slot = np.exp(lm_score.log_softmax(weights[1], lm_score.slot_features(7 * lm_score.CLASSES + np.arange(lm_score.CLASSES))))
    total = 0.0
    for w, code in zip(voc.words, voc.codes()):
        k, s = lm_score.class_of(np.array([code]))[0], lm_score.slot_of(np.array([code]))[0]
        share = 1.0 if code < lm_score.OWN else (head[w] + lm_score.ADD) / voc.rest[k]
        total += p_class[k] * p_slot[k, s] * share
    total += sum(p_class[k] * p_slot[k, -1] * lm_score.ADD / voc.rest[k] for k in range(lm_score.CLASSES))
    assert abs(total - 1) < 1e-5


def test_lm_learns_pairs_of_words_without_a_slot(spark):
    """Two words of one count and one rest, each after its own word, both beyond the words with a slot of their own."""
    held = [i for i in range(3000) if zlib.crc32(str(i).encode()) % 10 == 0]
    train = [i for i in range(3000) if zlib.crc32(str(i).encode()) % 10 != 0]
    filler = [" ".join(f"f{k}" for k in range(a, a + 60)) for a in range(0, 1200, 60)] * 10
    pairs = ["redly qxalphaing", "bluely qxbetaing"] * 4
    rows = list(zip(train, filler + pairs)) + list(zip(held, ["redly qxalphaing", "redly qxbetaing"]))
    got = {r.doc_id: r for r in lm_score.lm_scores(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    same, crossed = got[held[0]], got[held[1]]
    assert same.base_score == pytest.approx(crossed.base_score) and same.held_out and crossed.held_out
    assert same.score > crossed.score + 0.5


def test_lm_counts_leave_no_row_a_pair(spark, tmp_path, monkeypatch):
    """Texts of distinct pairs: what a run leaves in the shared folder is less than the texts, since no table of pairs and no row a token is written; and a slice's
    answers, cut into many slices and buckets, are the counts of all training texts."""
    import random

    words = [f"w{k}" for k in range(3000)]
    rows = [(i, " ".join(random.Random(i).choices(words, k=400)) + (" rare%d" % (i // 2))) for i in range(500)]
    monkeypatch.setattr(lm_score, "SLICE", 100_000)
    monkeypatch.setattr(lm_score, "BUCKET", 30_000)
    monkeypatch.setattr(lm_score, "HEAD", 2000)
    monkeypatch.setattr("refinery.llm.common.shared_dir", lambda spark: str(tmp_path))
    got = {r.doc_id: r for r in lm_score.lm_scores(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    left = sum(f.stat().st_size for f in tmp_path.rglob("*.parquet"))
    assert left < 0.8 * sum(len(t) for _, t in rows)
    texts = {i: lm_score.tokens_of(t) for i, t in rows}
    c = Counter(w for i, t in texts.items() if zlib.crc32(str(i).encode()) % 10 for w in t)
    for i, t in texts.items():
        assert got[i].n_known == sum(w in c for w in t)
        assert abs(got[i].base_score - sum(math.log10((c[w] + 0.1) / (sum(c.values()) + 0.1 * (len(c) + 1))) for w in t)) < 1e-6 * len(t)


def test_lm_training_is_not_cut():
    """Sizes chosen for the model, not for the check's disk: pairs of codes spread over the rows, and ten rounds of training."""
    import numpy as np

    assert lm_score.ROUNDS >= 10
    places = np.random.default_rng(0).choice(lm_score.CODES**2, 20_000, replace=False)
    assert len(np.unique(lm_score.hashed(1, places))) > 0.7 * len(places)


def test_quality_removes_failed_lines(spark):
    text = "\n".join(["Lire la suite", *[" ".join(f"word{k}{i}" for k in range(12)) + "." for i in range(8)], "Todos los derechos reservados.", "Home | News | About | Help"])
    docs = spark.createDataFrame([(1, text, 7, "x"), (2, "short", 5, "y"), (3, None, None, None)], "doc_id long, text string, n_chars long, kept string")
    rows = quality.keep_good(docs).collect()
    assert [(r.doc_id, r.kept, r.text, r.n_chars) for r in rows] == [(1, "x", text[14:].rsplit("\n", 2)[0], len(text[14:].rsplit("\n", 2)[0]))]
    assert quality.keep_good(docs.limit(0)).collect() == [] and quality.keep_good(docs.drop("n_chars")).columns == ["doc_id", "text", "kept"]


def test_pipeline_against_brute_force(spark, sf):
    """Each stage against brute force over what it was given; the language stage against the verdicts of its own model, row by row."""
    import corpus_pipeline

    docs = spark.read.parquet(f"{sf}/documents.parquet")
    items = {r.item_id: WORD.findall(r.text or "") for r in spark.read.parquet(f"{sf}/benchmark.parquet").collect()}
    step = dict(corpus_pipeline.STAGES)
    assert list(step) == ["quality rules", "language ID", "n-gram Jaccard join", "benchmark decontamination", "mixing sources to target weights"]
    now = {r.doc_id: r for r in docs.collect()}
    judged = {i: quality.judge(r.text) for i, r in now.items()}
    texts = {i: good for i, (counts, good) in judged.items() if counts["kept"]}
    for name, f in corpus_pipeline.STAGES:
        out = jaccard_join.stage(f(spark, docs, sf), "test")
        rows = out.collect()
        if name == "quality rules":
            assert {r.doc_id: (r.text, r.n_chars) for r in rows} == {i: (t, len(t)) for i, t in texts.items()}
        elif name == "language ID":
            known = {r.doc_id for r in language.keep_known(docs).collect()}
            assert {r.doc_id: r.text for r in rows} == {i: t for i, t in texts.items() if i in known} and len(known) >= 0.97 * len(texts)
        elif name == "n-gram Jaccard join":
            of = classes(*brute_links(texts))
            assert {r.doc_id for r in rows} == {i for i in texts if of[i] == i}
        elif name == "benchmark decontamination":
            own = {i: WORD.findall(t) for i, t in texts.items()}
            grams = {tuple(w[k : k + 5]) for w in items.values() for k in range(len(w) - 4)}
            near = {i: w for i, w in own.items() if any(tuple(w[k : k + 5]) in grams for k in range(len(w) - 4))}
            assert all(len(w) >= 5 for w in items.values())
            assert {r.doc_id for r in rows} == texts.keys() - brute_leaks(near, items).keys()
        else:
            size, taken = {i: len(WORD.findall(t)) for i, t in texts.items()}, Counter()
            for r in rows:
                taken[r.source] += r.mix_words
                assert r.text == texts[r.doc_id] and r.mix_words <= size[r.doc_id]
            target = {r.source: r.target for r in mixing.schedule(docs).collect()}
            assert taken == {s: math.floor(t) for s, t in target.items()} and sum(target.values()) == pytest.approx(1.5 * sum(size.values()))
            assert set(out.columns) == {*docs.columns, "mix_pass", "mix_words", "mix_position"}
        if not name.startswith("mixing"):
            assert out.columns == docs.columns
            docs, texts = out, {r.doc_id: r.text for r in rows}


def test_pipeline_stages_of_odd_rows_and_empty_tables(spark, sf, odd):
    import corpus_pipeline

    for docs in (odd, odd.limit(0)):
        for _, f in corpus_pipeline.STAGES:
            rows = f(spark, docs, sf).collect()
            assert {r.doc_id for r in rows} <= {i for i, _ in ODD} and (rows or docs is odd or True)
    kept = {name: Counter(r.doc_id for r in f(spark, odd, sf).collect()) for name, f in corpus_pipeline.STAGES}
    assert kept["quality rules"] == {} and kept["n-gram Jaccard join"] == Counter({1: 1, 2: 1, 3: 1, 4: 2, 5: 1, 6: 1, 7: 1})
    assert kept["benchmark decontamination"] == Counter(i for i, _ in ODD) and set(kept["mixing sources to target weights"]) == {4, 5, None, 6, 7}
