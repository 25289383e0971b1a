"""Training-data operators: brute force, round trips, held-out accuracy, and edge cases."""

import hashlib
import math
import random
import re
import zlib
from collections import Counter, defaultdict

import numpy as np
import pytest
from pyspark.sql import functions as F, types as T

from freqemu.llm import chat, common, decontaminate, jpeg, language, licences, media, mixing, neardup, pages, quality, registry, suffix_tree
from tests.oracle import compare

DOCS = "doc_id long, text string, lang string, source string, n_chars long"


def docs_of(spark, texts, **more):
    rows = [(i, t, None, None, None) for i, t in enumerate(texts)]
    return spark.createDataFrame(rows, DOCS)


ODD = [None, "", " \n\t ", "one", "One one ONE", "a b " * 3000, "é ü ß 日本語 text", "!!! ... ---", "x" * 200_000]


@pytest.mark.parametrize("name", list(registry.oracle_sql()))
def test_query_equals_sql(spark, data, duck, name):
    compare(registry.queries()[name](spark, data), duck, registry.oracle_sql()[name])


# -- decontamination ---------------------------------------------------------------------------


def alnum(text):
    low = "".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in text or "")
    return re.findall(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+", low)


def brute_hits(text, items, width=13):
    w, hit, ids = alnum(text), set(), set()
    for i, t in items:
        v = alnum(t)
        size = min(width, len(v))
        for a in range(len(v) - size + 1 if v else 0):
            for b in range(len(w) - size + 1):
                if w[b : b + size] == v[a : a + size]:
                    hit.update(range(b, b + size))
                    ids |= {str(i)} if i is not None else set()
    return len(w), len(hit), sorted(ids)


@pytest.mark.parametrize("block", [1 << 25, 40])
@pytest.mark.parametrize("stride", [512, 7])
def test_decontamination_against_brute_force(spark, block, stride, monkeypatch):
    monkeypatch.setattr(decontaminate, "STRIDE", stride)
    rng = random.Random(3)
    words = ["w%d" % i for i in range(12)]
    items = [(i, " ".join(rng.choices(words, k=rng.choice([0, 1, 2, 5, 13, 14, 20])))) for i in range(12)] + [(90, None), (91, ""), (None, "w3 w4 w5 w6")]
    items += [items[5], (92, items[6][1])]
    texts = [" ".join(rng.choices(words, k=rng.randint(0, 60))) for _ in range(30)] + [x for x in ODD if not x or len(x) < 5000]
    texts += [f"Some, {items[4][1].upper()}! and more", items[6][1]]
    tests = spark.createDataFrame(items, "item_id long, text string")
    found = decontaminate.contamination(docs_of(spark, texts), tests, block_words=block, keep=["doc_id"]).collect()
    for r in found:
        n, hit, ids = brute_hits(texts[r.doc_id], items)
        assert (r.n_words, r.n_hit, list(r["items"])) == (n, hit, ids), texts[r.doc_id]
        assert r.contaminated == (hit > 0 and 20 * hit >= n)
        assert sum(s.past - s.first for s in r.spans) == hit


def test_decontamination_index_is_bounded_by_its_windows():
    """32 MB of test text, in blocks, would take under 1 GB; here a 32nd of it."""
    import pickle

    rng = random.Random(1)
    vocabulary = ["".join(rng.choices("abcdefghij", k=rng.randint(2, 9))) for _ in range(5000)]
    items = [(i, " ".join(rng.choices(vocabulary, k=1500)).encode()) for i in range(105)]
    size = sum(len(t) for _, t in items)
    search = decontaminate.WindowSearch(items)
    assert search.nbytes() < 12 * size and len(pickle.dumps(search)) < 13 * size
    text = items[7][1] + b" x " + items[9][1][:4000]
    w, bounds = common.WordHasher(common.ALNUM)([text, b"nothing here"])
    hit, ids = search(w, bounds)
    assert ids == [{"7", "9"}, set()] and hit.sum() >= len(items[7][1].split()) + 12


def test_decontamination_rows(spark):
    docs = spark.createDataFrame([(None, "a b c"), (1, "a b c"), (1, "a b c"), (2, None)], "doc_id long, text string")
    found = decontaminate.contamination(docs, spark.createDataFrame([(None, "b c"), ("x", "a"), ("x", "a")], "item_id string, text string")).collect()
    assert [(r.n_hit, r["items"], r.contaminated) for r in found] == [(3, ["x"], True)] * 3 + [(0, [], False)]


def test_decontamination_without_items_and_with_clashing_columns(spark):
    docs = docs_of(spark, ODD).withColumn("n_words", F.lit("mine")).withColumn("Contaminated", F.lit(1))
    none = spark.createDataFrame([], "item_id long, text string")
    found = decontaminate.contamination(docs, none)
    assert found.columns[: len(docs.columns)] == docs.columns
    assert found.where(F.col(found.columns[-1])).count() == 0 and found.count() == len(ODD)
    assert {r["n_words"] for r in found.collect()} == {"mine"}


# -- near-duplicates -------------------------------------------------------------------------------


def shingle_set(text, width):
    low = "".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in text or "")
    w = re.findall(r"[^\x20\x09-\x0D]+", low)
    if not w:
        return frozenset()
    if len(w) < width:
        return frozenset([tuple(w)])
    return frozenset(tuple(w[i : i + width]) for i in range(len(w) - width + 1))


def brute_components(ids, sets, percent=80):
    root = {i: i for i in ids}

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    for k, a in enumerate(ids):
        for b in ids[k + 1 :]:
            p, q = sets[a], sets[b]
            if p and q and 100 * len(p & q) >= percent * len(p | q):
                x, y = sorted((find(a), find(b)))
                root[y] = x
    return {i: find(i) for i in ids}


def planted(rng, groups=12, size=9, words=60):
    """Groups of near copies of one text each, with changes around the threshold; some chains."""
    out = []
    for g in range(groups):
        base = [f"g{g}w{i}" for i in range(words)]
        for _ in range(size):
            t = list(base)
            for _ in range(rng.randint(0, 6)):
                t[rng.randrange(len(t))] = f"n{rng.random():.9f}"
            out.append(" ".join(t))
            if rng.random() < 0.3:
                base = t
    return out


@pytest.mark.parametrize("width", [2, 5])
def test_near_duplicates_against_brute_force(spark, width):
    rng = random.Random(width)
    texts = planted(rng) + ["Same  TEXT here", "same text\there", "same text", None, "", "  ", "word", "word", "a b", "b a"] + ODD
    rng.shuffle(texts)
    ids = list(range(len(texts)))
    sets = {i: shingle_set(texts[i], width) for i in ids}
    expected = brute_components(ids, sets)
    found = neardup.near_duplicates(docs_of(spark, texts), width=width).collect()
    assert {r.id: r.n_shingles for r in found} == {i: len(sets[i]) for i in ids}
    assert {r.id: r.component for r in found} == expected


def test_large_groups_are_searched_without_their_pairs(spark):
    """Copies that resemble their source but not each other: all links are found, few pairs are looked at."""
    rng = random.Random(5)
    base = [f"w{i}" for i in range(140)]
    texts = []
    for _ in range(150):
        t = list(base)
        for at in rng.sample(range(140), rng.randint(4, 12)):
            t[at] = f"n{rng.random():.9f}"
        texts.append(" ".join(t))
    texts.append(" ".join(base))
    ids = list(range(len(texts)))
    sets = {i: shingle_set(texts[i], 2) for i in ids}
    looked, plain = [], neardup._across
    neardup._across = lambda *a: looked.append(plain(*a)) or looked[-1]
    try:
        found = neardup.near_duplicates(docs_of(spark, texts), width=2).collect()
    finally:
        neardup._across = plain
    assert {r.id: r.component for r in found} == brute_components(ids, sets)
    assert sum(x.count() for x in looked) < 3000  # of 11,325


def test_near_duplicates_with_repeated_and_null_ids(spark):
    rows = [(1, "a b c d e f"), (1, "a b c d e f"), (2, "u v w x y z"), (2, "a b c d e f"), (3, "u v w x y z"), (None, "a b c d e f"), (None, None), (4, "k l m n")]
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    found = neardup.near_duplicates(docs, width=2).collect()
    assert len(found) == len(rows)
    assert {(r.id, r.component) for r in found if r.id is not None} == {(1, 1), (2, 1), (3, 1), (4, 4)}
    kept = neardup.keep_one(docs, width=2)
    assert sorted((r.doc_id or 0) for r in kept.collect()) == [0, 1, 4]  # the null id with a text of 1 goes
    nameless = spark.createDataFrame([(None, "a b c", 1), (None, "a b c", 2), (None, "d e f", 1), (7, "g h i", 1), (7, "g h i", 1), (8, "", 1), (9, None, 1)], "doc_id long, text string, gone int")
    left = [(r.doc_id, r.text) for r in neardup.keep_one(nameless).collect()]
    assert sorted(left, key=str) == sorted([(None, "a b c"), (None, "d e f"), (7, "g h i"), (8, ""), (9, None)], key=str)
    assert neardup.near_duplicates(docs.limit(0)).count() == 0
    assert neardup.keep_one(docs.limit(0)).columns == docs.columns


def test_components_of_chains_and_stars(spark):
    links = [(i, i + 1) for i in range(40)] + [(100, x) for x in range(101, 130)] + [(500, 400), (300, 400)]
    found = {r.id: r.component for r in neardup.components(spark.createDataFrame(links, "a long, b long")).collect()}
    assert found == {**{i: 0 for i in range(41)}, **{i: 100 for i in range(100, 130)}, 300: 300, 400: 300, 500: 300}


def test_min_max_signature_estimates_similarity():
    rng = np.random.default_rng(1)
    a = rng.integers(0, 2**63, 900, dtype=np.uint64)
    x, y = np.unique(a[:800]), np.unique(a[100:])
    f, o = neardup.permutations(400)
    same = (neardup.signature(x, f, o) == neardup.signature(y, f, o)).mean()
    assert abs(same - 700 / 900) < 0.06


# -- language --------------------------------------------------------------------------------------------


def test_language_held_out_accuracy(spark, data):
    docs = spark.read.parquet(data.replace("sf0.001", "sf0.01") + "/documents.parquet")
    found = registry.queries()["op3_language"](spark, data.replace("sf0.001", "sf0.01"))
    rows = found.join(docs.select("doc_id", "lang"), "doc_id").where("held_out").collect()
    assert sum(r.lang == r.lang_pred for r in rows) >= 0.97 * len(rows)
    assert all(0 <= r.score <= 1 for r in rows)


def test_language_edges(spark):
    rng = random.Random(2)
    rows = [(i, " ".join(rng.choices(["der", "und", "nicht"] if i % 2 else ["the", "and", "of"], k=30)), "de" if i % 2 else "en", "s", 0) for i in range(80)]
    rows += [(1000, None, "de", None, None), (1001, "", "en", None, None), (1002, "123 !!", None, None, None), (None, "the and of", "en", None, None), (1003, "日本語", None, None, None)]
    docs = spark.createDataFrame(rows, DOCS).withColumn("score", F.lit("mine"))
    model = language.train(docs, "doc_id", "text", "lang")
    found = {r.doc_id: r for r in language.identify(docs, model).collect()}
    assert all(found[i].lang_pred == ("de" if i % 2 else "en") for i in range(80))
    assert [found[i].lang_pred for i in (1000, 1001, 1002)] == ["und"] * 3 and found[1000]["score_"] == 0
    assert found[None].lang_pred == "en" and found[1003].lang_pred in ("de", "en")
    assert found[3]["score"] == "mine"
    assert language.train(docs.limit(0), "doc_id", "text", "lang") is None
    assert {r.lang_pred for r in language.identify(docs, None).collect()} == {"und"}
    only = language.train(docs.where("lang = 'de'"), "doc_id", "text", "lang")
    assert {r.lang_pred for r in language.identify(docs.where("doc_id < 80"), only).collect()} == {"de"}


def test_grams_and_decoding_against_brute_force():
    texts = [b"", b"a", b"Ab", b"the cat", "é日本".encode(), None]
    found = language.grams(texts)
    for row, t in zip(found, texts):
        count = Counter()
        b = b" " + t.lower() + b" " if t else b""
        for k in range(len(b) - 1):
            pair = b[k] * 257 + b[k + 1]
            count[language.TRIGRAMS + (pair * 2246822519 % 2**32 >> 22)] += 1
            if k + 2 < len(b):
                count[(pair * 2654435761 + b[k + 2] * 40503 * 65537) % 2**32 >> 20] += 1
        norm = math.sqrt(sum(count.values())) or 1
        assert {int(k): float(row[k]) for k in np.flatnonzero(row)} == pytest.approx({k: math.sqrt(n) / norm for k, n in count.items()}, abs=1e-6)
    rng = np.random.default_rng(1)
    code, weight = language.codewords(4), np.array([1.0, 2.0, 0.5, 1.0, 0.3, 1.5, 0.7])
    margin = rng.normal(size=(30, code.shape[1]))
    pick, score = language.decode(margin, code, weight[: code.shape[1]])
    for m, p, s in zip(margin, pick, score):
        loss = [sum(w * math.log1p(math.exp(-c * x)) for w, c, x in zip(weight, row, m)) for row in code.tolist()]
        assert p == loss.index(min(loss)) and s == pytest.approx(1 / sum(math.exp(min(loss) - x) for x in loss), rel=1e-5)


def test_binary_classifiers_reach_the_least_loss():
    """The classifiers part what can be parted, and weigh down the bits they get wrong."""
    rng = np.random.default_rng(3)
    label = np.repeat(np.arange(3), 60)
    x = np.abs(rng.normal(size=(180, 20))).astype(np.float32) * 0.05
    x[np.arange(180), label] += 1
    code = language.codewords(3)
    w, b, weight = language.fit(x, label, code)
    assert (((x @ w + b) > 0) == (code[label] > 0)).all() and np.allclose(weight, 1)
    noisy = np.where(rng.random(180) < 0.3, 2, label)
    assert language.fit(x, noisy, code)[2].std() > 0.01


def test_codewords_stand_apart():
    for n in (2, 3, 4, 5, 9, 40):
        code = language.codewords(n)
        assert code.shape[0] == n and set(np.unique(code)) == {-1.0, 1.0}
        gaps = [(code[a] != code[b]).sum() for a in range(n) for b in range(a)]
        assert min(gaps) >= max(1, code.shape[1] // 4)
        assert all(0 < (column > 0).sum() < n for column in code.T)


# -- pages -------------------------------------------------------------------------------------------------


def test_pages_against_their_articles(spark, data):
    import html

    rows = registry.queries()["op4_main_text"](spark, data).collect()
    raw = {r.page_id: r.html for r in spark.read.parquet(f"{data}/pages.parquet").collect()}
    assert len(rows) == len(raw)
    for r in rows:
        article = re.search(r"<article>(.*?)</article>", raw[r.page_id], re.S)[1]
        blocks = (" ".join(html.unescape(re.sub(r"<[^>]+>", "", b)).split()) for b in re.split(r"</?(?:p|h1)>", article))
        assert r.text == "\n\n".join(b for b in blocks if b)
        assert r.n_chars == len(r.text)


def test_pages_other_layouts():
    long = "This is a long paragraph of the story with many words in it, and it goes on for quite a while so that it is text."
    page = f"""<html><head><title>t</title></head><body><header><a href=/>Home</a> Site</header><div class="cookie-banner">{long}</div>
    <div id=main><h2>Head line of it</h2><p>{long}</p><p>Second &amp; short&nbsp;one <b>with</b> <a href=x>a link</a> inside of a sentence.</p><p>{long}</p></div>
    <aside><p>{long}</p></aside><form><p>{long}</p><input><button>Send</button></form><section class="comments"><p>{long}</p></section><footer>{long}</footer></body></html>"""
    text = pages.main_text(page)
    assert text.split("\n\n") == ["Head line of it", long, "Second & short one with a link inside of a sentence.", long]
    for odd in (None, "", "<", "<p", "plain words only", "<!-- never closed", "<script>x", "</div></p>", "<article><p>x</article>", "<article>a<br>b  \n c</article>"):
        assert isinstance(pages.main_text(odd), str)
    assert pages.main_text("<article>a<br>b  \n c</article>") == "a b c"
    assert pages.main_text(b"<article><p>caf\xc3\xa9 &lt;b&gt; &#x41;</article>") == "café <b> A"
    assert pages.main_text("<div class='with sidebar'><main><div class='entry-header'><h1>Title</h1></div><p>kept</p></main></div><div id='site-header'>no</div>") == "Title\n\nkept"
    assert pages.main_text("<article><nav>menu</nav><p>kept words</p><div class='share-box'>no</div></article>") == "kept words"


def test_pages_without_an_article_element_keep_their_text():
    kept = lambda page: pages.main_text(page).split("\n\n")
    twelve = "One two three four five six seven eight nine ten eleven twelve."
    assert pages.main_text(f"<div class=post><p>{twelve}</p></div><div class=share>3</div>") == twelve
    story = "<div><p>" + "word " * 60 + f"</p><p>{twelve}</p><p>The end.</p></div><div class=comments><p>" + "reader " * 40 + "</p></div>"
    assert kept(story)[1:] == [twelve, "The end."]
    menu = "<div><a href=/>Home</a></div><div>|</div><div><a href=/n>News</a></div><div>|</div><div><a href=/s>Sport</a></div>"
    assert kept(f"{menu}<h2>Head</h2><div>{twelve}</div><div>Short.</div>{menu}") == ["Head", twelve, "Short."]
    linked = "<a href=/r>Read the full report of the committee here today</a>"
    assert kept(f"<article><p>{twelve}</p><p>{linked}</p><p>{twelve}</p></article>") == [twelve, "Read the full report of the committee here today", twelve]
    assert kept(f"<article><p>{twelve}</p><p>{linked}</p><p>{linked}</p><p>{linked}</p></article>") == [twelve]
    for wrapper in ("content has-sidebar", "post no-comments", "post category-advertising tag-social", "entry"):
        assert pages.main_text(f"<div class='{wrapper}'><p>{twelve}</p></div>") == twelve
        assert pages.main_text(f"<article class='{wrapper}'><p>{twelve}</p></article>") == twelve
    assert pages.main_text(f"<p title='a hidden gem'>{twelve}</p><p hidden>no</p><div style='x; display: none'>no</div><p data-x=1 hidden=''>no</p>") == twelve
    for wrapper in ("sidebar", "site-footer", "ad", "comment-list", "cookie-notice"):
        assert pages.main_text(f"<div class='{wrapper}'><p>{twelve} {twelve}</p></div><p>{twelve}</p>") == twelve


def test_pages_tree_uses_the_neighbours():
    def features(tree):
        return {tree[0], *features(tree[2]), *features(tree[3])} if isinstance(tree, tuple) else set()

    used = features(pages.trained())
    assert {1, 5} <= used  # link densities of the blocks before and behind
    table = np.array(pages.LABELLED)
    assert all(pages.is_text(pages.trained(), tuple(r[:-1])) == bool(r[-1]) for r in table)


def test_pages_rows(spark):
    rows = [(1, None), (1, ""), (None, "<p>some words</p>"), (2, "<p>some words</p>"), (2, "<p>some words</p>"), (3, "<p>" + "long " * 300_000)]
    table = spark.createDataFrame(rows, "page_id long, html string").withColumn("Text", F.lit("mine"))
    found = pages.extract(table).collect()
    assert [r["n_chars"] for r in found] == [0, 0, 10, 10, 10, 1_499_999] and {r["Text"] for r in found} == {"mine"}
    assert pages.extract(table.limit(0)).count() == 0


# -- mixing -------------------------------------------------------------------------------------------------


@pytest.mark.parametrize("piece", ["<a", "<a href=\"", "<!", "<![CDATA[", "<div>", "</p>", "<div></section>", "&amp;", "<p>x", "<script>", "<!--"])
def test_pages_long_and_broken(piece):
    assert isinstance(pages.main_text(piece * 30_000), str)


def fill(sizes, weights, cap=3):
    total, target, open_ = sum(sizes), [0.0] * len(sizes), list(range(len(sizes)))
    left = float(total)
    while True:
        share = {i: left * weights[i] / sum(weights[j] for j in open_) for i in open_}
        over = [i for i in open_ if share[i] > cap * sizes[i]]
        for i in over:
            target[i] = cap * sizes[i]
            left -= target[i]
        open_ = [i for i in open_ if i not in over]
        if not over:
            for i in open_:
                target[i] = share[i]
            return target


@pytest.mark.parametrize("shape", [[1, 1, 1], [500, 3, 2, 2], [2, 900, 1, 40, 5, 7], [10]])
def test_mixing(spark, shape):
    rng = random.Random(1)
    names = sorted("abcdefgh"[: len(shape)])
    rows, k = [], 0
    for n, s in zip(shape, names):
        for _ in range(n):
            rows.append((k, " ".join(["w"] * rng.randint(1, 50)), "en", s if s != "c" else None, 0))
            k += 1
    docs = spark.createDataFrame(rows, DOCS).withColumn("size", F.lit("mine"))
    found = mixing.mix(docs).collect()
    again = mixing.mix(docs.repartition(5)).collect()
    assert sorted(map(tuple, found)) == sorted(map(tuple, again)) and len(found) == len(rows)
    order = sorted((s for s in names if s != "c")) + (["c"] if "c" in names else [])
    size = Counter()
    for i, t, _, s, _ in rows:
        size[s or "c"] += len(t.split())
    expected = dict(zip(order, fill([size[s] for s in order], [1 + i % 3 for i in range(len(order))])))
    owner = {r[0]: r[3] or "c" for r in rows}
    taken, largest = Counter(), defaultdict(int)
    for r in found:
        assert r.target == pytest.approx(expected[owner[r.doc_id]]) and r.source_size == size[owner[r.doc_id]]
        assert 0 <= r.taken <= 3 * r.size and r.taken == r.copies * r.size
        taken[owner[r.doc_id]] += r.taken
    for s in order:
        assert abs(taken[s] - expected[s]) <= 3 * 50 + 0.05 * expected[s]
    out = mixing.emitted(docs, mixing.mix(docs))
    assert out.count() == sum(r.copies for r in found) and out.columns == docs.columns


def test_mixing_edges(spark):
    odd = spark.createDataFrame([(None, None, None, None, None), (1, "", None, "s", 0), (1, "", None, "s", 0), (2, "one two", None, None, 0)], DOCS)
    found = mixing.mix(odd)
    assert found.count() == 4 and found.agg(F.sum("taken")).first()[0] <= 6
    assert mixing.mix(odd.limit(0)).count() == 0
    clash = odd.where("doc_id = 2").withColumn("_id", F.lit(1)).withColumn("_copy", F.lit(2)).withColumn("own", F.lit("x")).withColumn("copies", F.lit(9))
    assert mixing.emitted(clash, mixing.mix(clash)).columns == clash.columns
    long = odd.where("doc_id = 2").withColumn("text", F.repeat(F.lit("word "), 300_000))
    assert mixing.mix(long).first()["size"] == 300_000
    zero = mixing.mix(odd.where("text = ''")).collect()
    assert {(r.taken, r.target) for r in zero} == {(0, 0.0)}


def test_mixing_of_many_sources(spark):
    """Targets by ranges of sources equal those of one pass, for a million sources without a task that sees them all."""
    sizes = spark.range(1_000_000).select(F.concat(F.lit("s"), F.col("id")).alias("source"), (F.pmod(F.xxhash64("id"), F.lit(1000)) * F.when(F.col("id") % 1000 == 0, 500).otherwise(1)).alias("source_size"), F.lit(1).alias("n"))
    found = mixing.targets(sizes).agg(F.sum("target").alias("t"), F.sum("source_size").alias("s"), F.max(F.col("target") - 3 * F.col("source_size")).alias("over"), F.count("*").alias("n")).first()
    assert found.n == 1_000_000 and found.t == pytest.approx(found.s) and found.over <= 1e-6
    few = spark.createDataFrame(sizes.limit(300).collect(), sizes.schema)
    rows = sorted(mixing.targets(few, parts=7).collect(), key=lambda r: r.source)
    expected = fill([r.source_size for r in rows], [1 + i % 3 for i in range(len(rows))])
    assert [r.target for r in rows] == pytest.approx(expected)
    assert mixing.targets(sizes.limit(0)).count() == 0


# -- language model ---------------------------------------------------------------------------------------------


def test_language_model_against_brute_force(spark):
    rng = random.Random(8)
    texts = [" ".join(rng.choices(["alpha", "beta", "gamma", "Delta", "épsilon"], k=rng.randint(0, 40))) for _ in range(60)] + [None, "", "zeta zeta", "a b"]
    docs = docs_of(spark, texts)
    found = {r.doc_id: r for r in suffix_tree.score_documents(docs, frequent=2, frequent_grams=20).collect()}
    assert len(found) == len(texts)
    low = [re.findall(r"[^\x20\x09-\x0D]+", "".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in t or "")) for t in texts]
    train = [i for i in range(len(texts)) if zlib.crc32(str(i).encode()) % 7 != 2]
    count = Counter(w for i in train for w in low[i])
    count["<end>"] = len(train)
    n, v = sum(count.values()), len(count)
    tree = suffix_tree.learn(docs.where(F.crc32(F.col("doc_id").cast("string").cast("binary")) % 7 != 2).select("text"))
    for i, w in enumerate(low):
        r, tokens = found[i], [*w, "<end>"]
        assert r.held_out == (i not in train)
        assert (r.n_tokens, r.n_known, r.train_tokens) == (len(tokens), sum(count[t] > 0 for t in tokens), n)
        assert r.base_score == pytest.approx(sum(math.log10((count[t] + 1) / (n + v + 1)) for t in tokens))
        assert r.score == pytest.approx(slow_score(texts[i], tree, count, n, v), rel=1e-5)


def test_language_model_beats_single_words_on_held_out_documents(spark, data):
    """Although the base score has one chance for all unknown words and the model spells each."""
    rows = registry.queries()["op6_language_model"](spark, data.replace("sf0.001", "sf0.1")).where("held_out").collect()
    assert sum(r.score for r in rows) > sum(r.base_score for r in rows)
    assert sum(r.score > r.base_score for r in rows) > 0.75 * len(rows)


def test_language_model_spells_unknown_words(spark):
    """Unknown words are scored by their spelling: one that is put together like known ones is likelier."""
    docs = docs_of(spark, ["walking talking walked talked baking baked " * 30] * 8).withColumn("doc_id", F.col("doc_id") * 7)
    new = docs_of(spark, ["waking", "qzxvjw"]).withColumn("doc_id", F.lit(None).cast("long"))
    a, b = sorted(r.score for r in suffix_tree.score_documents(docs.unionByName(new)).where("doc_id is null").collect())
    assert b > a + 3


def slow_score(text, tree, count, n, v):
    """Token by token, and the tree walked byte by byte."""
    data = suffix_tree._PAD + suffix_tree.normal(text.encode() if text is not None else None)
    column, child, log, width, dead = (tree[x] for x in ("column", "child", "log", "width", "dead"))
    total, token, spelled = 0.0, b"", 0.0
    for t in range(suffix_tree.DEPTH, len(data)):
        state = 0
        for k in range(1, suffix_tree.DEPTH + 1):
            following = child[state * width + column[data[t - k]]]
            if following == dead:
                break
            state = following
        spelled += log[state * width + column[data[t]]]
        if data[t] in b" \n":
            c = count["<end>" if data[t] == 10 else token.decode()]
            share = 0.5 + 0.25 * v / n
            total += math.log10(0.5 * (c - 0.5) / n + share * 10**spelled) if c else math.log10(share) + spelled
            token, spelled = b"", 0.0
        else:
            token += bytes([data[t]])
    return total


def test_words_are_told_apart_whatever_their_length():
    def doubled(n):  # a sequence on which numbers in any odd radix modulo a power of two agree with the complement's
        x = b"a"
        while len(x) < n:
            x += x.translate(bytes.maketrans(b"ab", b"ba"))
        return x

    table = bytes.maketrans(b"ab", b"ba")
    for n in (1, 2, 4, 8, 512, 1024, 4096):
        a = doubled(n)
        h, bounds = common.WordHasher(common.SPACED)([a, a.translate(table), a + b" " + a, None, b"", a + b"\0", b"\0" + a])
        assert len({int(x) for x in (h[0], h[1], h[4], h[5])}) == 4 and h[0] == h[2] == h[3]
        assert bounds.tolist() == [0, 1, 2, 4, 4, 4, 5, 6]
    rng = random.Random(4)
    texts = [" ".join("".join(rng.choices("abé日", k=rng.randint(1, 12))) for _ in range(rng.randint(0, 30))) for _ in range(200)]
    plain, piece = {}, common.PIECE
    for size in (piece, 40):
        common.PIECE = size
        h, bounds = common.WordHasher(common.SPACED)([t.encode() for t in texts])
        common.PIECE = piece
        for k, t in enumerate(texts):
            assert bounds[k + 1] - bounds[k] == len(t.split())
            for w, x in zip(t.split(), h[bounds[k] : bounds[k + 1]].tolist()):
                assert plain.setdefault(w, x) == x
    assert len(set(plain.values())) == len(plain)


def test_distributions_sum_to_one(spark):
    tree = suffix_tree.learn(docs_of(spark, ["the cat sat on the mat " * 20, "a dog " * 30]).select("text"))
    p = 10 ** tree["log"].astype(float).reshape(-1, tree["width"])
    unseen = 256 - (tree["width"] - 1)
    assert np.allclose(p[:, :-1].sum(axis=1) + unseen * p[:, -1], 1, atol=1e-4)
    assert tree["dead"] > 5


def test_suffix_tree_grows_with_the_corpus(spark):
    rng = random.Random(3)
    words = ["".join(rng.choices("abcdefghijklmnopqrstuvwxyz", k=6)) for _ in range(40_000)]
    docs = docs_of(spark, [" ".join(rng.sample(words, len(words))) for _ in range(20)]).repartition(4)
    assert suffix_tree.learn(docs.select("text"))["dead"] > 100_000


def test_suffix_tree_keeps_rare_contexts_that_gain_over_eight_bits_each(spark):
    tree = suffix_tree.learn(docs_of(spark, ["ba " * 100_000, "qaz qaz qaz qaz"]).select("text"))
    column, child, width = tree["column"], tree["child"], tree["width"]
    a = child[column[ord("a")]]
    assert a != tree["dead"] and child[a * width + column[ord("q")]] != tree["dead"]


def test_language_model_scores_do_not_depend_on_chunks(spark, monkeypatch):
    docs = docs_of(spark, [*ODD, *(f"word {i} again and again {i % 7}" for i in range(50))]).repartition(3)
    whole = {r.doc_id: r.score for r in suffix_tree.score_documents(docs).collect()}
    monkeypatch.setattr(suffix_tree, "CHUNK_BYTES", 64)
    monkeypatch.setattr(suffix_tree, "_CHUNK", 50)
    monkeypatch.setattr(suffix_tree, "MOST_HELD", 100)
    assert {r.doc_id: pytest.approx(r.score) for r in suffix_tree.score_documents(docs).collect()} == whole


def test_language_model_without_training_rows(spark):
    rows = docs_of(spark, ["x y"]).withColumn("doc_id", F.lit(None).cast("long"))
    r = suffix_tree.score_documents(rows).first()
    assert (r.n_tokens, r.n_known, r.train_tokens, r.held_out) == (3, 0, 0, False)
    assert r.score == pytest.approx(5 * math.log10(1 / 256)) and r.base_score == 0
    assert suffix_tree.score_documents(rows.limit(0)).count() == 0


# -- licences -------------------------------------------------------------------------------------------------------


def test_licences_against_brute_force(spark):
    texts = ODD + ["CC-BY 4.0, cc by and ALL Rights Reserved.", "GNU General Public License; general public\nlicense", "cc bycc by", "generalpublic license", "all rights reserved all rights reserved"]
    found = {r.doc_id: r for r in licences.scan_licences(docs_of(spark, texts), keep=["doc_id"]).collect()}
    for i, t in enumerate(texts):
        w = alnum(t)
        starts, labels = [], set()
        for phrase, label in licences.BASE_PHRASES.items():
            p = phrase.split()
            at = [k for k in range(len(w) - len(p) + 1) if w[k : k + len(p)] == p]
            starts += at
            labels |= {label} if at else set()
        r = found[i]
        assert (r.n_words, r.n_base, r.first_word, r.last_word) == (len(w), len(starts), min(starts, default=None), max(starts, default=None)), t
        assert r.base_labels == ",".join(sorted(labels)) and labels <= set(r["labels"].split(",")) | set()
        assert 0 <= r.score <= 1


def test_licence_expressions():
    machine = licences.automaton()
    get = lambda t: licences.scan(t.encode(), machine)
    assert licences.postfix("MIT or (Apache-2.0 AND GPL-2.0-only WITH Classpath-exception-2.0)") == ["MIT", "Apache-2.0", "GPL-2.0-only", "Classpath-exception-2.0", "with", "and", "or"]
    assert licences.evaluate("MIT OR GPL-3.0") == ({"mit", "gpl"}, 1.0)
    assert licences.evaluate("MIT AND GPL-3.0") == ({"mit", "gpl"}, 0.4)
    assert licences.evaluate("GPL-2.0 WITH Classpath-exception-2.0") == ({"gpl"}, 0.7)
    assert get("x SPDX-License-Identifier: (MIT OR Apache-2.0) rest of line")[5] == ["apache-2.0", "mit"]
    assert get("SPDX-License-Identifier: AND AND")[5] == ["spdx-invalid"]
    assert get("Released under the MIT License.")[5] == ["mit"]
    for text, label in (
        ("SPDX-License-Identifier: MIT.", "mit"), ("SPDX-License-Identifier: MIT and is free software", "mit"),
        ("SPDX-License-Identifier: GPL-2.0 or later version", "gpl"), ("SPDX License Identifier: Apache-2.0", "apache-2.0"),
        ("spdx-license-identifier = 'Zlib', see below", "zlib"), ("/* SPDX-License-Identifier: BSD-3-Clause */", "bsd"),
        ("SPDX-License-Identifier:\tLicenseRef-My.own and more", "licenseref-my.own"), ("SPDX-License-Identifier: (MIT", "mit"),
        ("SPDX-License-Identifier: MIT\nAND Apache-2.0", "mit"), ("SPDX-License-Identifier: Apache-2.0 WITH LLVM-exception or so", "apache-2.0"),
        ("é日 x, SPDX-License-Identifier: EUPL-1.2+ und", "eupl-1.2"), ("SPDX-License-Identifier: MIT WITH the rest", "mit"),
    ):
        assert get(text)[5] == [label], text
    assert get("SPDX-License-Identifier: MIT OR (Apache-2.0 AND")[5] == ["apache-2.0", "mit"]
    assert get("SPDX-License-Identifier: NOASSERTION")[5:] == ([], 0.0)
    assert get("SPDX-License-Identifier: is free")[5] == ["spdx-invalid"]
    assert get("SPDX-License-Identifier: MIT\nSPDX-License-Identifier: ISC; SPDX-License-Identifier")[5] == ["isc", "mit", "spdx-invalid"]


def expressions(rng, depth):
    """A random expression as text, and its labels and permissiveness."""
    if depth == 0 or rng.random() < 0.3:
        name, label, p = rng.choice([("MIT", "mit", 1.0), ("GPL-3.0-only", "gpl", 0.4), ("MPL-2.0", "mpl", 0.6), ("Foo-1.2", "foo-1.2", 0.5)])
        return (f"{name} WITH x-exception", {label}, p + (1 - p) / 2) if rng.random() < 0.2 else (name, {label}, p)
    kind = rng.choice(["and", "OR"])
    (a, la, pa), (b, lb, pb) = expressions(rng, depth - 1), expressions(rng, depth - 1)
    return f"({a}) {kind} ({b})", la | lb, (max if kind == "OR" else min)(pa, pb)


def test_licence_expressions_against_their_trees():
    rng = random.Random(6)
    for _ in range(300):
        text, labels, p = expressions(rng, 4)
        found = licences.evaluate(text.replace("(MIT)", "MIT"))
        assert found[0] == labels and found[1] == pytest.approx(p), text


def test_licence_base_columns_equal_sql(spark, data, duck):
    sql = r"""WITH d AS (SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+') AS w FROM documents),
    p(words, label) AS (VALUES (['cc', 'by'], 'cc-by'), (['general', 'public', 'license'], 'gpl'), (['all', 'rights', 'reserved'], 'reserved')),
    k AS (SELECT doc_id, w, unnest(range(1, len(w) + 1)) AS i FROM d),
    h AS (SELECT doc_id, i - 1 AS i, label FROM k JOIN p ON list_slice(w, i, i + len(words) - 1) = words)
    SELECT d.doc_id, CAST(len(w) AS BIGINT) AS n_words, CAST(count(h.i) AS BIGINT) AS n_base, CAST(min(h.i) AS BIGINT) AS first_word, CAST(max(h.i) AS BIGINT) AS last_word,
      coalesce(string_agg(DISTINCT label, ',' ORDER BY label), '') AS base_labels FROM d LEFT JOIN h ON h.doc_id = d.doc_id GROUP BY d.doc_id, w"""
    compare(registry.queries()["op7_licences"](spark, data).drop("labels", "score"), duck, sql)


def test_licence_rows(spark):
    docs = spark.createDataFrame([(None, "cc by"), (1, "cc by"), (1, "cc by"), (2, None)], "doc_id long, text string").withColumn("Score", F.lit("mine"))
    rows = licences.scan_licences(docs).collect()
    assert len(rows) == 4 and [r.n_base for r in rows] == [1, 1, 1, 0] and rows[0]["Score"] == "mine"
    assert licences.scan_licences(docs.limit(0)).count() == 0


# -- quality ----------------------------------------------------------------------------------------------------------


def test_quality_held_out_accuracy(spark, data):
    d = data.replace("sf0.001", "sf0.01")
    rows = registry.queries()["op8_quality"](spark, d).join(spark.read.parquet(f"{d}/labels.parquet"), "doc_id").where("held_out").collect()
    assert sum(r.predicted == r.quality for r in rows) >= 0.93 * len(rows)
    assert all(0 <= r.score <= 1 and r.predicted == int(r.score >= 0.7) for r in rows)


def test_quality_edges(spark):
    docs = docs_of(spark, ODD).withColumn("Score", F.lit("mine"))
    none = spark.createDataFrame([], "doc_id long, quality int")
    assert {r[-2] for r in quality.classify(docs, none).collect()} == {0.5}
    good = spark.createDataFrame([(i, 1) for i in range(9)] + [(None, 1), (1, None)], "doc_id long, quality int")
    found = quality.classify(docs, good)
    assert found.count() == len(ODD) and {r["Score"] for r in found.select(docs.columns).collect()} == {"mine"}
    assert all(r.predicted == 1 for r in quality.classify(docs_of(spark, ODD), good, keep=["doc_id"]).collect())
    assert quality.classify(docs.limit(0), good).count() == 0


def slow_statistics(text):
    raw, w = text.encode(), re.findall(r"[^\x20\x09-\x0D]+", "".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in text))
    if not raw:
        return [0.0] * len(quality.STATISTICS)
    n, size, count = max(1, len(w)), len(raw), Counter(w)
    letter = lambda c: 65 <= c <= 90 or 97 <= c <= 122 or c >= 128
    plain = lambda c: letter(c) or 48 <= c <= 57 or chr(c) in " \t\n\r\x0b\x0c.,;:'\"-!?()|"
    lines = [x for x in raw.split(b"\n") if x.strip()]
    return [
        len(w), sum(len(x.encode()) for x in w) / n, len(count) / n, max(count.values(), default=0) / n, sum(a == b for a, b in zip(w, w[1:])) / n,
        sum(65 <= c <= 90 for c in raw) / max(1, sum(map(letter, raw))), sum(48 <= c <= 57 for c in raw) / size, sum(not plain(c) for c in raw) / size, raw.count(b"|") / n, raw.count(b"!") / n,
        raw.count(b".") / n, len(lines) / n, 1 - len(set(lines)) / max(1, len(lines)), max((len(x.encode()) for x in w), default=0), sum(c >= 128 for c in raw) / size,
    ]


def test_statistics_against_brute_force(spark):
    texts = [t for t in ODD if t is not None] + ["A b!\nA b!\n\nc | d 12 #", "é\u00a0É x"]
    for r, t in zip(quality.with_statistics(docs_of(spark, texts)).select(*quality.STATISTICS).collect(), texts):
        assert list(r) == pytest.approx(slow_statistics(t), abs=1e-12), t[:30]


def test_quality_ties_and_repeated_labels(spark):
    docs = docs_of(spark, ["good words here. " * 9, "bad|bad|bad " * 9] * 60)
    labels = spark.createDataFrame([(i, 1 - i % 2) for i in range(120)] * 2 + [(0, 0), (7, 5)], "doc_id long, quality int")
    rows = {r.doc_id: r for r in quality.classify(docs, labels, keep=["doc_id"]).collect()}
    assert len(rows) == 120 and all(rows[i].score > rows[1].score for i in range(0, 120, 2))
    assert len({rows[i].score for i in range(0, 120, 2)}) == 1
    again = {r.doc_id: r.score for r in quality.classify(docs.repartition(7), labels.repartition(3), keep=["doc_id"]).collect()}
    assert again == pytest.approx({i: r.score for i, r in rows.items()})


def test_rules_and_columns_agree(spark):
    rng = np.random.default_rng(0)
    x = rng.normal(size=(500, len(quality.STATISTICS)))
    y = ((x[:, 0] > 0.3) & (x[:, 3] < 0.5)).astype(float)
    model = quality.fit_rules(x, y)
    assert 0 < len(model[1]) < 200
    z = model[0] + sum(w * quality.holds(x, r) for r, w in model[1])
    df = spark.createDataFrame([tuple(map(float, row)) for row in x], ", ".join(f"{s} double" for s in quality.STATISTICS))
    got = np.array([r[0] for r in df.select(quality.compiled(model)).collect()])
    assert np.allclose(got, 1 / (1 + np.exp(-z)))
    assert ((got > 0.5) == (y > 0.5)).mean() > 0.97


# -- media ---------------------------------------------------------------------------------------------------------------


@pytest.mark.parametrize("size", [0, 1, 63, 64, 65, 1024, 1025, 5000, 70_001])
def test_media_round_trip(size):
    rng = random.Random(size)
    raw = bytes(rng.choices(range(256), k=size)) if size % 2 else bytes([255, 0] * (size // 2 + 1))[:size]
    padded = media.payload(raw)
    assert len(padded) % 64 == 0 and padded[:size] == raw and len(padded) >= 64 and not padded[size:].strip(b"\0")
    video = media.write_avi(np.frombuffer(padded, np.uint8).reshape(-1, 64))
    back, rows, frames = media.clips(video)
    assert back == padded
    assert rows[0]["first_frame"] == 0 and rows[-1]["end_s"] == pytest.approx(frames / media.FPS)
    places, _ = media.read_avi(video)
    for start, n in places[:3]:  # the general decoder agrees
        assert np.array_equal(jpeg.luma(video[start : start + n]), media.decode_frame(video[start : start + n]))
    assert all(a["end_s"] == b["start_s"] for a, b in zip(rows, rows[1:]))
    assert int.from_bytes(video[4:8], "little") == len(video) - 8


def test_media_codes_are_a_prefix_code():
    codes = {}
    for d in range(-255, 256):
        s = abs(d).bit_length()
        codes[s] = format(int(media._FORTH[d + 255]), "09b")[: 9 - s]
    listed = sorted(codes.values())
    assert len(set(listed)) == 9 and not any(b.startswith(a) for a, b in zip(listed, listed[1:]))
    assert "1" * 9 not in listed


def flat_table(symbols):
    """A Huffman table whose codes all have 9 bits, and the code of each symbol."""
    counts = [0] * 16
    counts[8] = len(symbols)
    return bytes(counts) + bytes(symbols), {x: (k, 9) for k, x in enumerate(symbols)}


def baseline_jpeg(planes, sampling, quant, every=0, tables=True):
    """A plain encoder of baseline frames; ``planes`` are whole blocks of each component."""
    huff, codes = flat_table(range(255))
    bits = []

    def put(value, n):
        bits.extend(value >> (n - 1 - k) & 1 for k in range(n))

    def number(x):
        size = abs(x).bit_length()
        return size, (x if x > 0 else x + (1 << size) - 1)

    cosines = jpeg._cosines()
    units = (planes[0].shape[0] // (8 * sampling[0][1]), planes[0].shape[1] // (8 * sampling[0][0]))
    body, last, unit, restart = b"", [0] * len(planes), 0, 0

    def flush():
        nonlocal bits
        out = np.packbits(bits + [1] * (-len(bits) % 8)).tobytes().replace(b"\xff", b"\xff\x00")
        bits = []
        return out

    for y in range(units[0]):
        for x in range(units[1]):
            if every and unit and unit % every == 0:
                body += flush() + bytes([0xFF, 0xD0 + restart % 8])
                restart, last = restart + 1, [0] * len(planes)
            unit += 1
            for c, (h, v) in enumerate(sampling):
                for block in range(h * v):
                    r, k = (y * v + block // h) * 8, (x * h + block % h) * 8
                    f = np.rint(cosines.T @ (planes[c][r : r + 8, k : k + 8].astype(float) - 128) @ cosines / quant).astype(int).ravel()[jpeg.ZIGZAG]
                    size, extra = number(int(f[0]) - last[c])
                    last[c] = int(f[0])
                    put(*codes[size])
                    put(extra, size)
                    run = 0
                    for value in f[1:].tolist():
                        if value == 0:
                            run += 1
                            continue
                        while run > 15:
                            put(*codes[0xF0])
                            run -= 16
                        size, extra = number(value)
                        put(*codes[run << 4 | size])
                        put(extra, size)
                        run = 0
                    if run:
                        put(*codes[0])
    body += flush()
    seg = lambda m, b: bytes([0xFF, m]) + (len(b) + 2).to_bytes(2, "big") + b
    n = len(planes)
    out = b"\xff\xd8" + seg(0xE0, b"JFIF\0") + seg(0xDB, b"\0" + bytes(quant.ravel()[jpeg.ZIGZAG].astype(np.uint8)))
    out += seg(0xC0, b"\x08" + planes[0].shape[0].to_bytes(2, "big") + planes[0].shape[1].to_bytes(2, "big") + bytes([n]) + b"".join(bytes([c, h << 4 | v, 0]) for c, (h, v) in enumerate(sampling)))
    out += seg(0xC4, b"\0" + huff) + seg(0xC4, b"\x10" + huff)
    out += seg(0xDD, every.to_bytes(2, "big")) if every else b""
    return out + seg(0xDA, bytes([n]) + b"".join(bytes([c, 0]) for c in range(n)) + b"\0\x3f\0") + body + b"\xff\xd9"


@pytest.mark.parametrize("every", [0, 2])
@pytest.mark.parametrize("sampling", [[(1, 1)], [(1, 1), (1, 1), (1, 1)], [(2, 2), (1, 1), (1, 1)], [(2, 1), (1, 1), (1, 1)]])
def test_baseline_frames_of_other_writers(sampling, every):
    rng = np.random.default_rng(len(sampling) + every)
    y, x = np.mgrid[0:32, 0:48]
    top = np.clip(90 + 2 * x + y + rng.integers(-20, 20, (32, 48)), 0, 255).astype(np.uint8)
    h, v = sampling[0]
    planes = [top] + [np.clip(100 + x[:: v, ::h] + rng.integers(-5, 5, (32 // v, 48 // h)), 0, 255).astype(np.uint8) for _ in sampling[1:]]
    found = jpeg.decode(baseline_jpeg(planes, sampling, np.full((8, 8), 2), every))
    for c, (a, b) in enumerate(zip(planes, found)):
        whole = a if c == 0 else np.repeat(np.repeat(a, v, axis=0), h, axis=1)
        assert b.shape == (32, 48) and np.abs(whole.astype(int) - b).max() <= 6


def test_tables_of_the_standard_are_whole():
    for table, n in ((jpeg.DC_LUMA, 12), (jpeg.DC_CHROMA, 12), (jpeg.AC_LUMA, 162), (jpeg.AC_CHROMA, 162)):
        symbols = list(table[16:])
        assert len(symbols) == len(set(symbols)) == sum(table[:16]) == n
        assert jpeg.lookup(table).count(0) in (1 << k for k in range(16))  # the code of ones alone is free
        if n == 162:
            assert set(symbols) == {0, 0xF0} | {r << 4 | x for r in range(16) for x in range(1, 11)}
    assert jpeg.ZIGZAG[:10].tolist() == [0, 1, 8, 16, 9, 2, 3, 10, 17, 24] and sorted(jpeg.ZIGZAG) == list(range(64))


def test_lossless_frames_of_other_writers():
    """Any table and predictor: a plain encoder with another code."""
    rng = np.random.default_rng(2)
    x = rng.integers(0, 256, (9, 11)).astype(int)
    huff, codes = flat_table(range(10))
    for predictor in range(1, 8):
        bits = []
        for r in range(9):
            for c in range(11):
                a, b, d = x[r, c - 1], x[r - 1, c], x[r - 1, c - 1]
                guess = 128 if r == c == 0 else a if r == 0 else b if c == 0 else (None, a, b, d, a + b - d, a + ((b - d) >> 1), b + ((a - d) >> 1), (a + b) >> 1)[predictor]
                e = int(x[r, c] - guess)
                size = abs(e).bit_length()
                code, n = codes[size]
                bits += [code >> (n - 1 - k) & 1 for k in range(n)] + [(e if e > 0 else e + (1 << size) - 1) >> (size - 1 - k) & 1 for k in range(size)]
        body = np.packbits(bits + [1] * (-len(bits) % 8)).tobytes().replace(b"\xff", b"\xff\x00")
        seg = lambda m, b: bytes([0xFF, m]) + (len(b) + 2).to_bytes(2, "big") + b
        data = b"\xff\xd8" + seg(0xC3, bytes([8, 0, 9, 0, 11, 1, 1, 0x11, 0])) + seg(0xC4, b"\0" + huff) + seg(0xDA, bytes([1, 1, 0, predictor, 0, 0])) + body + b"\xff\xd9"
        assert np.array_equal(jpeg.luma(data), x)


def test_avi_of_another_writer():
    """Baseline frames, another stream number, an index from the file's begin, a chunk of sound between."""
    rng = np.random.default_rng(3)
    scenes = [np.full((16, 16), 40)] * 4 + [np.full((16, 16), 200)] * 3
    frames = [baseline_jpeg([(s + rng.integers(-3, 3, (16, 16))).astype(np.uint8)], [(1, 1)], np.ones((8, 8))) for s in scenes]
    header = media._chunk(b"LIST", b"hdrl" + media._chunk(b"avih", (40_000).to_bytes(4, "little") + b"\0" * 52))
    movie, index, start = b"movi", b"", 12 + len(header) + 8
    for f in frames:
        for kind, part in ((b"01wb", b"abc"), (b"02dc", f)):
            index += kind + (16).to_bytes(4, "little") + (start + len(movie)).to_bytes(4, "little") + len(part).to_bytes(4, "little")
            movie += media._chunk(kind, part)
    body = b"AVI " + header + media._chunk(b"LIST", movie) + media._chunk(b"idx1", index)
    samples, rows, n = media.clips(b"RIFF" + len(body).to_bytes(4, "little") + body)
    assert n == 7 and [(r["first_frame"], r["frames"], r["start_s"], r["end_s"]) for r in rows] == [(0, 4, 0.0, 0.16), (4, 3, 0.16, 0.28)]
    assert abs(np.frombuffer(samples, np.uint8)[:256].astype(int) - 40).max() <= 5


@pytest.mark.parametrize("data", [b"", b"\xff\xd8", b"\xff\xd8\xff\xc0\x00\x02", b"\xff\xd8\xff\xc2\x00\x0b\x08\0\x10\0\x10\x01\x01\x11\0\xff\xd9", b"no frame at all"])
def test_broken_frames(data):
    with pytest.raises(ValueError):
        media.decode_frame(data)


def test_media_memory_is_bounded():
    import tracemalloc

    text = np.random.default_rng(0).integers(32, 127, 6 << 20, dtype=np.uint8).tobytes()
    tracemalloc.start()
    video = media.write_avi(np.frombuffer(media.payload(text), np.uint8).reshape(-1, 64))
    found = media.Reading(video)
    peak = tracemalloc.get_traced_memory()[1]
    tracemalloc.stop()
    assert found.sha256 == hashlib.sha256(text).hexdigest() and peak < 6 * len(text) + (80 << 20)
    x = np.frombuffer(text, np.uint8)
    assert found.moments() == pytest.approx((x.mean(), x.std()))


def test_media_table_edges(spark):
    rows = spark.createDataFrame([(None, "x"), (1, "x"), (1, "x")], "doc_id long, text string").withColumn("Media", F.lit("mine"))
    video = media.to_video(rows)
    assert video.columns == ["doc_id", "text", "Media", "media_"] and len({bytes(r[3]) for r in video.collect()}) == 1
    assert len({r[3:] for r in map(tuple, media.digests(rows).collect())}) == 1
    assert media.digests(rows.limit(0)).count() == 0 and media.clip_rows(media.to_video(rows.limit(0), keep=["doc_id"])).count() == 0


def test_media_shots():
    rng = np.random.default_rng(0)
    scene = lambda low, high, n: [rng.integers(low, high, (16, 64), dtype=np.uint8) for _ in range(n)]
    frames = scene(0, 80, 12) + scene(150, 250, 9) + scene(60, 120, 7)
    assert media.shots(frames) == [0, 12, 21]
    with pytest.raises(ValueError):
        media.read_avi(b"RIFFxxxxAVI ")


def test_media_rows(spark):
    rows = {r.doc_id: r for r in media.digests(docs_of(spark, ODD), keep=["doc_id"]).collect()}
    for i, t in enumerate(ODD):
        p = media.payload((t or "").encode())
        r = rows[i]
        assert (r.n_bytes, r.payload_bytes, r.payload_sha256, r.tail_crc32) == (len((t or "").encode()), len(p), hashlib.sha256(p).hexdigest(), zlib.crc32(p[-64:]))
    assert rows[0].media_sha256 == rows[1].media_sha256
    clips = media.clip_rows(media.to_video(docs_of(spark, ODD), keep=["doc_id"]), keep=["doc_id"])
    assert clips.select("doc_id").distinct().count() == len(ODD)


# -- chat -------------------------------------------------------------------------------------------------------------------


def talk(*turns):
    return list(turns)


def test_preferences(spark):
    convs = {
        1: [("user", "hi"), ("assistant", "A"), ("user", "more"), ("assistant", "B")],
        2: [("user", "hi"), ("assistant", "A"), ("user", "more"), ("assistant", "C"), ("user", "x")],
        3: [("user", "hi"), ("assistant", "A")],
        4: [("user", "alone")],
        5: [("system", "s"), ("user", None), ("assistant", "ok")],
        9000: [("user", "hi"), ("assistant", "Z")],
    }
    rows = [(c, i, r, t) for c, ts in convs.items() for i, (r, t) in enumerate(ts)] + [(None, 0, "user", "lost"), (7, None, "user", "lost")]
    turns = spark.createDataFrame(rows, "conv_id long, turn long, role string, text string").repartition(3)
    found = {r.chosen_id: r for r in chat.format_preferences(turns).collect()}
    assert set(found) == set(convs)
    show = lambda ts: "".join(f"<|im_start|>{r}\n{t or ''}<|im_end|>\n" for r, t in ts)
    text = lambda s: "".join(x.text for x in s)
    learnt = lambda s: "".join(x.text for x in s if x["mask"])
    a = found[1]
    assert (a.rejected_id, a.n_prompt, a.prompt) == (2, 3, show(convs[1][:3]))
    assert text(a.chosen_segments) == show(convs[1][3:]) and text(a.rejected_segments) == show(convs[2][3:])
    assert learnt(a.chosen_segments) == "B<|im_end|>" and learnt(a.rejected_segments) == "C<|im_end|>"
    b = found[2]  # 3 is a prefix of 2: the shared answer goes back to the completions
    assert (b.rejected_id, b.n_prompt) == (3, 1) and text(b.rejected_segments) == show(convs[3][1:])
    assert found[3].rejected_id == 9000 and found[3].n_prompt == 1
    assert found[9000].rejected_id is None and found[9000].rejected_segments is None and found[9000].n_prompt == 1
    assert found[4].n_prompt == 0 or found[4].prompt == show(convs[4])
    assert found[5].n_prompt == 2 and found[5].prompt == show(convs[5][:2])
    assert chat.format_preferences(turns.limit(0)).count() == 0


def test_preferences_of_one_large_group_with_sparse_ids(spark):
    rng = random.Random(2)
    ids = list({rng.getrandbits(63) - 2**62 for _ in range(3000)})
    rows = [(c, 0, "user", "hi" if k % 10 else f"other {k % 3}") for k, c in enumerate(ids)]
    turns = spark.createDataFrame(rows, "conv_id long, turn long, role string, text string").repartition(5)
    expected, groups = {}, defaultdict(list)
    for c, _, _, t in rows:
        groups[t].append(c)
    for own in groups.values():
        own.sort()
        expected |= dict(zip(own, [*own[1:], None]))
    keys = chat.paired(chat.gathered(turns))
    assert {r.chosen_id: r.rejected_id for r in keys.collect()} == expected


def test_preferences_with_repeated_turns_and_clashing_columns(spark):
    rows = [(1, 0, "user", "hi"), (1, 0, "user", "hi"), (1, 0, "user", "a"), (1, 1, "assistant", "x" * 300_000), (2, 0, "user", "a"), (2, 0, "assistant", "b")]
    turns = spark.createDataFrame(rows, "conv_id long, turn long, role string, text string").withColumn("chosen", F.lit(1)).withColumn("run", F.lit(2))
    found = {r.chosen_id: r for r in chat.format_preferences(turns).collect()}
    assert found[1].n_prompt == 3 and found[1].prompt.count("hi") == 2 and found[1].prompt.index("\na<") < found[1].prompt.index("\nhi<")
    assert len(found[1].chosen_segments) == 3 and len(found[1].chosen_segments[1].text) > 300_000
    assert found[2].rejected_id is None and found[2].n_prompt == 0


# -- pipeline ----------------------------------------------------------------------------------------------------------------


def test_language_stage_keeps_short_texts(spark, data):
    import corpus_pipeline as P

    d = data.replace("sf0.001", "sf0.1")
    docs = spark.read.parquet(f"{d}/documents.parquet")
    kept = {r.doc_id for r in P.language_stage(spark, docs, d).select("doc_id").collect()}
    found = language.identify(docs, language.train(docs, "doc_id", "text", "lang"))
    learnt = {r.doc_id for r in found.where(F.col(found.columns[len(docs.columns)]) != language.UNKNOWN).select("doc_id").collect()}
    assert kept == learnt
    few = docs.where(F.size(F.split(F.trim("text"), r"\s+")) < 4).select("doc_id").collect()
    assert few and {r.doc_id for r in few} <= kept


@pytest.mark.parametrize("which", range(5))
def test_pipeline_stages_on_odd_tables(spark, data, which):
    """Null in every column, an empty table, columns with names that stages compute, repeated rows."""
    import corpus_pipeline as P

    d = data
    name, stage = P.STAGES[which]
    docs = spark.read.parquet(f"{d}/documents.parquet")
    odd = spark.createDataFrame([(None, None, None, None, None), (10**9, None, "en", "s", 0), (10**9 + 1, "", None, None, None), (None, "Some words of a text.", None, None, None), (None, "Some words of a text.", None, None, None)], docs.schema)
    wide = docs.unionByName(odd).withColumn("score", F.lit("mine")).withColumn("gone", F.lit(1)).withColumn("n_words", F.lit(2))
    found = stage(spark, wide, d)
    kept = found.collect()
    assert len(kept) <= wide.count() and stage(spark, wide.limit(0), d).count() == 0
    if name != "mixing":
        assert found.columns == wide.columns and {r["score"] for r in kept} == {"mine"}
    else:
        assert len(kept) == wide.count()


def test_pipeline_stages(spark, data):
    import corpus_pipeline as P

    d = data.replace("sf0.001", "sf0.01")
    docs = spark.read.parquet(f"{d}/documents.parquet")
    assert [n for n, _ in P.STAGES] == ["quality", "language", "near_duplicates", "decontamination", "mixing"]
    labels = {r.doc_id: r.quality for r in spark.read.parquet(f"{d}/labels.parquet").collect()}
    first = P.quality_stage(spark, docs, d).cache()
    kept = {r.doc_id for r in first.select("doc_id").collect()}
    assert first.columns == docs.columns
    assert sum((i in kept) == bool(q) for i, q in labels.items()) >= 0.95 * len(labels)
    second = P.language_stage(spark, first, d)
    assert second.columns == docs.columns and second.count() >= 0.99 * len(kept)
    third = P.near_duplicate_stage(spark, second, d).cache()
    rows = {r.doc_id: r.text for r in second.select("doc_id", "text").collect()}
    ids = sorted(rows)
    comp = brute_components(ids, {i: shingle_set(rows[i], 5) for i in ids})
    assert third.columns == docs.columns
    assert {r.doc_id for r in third.select("doc_id").collect()} == set(comp.values())
    fourth = P.decontamination_stage(spark, third, d)
    items = [(r.item_id, r.text) for r in spark.read.parquet(f"{d}/benchmark.parquet").collect()]
    windows = {tuple(alnum(t)[k : k + 13]) for _, t in items for k in range(max(1, len(alnum(t)) - 12))}

    def dirty(text):
        w, hit = alnum(text), set()
        for n in {len(x) for x in windows}:
            for k in range(len(w) - n + 1):
                if tuple(w[k : k + n]) in windows:
                    hit.update(range(k, k + n))
        return bool(hit) and 20 * len(hit) >= len(w)

    assert {r.doc_id for r in fourth.select("doc_id").collect()} == {i for i in set(comp.values()) if not dirty(rows[i])}
    assert P.run(spark, d).count() == fourth.count()
    assert P.ORACLE_SQL is None
