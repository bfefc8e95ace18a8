"""Each text operator on a small table of hard cases, against a plain version of what it computes."""

import hashlib
import random
import zlib
from collections import Counter, defaultdict

import duckdb
import numpy as np
import public_tokenizers
import pytest

from prunedknn.llm import (
    aniso_index,
    bpe_words,
    chat_windows,
    fm_decontam,
    html_diff,
    kneser_ney,
    minhash_bbit,
    oracles,
    registry,
    shard_mixture,
    toxicity_nb,
    url_rules,
)

VOCABULARY = public_tokenizers.path(registry.VOCABULARY)
SCHEMA = "doc_id long, text string, lang string, source string, n_chars long, row long, block string, score double, gram string, size long"


def hard_cases():
    rng = random.Random(5)
    words = ["alpha", "beta", "gamma", "delta", "Über", "naïve", "x1", "don't", "日本", "the", "of"]
    texts = [None, "", " ", "one", "two words", "  lead and trail  ", "tab\tand\nline\r\n", "\x00ctl\x1f", "A" * 40_000, "😀 emoji 😀", "a  b", "'s 's"]
    texts += [" ".join(rng.choice(words) for _ in range(rng.randint(1, 60))) for _ in range(60)]
    base = " ".join(rng.choice(words) + str(rng.randint(0, 99)) for _ in range(200))
    texts += [base, base, base.upper(), base + " tail", base.replace("alpha", "changed", 1), base[:300]]
    rows = [(i, t, rng.choice(["en", "de", None]), rng.choice(["a", "a", "a", "b", None]), None, i, "b", 0.5, "g", 1) for i, t in enumerate(texts)]
    rows += [rows[20], (None, "no id", "en", "a", 5, 1, "b", 0.5, "g", 1), (None, None, None, None, None, None, None, None, None, None)]
    return rows


@pytest.fixture(scope="module")
def docs(spark):
    return spark.createDataFrame(hard_cases(), SCHEMA).repartition(3)


@pytest.fixture(scope="module")
def none(spark):
    return spark.createDataFrame([], SCHEMA)


# --- 1: shards ----------------------------------------------------------------------------------


def test_shards(docs, none):
    rows = shard_mixture.interleave(docs, 4).collect()
    assert len(rows) == docs.count() and shard_mixture.interleave(none, 4).count() == 0
    by_shard = defaultdict(list)
    for r in rows:
        by_shard[r["shard"]].append(r)
    sizes = [len(v) for v in by_shard.values()]
    assert set(by_shard) == {0, 1, 2, 3} and max(sizes) - min(sizes) <= 1
    for own in by_shard.values():
        assert sorted(r["slot"] for r in own) == list(range(len(own)))
    total = Counter(r["source"] for r in rows)
    for own in by_shard.values():  # every shard matches the mixture
        for source, n in Counter(r["source"] for r in own).items():
            assert abs(n - total[source] / 4) <= 2
    texts = {r[0]: r[1] for r in hard_cases() if r[0] is not None}
    for r in rows:
        if r["doc_id"] in texts:
            raw = (texts[r["doc_id"]] or "").encode()
            assert (r["size"], r["text_crc32"]) == (len(raw) + 1, zlib.crc32(raw))


def test_shards_do_not_depend_on_the_order_of_rows(docs):
    key = lambda df: sorted((str(r["doc_id"]), r["size"], r["shard"], r["slot"]) for r in df.collect())
    assert key(shard_mixture.interleave(docs, 3)) == key(shard_mixture.interleave(docs.repartition(5, "text"), 3))


# --- 2: html ------------------------------------------------------------------------------------


@pytest.mark.parametrize(
    "html,want",
    [
        (None, ""), ("", ""), ("plain", "plain"),
        ("<nav>m</nav><article><h1>T &amp; t</h1><p>a<br>b &lt;x&gt;<p>c <b>d</b></article><footer>f</footer>", "T & t\n\na b <x>\n\nc d"),
        ("<article>x<div class='ad'>buy</div><script>if(a<b){}</script><style>p{}</style>y</article>", "x\n\ny"),
        ("<main><p>keep</p><aside>s</aside><section id='comments'><p>me too</p></section></main>", "keep"),
        ("<article><p><b>open<br><p>next</article>", "open\n\nnext"),
        ("<article>caf&eacute; &#233; &#x65E5;&nbsp;&am</article>", "café é 日 &am"),
        ("<body><div class='cookie-notice'>ok?</div><p>text</p></body>", "text"),
        ("<article class='post has-sidebar'><p>text</p></article><article class='related'><p>other</p></article><article class='card teaser-small'>x</article>", "text"),
    ],
)
def test_page_text(html, want):
    article, frame = html_diff.lines(html)
    assert "\n\n".join(article or frame) == want


def long_subsequence(n: int) -> float:
    import time

    rng = random.Random(n)
    a, b = ([f"line {rng.randint(0, n)}" for _ in range(n)] for _ in range(2))
    began = time.time()
    found = html_diff.common(a, b)
    assert [a[k] for k in sorted(found)] and len(found) > n ** 0.5
    return time.time() - began


def test_long_pages_are_aligned_soon():
    assert long_subsequence(3000) < 2.0


def test_halves_agree_with_the_whole(monkeypatch):
    rng = random.Random(3)
    pairs = [([rng.choice("abcdef") for _ in range(60)], [rng.choice("abcdef") for _ in range(70)]) for _ in range(20)]
    whole = [len(html_diff.common(a, b)) for a, b in pairs]
    monkeypatch.setattr(html_diff, "ALIGN_BITS", 64)
    for (a, b), n in zip(pairs, whole):
        found = sorted(html_diff.common(a, b))
        assert len(found) == n
        rest = iter(b)
        assert all(a[k] in rest for k in found)  # a subsequence of the other


def test_common_subsequence():
    rng = random.Random(2)
    for _ in range(200):
        a, b = ([rng.choice("abcd") for _ in range(rng.randint(0, 9))] for _ in range(2))
        t = [[0] * (len(b) + 1) for _ in range(len(a) + 1)]
        for i, x in enumerate(a):
            for j, y in enumerate(b):
                t[i + 1][j + 1] = t[i][j] + 1 if x == y else max(t[i][j + 1], t[i + 1][j])
        assert len(html_diff.common(a, b)) == t[-1][-1]


def test_pages_without_an_article_are_differenced(spark):
    frame = "<div>Site name</div><ul><li>Home</li></ul>{}<div>All rights</div>"
    rows = [(i, f"http://h.org/a/{i}", frame.format(f"<p>story {i}</p>")) for i in range(6)]
    rows += [(10, None, None), (11, "http://alone.org/x", "<p>only</p>"), (12, "no scheme", frame.format("<p>z</p>")), rows[0]]
    pages = spark.createDataFrame(rows, "page_id long, url string, html string")
    out = {(r["page_id"], r["url"]): r["text"] for r in html_diff.main_text(pages).collect()}
    assert out[(3, "http://h.org/a/3")] == "story 3" and out[(11, "http://alone.org/x")] == "only" and out[(10, None)] == ""
    assert html_diff.main_text(pages).count() == len(rows)
    assert html_diff.main_text(pages.limit(0)).count() == 0


def test_copies_and_pages_with_an_article_show_what_a_site_repeats(spark):
    from pyspark.sql import functions as F

    frame = "<div>Site name</div><ul><li>Home</li></ul>{}<div>All rights</div>"
    story = frame.format("<p>same story</p>")
    rows = [(i, f"http://h.org/b/{i}", story) for i in range(4)]  # copies only have each other next to them
    rows += [(10, "http://h.org/a", frame.format("<article><p>told</p></article>")), (11, "http://h.org/c", frame.format("<article><p>last</p></article>"))]
    rows += [(20 + i, f"http://copies.org/{i}", story) for i in range(3)]
    pages = spark.createDataFrame(rows, "page_id long, url string, html string").withColumn("frame", F.lit(1)).withColumn("row", F.lit(2))
    out = {r["page_id"]: r["text"] for r in html_diff.main_text(pages).collect()}
    assert len(out) == len(rows) and all(out[i] == "same story" for i in range(4)) and out[10] == "told" and out[11] == "last"
    assert all(out[20 + i] == "Site name\n\nHome\n\nsame story\n\nAll rights" for i in range(3))


# --- 3: language model --------------------------------------------------------------------------


def test_kneser_ney_sums_to_one_and_matches_a_plain_version(spark):
    texts = ["abab abba", "baab", "abc", "aab cab"]
    model = kneser_ney.train(spark.createDataFrame([(t,) for t in texts], "text string"))
    order, lead = kneser_ney.ORDER, chr(kneser_ney.START) * (kneser_ney.ORDER - 1)
    counts = {order: Counter()}
    for t in texts:
        s = lead + t
        counts[order].update(s[i : i + order] for i in range(len(s) - order + 1))
    for n in range(order - 1, 0, -1):
        counts[n] = Counter(g[1:] for g in counts[n + 1])
    alphabet = len(counts[1]) + 1
    discounts = {}
    for n, c in counts.items():
        n1, n2, n3, n4 = (sum(v == k for v in c.values()) for k in range(1, 5))
        y = n1 / (n1 + 2 * n2) if n1 + n2 else 0.5
        found = [k - (k + 1) * y * b / a if a else k / 2 for k, a, b in ((1, n1, n2), (2, n2, n3), (3, n3, n4))]
        discounts[n] = [min(max(d, 0.05), k - 0.05) for k, d in zip((1, 2, 3), found)]

    def p(gram):
        n = len(gram)
        if n == 0:
            return 1 / alphabet
        same = {g: v for g, v in counts[n].items() if g[:-1] == gram[:-1]}
        if not same:
            return p(gram[1:])
        d = lambda v: discounts[n][min(v, 3) - 1]
        total = sum(same.values())
        v = same.get(gram, 0)
        return (v - d(v) if v else 0) / total + sum(map(d, same.values())) / total * p(gram[1:])

    grams = ["abab", "xaba", "zzzz", lead + "a", "bcab", "a ab"]
    got = {r["gram"]: r["logp"] for r in kneser_ney.log_probabilities(model, spark.createDataFrame([(g,) for g in grams], "gram string")).collect()}
    for g in grams:
        assert got[g] == pytest.approx(np.log(p(g)), abs=1e-9)
    symbols = [*counts[1], "?"]
    assert sum(p("aba" + s) for s in symbols) == pytest.approx(1.0)


def test_kneser_ney_sees_four_characters_back(spark):
    """What follows "xyz" hangs on the character before it, which a model over 4-grams never sees."""
    model = kneser_ney.train(spark.createDataFrame([("axyzb",), ("cxyzd",)] * 20, "text string"))
    lead = chr(kneser_ney.START) * kneser_ney.ORDER
    grams = {end: (lead + end)[-kneser_ney.ORDER :] for end in ("axyzb", "axyzd", "cxyzb", "cxyzd")}
    asked = spark.createDataFrame([(g,) for g in set(grams.values())], "gram string")
    logp = {r["gram"]: r["logp"] for r in kneser_ney.log_probabilities(model, asked).collect()}
    assert logp[grams["axyzb"]] > logp[grams["axyzd"]] + 1
    assert logp[grams["cxyzd"]] > logp[grams["cxyzb"]] + 1


def test_quality_keeps_every_row_once(docs, none, spark):
    labels = spark.createDataFrame([(i, i % 2) for i in range(20, 60)] + [(None, 1), (3, None)], "doc_id long, quality int")
    rows = kneser_ney.judged(docs, labels).collect()
    assert len(rows) == docs.count() and set(docs.columns) <= set(rows[0].asDict())
    assert all(r["kept"] and r["perplexity"] is None for r in rows if not r["text"])
    assert kneser_ney.judged(none, labels).count() == 0
    untrained = kneser_ney.judged(docs, labels.limit(0)).collect()
    assert all(r["kept"] for r in untrained)


# --- 4: near duplicates -------------------------------------------------------------------------


def plain_components(rows, width, percent):
    sets = {}
    for i, (doc_id, text) in enumerate(rows):
        words = (text or "").encode().lower().split()
        n = min(width, len(words))
        sets[i] = {tuple(words[k : k + n]) for k in range(len(words) - n + 1)} if words else set()
    parent = list(range(len(rows)))

    def root(x):
        while parent[x] != x:
            x = parent[x]
        return x

    for i in range(len(rows)):
        for j in range(i):
            if sets[i] and sets[j] and 100 * len(sets[i] & sets[j]) >= percent * len(sets[i] | sets[j]):
                parent[root(i)] = root(j)
    least = {}
    for i, (doc_id, _) in enumerate(rows):
        if doc_id is not None:
            least[root(i)] = min(least.get(root(i), doc_id), doc_id)
    return sorted((str(rows[i][0]), len(sets[i]), str(least.get(root(i)))) for i in range(len(rows)))


@pytest.mark.parametrize("width", [2, 5])
def test_near_duplicates(docs, none, width):
    rows = [(r["doc_id"], r["text"]) for r in docs.collect()]
    got = sorted((str(r["doc_id"]), r["n_shingles"], str(r["component_id"])) for r in minhash_bbit.near_duplicates(docs, width, 80).collect())
    assert got == plain_components(rows, width, 80)
    assert minhash_bbit.near_duplicates(none, width, 80).count() == 0


def test_a_family_of_near_copies_is_linked_as_by_brute_force(spark):
    rng = random.Random(11)
    base = [f"w{rng.randint(0, 999)}" for _ in range(120)]
    rows = []
    for i in range(150):
        own = list(base)
        for _ in range(rng.choice([0, 2, 5, 9, 14])):
            own[rng.randrange(len(own))] = f"e{rng.randint(0, 10**9)}"
        rows.append((i, " ".join(own)))
    df = spark.createDataFrame(rows, "doc_id long, text string")
    got = sorted((str(r["doc_id"]), r["n_shingles"], str(r["component_id"])) for r in minhash_bbit.near_duplicates(df, 2, 80).collect())
    assert got == plain_components(rows, 2, 80)


def test_block_search_is_exact(monkeypatch, spark):
    monkeypatch.setattr(minhash_bbit, "BLOCK", 7)
    test_a_family_of_near_copies_is_linked_as_by_brute_force(spark)


def test_estimate_is_near_the_similarity():
    a, b = minhash_bbit._coefficients()
    rng = np.random.default_rng(3)
    x = np.unique(rng.integers(0, 1 << 62, 1000).astype(np.uint64))
    y = np.unique(np.concatenate((x[:800], rng.integers(0, 1 << 62, 200).astype(np.uint64))))
    true = len(np.intersect1d(x, y)) / len(np.union1d(x, y))
    same = ((minhash_bbit.minima(x, a, b) & 15) == (minhash_bbit.minima(y, a, b) & 15)).mean()
    assert abs((same - 1 / 16) / (1 - 1 / 16) - true) < 0.16


# --- 5: toxicity --------------------------------------------------------------------------------


def test_toxicity_learns_and_never_sees_the_held_out_fold(spark, none):
    rng = random.Random(1)
    rows, labels = [], []
    for i in range(600):
        toxic = i % 3 == 0
        words = [f"{rng.choice('abcdef')}{rng.choice('xyz')}{rng.randint(0, 30)}" for _ in range(30)] + (["blargh"] if toxic else [])
        rng.shuffle(words)
        rows.append((i, " ".join(words)))
        labels.append((i, 1, int(toxic)))
    df, lab = spark.createDataFrame(rows, "doc_id long, text string"), spark.createDataFrame(labels, "doc_id long, quality int, toxic int")
    out = toxicity_nb.score(df, toxicity_nb.fit(df, lab)).collect()
    held = [r for r in out if zlib.crc32(str(r["doc_id"]).encode()) % 4 == 2]
    assert np.mean([(r["score"] >= 0.3) == (r["doc_id"] % 3 == 0) for r in held]) > 0.98
    from pyspark.sql import functions as F

    flipped = lab.withColumn("toxic", F.when(toxicity_nb.held_out(F.col("doc_id")), 1 - F.col("toxic")).otherwise(F.col("toxic")))
    again = {r["doc_id"]: r["score"] for r in toxicity_nb.score(df, toxicity_nb.fit(df, flipped)).collect()}
    assert all(abs(again[r["doc_id"]] - r["score"]) < 1e-9 for r in out)


def test_toxicity_edges(docs, none, spark):
    labels = spark.createDataFrame([(i, 1, int(i > 40)) for i in range(20, 60)] + [(None, 1, 1), (5, 1, None)], "doc_id long, quality int, toxic int")
    model = toxicity_nb.fit(docs, labels)
    rows = toxicity_nb.score(docs, model, out_col="toxicity").collect()
    assert len(rows) == docs.count() and all(0 <= r["toxicity"] <= 1 for r in rows)
    assert len({r["toxicity"] for r in rows if not (r["text"] or "").strip()}) == 1
    assert toxicity_nb.score(none, model, out_col="toxicity").count() == 0
    assert 0 <= toxicity_nb.score(docs, toxicity_nb.fit(docs, labels.limit(0)), out_col="toxicity").first()["toxicity"] <= 1


# --- 6: byte-level BPE --------------------------------------------------------------------------


@pytest.mark.parametrize("block_chars", [50, 1_000_000])
def test_bpe_equals_the_library(docs, none, block_chars):
    import tiktoken

    ranks = bpe_words.load_ranks(VOCABULARY)
    whole = tiktoken.Encoding("whole", pat_str=public_tokenizers.PATTERN, mergeable_ranks=ranks, special_tokens={})
    out = bpe_words.encode_decode(docs, VOCABULARY, public_tokenizers.PATTERN, block_chars=block_chars).collect()
    want = Counter()
    for r in docs.collect():
        ids = np.asarray(whole.encode_ordinary(r["text"] or ""), dtype="<u4").tobytes()
        want[(r["doc_id"], ids, (r["text"] or "").encode())] += 1
    assert Counter((r["doc_id"], bytes(r["token_ids"]), bytes(r["decoded"])) for r in out) == want
    assert bpe_words.encode_decode(none, VOCABULARY, public_tokenizers.PATTERN).count() == 0


def test_short_numbers_round_trip():
    for top in (10, 223, 224, 70_000, 2_097_375, 2_097_376, 2**32 - 1):
        x = np.unique(np.random.default_rng(1).integers(0, top + 1, 500, dtype=np.uint64).astype(np.uint32))
        assert (bpe_words._from_short(list(bpe_words._short(x))) == x).all()


# --- 7: urls ------------------------------------------------------------------------------------


@pytest.mark.parametrize(
    "url,host,path",
    [
        (None, "", ""), ("no scheme/x", "", ""), ("http://A.Org/P?q#f", "a.org", "/P"), ("x://h?a=/b", "h", ""), ("x://h#/b", "h", ""),
        ("x://h", "h", ""), ("x:///p", "", "/p"), ("http://a/b://c", "a", "/b://c"),
    ],
)
def test_url_parts(spark, url, host, path):
    r = url_rules.parts(spark.createDataFrame([(1, url)], "page_id long, url string")).first()
    assert (r["host"], r["path"]) == (host, path)


def test_rules_and_mining(spark):
    rows = [(i, f"http://{'good' if i % 4 else 'spam'}.example.net/en/{i}") for i in range(40)]
    rows += [(50, "https://sub.example.org/en/12"), (51, "http://example.org/es/"), (52, "http://notexample.org/es/1"), (53, None), (53, None), (54, "http://x.com/de/1")]
    pages = spark.createDataFrame(rows, "page_id long, url string")
    labels = spark.createDataFrame([(i, int(i % 4 > 0), 0) for i in range(40)], "doc_id long, quality int, toxic int")
    out = {r["page_id"]: r for r in url_rules.judged(pages, labels, registry.URL_RULES).collect()}
    assert out[4]["verdict"] == "block" and out[2]["verdict"] == "allow" and out[4]["mined"]
    assert (out[50]["rule"], out[50]["verdict"]) == ("example.org/en/1", "block")
    assert (out[52]["rule"], out[52]["verdict"]) == ("org/", "allow") and out[54]["rule"] == "com/de/" and out[53]["verdict"] == "allow"
    assert url_rules.judged(pages, labels, registry.URL_RULES).count() == len(rows)
    assert url_rules.judged(pages, labels.limit(0), []).where("verdict = 'block'").count() == 0
    assert url_rules.judged(pages.limit(0), labels, []).count() == 0


# --- 8: neighbours ------------------------------------------------------------------------------


def test_neighbours_on_hard_vectors(spark):
    rng = np.random.default_rng(4)
    rows = [(i, rng.normal(size=8).tolist()) for i in range(400)]
    rows[5] = (5, rows[4][1])
    rows += [(900, None), (901, [0.0] * 8), (902, [float("nan")] * 8), (903, [None] * 8), (904, [float("inf")] * 8), (905, [1.0] * 7)]
    df = spark.createDataFrame(rows, "vec_id long, embedding array<double>")
    indexed, book = aniso_index.index(df)
    assert indexed.count() == 400
    got = aniso_index.nearest(indexed, book, indexed.where("id % 50 = 0"), k=5, rerank=64).collect()
    x = np.asarray([v for _, v in rows[:400]])
    hits = 0
    for q in range(0, 400, 50):
        s = aniso_index.exact(x, x[q])
        s[q] = -9
        want = sorted(range(400), key=lambda i: (-s[i], i))[:5]
        own = sorted((r["rank"], r["vec_id"], r["score"]) for r in got if r["query_id"] == q)
        assert [r for r, _, _ in own] == [1, 2, 3, 4, 5] and all(abs(v - s[i]) < 1e-12 for _, i, v in own)
        hits += len(set(want) & {i for _, i, _ in own})
    assert hits / 40 >= 0.9
    few = spark.createDataFrame(rows[:3], df.schema)
    indexed, book = aniso_index.index(few)
    assert aniso_index.nearest(indexed, book, indexed, k=5).count() == 6
    indexed, book = aniso_index.index(df.limit(0))
    assert aniso_index.nearest(indexed, book, indexed, k=5).count() == 0


def test_anisotropic_codes_keep_inner_products():
    rng = np.random.default_rng(6)
    x = aniso_index._unit(rng.normal(size=(2000, 64)))
    own = aniso_index.Codebook(64).fit(x)
    plain = aniso_index.Codebook(64)
    plain.weight = 1.0
    plain.fit(x)
    along = lambda b: np.abs(((x - np.take_along_axis(b.centres[None], b.encode(x)[:, :, None, None].astype(int), 2)[:, :, 0].reshape(len(x), -1)) * x).sum(axis=1)).mean()  # noqa: E731,E501
    assert along(own) < along(plain)


# --- 9: decontamination -------------------------------------------------------------------------


def test_suffix_order_and_fm_index():
    rng = np.random.default_rng(8)
    for n in (1, 2, 17, 200):
        text = np.append(rng.integers(0, 4, n), 0)
        index = fm_decontam.FmIndex(text, sample_every=3)
        for length in (1, 2, 3, 5):
            phrases = rng.integers(1, 4, (20, length))
            phrases = phrases[(phrases <= text.max(initial=0)).all(axis=1)]
            low, high = index.search(phrases)
            for f, a, b in zip(phrases, low, high):
                want = [i for i in range(len(text) - length + 1) if (text[i : i + length] == f).all()]
                assert sorted(index.locate(np.arange(a, b)).tolist()) == want


@pytest.mark.parametrize("shard_words", [8, 1 << 20])
def test_contamination(docs, none, spark, shard_words):
    tests = [(1, "alpha beta gamma"), (2, "the of the"), (3, None), (4, "..."), (5, "One"), (1, "alpha beta gamma"), (None, "two words"), (7, hard_cases()[72][1])]
    tests = spark.createDataFrame(tests, "item_id long, text string")
    out = fm_decontam.contaminated(docs, tests, 10, shard_words=shard_words, clean=True, extra=("row",)).collect()
    assert len(out) == docs.count() and fm_decontam.contaminated(none, tests, 10).count() == 0
    windows = {}
    for item, text in [(r["item_id"], r["text"]) for r in tests.collect()]:
        w = fm_decontam.words_of(text)
        for i in range(max(1, len(w) - 9) if w else 0):
            windows.setdefault(tuple(w[i : i + 10]), set()).update([] if item is None else [str(item)])
    for r, original in zip(sorted(out, key=lambda r: (r["row"] or -1, str(r["text"]))), sorted(docs.collect(), key=lambda r: (r["row"] or -1, str(r["text"])))):
        w = fm_decontam.words_of(original["text"]) if original["doc_id"] is not None else None
        if w is None:
            continue
        cover, items = set(), set()
        for f, names in windows.items():
            for i in range(len(w) - len(f) + 1):
                if tuple(w[i : i + len(f)]) == f:
                    cover.update(range(i, i + len(f)))
                    items |= names
        assert (r["n_words"], sum(s["end"] - s["start"] for s in r["spans"]), set(r["items"])) == (len(w), len(cover), items)
    assert fm_decontam.contaminated(docs, tests.limit(0), 10).where("size(items) > 0").count() == 0


def test_passes_over_large_test_sets_agree(docs, spark, monkeypatch):
    tests = spark.createDataFrame([(i, t) for i, t in enumerate(["alpha beta", "the of", "gamma delta x1", "naïve"])], "item_id long, text string")
    key = lambda df: sorted((str(r["doc_id"]), r["n_words"], str(r["spans"]), str(r["items"])) for r in df.collect())
    one = key(fm_decontam.contaminated(docs, tests))
    monkeypatch.setattr(fm_decontam, "BLOCK_BYTES", 12)
    assert key(fm_decontam.contaminated(docs, tests)) == one


def test_an_item_without_a_name_still_hits(spark):
    df = spark.createDataFrame([(1, "say two words here")], "doc_id long, text string")
    tests = spark.createDataFrame([(None, "two words"), (3, "words here")], "item_id long, text string")
    r = fm_decontam.contaminated(df, tests).first()
    assert (r["spans"], r["items"]) == ([(1, 4)], ["3"])


@pytest.mark.parametrize("block_bytes", [1 << 20, 12])
def test_cutting_goes_on_until_nothing_is_left(spark, monkeypatch, block_bytes):
    monkeypatch.setattr(fm_decontam, "BLOCK_BYTES", block_bytes)
    tests = spark.createDataFrame([(1, "alpha beta"), (2, "gamma delta"), (3, "epsilon zeta")], "item_id long, text string")
    rows = [(1, "x alpha gamma delta beta y"), (2, "epsilon alpha gamma delta beta zeta"), (3, "clean text"), (4, None)]
    df = spark.createDataFrame([(i, t, 7, "s") for i, t in rows], "doc_id long, text string, n_words int, spans string")
    out = {r["doc_id"]: r for r in fm_decontam.contaminated(df, tests, clean=True, extra=("n_words", "spans"), names=("a", "b", "c")).collect()}
    assert [(out[i]["text"] or "").split() for i in (1, 2, 3, 4)] == [["x", "y"], [], ["clean", "text"], []]
    assert (out[1]["n_words"], out[1]["spans"], out[1]["a"], out[1]["b"], out[1]["c"]) == (7, "s", 6, [(2, 4)], ["2"])


def test_cut_out():
    assert fm_decontam.without("Keep this, cut THAT part! end", [(2, 5)]) == "Keep this, ! end"


# --- 10: chat -----------------------------------------------------------------------------------


def plain_digest(rows):
    said = "".join(f"{r or ''}\n{t or ''}\n" for r, t in rows)
    loss = "".join(t or "" for r, t in rows if r == "assistant")
    sha = lambda s: hashlib.sha256(s.encode()).hexdigest()
    return len(rows), sha(said), len(loss), sha(loss)


@pytest.mark.parametrize("budget,history", [(1024, 256), (30, 10), (1, 0)])
def test_chat_round_trip(spark, budget, history):
    rng = random.Random(7)
    pieces = ["</s>[INST] ok [/INST]", "\\", "<|im_end|>\n", "a\nb", "", None, "<\\|im_start|>", "<s><s>", "plain text " * 20, "<|im_start|>assistant\n", "日本 😀"]
    rows = [(c, t, rng.choice(["user", "assistant", "system", "tool", None, "a\nb\\"]), rng.choice(pieces)) for c in range(8) for t in range(rng.randint(1, 12))]
    rows += [(None, 0, "system", "s"), (None, 1, "assistant", "x"), (9, None, "assistant", "n"), (9, None, "assistant", "n")]
    df = spark.createDataFrame(rows, "conv_id long, turn long, role string, text string")
    made = chat_windows.windows(df, VOCABULARY, public_tokenizers.PATTERN, budget, history)
    got = {r["conv_id"]: (r["n_turns"], r["turns_sha256"], r["loss_chars"], r["loss_sha256"]) for r in chat_windows.digests(made).collect()}
    key = lambda r: tuple((x is not None, x) if x is not None else (False, 0 if i == 0 else "") for i, x in enumerate(r))
    for conv in {r[0] for r in rows}:
        own = sorted(((t, r, x) for c, t, r, x in rows if c == conv), key=key)
        assert got[conv] == plain_digest([(r, x) for _, r, x in own])
    assert chat_windows.digests(chat_windows.windows(df.limit(0), VOCABULARY, public_tokenizers.PATTERN)).count() == 0
    for w in made.collect():
        assert w["window"] == 0 or w["repeated"] >= 0
        if w["n_tokens"] > budget:  # only a window of one fresh turn may be too long
            assert len(chat_windows.read_turns(w["formatted"])) - w["repeated"] == 1


def test_escape():
    rng = random.Random(9)
    bits = [*chat_windows.CONTROLS, "\\", "<", "|", "[", "x", "\n"]
    for _ in range(2000):
        s = "".join(rng.choice(bits) for _ in range(rng.randint(0, 8)))
        e = chat_windows.escape(s)
        assert chat_windows.unescape(e) == s and not any(c in e for c in chat_windows.CONTROLS)
        assert chat_windows.unescape_role(chat_windows.escape_role(s)) == s


# --- queries and pipeline -----------------------------------------------------------------------


@pytest.mark.parametrize("name", ["op2_html_difference", "op4_minhash_bbit", "op7_url_rules", "op9_fm_decontam"])
def test_query_equals_sql(name, spark, sf):
    from tests.test_queries import TABLES, same

    con = duckdb.connect()
    for t in TABLES:
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM read_parquet('{sf}/{t}.parquet')")
    df = registry.QUERIES[name](spark, sf)
    cursor = con.execute(oracles.ORACLE_SQL[name])
    columns = [c[0] for c in cursor.description]
    same(df.collect(), df.columns, cursor.fetchall(), columns)


def test_pipeline_stages(spark, sf):
    """Each stage against a plain version over what its predecessor kept."""
    import tiktoken

    import corpus_pipeline as P
    from prunedknn.llm._shared import table, written

    docs = before = table(spark, sf, "documents")
    kept = {}
    for name, stage in P.STAGES:
        docs = written(stage(spark, before, sf), f"test-{name}")
        rows = docs.collect()
        kept[name] = rows
        ids = {r["doc_id"] for r in before.select("doc_id").collect()}
        assert {r["doc_id"] for r in rows} <= ids
        if name != "encoding":
            assert docs.columns == before.columns
        if name == "near_duplicates":
            plain = plain_components([(r["doc_id"], r["text"]) for r in before.collect()], 5, 80)
            assert {str(r["doc_id"]) for r in rows} == {c for _, _, c in plain}
        if name == "decontamination":
            tests = fm_decontam.Windows([(str(r["item_id"]), r["text"]) for r in table(spark, sf, "benchmark").collect()], 10)
            assert len(rows) == before.count()
            again = fm_decontam.search_shard([r["text"] for r in rows], tests)
            assert not any(spans for _, spans, _ in again)
        if name == "encoding":
            whole = tiktoken.Encoding("w", pat_str=public_tokenizers.PATTERN, mergeable_ranks=bpe_words.load_ranks(VOCABULARY), special_tokens={})
            texts = {r["doc_id"]: r["text"] for r in before.collect()}
            for r in rows:
                assert r["n_tokens"] == len(whole.encode_ordinary(texts[r["doc_id"]] or ""))
        before = docs
    clean = {r["doc_id"] for r in table(spark, sf, "labels").where("quality = 1 and toxic = 0").collect()}
    left = [len(clean & {r["doc_id"] for r in kept[n]}) for n in ("toxicity", "quality")]
    assert left[0] >= 0.85 * len(clean) and left[1] >= 0.95 * left[0]
