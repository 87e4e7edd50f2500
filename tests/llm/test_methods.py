"""What the methods promise beyond right results on plain tables: ties, clashes, hostile pages, planted repeats."""

import itertools
import re
import time
from collections import defaultdict

import duckdb
import numpy as np
import pytest
from pyspark.sql import functions as F

import corpus_pipeline
from tests_llm_shared import WORD
from treesketch.llm import byte_bpe, components, factorization, hnsw, html_text, line_dedup, near_dedup, packing, passages, prefix_forest, sharding, storage, token_shards


def gibberish(rng, n, vocabulary=50_000):
    return [f"w{int(x)}" for x in rng.integers(0, vocabulary, n)]


# columns and rows


CLASHES = ["TEXT", "Doc_Id", "score", "SCORE", "label", "n_words", "Spans", "N_Removed", "dk", "th", "dropped", "n_lines", "N_DROPPED", "rows", "id", "hub", "h", "_0", "_passage_x", "token", "lang", "source", "n_chars"]


@pytest.fixture(scope="module")
def clashing(spark):
    rng = np.random.default_rng(1)
    rows = [(i, " ".join(gibberish(rng, 80)) + "\nshared line") for i in range(12)]
    rows.append((12, rows[3][1]))
    df = spark.createDataFrame(rows, "doc_id long, text string")
    return df.select(*[F.lit(f"x{i}").alias(c) for i, c in enumerate(CLASHES)], "doc_id", "text").toDF(*CLASHES, "doc_id", "text")


def test_clashing_columns_pass_through(spark, clashing):
    rows = [r.asDict() for r in storage.only(clashing, "doc_id", "text").collect()]
    labels = spark.createDataFrame([(i, i % 2) for i in range(12)], "doc_id long, label int").selectExpr("doc_id", "label", "'x' as LABEL")
    model = factorization.fit_quality(clashing, labels)
    scored = factorization.score_quality(clashing, model)
    assert scored.columns == [c for c in clashing.columns if c.lower() != "score"] + ["score"] and scored.count() == 13
    cut = passages.remove_repeats(clashing)
    assert cut.columns == [c for c in clashing.columns if c.lower() not in passages.ADDED] + list(passages.ADDED)
    assert sum(r["n_removed"] > 0 for r in cut.toDF(*[f"c{i}" for i in range(len(cut.columns) - 3)], *passages.ADDED).collect()) == 1
    lines = line_dedup.drop_lines(clashing, line_dedup.keep_bitmaps(clashing, min_docs=10))
    assert lines.toDF(*[f"c{i}" for i in range(len(lines.columns) - 3)], "text", "n_lines", "n_dropped").agg(F.sum("n_dropped")).first()[0] == 13
    assert {r.component_id for r in near_dedup.near_duplicates(clashing).collect()} == set(range(12))
    assert packing.token_pieces(clashing).select("doc_id").distinct().count() == byte_bpe.encode_byte_bpe(clashing).count() == len(rows)
    docs = clashing
    for _, stage in corpus_pipeline.STAGES[1:4]:
        docs = storage.materialize(stage(spark, docs, None), "test-clash")
        assert docs.columns == list(corpus_pipeline.COLUMNS)


def test_texts_of_one_doc_id_stay_together(spark):
    rng = np.random.default_rng(2)
    a, b, c = (" ".join(gibberish(rng, 60)) for _ in range(3))
    rows = [(5, a, "en"), (5, b, "fr"), (5, b, "de"), (6, c, "en"), (7, c + " more", "en"), (6, c, "en"), (8, b, "en")]
    docs = spark.createDataFrame([(d, t, lang, "s", 1) for d, t, lang in rows], "doc_id long, text string, lang string, source string, n_chars long").repartition(4)
    got = sorted((r.doc_id, r.text, r.lang) for r in corpus_pipeline.near(spark, docs, None).collect())
    assert got == sorted([(5, a, "en"), (5, b, "de"), (6, c, "en")])


def test_vectors_of_one_id_share_a_component(spark):
    rows = [(1, [1.0, 0.0, 0.0]), (1, [0.0, 1.0, 0.0]), (2, [1.0, 0.01, 0.0]), (3, [0.0, 1.0, 0.01]), (4, [0.0, 0.0, 1.0]), (4, [0.0, 0.0, 1.0]), (5, [0.0, 0.0, 2.0])]
    got = sorted((r.vec_id, r.n_links, r.component_id) for r in hnsw.near_duplicate_vectors(spark.createDataFrame(rows, "vec_id long, embedding array<float>")).collect())
    assert got == [(1, 1, 1), (1, 1, 1), (2, 1, 1), (3, 1, 1), (4, 1, 4), (4, 1, 4), (5, 1, 4)]


# 1, 9: vectors


def test_equal_vectors_rank_by_id():
    rng = np.random.default_rng(3)
    for n in (30, 38, 200):
        x = rng.standard_normal((n + 50, 64))
        x[10 : 10 + n] = x[10]
        forest = prefix_forest.PrefixForest(x, float(np.linalg.norm(x, axis=1).max()))
        for found, scores in forest.nearest(rng.standard_normal((20, 64)) + x[10], n, 10_000):
            same = [(p, s) for p, s in zip(found.tolist(), scores.tolist()) if 10 <= p < 10 + n]
            assert len({s for _, s in same}) == 1 and [p for p, _ in same] == sorted(p for p, _ in same)


def test_descent_finds_the_longest_match():
    rng = np.random.default_rng(4)
    forest = prefix_forest.PrefixForest(rng.standard_normal((300, 8)), 10.0)
    strings = forest.query_strings(rng.standard_normal((25, 8)))
    for t in range(forest.trees):
        for q in range(25):
            best = max(forest.bits - int(int(s) ^ int(strings[t, q])).bit_length() for s in forest.sorted[t])
            assert forest._longest(strings)[t, q] == best


def test_few_shards_and_few_links():
    assert sharding.shards_for(500, 8) == 1 and sharding.shards_for(51_282, 6) == 4 and sharding.shards_for(10**9, 8) == 5000
    rng = np.random.default_rng(5)
    x = rng.standard_normal((400, 16))
    x[:300] = x[0] + 0.01 * rng.standard_normal((300, 16))
    shard = hnsw._Shard(x, np.arange(400), np.ones(400, np.int64), 0.95, 24)
    found = shard.links(x, np.arange(400))
    assert all(len(f) == (299 if i < 300 else 0) for i, f in enumerate(found))
    at, to = shard.joins(found)
    assert len(at) < 650 and {(min(a, b)) for a, b in zip(at.tolist(), to.tolist())} <= set(range(300))


def test_star_forest():
    rng = np.random.default_rng(6)
    for _ in range(20):
        a, b = rng.integers(0, 60, 50), rng.integers(0, 60, 50)
        x, y = components.star_forest(a, b)
        label = {v: v for v in np.concatenate([a, b]).tolist()}
        for _ in range(60):
            for u, v in zip(a.tolist(), b.tolist()):
                label[u] = label[v] = min(label[u], label[v])
        assert dict(zip(x.tolist(), y.tolist())) == {v: r for v, r in label.items() if v != r}


# 3: passages


def test_seed_runs_equal_brute_force():
    rng = np.random.default_rng(7)
    rows = sorted({(int(h), int(d), int(p)) for h, d, p in zip(rng.integers(0, 12, 400), rng.integers(0, 15, 400), rng.integers(0, 9, 400))})
    want = set()
    for h, d, p in rows:
        before = [(e, q) for g, e, q in rows if g == h and e < d]
        if before:
            want |= {(d, p, *before[0]), (d, p, *before[-1])} if before[-1][0] != before[0][0] else {(d, p, *before[0])}
    runs, got = passages.SeedRuns(), set()
    for at in range(0, len(rows), 7):
        got |= set(zip(*(c.tolist() for c in runs.feed(*map(np.array, zip(*rows[at : at + 7]))))))
    assert got == want


def local_alignment(x, y, miss=2):
    """Places of x in the best local alignment with y (one for a match, less ``miss`` for a difference or a gap), and how many agree."""
    s = np.zeros((len(x) + 1, len(y) + 1), int)
    for i in range(len(x)):
        for j in range(len(y)):
            s[i + 1, j + 1] = max(0, s[i, j] + (1 if x[i] == y[j] else -miss), s[i, j + 1] - miss, s[i + 1, j] - miss)
    i, j = np.unravel_index(s.argmax(), s.shape)
    places, agreed = [], 0
    while s[i, j] > 0:
        if s[i, j] == s[i - 1, j - 1] + (1 if x[i - 1] == y[j - 1] else -miss):
            agreed += x[i - 1] == y[j - 1]
            i, j = i - 1, j - 1
            places.append(i)
        elif s[i, j] == s[i - 1, j] - miss:
            i -= 1
            places.append(i)
        else:
            j -= 1
    return places, agreed


def test_repeats_equal_brute_force(spark):
    """Every exact run of 50 words of an earlier document goes; what goes is in a local alignment with one."""
    rng = np.random.default_rng(8)
    passages_ = [gibberish(rng, int(n)) for n in (50, 60, 75, 90)]
    docs = {}
    for i in range(24):
        parts = [gibberish(rng, int(rng.integers(5, 40)))]
        for j in rng.integers(0, 4, int(rng.integers(0, 3))):
            p = list(passages_[j])
            for e in rng.integers(0, len(p), int(rng.integers(0, 4))):
                p[e] = f"edit{int(rng.integers(1e6))}"
            parts += [p, gibberish(rng, int(rng.integers(5, 40)))]
        docs[i] = [w for p in parts for w in p]
    df = spark.createDataFrame([(d, " ".join(t)) for d, t in docs.items()], "doc_id long, text string").repartition(6)
    got = {r.doc_id: r for r in passages.remove_repeats(df).collect()}
    windows: dict[tuple, int] = {}
    for d, t in docs.items():
        gone = {i for s in got[d].spans for i in range(s.start, s.end)}
        assert got[d].n_removed == len(gone) and got[d].text.split() == [w for i, w in enumerate(t) if i not in gone]
        for i in range(len(t) - 49):
            if windows.setdefault(tuple(t[i : i + 50]), d) < d:
                assert set(range(i, i + 50)) <= gone
        for s in got[d].spans:
            places, agreed = local_alignment(t[max(0, s.start - 5) : s.end + 5], docs[s.doc_id])
            assert s.doc_id < d and s.end - s.start >= 50 and agreed >= 0.8 * (s.end - s.start) - 2 and len(places) >= s.end - s.start - 4


def test_planted_repeats(spark):
    """Twice in a later document; put together from older fragments; one word in ten replaced."""
    rng = np.random.default_rng(9)
    rows, kinds = [], defaultdict(list)
    for case in range(30):
        at, passage = 1000 * case, gibberish(rng, 75)
        rows += [(at, gibberish(rng, 60) + passage + gibberish(rng, 60)), (at + 1, gibberish(rng, 50) + passage + gibberish(rng, 90) + passage + gibberish(rng, 20))]
        kinds["twice"].append((at + 1, 150))
        pieces = [gibberish(rng, 30) for _ in range(3)]
        rows += [(at + 10 + i, gibberish(rng, 40) + p + gibberish(rng, 40)) for i, p in enumerate(pieces)]
        whole = [w for p in pieces for w in p]
        rows += [(at + 20, gibberish(rng, 40) + whole + gibberish(rng, 40)), (at + 21, gibberish(rng, 40) + whole + gibberish(rng, 40))]
        kinds["fragments"].append((at + 21, 90))
        edited = gibberish(rng, 80)
        rows.append((at + 30, gibberish(rng, 30) + edited + gibberish(rng, 30)))
        edited = list(edited)
        for i in rng.choice(80, 8, replace=False):
            edited[i] = f"new{int(rng.integers(1e6))}"
        rows.append((at + 31, gibberish(rng, 30) + edited + gibberish(rng, 30)))
        kinds["replaced"].append((at + 31, 80))
    df = spark.createDataFrame([(d, " ".join(t)) for d, t in rows], "doc_id long, text string").repartition(8)
    got = {r.doc_id: r.n_removed for r in passages.remove_repeats(df).collect()}
    share = {k: [min(1, got[d] / n) for d, n in v] for k, v in kinds.items()}
    assert min(share["twice"]) >= 0.98 and min(share["fragments"]) >= 0.98 and np.mean(share["replaced"]) >= 0.95
    assert all(got[d] <= n + 2 for v in kinds.values() for d, n in v) and sum(got.values()) <= sum(n + 2 for v in kinds.values() for _, n in v)


def test_hot_seeds_make_few_rows(spark):
    passage = gibberish(np.random.default_rng(10), 60)
    rng = np.random.default_rng(11)
    df = spark.createDataFrame([(i, " ".join(gibberish(rng, 20) + passage)) for i in range(400)], "doc_id long, text string").coalesce(1)
    found = passages.seeds(df)
    assert found.where("hub is null").groupBy("h").count().agg(F.max("count")).first()[0] == 2
    got = passages.remove_repeats(df).collect()
    assert all((r.n_removed >= 58) == (r.doc_id > 0) for r in got)


def test_window_minima_equal_brute_force():
    rng = np.random.default_rng(5)
    for n, window in [(9, 8), (40, 8), (40, 1), (25, 5), (300, 7)]:
        order = rng.integers(0, 6, n).astype(np.uint64)  # with equals
        want = sorted({int(order[i : i + window].argmin()) + i for i in range(n - window + 1)})
        assert passages._window_minima(order, window).tolist() == want


def test_extension_stops_at_once_where_nothing_agrees(monkeypatch):
    """Beside a seed that two documents share by chance, words are not compared once for each way to pass over some."""
    compared, equal = [], np.array_equal
    monkeypatch.setattr(np, "array_equal", lambda *c: compared.append(1) or equal(*c))
    x, y = np.arange(200, dtype=np.uint32), np.arange(1000, 1200, dtype=np.uint32)
    y[90:96] = x[90:96]
    start, agreeing = passages.align(x, y, np.array([90]), np.array([90]))
    assert (start, agreeing.tolist()) == (90, [True] * 6)
    assert len(compared) <= 1  # the seed itself


def test_extension_passes_over_the_fewest_words():
    """Held against every way tried in turn."""
    rng = np.random.default_rng(6)
    ways = sorted(((p, q) for p in range(5) for q in range(5) if p != q), key=lambda w: (max(w), sum(w)))
    resumed = 0
    for _ in range(2_000):
        x, y = (rng.integers(0, 2, int(rng.integers(0, 12))) for _ in range(2))
        want = next((w for w in ways if w[0] + 4 <= len(x) and w[1] + 4 <= len(y) and np.array_equal(x[w[0] : w[0] + 4], y[w[1] : w[1] + 4])), None)
        assert passages._resumed(x, y) == want
        resumed += want is not None
    assert resumed > 100


# 5: signatures


def test_least_matches_by_simulation():
    rng = np.random.default_rng(12)
    for n in (32, 128):
        draws = (rng.random((200_000, n)) < 0.75).sum(1)
        assert (draws < near_dedup.least_matches(n, 75)).mean() < 5e-5 < (draws < near_dedup.least_matches(n, 75) + 4).mean()
    sign, a = near_dedup.Signer(), rng.integers(0, 1 << 62, 1000).astype(np.uint64)
    agree = lambda x, y: np.mean([p == q for p, q in zip(sign(x)[1], sign(y)[1])])
    assert len(sign(a)[1]) == 128 and agree(a, a[::-1]) == 1 and abs(agree(a, np.concatenate([a[:800], rng.integers(0, 1 << 62, 200).astype(np.uint64)])) - 2 / 3) < 0.17


# 8: pages


PAGES = "/root/testdata/sf0.01/pages.parquet"


def test_path_sums_and_labels_equal_brute_force():
    rng = np.random.default_rng(13)
    reader = html_text.PageReader()
    page = html_text.Page("<div><p>One, two.</p><p>Three <a href=x>four</a>!</p></div><ul><li>a<li>b, c</ul>")
    got = list(zip(*(x.tolist() for x in reader.ratios(page))))
    assert page.text == ["One, two.", "Three four!", "a", "b, c"]
    assert got == [(10.0, 1.5, 4 / 20)] * 2 + [(2.5, 0.5, 0.0)] * 2
    for _ in range(60):
        n = int(rng.integers(1, 6))
        parent = [-1] + [int(rng.integers(0, i)) for i in range(1, n)]
        change = [0.0] + rng.choice([0.5, 2.0], n - 1).tolist()
        element = rng.integers(0, n, int(rng.integers(1, 6))).tolist()
        votes = rng.normal(0, 3, len(element)).tolist()

        def value(label, kept):
            return sum(v for v, k in zip(votes, kept) if k) - sum(change[e] for e in range(1, n) if label[e] != label[parent[e]]) - html_text.CHANGE * sum(label[e] != k for e, k in zip(element, kept))

        best = max(value(label, kept) for label in itertools.product([False, True], repeat=n) for kept in itertools.product([False, True], repeat=len(votes)))
        kept = reader.labels(parent, change, element, votes)
        assert abs(max(value(label, kept) for label in itertools.product([False, True], repeat=n)) - best) < 1e-9


def expected(page):
    inside = page[page.index("<article>") + 9 : page.index("</article>")]
    lines = re.split(r"<p>|</p>|</h1>", inside)
    text = [" ".join(re.sub(r"<[^>]*>", " ", line.replace("<b>", "").replace("</b>", "")).replace("&lt;", "<").replace("&gt;", ">").replace("&quot;", chr(34)).replace("&amp;", "&").split()) for line in lines]
    return "\n".join(t for t in text if t)


def test_scores_select_the_article(monkeypatch):
    pages = [h for (h,) in duckdb.sql(f"select html from '{PAGES}' where html is not null order by page_id").fetchall()]
    want = [expected(h) for h in pages]
    right = lambda source: np.mean([html_text.PageReader().text(h) == w for h, w in zip(source, want)])
    assert right(pages) == 1
    plain = [h.replace("article>", "div>") for h in pages]
    assert right(plain) >= 0.95
    monkeypatch.setattr(html_text, "MARKED", frozenset())
    assert right(pages) >= 0.98
    monkeypatch.setattr(html_text, "MARGINS", frozenset())
    assert right(pages) >= 0.98
    monkeypatch.setattr(html_text.PageReader, "scores", lambda self, page: np.ones(len(page.text)))
    assert right(pages) == 0


@pytest.mark.parametrize(
    "page",
    ["<a " + "a" * 20_000, "<" * 20_000, "<a" * 20_000, '<a "' * 20_000, '<a ="x>' * 20_000, "<a ='x" * 20_000, "<div>a" * 20_000, "<span>" * 20_000 + "<p>b" * 20_000, "<div>" * 20_000 + "</p>" * 20_000, "<!--" * 20_000,
     "<![CDATA[" * 20_000, "<p " + 'style="' * 20_000 + ">x", "<p " + "= " * 20_000 + ">x", "<script></scrip " * 20_000, "<p>" + "<b class=ad>x</b>y" * 20_000, "&" * 20_000, "<p>cut off here</p><a class=" + "story-" * 5000],
)
def test_hostile_pages_take_linear_time(page):
    began = time.perf_counter()
    html_text.PageReader().text(page)
    assert time.perf_counter() - began < 5


def test_cut_off_pages():
    text = html_text.PageReader().text
    assert text("<p>cut off here</p><a class=story-link-title-and-more") == "cut off here"
    assert text('<p>Quote stays <a href="x>open</a> here.</p><p>More.') in ("Quote stays open here.\nMore.", "Quote stays")
    assert text("<p>1 < 2 and 3 > 2, yes.") == "1 < 2 and 3 > 2, yes."


def test_words_are_the_contract_s():
    assert WORD.findall("a\x0bb\x1cc d") == ["a", "b\x1cc", "d"]
