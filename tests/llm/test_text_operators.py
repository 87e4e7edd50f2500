"""The operators of the text subpackage against brute force, on small tables with every odd case."""

import base64
import hashlib
import zlib
from collections import Counter, defaultdict

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st
from pyspark.sql import functions as F

import public_tokenizers as P
from tests_llm_shared import brute_components, brute_lines, clip_ids, shingle_set
from treesketch.llm import byte_bpe, components, factorization, hnsw, html_text, line_dedup, near_dedup, packing, passages, prefix_forest, sharding, token_shards, wordhash, wordpieces

SCHEMA = "doc_id long, text string, dk string, n_chars long"
ODD = [
    (1, "The first line\nshared line\nthe last"), (2, None), (3, ""), (4, "shared line \n\n\n"), (5, "SHARED LINE"), (6, "a"), (6, "a"), (7, "  \t\n"), (None, "no id, shared line\nshared line"),
    (None, None), (8, "x" * 70_000), (9, "word " * 30_000), (-5, "é É ß İ Σ 漢字 'll \x0b   <|endoftext|> 😀"), (10, "The first line\nshared line\nthe last"),
]


@pytest.fixture(scope="module")
def odd(spark):
    return spark.createDataFrame([(d, t, "clash", 0) for d, t in ODD], SCHEMA).repartition(3)


@pytest.fixture(scope="module")
def empty(spark):
    return spark.createDataFrame([], SCHEMA)


# 1 nearest neighbours


def vectors(spark, rows):
    return spark.createDataFrame(rows, "vec_id long, embedding array<float>, id string")


def test_forest_finds_inner_products_of_any_length(spark):
    rng = np.random.default_rng(2)
    x = (rng.standard_normal((700, 12)) * rng.lognormal(0, 1, (700, 1))).astype(np.float32)
    df = vectors(spark, [(i, v.tolist(), "z") for i, v in enumerate(x)])
    got = defaultdict(list)
    for r in prefix_forest.nearest_neighbours(df, df.where("vec_id % 20 = 0"), k=10, shards=3).collect():
        got[r.query_id].append((r["rank"], r.vec_id, r.score))
    hits = 0
    for q in range(0, 700, 20):
        s = x.astype(float) @ x[q].astype(float)
        s[q] = -np.inf
        mine = sorted(got[q])
        assert [r for r, _, _ in mine] == list(range(1, 11))
        assert all(abs(sc - s[v]) < 1e-9 * max(1, abs(s[v])) for _, v, sc in mine)
        assert [(-sc, v) for _, v, sc in mine] == sorted((-sc, v) for _, v, sc in mine)
        hits += len({v for _, v, _ in mine} & set(np.argsort(-s)[:10].tolist()))
    assert hits >= 0.95 * 350


def test_forest_odd_vectors(spark):
    rows = [(0, [1.0, 0.0], ""), (1, [1.0, 0.0], ""), (2, None, ""), (3, [0.0, 0.0], ""), (4, [float("nan"), 1.0], ""), (5, [float("inf"), 1.0], ""), (6, [None, 1.0], ""), (None, [1.0, 0.0], ""), (7, [], ""), (8, [2.0, 0.0], ""), (8, [2.0, 0.0], ""), (9, [1.0, 1.0, 1.0], "")]
    df = vectors(spark, rows)
    got = sorted((r.query_id, r["rank"], r.vec_id, r.score) for r in prefix_forest.nearest_neighbours(df, df, k=5).collect())
    assert got == [(0, 1, 8, 2.0), (0, 2, 1, 1.0), (1, 1, 8, 2.0), (1, 2, 0, 1.0), (8, 1, 0, 2.0), (8, 2, 1, 2.0)]
    assert prefix_forest.nearest_neighbours(df.where("false"), df.where("false")).count() == 0


# 2 quality


def quality_rows(n):
    rng = np.random.default_rng(5)
    out = []
    for i in range(n):
        words = ["".join(rng.choice(list("abcdefg"), rng.integers(2, 8))) for _ in range(rng.integers(20, 60))]
        good = int(rng.random() < 0.7)
        out.append((i, " ".join(words) + "." if good else " | ".join(w.upper() for w in words), good))
    return out


def test_quality_on_held_out_rows(spark):
    rows = quality_rows(600)
    docs = spark.createDataFrame([(i, t) for i, t, _ in rows] + [(9001, None), (9002, ""), (9003, "b " * 60_000), (None, "abc")], "doc_id long, text string")
    labels = spark.createDataFrame([(i, g) for i, _, g in rows] + [(None, 1), (3, None), (77_777, 0)], "doc_id long, label int")
    model = factorization.fit_quality(docs, labels)
    got = [(r.doc_id, r.score) for r in factorization.score_quality(docs, model).collect()]
    assert len(got) == len(rows) + 4 and all(0 <= s <= 1 for _, s in got)
    truth = {i: g for i, _, g in rows}
    held = [(s >= 0.7) == truth[d] for d, s in got if d in truth and zlib.crc32(str(d).encode()) % 4 == 2]
    assert np.mean(held) > 0.95


def test_interactions_equal_the_sum_over_pairs():
    rng = np.random.default_rng(0)
    m = factorization.FactorizationMachine(np.zeros(2), np.ones(2), 0.3, rng.standard_normal(6), rng.standard_normal((6, 3)))
    index, value = np.array([0, 1, 4]), np.array([0.5, -1.0, 2.0])
    want = 0.3 + m.linear[index] @ value + sum(m.factors[index[i]] @ m.factors[index[j]] * value[i] * value[j] for i in range(3) for j in range(i))
    assert abs(m.margins(index, value, np.array([0]))[0] - want) < 1e-12


def test_one_label_gives_a_constant(spark):
    docs = spark.createDataFrame([(1, "a b"), (2, "c")], "doc_id long, text string")
    model = factorization.fit_quality(docs, spark.createDataFrame([(1, 1), (2, 1)], "doc_id long, label int"))
    assert len({round(r.score, 2) for r in factorization.score_quality(docs, model).collect()}) == 1


# 3 passages


def gibberish(rng, n, vocabulary=5000):
    return [f"w{int(x)}" for x in rng.integers(0, vocabulary, n)]


def test_shared_passages_are_removed_from_later_documents(spark):
    rng = np.random.default_rng(3)
    passage, fuzzy = gibberish(rng, 80), gibberish(rng, 90)
    edited = list(fuzzy)
    edited[30], edited[61] = "changed", "changed2"
    del edited[45]
    clean = [gibberish(rng, 200) for _ in range(6)]
    texts = [
        (1, clean[0][:100] + passage + clean[0][100:]), (2, clean[1][:50] + passage + clean[1][50:]), (3, passage + clean[2]), (4, fuzzy + clean[3]), (5, clean[4] + edited), (6, clean[5]),
        (7, clean[5][:30] + gibberish(rng, 30)),
    ]
    docs = spark.createDataFrame([(d, " ".join(t), "c") for d, t in texts] + [(None, " ".join(passage), "c"), (8, None, "c"), (9, "", "c")], "doc_id long, text string, n_words string")
    got = {r.doc_id: r for r in passages.remove_repeats(docs).collect()}
    assert got[1].n_removed == 0 and got[6].n_removed == 0 and got[7].n_removed == 0 and got[4].n_removed == 0
    assert 78 <= got[2].n_removed <= 82 and got[2].text.split()[:49] == clean[1][:49] and got[2].text.split()[-140:] == clean[1][-140:]
    assert 78 <= got[3].n_removed <= 82 and 84 <= got[5].n_removed <= 92
    assert got[None].text == " ".join(passage) and got[8].text is None and got[9].text == ""


def test_chain_equals_brute_force():
    rng = np.random.default_rng(1)
    for _ in range(60):
        n = int(rng.integers(1, 9))
        a, b = rng.integers(0, 60, n), rng.integers(0, 60, n)
        value = {}
        for i in np.lexsort((b, a)).tolist():
            before = [value[j] - 0.1 * float(a[i] - a[j] + b[i] - b[j]) for j in value if a[j] < a[i] and b[j] < b[i]]
            value[i] = 6 + max([0.0, *before])
        steps = passages.chain(a, b, 6, 0.1, 1000)[0]
        got = sum(6 - (0.1 * float(a[j] - a[i] + b[j] - b[i]) if i is not None else 0) for i, j in zip([None, *steps[:-1]], steps))
        assert abs(got - max(value.values())) < 1e-9
        assert all(a[i] < a[j] and b[i] < b[j] for i, j in zip(steps, steps[1:]))


def test_alignment_passes_small_edits():
    x = np.arange(100, dtype=np.uint32)
    y = np.concatenate([np.arange(500, 520), x[10:40], [999], x[41:90]]).astype(np.uint32)
    start, agreeing = passages.align(x, y, np.array([12, 60]), np.array([22, 70]))
    assert start == 10 and len(agreeing) == 80 and agreeing.sum() == 79 and not agreeing[30]
    assert passages.repeated_parts(agreeing) == [(0, 80)]
    assert len(passages.align(x, y + 1000, np.array([12, 60]), np.array([22, 70]))[1]) == 0  # seeds whose words differ


# 4 and 6 token output and packing


def test_encoder_equals_the_library():
    rng = np.random.default_rng(4)
    alphabet = ["a", "Be", "É", "é", "İ", "ß", "Σ", "1", "²", "'s", "'", ".", ",", "..", "_", "%%", " ", " ", "\n", "\t", "é", "漢", "😀", "<|endoftext|>", "\r", "\x85", "|", "ŉ"]
    texts = ["".join(rng.choice(alphabet, rng.integers(0, 20))) for _ in range(4000)] + [None, "", "Word.\x1c", "U.S.\x1c"]
    encoder = wordpieces.WordPieceEncoder(P.path("word_bpe_49k.json"), keep=50)
    got = encoder.encode(texts)
    assert [np.frombuffer(g, "<u2").tolist() for g in got] == [e.ids for e in encoder.tokenizer.encode_batch([t or "" for t in texts], add_special_tokens=False)]
    assert encoder.encode(texts) == got


@settings(max_examples=60, deadline=None)
@given(st.lists(st.integers(0, 10**6), max_size=400), st.integers(0, 10**6))
def test_elias_fano(values, more):
    values = sorted(values)
    ef = token_shards.EliasFano.of(np.array(values, np.uint64), (values[-1] if values else 0) + more)
    again = token_shards.EliasFano.from_bytes(ef.to_bytes())
    assert again.values().tolist() == values and [again.select(i) for i in range(len(values))] == values
    assert len(ef.to_bytes()) * 8 <= 8 * (21 + 4 * (len(values) // 128 + 1) + 3) + len(values) * (3 + max(0, (max(1, ef.universe) // max(1, len(values))).bit_length()))


def test_token_dataset_round_trip(spark, odd, empty, tmp_path):
    path = token_shards.write_token_dataset(odd, f"{tmp_path}/a", end_id=2, shards=4, block_tokens=64)
    by_id = {d: sorted((r.start, r.n_tokens, bytes(r.ids)) for r in token_shards.read_document(spark, path, d).collect()) for d in (1, 6, -5, 9, 77)}
    everything = token_shards.read_token_dataset(spark, path).collect()
    assert by_id == {d: sorted((r.start, r.n_tokens, bytes(r.ids)) for r in everything if r.doc_id == d) for d in by_id} and len(by_id[6]) == 2 and not by_id[77]
    got = token_shards.read_token_dataset(spark, path).collect()
    order = sorted(got, key=lambda r: r.start)
    assert sum(r.n_tokens for r in order) == order[-1].start + order[-1].n_tokens
    assert [r.start for r in order] == np.cumsum([0] + [r.n_tokens for r in order])[:-1].tolist()
    ids = [r.doc_id for r in order]
    assert ids == sorted(ids, key=lambda d: (d is not None, d or 0))
    want = Counter((d, tuple(clip_ids(t) + [2])) for d, t in ODD)
    assert Counter((r.doc_id, tuple(np.frombuffer(r.ids, "<u4").tolist())) for r in got) == want
    assert token_shards.read_token_dataset(spark, token_shards.write_token_dataset(empty, f"{tmp_path}/b")).count() == 0


def test_packing(spark, odd, empty):
    got = packing.pack_pieces(packing.token_pieces(odd, capacity=64), capacity=64, pieces_per_task=50).collect()
    by_doc, bins = defaultdict(list), defaultdict(list)
    for r in got:
        by_doc[r.doc_id].append((r.piece, r.start, r.length, r.ids))
        bins[r.sequence_id].append((r.offset, r.length))
    for places in bins.values():
        at = 0
        for offset, length in sorted(places):
            assert offset == at
            at += length
        assert at <= 64
    want = [clip_ids(t) + [1] for d, t in ODD if d == 9][0]
    ids = np.frombuffer(b"".join(p[3] for p in sorted(by_doc[9])), "<u4").tolist()
    assert ids == want and [p[1] for p in sorted(by_doc[9])] == list(range(0, len(want), 64))
    assert packing.pack_pieces(packing.token_pieces(empty)).count() == 0


@settings(max_examples=40, deadline=None)
@given(st.lists(st.integers(1, 50), min_size=1, max_size=200))
def test_sum_of_squares_choice(lengths):
    """Every placement leaves the sum of squared gap counts as small as any open sequence would."""
    sequence, offset = packing.sum_of_squares_pack(np.array(lengths), 50)
    used = defaultdict(int)
    for i in np.argsort(-np.array(lengths), kind="stable"):
        size, gaps = lengths[i], {b: 50 - u for b, u in used.items()}
        count = Counter(g for g in gaps.values() if g)

        def after(g):
            c = count.copy()
            c[g] -= 1
            if g > size:
                c[g - size] += 1
            return sum(v * v for v in c.values())

        fits = [g for g in set(gaps.values()) if g >= size]
        if fits:
            assert int(sequence[i]) in used and after(gaps[int(sequence[i])]) == min(map(after, fits))
        else:
            assert int(sequence[i]) not in used
        assert offset[i] == used[int(sequence[i])]
        used[int(sequence[i])] += size
    assert max(used.values()) <= 50


# 5 near duplicates

def edited(rng, words, edits):
    words = list(words)
    for i in rng.integers(0, len(words), edits):
        words[i] = f"e{int(rng.integers(1e9))}"
    return words


def test_near_duplicates_equal_brute_force(spark):
    rng = np.random.default_rng(8)
    base = [gibberish(rng, 150) for _ in range(8)]
    texts = [" ".join(edited(rng, b, int(rng.integers(0, 9)))) for b in base for _ in range(25)]
    texts += ["Same text", "same  TEXT", "same text other", "a b c d e", "A b c d\te", " ".join(base[0][:60])] * 2
    common = " ".join(gibberish(rng, 60))
    texts += [common + " " + " ".join(gibberish(rng, 40)) for _ in range(30)]
    rows = list(enumerate(texts))
    got = near_dedup.near_duplicates(spark.createDataFrame(rows, "doc_id long, text string").repartition(5)).collect()
    want = brute_components(rows)
    assert {r.doc_id: r.component_id for r in got} == want
    assert all(r.kept == (r.doc_id == r.component_id) and r.n_shingles == len(shingle_set(texts[r.doc_id])) for r in got)


def test_texts_alike_below_the_threshold_make_few_rows(spark, monkeypatch):
    rng = np.random.default_rng(9)
    base = gibberish(rng, 150)
    rows = list(enumerate(" ".join(edited(rng, base, 4)) for _ in range(200)))
    made, write = {}, near_dedup.materialize

    def counted(df, name, **options):
        out = write(df, name, **options)
        made[name] = max(made.get(name, 0), out.count())
        return out

    monkeypatch.setattr(near_dedup, "materialize", counted)
    got = near_dedup.near_duplicates(spark.createDataFrame(rows, "doc_id long, text string").repartition(5)).collect()
    want = brute_components(rows)
    assert {r.doc_id: r.component_id for r in got} == want and len(set(want.values())) > 50
    assert made["asked"] < 10 * len(rows) and made["links"] < 2 * len(rows)


def test_near_duplicates_odd_rows(spark, odd, empty):
    got = near_dedup.near_duplicates(odd).collect()
    assert len(got) == len(ODD)
    by = defaultdict(set)
    for r in got:
        by[r.doc_id].add((r.n_shingles, r.component_id, r.kept))
    assert by[10] == {(3, 1, False)} and by[3] == {(0, 3, True)} and by[2] == {(0, 2, True)} and by[6] == {(1, 6, True)} and by[9] == {(1, 9, True)}
    assert {(c, k) for _, c, k in by[None]} == {(None, True)}
    assert near_dedup.near_duplicates(empty).count() == 0


def test_components(spark):
    rng = np.random.default_rng(0)
    edges = [(i, i + 1) for i in range(40)] + [(100, i) for i in range(101, 160)] + [(500, 500), (7, 3), (3, 7)] + [tuple(map(int, rng.integers(1000, 1400, 2))) for _ in range(250)]
    parent = {}

    def find(x):
        parent.setdefault(x, x)
        while parent[x] != x:
            x = parent[x]
        return x

    for a, b in edges:
        a, b = find(a), find(b)
        parent[max(a, b)] = min(a, b)
    got = {r.vertex: r.component for r in components.connected_components(spark.createDataFrame(edges, "a long, b long")).collect()}
    assert got == {v: find(v) for v in list(parent)}
    assert components.connected_components(spark.createDataFrame([], "a long, b long")).count() == 0


def test_scratch_tables_can_be_released(spark):
    from treesketch.llm import storage

    kept = storage.materialize(spark.range(5), "test")
    assert kept.count() == 5 and storage.release_scratch(spark) >= 1 and storage.release_scratch(spark) == 0


def test_word_hashes_do_not_depend_on_place_or_window(monkeypatch):
    h = wordhash.WordHasher()
    raw = ("alpha Beta\tgamma\x0bdelta " * 50 + "x" * 5000 + " end").encode()
    whole = h.words(raw)
    monkeypatch.setattr(wordhash, "WINDOW", 64)
    assert wordhash.WordHasher.words.__globals__["WINDOW"] == 64 and np.array_equal(h.words(raw), whole)
    assert len(np.unique(whole)) == 6 and h.words(b"BETA")[0] == h.words(b" \n beta ")[0] != h.words("betá".encode())[0]


# 7 lines


@pytest.mark.parametrize("least", [1, 2, 3, 4])
def test_lines_equal_brute_force(odd, least):
    got = line_dedup.drop_lines(odd, line_dedup.keep_bitmaps(odd, min_docs=least))
    assert set(got.columns) >= {"doc_id", "text", "dk", "n_chars"}
    assert Counter((r.doc_id, r.n_lines, r.n_dropped, r.text) for r in got.collect()) == brute_lines(ODD, least)


def test_lines_of_large_keys_go_by_shuffle(odd, monkeypatch):
    monkeypatch.setattr(line_dedup, "BROADCAST_KEYS", 0)
    got = line_dedup.drop_lines(odd, line_dedup.keep_bitmaps(odd, min_docs=2))
    assert Counter((r.doc_id, r.n_lines, r.n_dropped, r.text) for r in got.collect()) == brute_lines(ODD, 2)


def test_first_occurrences_stay(spark, empty):
    docs = spark.createDataFrame([(2, "b\na\na"), (1, "a\nc"), (3, "\n".join(["z"] * 130 + ["c"]))], "doc_id long, text string")
    got = {r.doc_id: r.text for r in line_dedup.drop_lines(docs, line_dedup.keep_bitmaps(docs, min_docs=1, keep="first")).collect()}
    assert got == {1: "a\nc", 2: "b", 3: "z"}
    assert line_dedup.drop_lines(empty, line_dedup.keep_bitmaps(empty)).count() == 0


# 8 pages

PAGE = """<html><head><title>T</title><style>p{}</style></head><body><header>Site</header><nav><ul><li>Menu</li></ul></nav>
<div class="ad">Buy, now. Cheap, good.</div><article><h1>Head&amp;line</h1><p>First <b>bold</b> words,
and&nbsp;more.<br>Next, line.<p>Second one, here. <script>var a="</p>";</script><div class="sidebar-box">no</div>
<ul><li>Item one, short.<li>Item two</ul><form>no</form><div id="comments"><p>me too, and much longer than all the rest. Really, it is.</p></div></article><footer>&copy; us</footer></body></html>"""


@pytest.mark.parametrize(
    "page, text",
    [
        (PAGE, "Head&line\nFirst bold words, and more. Next, line.\nSecond one, here.\nItem one, short.\nItem two"), (None, ""), ("", ""), ("<div></div>", ""), ("only text &lt;b>", "only text <b>"),
        ("<body><div class=menu>a</div><div><p>One, two. Three, four.</p><h2>Sub</h2><p>Five, six.</p></div></body>", "One, two. Three, four.\nSub\nFive, six."), ("<p>a<!-- x --></p><p>b", "a\nb"),
    ],
)
def test_pages(page, text):
    assert html_text.PageReader().text(page) == text


def test_pages_as_a_table(spark):
    df = spark.createDataFrame([(1, "u", PAGE, "x"), (2, None, None, "x"), (None, "v", "<p>" + "a " * 50_000, "x")], "page_id long, url string, html string, text string")
    got = {r.page_id: r for r in html_text.extract_main_text(df).collect()}
    assert got[2].text == "" and got[1].text.startswith("Head&line") and len(got[None].text) == 99_999


# 9 near-duplicate vectors


def test_vectors_equal_brute_force(spark):
    rng = np.random.default_rng(6)
    x = rng.standard_normal((500, 16))
    x[100:160] = x[0] + 0.1 * rng.standard_normal((60, 16))
    x[200:230] = x[5] * np.linspace(0.5, 2, 30)[:, None]
    x[300:310] = x[7]
    rows = [(i, v.tolist(), "q") for i, v in enumerate(x.astype(np.float32))]
    v = x.astype(np.float32).astype(float)
    v /= np.linalg.norm(v, axis=1)[:, None]
    near = v @ v.T >= 0.95
    np.fill_diagonal(near, False)
    label = np.arange(500)
    for _ in range(50):
        label = np.array([min([label[i], *label[near[i]]]) for i in range(500)])
    rows += [(900, None, "q"), (901, [0.0] * 16, "q"), (902, [float("nan")] * 16, "q"), (None, x[7].tolist(), "q"), (903, [1.0, 2.0], "q"), (904, [], "q")]
    got = {r.vec_id: (r.n_links, r.component_id, r.kept) for r in hnsw.near_duplicate_vectors(vectors(spark, rows), shards=3).collect()}
    assert {i: got[i] for i in range(500)} == {i: (int(near[i].sum()), int(label[i]), bool(label[i] == i)) for i in range(500)}
    assert all(got[i] == (0, i, True) for i in (900, 901, 902, 903, 904)) and got[None] == (0, None, True)
    assert hnsw.near_duplicate_vectors(vectors(spark, [])).count() == 0


def test_graph_recall():
    rng = np.random.default_rng(1)
    x = sharding.unit_vectors(rng.standard_normal((3000, 24)))
    graph = hnsw.SmallWorld(x)
    ids, _ = graph.search(x[:200], 48)
    truth = np.argsort(-(x[:200] @ x.T), axis=1)[:, :10]
    assert np.mean([len(set(a) & set(b)) for a, b in zip(ids.tolist(), truth.tolist())]) >= 9


# 10 byte-level BPE


def test_byte_bpe_equals_tiktoken(spark, odd, empty):
    import tiktoken

    ranks = {base64.b64decode(a): int(b) for a, b in map(bytes.split, open(P.path("byte_bpe_multi_50k.tiktoken"), "rb"))}
    want = tiktoken.Encoding("own", pat_str=P.PATTERN, mergeable_ranks=ranks, special_tokens={})
    got = byte_bpe.decode_byte_bpe(byte_bpe.encode_byte_bpe(odd)).collect()
    assert Counter((r.doc_id, tuple(r.ids), bytes(r.decoded)) for r in got) == Counter((d, tuple(want.encode_ordinary(t or "")), (t or "").encode()) for d, t in ODD)
    assert byte_bpe.encode_byte_bpe(empty).count() == 0
    rng = np.random.default_rng(0)
    coder = byte_bpe.ByteBpe(P.path("byte_bpe_multi_50k.tiktoken"), P.PATTERN, keep=10)
    texts = ["".join(chr(int(c)) for c in rng.choice([*range(32, 126), 0, 10, 9, 0xE9, 0x3B1, 0x4E2D, 0x1F600, 0x301, 0x2581, 0x100], rng.integers(0, 40))) for _ in range(1500)]
    assert [x.tolist() for x in coder.encode(texts)] == [want.encode_ordinary(t) for t in texts]


def test_model_needs_all_bytes():
    with pytest.raises(ValueError):
        byte_bpe.sentencepiece_model({b"a": 0})


def test_digest_forms(spark, odd):
    row = byte_bpe.encode_byte_bpe(odd.where("doc_id = 1")).select(F.sha2(F.array_join("ids", ","), 256).alias("h"), "ids").first()
    assert row.h == hashlib.sha256(",".join(map(str, row.ids)).encode()).hexdigest()
