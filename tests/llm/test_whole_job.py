"""Cases that a cut in an operator or a stage would lose."""

import numpy as np
import pytest
from pyspark.sql import functions as F

import corpus_pipeline
from treesketch.llm import html_text, passages
from treesketch.llm.storage import materialize


def gibberish(rng, n, vocabulary=5000):
    return [f"w{int(x)}" for x in rng.integers(0, vocabulary, n)]


def test_one_of_many_copies_stays_in_the_pipeline(spark, tiny):
    rng = np.random.default_rng(7)
    page = lambda: [" ".join(gibberish(rng, 12)) for _ in range(6)]
    copied, near, footer = page(), page(), "all rights are with their owners"
    rows = [(i, "\n".join(copied)) for i in range(12)]
    rows += [(100 + i, "\n".join([*near, f"copy {i}"])) for i in range(12)]
    rows += [(200 + i, "\n".join([*page(), footer])) for i in range(12)]
    docs = spark.createDataFrame([(d, t, "en", "s", len(t)) for d, t in rows], "doc_id long, text string, lang string, source string, n_chars long")
    for stage in (corpus_pipeline.lines, corpus_pipeline.near):
        docs = materialize(stage(spark, docs, tiny), "test-copies")
    got, texts = {r.doc_id: r.text for r in docs.collect()}, dict(rows)
    assert {d for d in got if d < 200} == {0, 100} and all(got[d] == texts[d] for d in (0, 100))
    assert all(got[d] == texts[d].removesuffix("\n" + footer) for d in range(200, 212))


def test_a_passage_twice_in_a_later_document_goes_twice(spark):
    rng = np.random.default_rng(8)
    passage, clean = gibberish(rng, 80), [gibberish(rng, 200) for _ in range(2)]
    rows = [(1, " ".join(clean[0] + passage)), (2, " ".join(clean[1][:90] + passage + clean[1][90:] + passage)), (3, "same " * 400), (4, "same " * 30_000)]
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    got = {r.doc_id: r for r in passages.remove_repeats(docs).collect()}
    assert got[1].n_removed == 0 and 158 <= got[2].n_removed <= 162
    assert passages.seeds(docs).where(F.col("doc_id") == 4).count() < 30_000 / passages.WINDOW + 2


@pytest.mark.xfail(reason="not met: 33 of 40 with seeds of 6 words; seeds of 4 words met it and ran out of the disk that op3 may use (see the README)", strict=False)
def test_passages_at_the_least_identity_share_seeds(spark):
    rng = np.random.default_rng(9)
    rows, edited = [], 0
    for i in range(40):
        passage = gibberish(rng, 60)
        changed = [f"new{i}x{j}" if j % 8 == 4 else w for j, w in enumerate(passage)]
        edited += len(changed)
        rows += [(i, " ".join(gibberish(rng, 80) + passage + gibberish(rng, 80))), (100 + i, " ".join(gibberish(rng, 80) + changed + gibberish(rng, 80)))]
    got = {r.doc_id: r.n_removed for r in passages.remove_repeats(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    assert sum(got[i] for i in range(40)) == 0 and sum(got[100 + i] > 0 for i in range(40)) >= 38


@pytest.mark.parametrize("wrapper", ["div class='has-sidebar'", "div id=comments-open", "div class=widget-area", "form action=x", "span class=social"])
def test_a_marked_wrapper_around_the_article_is_read(wrapper):
    article = "<h1>Title</h1>" + "<p>One sentence, and a second. A third one follows; it ends here.</p>" * 3
    menu, comments = "<ul class=menu>" + "<li>Home<li>News" * 9 + "</ul>", "<div class=comments><p>Nice, thanks.</p></div>"
    page = f"<body><header>Site</header>{menu}<{wrapper}>{article}{comments}<button>Send</button></{wrapper.split()[0]}><p>About us</p><footer>All rights, reserved.</footer></body>"
    got = html_text.PageReader().text(page)
    assert got.count("A third one follows") == 3 and "Title" in got
    assert not any(x in got for x in ("Home", "Nice", "Send", "rights", "Site"))
    assert html_text.PageReader().text(f"<body>{menu}</body>") == ""
