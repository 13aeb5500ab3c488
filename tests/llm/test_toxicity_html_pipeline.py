"""Toxicity, page extraction and the pipeline."""

import random
import zlib
from collections import Counter

import numpy as np
import pytest

from temporal_rules.llm import html_blocks, minhash_dedup, mixing, toxicity


def test_index_is_exact():
    rng = random.Random(5)
    vectors = []
    for _ in range(700):
        terms = sorted(rng.sample(range(40), rng.randrange(1, 6)))
        w = np.array([rng.random() + 0.1 for _ in terms])
        vectors.append((tuple(terms), tuple(w / np.sqrt((w * w).sum()))))
    vectors += vectors[:50]
    index = toxicity.BlockMaxIndex(vectors, block=16)
    dense = np.zeros((len(vectors), 40))
    for i, (t, w) in enumerate(vectors):
        dense[i, list(t)] = w
    for q in rng.sample(vectors, 60) + [((3,), (1.0,)), ((), ())]:
        x = np.zeros(40)
        x[list(q[0])] = q[1]
        sims = np.round(dense @ x, 12)
        want = [(sims[i], int(i)) for i in np.lexsort((np.arange(len(sims)), -sims))[:7] if sims[i] > 0]
        got = index.nearest(*q, 7)
        assert [i for _, i in got] == [i for _, i in want] and [s for s, _ in got] == pytest.approx([s for s, _ in want])


def test_isotonic_is_monotone_and_likelihood_ratio():
    x = np.array([0.1, 0.2, 0.3, 0.4, 0.5, 0.6])
    at, to = toxicity.isotonic(x, np.array([0, 1, 0, 1, 1, 1.0]))
    assert (np.diff(to) >= 0).all() and to[0] < 0.5 < to[-1] and len(at) == len(to)
    assert toxicity.likelihood_ratio(10, 90, 100, 900) == pytest.approx(0, abs=1e-9)
    assert toxicity.likelihood_ratio(50, 0, 100, 900) > 200


def test_held_out_accuracy(spark):
    d = "/root/testdata/sf0.1"
    from temporal_rules.llm.queries import op6_toxicity

    got = {r.doc_id: r for r in op6_toxicity(spark, d).collect()}
    assert all((zlib.crc32(str(i).encode()) % 5 == 0) == r.held_out and 0 <= r.score <= 1 and r.predicted == int(r.score >= 0.5) for i, r in got.items())
    labels = [(r.toxic, got[r.doc_id]) for r in spark.read.parquet(f"{d}/labels.parquet").collect() if got[r.doc_id].held_out]
    hit = sum(y and r.predicted for y, r in labels)
    assert hit >= 0.8 * sum(y for y, _ in labels) and hit >= 0.9 * sum(r.predicted for _, r in labels)


def test_toxicity_odd_rows(spark):
    docs = [(i, ("foul" if i % 4 == 0 else "fine") + f" word{i} text", "x") for i in range(400)] + [(None, None, None), (900, "", None), (901, "foul " * 40_000, "y"), (4, "foul again", "x")]
    docs = spark.createDataFrame(docs, "doc_id long, text string, score string")
    labels = spark.createDataFrame([(i, int(i % 4 == 0), 5) for i in range(300)] + [(3, None, 1), (None, 1, 1), (8, 1, 1)], "doc_id long, toxic int, text int")
    scorer = toxicity.fit(docs, labels)
    got = toxicity.score_documents(docs, scorer).collect()
    assert len(got) == 404
    by = {r.doc_id: r for r in got if r.doc_id != 4}
    assert by[396].predicted == 1 and by[397].predicted == 0 and by[901].predicted == 1 and by[None].predicted == by[900].predicted == 0
    assert by[396].evidence and all(e.toxic == 1 for e in by[396].evidence)
    kept = toxicity.without_toxic(docs, scorer)
    assert kept.columns == docs.columns and {r.doc_id for r in kept.collect()} == {r.doc_id for r in got if not r.predicted}
    nothing = toxicity.fit(docs, labels.limit(0))
    assert {r.score for r in toxicity.score_documents(docs, nothing).collect()} == {0.0}
    assert toxicity.score_documents(docs.limit(0), scorer).collect() == []


PARAGRAPH = "This is the text of a story that was told in the town, and it is long enough to be the main part of what a page says to us. "


def test_marked_article():
    page = f"""<!DOCTYPE html><html><head><title>T</title><script>var a="</p>";</script></head><body class="no-sidebar">
    <header><h1>Site</h1></header><nav><ul><li><a href="/a">Home</a></li></ul></nav><div class="cookie-notice">We use cookies on this site.</div>
    <div class="ad">Buy now.</div><article><h1>The &amp;amp; head&eacute;</h1><p><b>{PARAGRAPH}<br><p>Be.
    Erin.</p><!-- c --><form>Name <input name=x></form><aside>Aside</aside><table><tr><td>one<td>two</table>
    <p>A <a href="x">link</a> in&nbsp;&nbsp;it, a < b &lt;c&gt;.</p><pre>x   y</pre><div id="comments"><p>{PARAGRAPH}</p></div></article>
    <div class="sidebar"><p>{PARAGRAPH}</p></div><footer>&copy; us</footer></body></html>"""
    assert html_blocks.main_text(page) == "\n\n".join(["The &amp; headé", PARAGRAPH.strip(), "Be. Erin.", "one", "two", "A link in it, a < b <c>.", "x y"])


def test_unmarked_page_by_rules():
    page = f"""<body><div><a href=1>News</a> <a href=2>Sport</a></div><h2>A short head</h2><p>{PARAGRAPH * 2}</p><p>Yes.</p><p>{PARAGRAPH * 2}</p>
    <div><a href=1>one more</a> <a href=2>and more of them</a></div><p>Tail.</p><div>© 2020 All rights</div>"""
    assert html_blocks.main_text(page) == "\n\n".join(["A short head", (PARAGRAPH * 2).strip(), "Yes.", (PARAGRAPH * 2).strip()])


@pytest.mark.parametrize("page,text", [(None, ""), ("", ""), ("plain words", "plain words"), ("<p>", ""), ("<", "<"), ("<!-- open", ""), ("<p class='a>b", "b"), ("<script>x", ""), ("a<br>b", "a b"), ("&#55296;", "�")])
def test_odd_pages(page, text):
    assert html_blocks.main_text(page) == text


def test_pages_table(spark, sf):
    import re

    from temporal_rules.llm.queries import op4_main_text

    rows = op4_main_text(spark, sf).collect()
    pages = {r.page_id: r.html for r in spark.read.parquet(f"{sf}/pages.parquet").collect()}
    assert len(rows) == len(pages)
    for r in rows:
        inner = re.search(r"<article>(.*?)(</article>|\Z)", pages[r.page_id], re.S)[1]
        import html

        want = [" ".join(html.unescape(re.sub(r"<[^>]*>", " ", x)).split()) for x in re.split(r"</?(?:p|h1)>", inner)]
        assert r.text == "\n\n".join(x for x in want if x) and r.n_chars == len(r.text)


def test_pages_odd_rows(spark):
    from pyspark.sql import functions as F

    df = spark.createDataFrame([(1, None, None, 3), (None, "u", "", 3), (2, "u", "<p>" + PARAGRAPH * 20_000, 3), (2, "u", "<p>x", 3)], "page_id long, url string, html string, text int")
    got = html_blocks.extract(df)
    assert got.columns == ["page_id", "url", "text", "n_chars"] and Counter(r.n_chars for r in got.collect()) == Counter([0, 0, len(PARAGRAPH) * 20_000 - 1, 1])
    assert html_blocks.extract(df.where(F.lit(False))).collect() == []


def test_mixed_documents_follow_the_mix(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    taken = Counter()
    for r in mixing.taken_words(mixing.mix(docs)).collect():
        taken[r.doc_id] += r.taken
    got = mixing.mixed_documents(docs)
    assert got.columns == docs.columns
    have, texts = Counter(), {r.doc_id: r.text for r in docs.collect()}
    for r in got.collect():
        have[r.doc_id] += len(r.text.encode().split())
        assert texts[r.doc_id].startswith(r.text) and r.n_chars == len(r.text)
    assert have == Counter({k: v for k, v in taken.items() if v})
    twice = docs.limit(5).unionByName(docs.limit(5))
    assert sum(len(r.text.split()) for r in mixing.mixed_documents(twice).collect()) == sum(r.taken for r in mixing.taken_words(mixing.mix(twice)).collect())
    assert mixing.mixed_documents(docs.limit(0)).collect() == []


def test_one_of_each(spark):
    df = spark.createDataFrame([(1, "a b c", 1), (1, "a b c", 2), (2, "a b c", 3), (3, "other words here", 4), (None, "a b c", 5), (None, "a b c", 6)], "doc_id long, text string, n int")
    got = minhash_dedup.one_of_each(df)
    assert got.columns == df.columns and Counter(r.doc_id for r in got.collect()) == Counter([1, 3, None, None])


def test_pipeline(spark, sf):
    import corpus_pipeline

    docs = spark.read.parquet(f"{sf}/documents.parquet")
    texts = {r.doc_id: r.text for r in docs.collect()}
    at = docs
    counts = []
    for name, stage in corpus_pipeline.STAGES[:-1]:
        at = stage(spark, at, sf)
        assert at.columns == docs.columns
        at = spark.createDataFrame(at.collect(), docs.schema)
        counts.append(at.count())
    assert counts[1] < counts[0] <= len(texts)
    clean = [r.doc_id for r in at.collect()]
    out = corpus_pipeline.run(spark, sf).collect()
    assert {r.doc_id for r in out} == set(clean)
    per = Counter()
    for r in out:
        per[r.sequence_id] += r.length
    assert max(per.values()) <= 1024
