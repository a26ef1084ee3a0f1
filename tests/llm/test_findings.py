"""Small inputs on which operators once did less than the whole job."""

import pytest

pytest.importorskip("ordsum.llm")
from ordsum.llm import language_id, spans, wrappers  # noqa: E402


def cut(spark, *texts):
    """What op6 leaves of texts given under ids 1, 2 and so on."""
    df = spark.createDataFrame(list(enumerate(texts, 1)), "doc_id bigint, text string")
    return {r.doc_id: r.text for r in spans.op6_spans(df).collect()}


def test_spans_of_one_word_sentences(spark):
    passage = " ".join(f"word{i}!!" for i in range(60))
    got = cut(spark, f"Start of one. {passage} Own end.", f"Another start. {passage} Last words here.")
    assert passage in got[1] and got[2] == "Another start. Last words here."


def test_spans_reach_both_ends_of_a_passage(spark):
    body = "A sentence of twenty words or more stands here, between short ones, as it must, and has the greater part of all words."
    passage = f"One. Two. {body} Three. Four. Five."
    got = cut(spark, f"Start of one. {passage} Own end.", f"Another start. {passage} Last words here.")
    assert passage in got[1] and got[2] == "Another start. Last words here."


def test_every_unit_of_a_passage_is_under_a_run():
    import random

    pick = random.Random(5)
    for _ in range(300):
        sizes = [pick.choice((1, 1, 2, 3, 6, 12)) for _ in range(pick.randint(1, 12))]
        _, at, _, size = spans.runs([" ".join(f"w{k}x{j}" for j in range(n)) + "." for k, n in enumerate(sizes)])
        whole = len(sizes) >= spans.RUN and sum(sizes) >= spans.LEAST
        assert {k for a, n in zip(at.tolist(), size.tolist()) for k in range(a, a + n)} == (set(range(len(sizes))) if whole else set())


def extracted(spark, *pages):
    """What op7 gives for pages of (url, html)."""
    df = spark.createDataFrame([(i, *p) for i, p in enumerate(pages)], "page_id bigint, url string, html string")
    return [r.text for r in wrappers.op7_html(df).orderBy("page_id").collect()]


def test_wrappers_tell_template_from_slots(spark):
    box = "<div class=box><p>Get our weekly letter with all the news</p></div>"
    page = f"<body><article><h1>Facts</h1><p>The body of page number {{0}} tells of {{0}} things and {{0}} more of them.</p>{box}<p>Page {{0}} ends.</p></article></body>"
    own = [f"Facts\nThe body of page number {i} tells of {i} things and {i} more of them.\nPage {i} ends." for i in range(5)]
    assert extracted(spark, *[(f"http://a.example/{i}", page.format(i)) for i in range(5)]) == own
    # copies of one page, near copies, and pages without a host hold no template
    copies = extracted(spark, *[("http://b.example/", page.format(1))] * 5)
    assert all("weekly letter" in t for t in copies)
    near = "<article><p>A long text that many pages of this host give word for word.</p><p>Copy {}</p></article>"
    assert all("word for word" in t for t in extracted(spark, *[(f"http://c.example/{i}", near.format(i)) for i in range(5)]))
    assert all("weekly letter" in t for t in extracted(spark, *[(None, page.format(i)) for i in range(5)]))


def test_wrappers_keep_blocks_outside_the_densest_container(spark):
    long = "words of a long body " * 60
    plain = f"<body><h1>Title</h1><p>Lead</p><div>{long}</div></body>"
    two = f"<body><article>{long}</article><div><article>A second article.</article></div><p>An end.</p></body>"
    got = extracted(spark, ("http://a.example/1", plain), ("http://b.example/1", two), (None, plain), ("bad", two))
    assert got == [f"Title\nLead\n{long.strip()}", f"{long.strip()}\nA second article.\nAn end."] * 2


@pytest.mark.parametrize("n", [1, 2, 5, 10])
def test_every_language_is_trained(spark, n):
    """Equally common languages, each with letters of its own, whatever their number."""
    import random

    rng, rows = random.Random(n), []
    for k in range(60 * n):
        letters = [chr(0x3400 + 40 * (k % n) + j) for j in range(40)]
        rows.append((k, " ".join("".join(rng.choices(letters, k=4)) for _ in range(12)), f"l{k % n}"))
    docs = spark.createDataFrame(rows, "doc_id bigint, text string, lang string")
    got = language_id.op2_language(docs).join(docs.select("doc_id", "lang"), "doc_id").collect()
    assert all(r.lang_pred == r.lang for r in got)
    few = language_id.fit(docs.select("doc_id", docs.text.alias("t"), "lang"), rows=2 * n)
    assert few.langs == sorted({x[2] for x in rows})


@pytest.mark.parametrize("together", [1, 40, 200_000])
def test_spans_of_a_passage_in_every_document(spark, monkeypatch, together):
    """However runs are gathered: the first document keeps the passage, copies without an id come first."""
    monkeypatch.setattr(spans, "TOGETHER", together)
    passage = "A passage that all documents have begins here. " + " ".join(f"It has sentence number {i} too." for i in range(8))
    rows = [(i, f"Document {i} has words of its own, {i}. {passage} It ends with {i}.") for i in (-5, *range(1, 40))]
    rows += [(None, f"No id here. {passage} The end."), (7, rows[7][1]), (60, f"{passage} {passage}"), (61, None), (62, "")]
    df = spark.createDataFrame(rows, "doc_id bigint, text string").repartition(3)
    got = sorted(map(tuple, spans.op6_spans(df).collect()), key=str)
    want = []
    for i, t in rows:
        left = t if i is None or not t else t.replace(f"{passage} ", "").replace(passage, "")
        want.append((i, left, None if not t else t.count("It has sentence number 3")))
    assert [(r[0], r[1]) for r in got] == sorted([w[:2] for w in want], key=str)
    assert all((r[3] > 0) == (r[0] is not None and r[0] < 61) for r in got)


def test_spans_leave_set_phrases(spark):
    line = "Published under the terms of a licence, of which a copy comes with this text. "
    got = cut(spark, f"{line} First own words.", f"{line} Second own words.")
    assert got == {1: f"{line} First own words.", 2: f"{line} Second own words."}


def test_pipeline_stages_without_clear_ids(spark, tmp_path):
    """Copies under one id or none: one stays. A contaminated row without an id goes, another stays."""
    import corpus_pipeline as p

    item = " ".join(f"item{i}" for i in range(30))
    clean = " ".join(f"clean{i}" for i in range(40))
    other = " ".join(f"other{i}" for i in range(40))
    spark.createDataFrame([(1, item)], "item_id bigint, text string").write.parquet(str(tmp_path / "benchmark.parquet"))
    rows = [(5, clean), (5, clean), (None, clean), (None, f"so {item} then"), (None, other), (7, None), (7, "")]
    docs = spark.createDataFrame([(i, t, "en", "s", 1, "x") for i, t in rows], "doc_id bigint, text string, lang string, source string, n_chars bigint, row string")
    kept = p.near_duplicate_stage(spark, docs, str(tmp_path))
    assert sorted((r.text or "") for r in kept.collect()) == sorted(["", "", clean, other, f"so {item} then"]) and tuple(kept.columns) == p.COLUMNS
    left = p.decontaminate_stage(spark, kept, str(tmp_path))
    assert sorted((r.text or "") for r in left.collect()) == sorted(["", "", clean, other])
    assert p.near_duplicate_stage(spark, docs.limit(0), str(tmp_path)).count() == p.decontaminate_stage(spark, docs.limit(0), str(tmp_path)).count() == 0
