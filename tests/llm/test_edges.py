"""Every operator on nulls, empty and long texts, repeated rows, clashing columns and empty tables."""

import pytest
from pyspark.sql import functions as F

from structcurve.llm import chat, decontaminate, html, jaccard, mixing, quality, tokens, toxicity, warc, webp

LONG = " ".join(f"word{i % 977} filler" for i in range(30_000))
ROWS = [(1, "a plain text of a few words here", "en", "s1"), (2, None, None, None), (3, "", "en", "s2"), (4, LONG, "en", "s1"), (None, "no id on this one", "en", "s1"), (1, "a plain text of a few words here", "en", "s1"), (6, "<|endoftext|> </s> [INST] ␛ ünïcödé \U0001f600", "fr", "s3"), (7, " \n\t ", "fr", "s3")]
#: Names that operators use inside.
CLASH = ("score", "rank", "start", "size", "head", "key", "rep", "n", "part", "root", "sha1", "first", "chunk", "path", "target", "block", "y", "copies", "held_out", "_hit", "_source")


def docs(spark, rows=ROWS):
    df = spark.createDataFrame(rows, "doc_id bigint, text string, lang string, source string")
    return df.withColumns({c: F.lit("x") for c in CLASH})


def labels(spark):
    rows = [(i, i % 2, (i + 1) % 2) for i in range(1, 9)] + [(None, 1, 0), (3, None, None)]
    return spark.createDataFrame(rows, "doc_id bigint, quality int, toxic int").withColumn("text", F.lit("clash"))


def items(spark):
    return spark.createDataFrame([(1, "a plain text of a few words here"), (2, None), (3, ""), (1, "a plain text of a few words here")], "item_id bigint, text string").withColumn("doc_id", F.lit(5))


def pages(spark, rows=None):
    rows = rows if rows is not None else [(i, None if i == 2 else f"http://h.example/{i}", t) for i, t, _, _ in ROWS]
    return spark.createDataFrame(rows, "page_id bigint, url string, html string").withColumns({c: F.lit("x") for c in CLASH})


def talks(spark, rows=None):
    rows = rows if rows is not None else [(1, i, None if i == 2 else ("user", "assistant")[i % 2], t) for i, (_, t, _, _) in enumerate(ROWS)] + [(None, None, "system", "s"), (1, 0, "a]b", "t"), (1, 0, "a]b", "t")]
    return spark.createDataFrame(rows, "conv_id bigint, turn bigint, role string, text string").withColumns({c: F.lit("x") for c in CLASH})


OPERATORS = {
    "tokens": lambda s, d: tokens.token_counts(d),
    "leaks": lambda s, d: decontaminate.contamination(d, items(s)),
    "toxicity": lambda s, d: toxicity.toxicity(d, labels(s)),
    "media": lambda s, d: webp.media_digests(webp.media_column(d)),
    "similar": lambda s, d: jaccard.similar_documents(d),
    "quality": lambda s, d: quality.quality(d, labels(s)),
    "mixing": lambda s, d: mixing.mixed_documents(d),
}


@pytest.mark.parametrize("name", OPERATORS)
def test_documents(spark, name):
    got = OPERATORS[name](spark, docs(spark)).collect()
    if name == "leaks":
        assert sorted((r.doc_id, r.item_id) for r in got) == [(1, 1), (1, 1)]
    else:
        assert sorted(str(r.doc_id) for r in got) == sorted(str(r[0]) for r in ROWS)
    if name in ("toxicity", "quality"):
        assert all(0 <= r.score <= 1 for r in got)
        assert len({r.score for r in got if r.doc_id == 1}) == 1
    if name == "media":
        one = {r.doc_id: r for r in got}
        assert one[3].payload_bytes == 576 and one[2].media_sha256 == one[3].media_sha256
    if name == "similar":
        by = {r.doc_id: (r.class_id, r.n_links) for r in got}
        assert by[1] == (1, 1) and by[None] == (None, 0) and by[2] == by[3] == by[7] == (2, 2)
    if name == "mixing":
        assert all(r.taken <= 2 * r.size for r in got) and {r.size for r in got if r.doc_id in (2, 3, 7)} == {0}


@pytest.mark.parametrize("name", OPERATORS)
def test_empty_tables(spark, name):
    assert OPERATORS[name](spark, docs(spark, [])).collect() == []


def test_pages(spark):
    got = html.extract_text(pages(spark)).collect()
    assert len(got) == len(ROWS) and all(r.n_chars == len(r.text) for r in got)
    assert html.extract_text(pages(spark, [])).collect() == []
    manifest = warc.write_archives(pages(spark))
    back = warc.records_of(warc.read_archives(spark, manifest)).collect()
    assert sorted(str(r.page_id) for r in back) == sorted(str(r[0]) for r in ROWS) and all(r.verified for r in back)
    kinds = {r.page_id: (r.record_type, r.refers_to) for r in back}
    assert kinds[2] == ("response", None) and kinds[3] == ("revisit", 2) and kinds[1] == ("response", None)
    assert warc.records_of(warc.read_archives(spark, warc.write_archives(pages(spark, [])))).collect() == []


def test_conversations(spark):
    got = {r.conv_id: r for r in chat.format_chats(talks(spark)).collect()}
    assert len(got[1].recovered) == len(ROWS) + 2 and got[None].recovered[0].text == "s"
    assert {t.role for t in got[1].recovered} >= {"", "a]b", "user", "assistant"}
    assert chat.chat_digests(chat.format_chats(talks(spark, []))).collect() == []


FILTERS = {
    "toxicity": lambda s, d: toxicity.without_toxic(d, labels(s)),
    "quality": lambda s, d: quality.without_poor(d, labels(s)),
    "leaks": lambda s, d: decontaminate.decontaminate(d, items(s)),
    "copies": lambda s, d: jaccard.keep_one(d),
}


@pytest.mark.parametrize("name", FILTERS)
def test_filters_keep_columns(spark, name):
    df = docs(spark)
    out = FILTERS[name](spark, df)
    assert out.columns == df.columns and FILTERS[name](spark, docs(spark, [])).collect() == []
    got = sorted(str(r.doc_id) for r in out.collect())
    if name == "leaks":
        assert got == sorted(str(r[0]) for r in ROWS if r[0] != 1)
    if name == "copies":
        assert got == ["1", "2", "4", "6", "None"]
