"""Nulls, empty and long texts, repeats, empty tables and clashing names, for every operator and stage."""

import pytest
from pyspark.sql import functions as F

from rankloom.llm.chat import format_chats
from rankloom.llm.decontaminate import decontaminate_stage, find_leaks
from rankloom.llm.html import extract_pages, page_text
from rankloom.llm.jaccard import dedupe_stage, jaccard_components
from rankloom.llm.language import predict_languages
from rankloom.llm.lm import score_texts
from rankloom.llm.mixing import mix_documents, mix_stage
from rankloom.llm.quality import classify_quality, quality_stage
from rankloom.llm.sharding import shard_documents
from rankloom.llm.simhash import simhash_documents

SCHEMA = "doc_id long, text string, lang string, source string, n_chars long"
LABELS = "doc_id long, quality int, toxic int"
BENCH = "item_id long, text string"
CLASHES = ["rid", "n", "grp", "bucket", "score", "tokens", "domain", "copies", "id", "hub", "shard", "block", "_score", "c", "k1", "key"]


@pytest.fixture(scope="module")
def odd(spark):
    rows = [
        (1, "one two three four five six", "en", "src1", 27),
        (1, "one two three four five six", "en", "src1", 27),
        (2, None, None, None, None),
        (3, "", "en", "src0", 0),
        (None, "no id at all here", "de", None, 5),
        (None, None, None, None, None),
        (4, " \n\t ", "en", "src0", 4),
        (5, "é ü ñ 漢字 😀 ٣", "fr", "src0", 9),
        (6, "long " * 60_000, "en", "src0", 300_000),
        (7, "x" * 200_000, "en", "src2", 200_000),
        (8, "one two three four five six", "en", "src3", 27),
        (9, "\x00 nul and   separators here", "en", "src3", 20),
    ]
    df = spark.createDataFrame(rows, SCHEMA)
    for c in CLASHES:
        df = df.withColumn(c, F.lit("clash"))
    return df


@pytest.fixture(scope="module")
def labels(spark):
    return spark.createDataFrame([(1, 1, 0), (3, 0, 0), (5, 1, 0), (6, 0, 1), (9, None, None), (None, 1, 0)], LABELS)


@pytest.fixture(scope="module")
def bench(spark):
    return spark.createDataFrame([(1, "one two three four five six"), (None, None), (2, "")], BENCH)


def test_rows_are_kept(spark, odd, labels):
    for f in (simhash_documents, jaccard_components, shard_documents, predict_languages, score_texts):
        assert f(odd).count() == 12, f
    assert classify_quality(odd, labels).count() == 12


def test_mix(odd):
    rows = mix_documents(odd).collect()
    assert all(r.copies > 0 and r.take_tokens <= r.copies * r.tokens for r in rows)
    assert {(r.lang, r.source) for r in rows} <= {("en", f"src{i}") for i in range(4)} | {("unknown", "unknown"), ("de", "unknown"), ("fr", "src0")}


def test_stages_keep_columns(spark, odd, labels, bench):
    for out in (quality_stage(odd, labels), dedupe_stage(odd), decontaminate_stage(odd, bench), mix_stage(odd)):
        assert out.columns == odd.columns
        out.collect()
    left = {r.doc_id for r in decontaminate_stage(odd, bench).collect()}
    assert 1 not in left and 8 not in left and {2, 3, 4, 5, 6, 7, 9} <= left
    kept = [r.doc_id for r in dedupe_stage(odd).collect()]
    assert kept.count(1) == 1 and 8 not in kept and kept.count(None) == 2


def test_leaks_of_odd_rows(odd, bench):
    assert sorted(r.doc_id for r in find_leaks(odd, bench).collect()) == [1, 1, 8]


def test_equal_texts_get_equal_results(odd, labels):
    prints = {(r.doc_id, r.fingerprint) for r in simhash_documents(odd).collect() if r.doc_id in (1, 8)}
    assert len({p for _, p in prints}) == 1
    scores = [r.score for r in classify_quality(odd, labels).collect() if r.doc_id in (1, 8)]
    assert len(scores) == 3 and len(set(scores)) == 1
    lm = [r.score for r in score_texts(odd).collect() if r.doc_id in (1, 8)]
    assert len(lm) == 3 and max(lm) - min(lm) < 1e-9
    empty = [r for r in simhash_documents(odd).collect() if r.n_chars == 0]
    assert len(empty) == 3 and {r.fingerprint for r in empty} == {"0" * 16}


def test_und(odd):
    got = {(r.doc_id, r.lang_pred, r.score) for r in predict_languages(odd).collect() if r.doc_id in (2, 3, 4)}
    assert got == {(i, "und", 0.0) for i in (2, 3, 4)}


def test_empty_tables(spark):
    docs, labels, bench = (spark.createDataFrame([], s) for s in (SCHEMA, LABELS, BENCH))
    for f in (simhash_documents, jaccard_components, shard_documents, predict_languages, score_texts, mix_documents, mix_stage, dedupe_stage):
        assert f(docs).collect() == [], f
    assert classify_quality(docs, labels).collect() == [] == quality_stage(docs, labels).collect()
    assert find_leaks(docs, bench).collect() == [] == decontaminate_stage(docs, bench).collect()
    assert format_chats(spark.createDataFrame([], "conv_id long, turn long, role string, text string")).collect() == []
    assert extract_pages(spark.createDataFrame([], "page_id long, url string, html string")).collect() == []


def test_one_row(spark):
    docs = spark.createDataFrame([(5, "just one text", "en", "src0", 13)], SCHEMA)
    r = simhash_documents(docs).collect()[0]
    assert r.near_next == 1.0 and r.n_chars == 13
    assert jaccard_components(docs).collect()[0].component_id == 5
    assert shard_documents(docs).collect()[0].slot == 0
    assert classify_quality(docs, spark.createDataFrame([], LABELS)).collect()[0].score == 0.5


def test_chat_edges(spark):
    rows = [
        (1, 0, "user", "hi"), (1, 1, "assistant", "yo"), (1, 2, "user", "more"),
        (2, 0, "user", "hi"), (2, 1, "assistant", "yo"),
        (3, 5, "user", "hi"),
        (4, 0, "user", "hi"), (4, 1, "assistant", "other"),
        (6, 0, "user", "hi"), (6, 3, "assistant", "other"),
        (7, 0, None, None), (None, 0, "user", "lost"), (None, 0, "user", "lost"), (None, 1, "user", "hi"),
        (8, 0, "user", "x"), (8, 0, "user", "x"),
    ]
    df = spark.createDataFrame(rows, "conv_id long, turn long, role string, text string").withColumn("pos", F.lit(1)).withColumn("h0", F.lit("clash"))
    got = {(r.conv_id, r.n_turns, r.n_copies) for r in format_chats(df).collect()}
    assert got == {(1, 3, 1), (4, 2, 2), (7, 1, 1), (None, 1, 2), (8, 2, 1)}
    text = next(r.rendered for r in format_chats(df).collect() if r.conv_id == 4)
    assert text == "<|user|>\nhi<|end|>\n<|assistant|>\nother<|end|>\n"


def test_html_rules(spark):
    assert page_text(None) == page_text("") == ""
    assert page_text("<p>a<p>b") == "a\n\nb"
    assert page_text("<ul><li>a<li>b<ul><li>c</ul></ul><ol start=3><li>x<li>y</ol>") == "- a\n- b\n  - c\n\n3. x\n4. y"
    assert page_text("<table><tr><th>Name<th>N<tr><td>longer name<td>7</table>") == "Name         N\nlonger name  7"
    assert page_text("<div hidden>x</div><p style='display: none'>y</p><b style='color:red'>z</b><script>s</script><template>t</template>") == "z"
    assert page_text("<pre>  a\n   b</pre>") == "  a\n   b"
    assert page_text("a &lt;b&gt; &amp; c&nbsp;d") == "a <b> & c d"
    assert page_text("1 < 2 and <b>3") == "1 < 2 and 3"
    assert page_text("line<br>break<br><br>gap") == "line\nbreak\n\ngap"
    assert page_text("<div>" * 20_000 + "deep").strip() == "deep"
    assert page_text("<select><option>a<option>b</select>") .split() == ["a", "b"]
    assert page_text("<p>x<!-- no --><!-- open").strip() == "x"
    rows = spark.createDataFrame([(1, "u", None), (1, "u", "<p>t"), (None, None, "<p>t" * 50_000)], "page_id long, url string, html string").withColumn("text", F.lit("clash"))
    assert [len(r.text) for r in extract_pages(rows).orderBy("n_chars").collect()] == [0, 1, 149_998]
