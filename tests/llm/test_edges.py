"""Every dealt operator and pipeline stage on nulls, empty and long texts, ties, empty tables and clashing columns."""

import pytest
from pyspark.sql import functions as F

import corpus_pipeline
from boundpath.llm import ctw, decontaminate, mixing, neardup, quality, sharding, tokencount, toxicity, urlgraph, warc
from boundpath.llm.shared import fresh_path

LONG = " ".join(f"w{i % 977} x{i}" for i in range(30000))
PROSE = "the quick brown fox jumps over the lazy dog near the old river bank while seven small birds sing in the tall trees today"
ROWS = [
    (1, PROSE, "en", "a", None),
    (2, PROSE, "en", "b", 3),
    (2, PROSE, "en", "b", 3),
    (3, None, None, None, None),
    (4, "", "en", "a", 0),
    (5, " \n\t ", "en", "a", 1),
    (None, PROSE, "en", None, 4),
    (None, None, None, None, None),
    (None, "alone without an id but with quite enough different words to be kept by every single rule of the cascade here", "xx", "c", 1),
    (6, LONG, "en", "a", 9),
    (7, LONG + " end", "en", "c", 9),
    (8, "word", "en", "a", 1),
    (9, "é" * 3000, "fr", "b", 1),
]
COLUMNS = "doc_id bigint, text string, lang string, source string, n_chars bigint"


def frame(spark, rows=ROWS, clash=True):
    df = spark.createDataFrame(rows, COLUMNS)
    if clash:
        for name in ("size", "score", "kept", "n_words", "shard", "slot", "component_id", "rank", "hash", "copies", "expected", "group_key", "rid"):
            df = df.withColumn(name, F.lit("clash"))
    return df


def labels(spark):
    return spark.createDataFrame([(1, 0, 1), (2, 1, 0), (3, None, None), (None, 1, 1), (6, 0, 0)], "doc_id bigint, quality int, toxic int")


BENCH = "item_id bigint, text string"


def benchmark(spark):
    return spark.createDataFrame([(0, PROSE), (1, None), (2, ""), (3, "word"), (None, "x y z"), (0, PROSE)], BENCH)


OPERATORS = {
    "near_duplicates": lambda s, d: neardup.near_duplicates(d),
    "quality": lambda s, d: quality.judge(d),
    "sharding": lambda s, d: sharding.shard_documents(d, 3),
    "capacity": lambda s, d: sharding.shard_documents(d, None, 5000),
    "mixing": lambda s, d: mixing.mix(d),
    "tokens": lambda s, d: tokencount.count_tokens(d),
    "scores": lambda s, d: ctw.score_texts(d, F.col("doc_id") == 2),
    "toxicity": lambda s, d: toxicity.score_toxicity(d, toxicity.fit(d, labels(s))),
}


@pytest.mark.parametrize("name", OPERATORS)
def test_row_for_row(spark, name):
    docs = frame(spark)
    out = OPERATORS[name](spark, docs)
    assert out.count() == len(ROWS)
    none = frame(spark, [])
    assert OPERATORS[name](spark, none).count() == 0


def test_decontamination(spark):
    out = decontaminate.contaminated(frame(spark), benchmark(spark)).collect()
    assert {r.doc_id for r in out} == {1, 2, None, 8}
    assert sorted(r.item_id for r in out if r.doc_id == 1) == [0, 0]
    assert decontaminate.contaminated(frame(spark, []), benchmark(spark)).count() == 0
    assert decontaminate.contaminated(frame(spark), spark.createDataFrame([], BENCH)).count() == 0


def test_pipeline_stages(spark, tmp_path):
    benchmark(spark).write.parquet(f"{tmp_path}/benchmark.parquet")
    for name, stage in corpus_pipeline.STAGES:
        for rows in (ROWS, []):
            docs = frame(spark, rows)
            out = stage(spark, docs, str(tmp_path))
            kept = out.collect()
            if name != "sharding":
                assert out.columns == docs.columns, name
            else:
                assert len(kept) == len(rows)
            if name == "near_dedup" and rows:
                ids = [r.doc_id for r in kept]
                assert ids.count(2) == 0 and ids.count(1) == 1 and ids.count(None) == 2  # the blank one and the lone one
            if name == "decontamination" and rows:
                assert sum(r.text == PROSE for r in kept) == 0
            if name == "quality_rules" and rows:
                assert sum(r.text == PROSE for r in kept) == 4 and all(r.text for r in kept)


PAGES = [
    (1, "http://www.A.com/en/1?x", "<p>" + "a" * 2000),
    (2, "http://b.net/de/9", "<p>" + "a" * 2000),
    (2, "http://b.net/de/9", "<p>" + "a" * 2000),
    (3, None, None),
    (4, "nothing", "short"),
    (5, "https://c.org/es/1#f", 'short <a href="http://bad.com/">x</a>'),
    (6, "https://c.org", "short"),
    (None, "x://y/z", "<p>" + "a" * 2000),
    (7, "http://m.example.com/en/77\n", "é" * 900),
    (8, "http://m.example.com/en/7\x01", "é" * 900),
]


def pages(spark, rows=PAGES):
    return spark.createDataFrame(rows, "page_id bigint, url string, html string").withColumn("host", F.lit("clash")).withColumn("answer", F.lit(1)).withColumn("verdict", F.lit(2))


def test_urls(spark):
    out = {r.page_id: r for r in urlgraph.filter_urls(pages(spark)).collect()}
    assert (out[1].host, out[1].path, out[1].rule, out[1].verdict) == ("www.a.com", "/en/1", "com/en/", "block")
    assert (out[2].rule, out[2].verdict) == ("net/de/", "allow")
    assert (out[3].host, out[3].path, out[3].rule, out[3].verdict) == ("", "", None, "allow")
    assert (out[5].path, out[5].rule) == ("/es/1", "org/es/") and (out[6].path, out[6].rule) == ("", None)
    assert out[7].rule == "example.com/en/7"
    assert urlgraph.filter_urls(pages(spark, [])).count() == 0


def test_distrust_flows_against_links(spark):
    rows = [(1, "http://bad.com/en/1", ""), (2, "http://friend.example/x", '<a href="http://bad.com/a">'), (3, "http://lone.example/x", ""), (4, "http://good.net/de/", '<a href="//known.example/">'), (5, "http://known.example/", "<a href=http://bad.com/>")]
    out = {r.page_id: r.verdict for r in urlgraph.filter_urls(pages(spark, rows)).collect()}
    assert out[1] == "block" and out[2] == "block" and out[3] == "allow" and out[4] == "allow" and out[5] == "allow"


def test_distrust_reaches_far_and_stops(spark):
    """Along a chain of 22 hosts distrust falls by the damping a link; verdicts are those of the converged ranks."""
    n = 22
    rows = [(0, "http://h0.com/en/1", "")] + [(i, f"http://h{i}.example/x", f'<a href="http://h{i - 1}.{"com" if i == 1 else "example"}/a">') for i in range(1, n)]
    out = {r.page_id: r.verdict for r in urlgraph.filter_urls(pages(spark, rows)).collect()}
    lost = 0.15 / (1 - 0.85**n)  # the last host's mass returns to the seed
    assert out == {i: "block" if i == 0 or lost * 0.85**i >= 0.01 else "allow" for i in range(n)}
    assert sum(v == "block" for v in out.values()) > 13


def test_null_ids_revisit_those_with_an_id(spark):
    body = "<p>" + "a" * 2000
    for ids, want in (((5, None), {5: ("response", None), None: ("revisit", 5)}), ((None, None), {None: ("response", None)}), ((5, 7, None), {5: ("revisit", 7), 7: ("response", None), None: ("revisit", 7)})):
        folder = fresh_path(spark, "warc")
        warc.write_warc(spark.createDataFrame([(i, "http://a/", body) for i in ids], "page_id bigint, url string, html string"), folder)
        assert {r.page_id: (r.record_type, r.refers_to) for r in warc.read_warc(spark, folder).collect()} == want


def test_a_task_may_write_again(spark):
    """A second attempt finds its files under their final names and replaces them by the same bytes."""
    folder = fresh_path(spark, "warc")
    rows = spark.createDataFrame([(i, "http://a/", bytearray(b"x" * 50), "d", None) for i in range(9)], "page_id bigint, url string, payload binary, digest string, answer bigint").coalesce(1)
    first, again = (sorted(map(tuple, rows.mapInArrow(warc._writer(folder, 300), warc.MANIFEST_SCHEMA).collect())) for _ in range(2))
    assert first == again and len(first) > 2


LONG_HTML = "<p>" + " ".join(f'<a href="http://h{i % 40}.example/{i}">t{i}</a>' for i in range(60000))


def test_long_pages(spark):
    rows = [(1, "http://a.example/1", LONG_HTML), (2, "http://a.example/2", LONG_HTML), (3, "http://b.example/" + "x" * 100000, None)]
    assert {r.page_id: (len(r.path), r.verdict) for r in urlgraph.filter_urls(pages(spark, rows)).collect()} == {1: (2, "allow"), 2: (2, "allow"), 3: (100001, "allow")}
    assert urlgraph.host_edges(pages(spark, rows).withColumn("host", urlgraph.host_of(F.col("url")))).count() == 40
    folder = fresh_path(spark, "warc")
    warc.write_warc(pages(spark, rows), folder)
    back = {r.page_id: r for r in warc.read_warc(spark, folder, True).collect()}
    assert back[2].payload.decode() == LONG_HTML and back[1].refers_to == 2 and len(back[3].url) == 100017


def test_warc(spark):
    for rows in (PAGES, []):
        folder = fresh_path(spark, "warc")
        warc.write_warc(pages(spark, rows), folder, roll_bytes=300)
        out = warc.read_warc(spark, folder, True).collect()
        assert len(out) == len(rows)
    folder = fresh_path(spark, "warc")
    warc.write_warc(pages(spark), folder, roll_bytes=300)
    back = warc.read_warc(spark, folder, True).collect()
    kinds = {}
    for r in back:
        kinds.setdefault(r.page_id, []).append((r.record_type, r.refers_to))
    assert kinds[1] == [("revisit", 2)] and kinds[2] == [("response", None)] * 2 and kinds[None] == [("revisit", 2)]
    assert kinds[7] == [("revisit", 8)] and kinds[6] == [("response", None)] and kinds[4] == [("response", None)]
    texts = {r.page_id: bytes(r.payload).decode() for r in back if r.record_type == "response"}
    assert texts[2] == PAGES[1][2] and texts[3] == "" and texts[8] == "é" * 900
