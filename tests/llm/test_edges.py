"""Every operator and stage: empty tables, clashing columns, null ids and texts, repeated rows, a very long text."""

import uuid

import pytest
from pyspark.sql import functions as F

import corpus_pipeline
from optjoin.llm import html_text, jpeg, lm, near_text, packing, pieces, quality, simhash, substring_dedup, suffix_dedup, warc

LONG = " ".join(f"w{i * 7919 % 4001}x{i % 13}" for i in range(500_000))  # over 4 MB
ROWS = [(1, "one two three four five six"), (2, None), (3, ""), (4, " \t\n"), (5, "one two three four five six"), (5, "one two three four five six"), (None, "no id at all"), (6, "größe \U0001f600 ß \x00 tail"), (7, LONG)]


def docs(spark, rows):
    clash = {c: F.lit(1) for c in ("id", "k0", "src", "kind", "bucket", "body", "n_words", "kept", "print", "root", "node", "a", "least")}
    return spark.createDataFrame(rows, "doc_id long, text string").withColumns(clash)


def archive(df):
    folder = f"file:///tmp/edges-{uuid.uuid4().hex}"
    pages = df.select(F.col("doc_id").alias("page_id"), F.lit("http://x/").alias("url"), F.col("text").alias("html"), "kind", "range_" if "range_" in df.columns else F.lit(1).alias("range"), F.lit(2).alias("first"), F.lit(3).alias("sha1"))
    return warc.read_warc(warc.write_warc(pages, folder), folder).withColumnRenamed("page_id", "doc_id")


def pages(df):
    return html_text.extract_pages(df.withColumnsRenamed({"doc_id": "page_id", "text": "html"})).withColumnRenamed("page_id", "doc_id")


OPERATORS = {
    "op1": archive,
    "op2": suffix_dedup.remove_repeats,
    "op3": simhash.near_duplicates,
    "op4": substring_dedup.remove_repeated_windows,
    "op5": lm.score_documents,
    "op6": jpeg.media_columns,
    "op7": quality.quality,
    "op8": pieces.encode_documents,
    "op9": pages,
    "near_text": near_text.distinct_texts,
}


@pytest.mark.parametrize("name", OPERATORS)
def test_rows_are_kept(spark, name):
    out = OPERATORS[name](docs(spark, ROWS))
    ids = sorted((r.doc_id for r in out.select("doc_id").collect()), key=str)
    want = [r[0] for r in ROWS if not (name == "near_text" and r[0] == 5)]
    assert ids == sorted(want, key=str)
    assert len(set(out.columns)) == len(out.columns)


@pytest.mark.parametrize("name", [*OPERATORS, "op10"])
def test_empty_tables(spark, name):
    work = OPERATORS.get(name, packing.pack)
    assert work(docs(spark, [])).count() == 0
    assert work(docs(spark, [(1, None)])).count() == 1


def test_packing_of_edge_rows(spark):
    found = packing.pack(docs(spark, ROWS)).select("doc_id", "start", "length", "doc_tokens", "sequence_id", "offset").collect()
    want = sorted(str(r[0]) for r in ROWS)
    firsts = sorted(str(r.doc_id) for r in found if r.start == 0)
    assert firsts == want
    total = {}
    for r in found:
        total.setdefault((r.doc_id, r.doc_tokens), []).append((r.start, r.length))
    for (_, tokens), parts in total.items():
        assert sum(n for _, n in parts) % tokens == 0
    places = {}
    for r in found:
        places.setdefault(r.sequence_id, []).append((r.offset, r.length))
    for parts in places.values():
        at = 0
        for offset, n in sorted(parts):
            assert offset == at
            at += n
        assert at <= 2048


@pytest.mark.parametrize("rows", [[], ROWS])
def test_pipeline_stages(spark, rows):
    table = spark.createDataFrame([(i, t, "en", "s", None if t is None else len(t)) for i, t in rows], "doc_id long, text string, lang string, source string, n_chars long")
    for name, stage in corpus_pipeline.STAGES[:-1]:
        out = stage(spark, table.withColumns({"bucket": F.lit(1), "kind": F.lit("x"), "id": F.lit(2)}), "")
        assert out.columns == ["doc_id", "text", "lang", "source", "n_chars"], name
        kept = out.collect()
        assert len(kept) <= len(rows)
    assert corpus_pipeline.STAGES[-1][1](spark, table, "").count() >= len(rows)


def test_a_long_repeat_is_removed_whole(spark):
    found = {r.doc_id: r.n_removed for r in suffix_dedup.remove_repeats(docs(spark, [(1, LONG), (2, "x" + LONG)])).collect()}
    assert found == {1: 0, 2: len(LONG)}
    found = {r.doc_id: r.n_removed for r in substring_dedup.remove_repeated_windows(docs(spark, [(1, LONG), (2, "x " + LONG)])).collect()}
    assert found == {1: 0, 2: 500_000}
