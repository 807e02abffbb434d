"""The five stages in sequence, on odd rows and on a table, against what each says of itself."""

import re

import pytest
from pyspark.sql import functions as F

pytest.importorskip("public_tokenizers")
pipeline = pytest.importorskip("corpus_pipeline")

from kbmap.llm import pieces, quality, simhash  # noqa: E402
from kbmap.llm.common import DOCUMENT_COLUMNS  # noqa: E402

SF = "/root/testdata/sf0.001"


@pytest.fixture(scope="module")
def after(spark, tmp_path_factory):
    """The rows after each stage, written and read again as the driver does."""
    docs, out = spark.read.parquet(f"{SF}/documents.parquet"), []
    for name, stage in pipeline.STAGES:
        path = str(tmp_path_factory.mktemp("stage") / "out")
        stage(spark, docs, SF).write.parquet(path)
        docs = spark.read.parquet(path)
        out.append(docs)
    return out


def test_stages_in_order(spark, after):
    assert [n for n, _ in pipeline.STAGES] == ["quality rules", "SimHash near-dedup", "PII", "mixing sources to target weights", "SentencePiece encoding and decoding"]
    source = spark.read.parquet(f"{SF}/documents.parquet")
    kept = {r.doc_id for r in quality.judge(source).where("kept").select("doc_id").collect()}
    assert {r.doc_id for r in after[0].collect()} == kept
    for docs in after[:4]:
        assert docs.columns == list(DOCUMENT_COLUMNS)
    assert after[2].count() == after[1].count() and after[4].count() == after[3].count() > 0


def test_one_of_each_group_stays_by_brute_force(after):
    rows = {r.doc_id: simhash.text_words(r.text) for r in after[0].collect()}
    sets = {i: {tuple(w[k : k + 5]) for k in range(max(1, len(w) - 4))} for i, w in rows.items()}
    label = {i: i for i in sets}
    links = [(a, b) for a in sets for b in sets if a < b and len(sets[a] & sets[b]) >= 0.8 * len(sets[a] | sets[b])]
    changed = True
    while changed:
        changed = False
        for a, b in links:
            low = min(label[a], label[b])
            if label[a] != low or label[b] != low:
                label[a] = label[b] = low
                changed = True
    assert {r.doc_id for r in after[1].collect()} == set(label.values())


def test_no_plain_identifiers_are_left(after):
    left = after[2].where(F.col("text").rlike(r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+")).count()
    assert left == 0


def test_whole_run_equals_the_stages_and_decodes(spark, after):
    import public_tokenizers

    run = {r.doc_id: r.ids for r in pipeline.run(spark, SF).collect()}
    assert run == {r.doc_id: r.ids for r in after[4].collect()}
    texts = {r.doc_id: r.text for r in pieces.decode(after[4], public_tokenizers.path(pipeline.PIECE_MODEL)).collect()}
    assert texts == {r.doc_id: re.sub("▁", " ", r.text or "") for r in after[3].collect()}


def test_stages_on_odd_rows(spark, tmp_path):
    """Nulls in any column, empty and long texts, repeated rows, more columns, and no rows at all."""
    text = "the cat and the dog of the house have a long way to go and that is with what it was " * 6
    rows = [(1, text, None, None, None, 7), (1, text, None, None, None, 7), (None, text + " more", "en", "s", 1, 7), (2, None, "en", "s", 0, 7), (3, "", "en", "s", 0, 7), (4, "word " * 30_000, "en", "s", 0, 7)]
    odd = spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long, kept int")
    for docs in (odd, odd.limit(0)):
        for k, (_, stage) in enumerate(pipeline.STAGES):
            docs = stage(spark, docs, SF)
            docs.write.mode("overwrite").parquet(f"{tmp_path}/{k}")
            docs = spark.read.parquet(f"{tmp_path}/{k}")
        assert docs.columns[:2] == ["doc_id", "ids"]
