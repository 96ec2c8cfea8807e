import corpus_pipeline
import pytest

from freeseg.llm import pieces, queries
from freeseg.sources.store import kept

from .helpers import documents, empty, odd_documents


def test_stages_keep_the_columns_and_only_drop_rows(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    for name, stage in corpus_pipeline.STAGES[:-1]:
        before = {r.doc_id: r.text for r in docs.collect()}
        docs = kept(stage(spark, docs, sf))
        assert docs.columns == ["doc_id", "text", "lang", "source", "n_chars"], name
        after = {r.doc_id: r.text for r in docs.collect()}
        assert set(after) <= set(before) and len(after) > 0.7 * len(before), name
        if name != "line_dedup":
            assert all(before[k] == t for k, t in after.items())


def test_the_last_stage_decodes(spark, sf):
    out = corpus_pipeline.run(spark, sf).collect()
    codec = pieces.Codec(pieces.read_pieces(queries.VOCABULARY))
    assert all(r.decodes and r.n_pieces == len(r.piece_ids) for r in out)
    assert len({r.doc_id for r in out}) == len(out) and codec.decode(out[0].piece_ids)


@pytest.mark.parametrize("make", [odd_documents, empty])
def test_odd_rows_and_empty_tables(spark, sf, make):
    docs = make(spark)
    for _, stage in corpus_pipeline.STAGES:
        out = kept(stage(spark, docs, sf))
        docs = out if "text" in out.columns else docs
    assert out.count() <= make(spark).count()


def test_planted_cases(spark, sf):
    item = spark.read.parquet(f"{sf}/benchmark.parquet").orderBy("item_id").first().text
    words = lambda p, n: " ".join(f"{p}{chr(97 + k % 26)}{chr(97 + k // 26)}" for k in range(n))
    passage, copy = words("pass", 60), words("copy", 80)
    texts = [words("clean", 50), copy, copy, copy + " end", f"{passage}\n{words('one', 20)}", f"{passage}\n{words('two', 20)}", f"intro text\n{item}\nmore text", "..."]
    docs = documents(spark, texts)
    left = docs
    for _, stage in corpus_pipeline.STAGES[:-1]:
        left = kept(stage(spark, left, sf))
    got = {r.doc_id: r.text for r in left.collect()}
    assert set(got) == {0, 1, 4, 5}
    assert sum(passage in t for t in got.values()) == 1 and got[0] == texts[0]
