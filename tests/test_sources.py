"""Lines of HTML, JSON, text and CSV, leaks, statements, sequences and the shared folder."""

import pytest
from pyspark.sql import functions as F

from freeseg import shipping
from freeseg.sources import corpus


def test_html_lines_keep_paragraphs_with_tags_and_attributes(spark):
    page = """<html><head><title lang=en>A &amp;amp; b</title><style>p{}</style><script>var t = "<p>no</p>"</script></head><body><h1 class="x">He<i>ad</i></h1>
        <p id="1">One <b>bold</b>\n word</p><!-- <p>hidden</p> --><p>open<br><p>next &lt;3</p><p></p><pre>no line</pre><P>last</P></body></html>"""
    rows = corpus.html_lines(spark.createDataFrame([(1, page), (2, None), (3, "")], "page_id long, html string")).collect()
    assert {(r.kind, r.line) for r in rows} == {("title", "A &amp; b"), ("heading", "Head"), ("paragraph", "One bold word"), ("paragraph", "open"), ("paragraph", "next <3"), ("paragraph", "last")}


def test_json_text_and_lexicon_files(spark, tmp_path):
    records = spark.createDataFrame([(1, '{"title": "T", "desc": "", "content": "two words"}'), (2, "no json"), (3, None)], "id long, j string")
    assert sorted((r.id, r.field, r.line) for r in corpus.json_lines(records, "j", ["title", "desc", "content"], "id").collect()) == [(1, "content", "two words"), (1, "title", "T")]
    (tmp_path / "t.txt").write_text("one\n\ntwo\n")
    assert [r.line for r in corpus.text_lines(spark, str(tmp_path / "t.txt")).collect()] == ["one", "two"]
    lexicon = spark.createDataFrame([("a,b", 3), ("é", 1)], "word string, freq long")
    corpus.write_lexicon(lexicon, str(tmp_path / "l"))
    assert sorted(map(tuple, corpus.read_lexicon(spark, str(tmp_path / "l")).collect())) == [("a,b", 3), ("é", 1)]


def test_leaks_are_found_in_blocks(spark):
    docs = spark.createDataFrame([(1, "x needle y"), (2, "hay"), (3, None), (4, "pins"), (5, "")], "doc_id long, text string")
    items = spark.createDataFrame([("needle",), ("pin",), ("",), (None,)], "text string")
    for most in (1, 100):
        assert sorted(r.doc_id for r in corpus.without_leaks(docs, items, most=most).collect()) == [2, 3, 5]
    assert corpus.without_leaks(docs, items.limit(0)).count() == 5


def test_statements_are_whole(spark, sf):
    st = corpus.statements(spark, sf)
    docs = spark.read.parquet(f"{sf}/documents.parquet").where("doc_id % 10 = 0")
    want = sum(len(t) for r in docs.collect() for t in r.text.split("\n"))
    assert st.where("stmt_id like 'd%'").agg(F.sum(F.length("text"))).first()[0] == want
    assert st.count() == st.select("stmt_id").distinct().count() and {r.half for r in st.select("half").distinct().collect()} == {0, 1}


def test_sequences_over_several_tasks(spark):
    rows = [(u, t, chr(97 + (u * 7 + t) % 26)) for u in (1, 2, 3) for t in range(1 if u == 3 else 400)]
    df = spark.createDataFrame(rows, "u long, t long, s string").repartition(3)
    got = {r.u: r.line for r in corpus.sequences(df, "u", ["t"], F.col("s")).collect()}
    assert got == {u: "".join(s for v, _, s in sorted(rows) if v == u) for u in (1, 2, 3)}


def test_a_cluster_has_to_name_its_shared_folder(spark, monkeypatch):
    class Conf:
        def get(self, *a):
            return None

    class Context:
        master = "spark://somewhere:7077"

        def getCheckpointDir(self):
            return None

    class Session:
        conf, sparkContext = Conf(), Context()

    with pytest.raises(RuntimeError):
        shipping.shared_dir(Session())


def test_release_deletes_what_was_kept(spark, tmp_path):
    from pathlib import Path

    from freeseg.sources.store import kept

    kept(spark.range(3))
    at = Path(shipping.work_dir(spark).removeprefix("file:"))
    assert any(at.iterdir())
    shipping.release(spark)
    assert not at.exists()
