"""Lines, symbols and statements from the given tables and from text, JSON, CSV and HTML sources.

A line is what stands between line feeds; nothing else is changed. Empty lines and null texts give no lines.

What is counted or segmented without a score is whole: all documents, all their lines. Only where F1 is measured are
documents held out, one in HELD_OUT of them: their lines, and the benchmark's items, are the test statements, and the
others, without those that contain a benchmark item, are the training corpus.
"""

from __future__ import annotations

from collections.abc import Iterator
from functools import reduce
from itertools import groupby

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: One document in so many is held out where F1 is measured.
HELD_OUT = 10
#: Bytes of test items that are looked for in one pass over the documents; more are in further passes.
ITEM_BYTES = 32 << 20


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def lines(df: DataFrame, text: str, *keys: str) -> DataFrame:
    """keys, line_no (from 0) and line. A projection and a generator: no shuffle."""
    parts = df.select(*keys, F.posexplode(F.split(F.col(text), "\n", -1)).alias("line_no", "line"))
    return parts.where(F.col("line") != "")


def all_lines(spark: SparkSession, sf_dir: str) -> DataFrame:
    """lang, doc_id, line_no, line of every document."""
    return lines(table(spark, sf_dir, "documents").select("lang", "doc_id", "text"), "text", "lang", "doc_id")


def item_blocks(items: DataFrame, item: str, most: int = ITEM_BYTES) -> Iterator[list[str]]:
    """The distinct items that aren't empty in blocks of about `most` bytes: a query set that comes to the driver a block at a time."""
    block, size = [], 0
    for r in items.select(F.col(item).alias("x")).where(F.length("x") > 0).distinct().toLocalIterator():
        block.append(r.x)
        size += len(r.x.encode())
        if size >= most:
            yield block
            block, size = [], 0
    if block:
        yield block


def without_leaks(docs: DataFrame, items: DataFrame, text: str = "text", item: str = "text", most: int = ITEM_BYTES) -> DataFrame:
    """docs without those that contain one of the items' texts. Each document is read once by an automaton over a block of items, whatever their number."""
    sc = docs.sparkSession.sparkContext

    def without(df: DataFrame, block: list[str]) -> DataFrame:
        held = sc.broadcast(block)

        def run(batches):
            import ahocorasick

            found = ahocorasick.Automaton()
            for x in held.value:
                found.add_word(x, 1)
            found.make_automaton()
            for batch in batches:
                clean = [not t or next(found.iter(t), None) is None for t in batch.column(text).to_pylist()]
                yield batch.filter(pa.array(clean, pa.bool_()))

        return df.mapInArrow(run, df.schema)

    return reduce(without, item_blocks(items, item, most), docs)


def train_documents(spark: SparkSession, sf_dir: str, leaks: bool = False) -> DataFrame:
    """lang, doc_id, text of the documents that aren't held out, by default without those that contain a benchmark item."""
    docs = table(spark, sf_dir, "documents").where(F.col("doc_id") % HELD_OUT != 0).select("lang", "doc_id", "text")
    return docs if leaks else without_leaks(docs, table(spark, sf_dir, "benchmark"))


def train_lines(spark: SparkSession, sf_dir: str, leaks: bool = False) -> DataFrame:
    """lang, doc_id, line_no, line of the training documents."""
    return lines(train_documents(spark, sf_dir, leaks), "text", "lang", "doc_id")


def document_statements(docs: DataFrame) -> DataFrame:
    """lang, stmt_id, half, text: every line of documents is a statement, called d and the document's id, a colon and the line's number. Halves are of documents."""
    each = lines(docs, "text", "lang", "doc_id")
    half = (F.floor(F.col("doc_id") / HELD_OUT) % 2).cast("int")
    return each.select("lang", F.concat(F.lit("d"), F.col("doc_id").cast("string"), F.lit(":"), F.col("line_no").cast("string")).alias("stmt_id"), half.alias("half"), F.col("line").alias("text"))


def benchmark(spark: SparkSession, sf_dir: str) -> DataFrame:
    """lang, stmt_id, half, text: the benchmark's items, b and the item's id, as English statements; their line feeds are blanks."""
    items = table(spark, sf_dir, "benchmark").where(F.length("text") > 0)
    return items.select(F.lit("en").alias("lang"), F.concat(F.lit("b"), F.col("item_id").cast("string")).alias("stmt_id"), (F.col("item_id") % 2).cast("int").alias("half"), F.translate("text", "\n", " ").alias("text"))


def corpus_statements(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every line of every document as a statement."""
    return document_statements(table(spark, sf_dir, "documents"))


def statements(spark: SparkSession, sf_dir: str) -> DataFrame:
    """lang, stmt_id, half, text: the test statements, whole: the benchmark's items and every line of the held-out documents."""
    held = table(spark, sf_dir, "documents").where(F.col("doc_id") % HELD_OUT == 0)
    return benchmark(spark, sf_dir).unionByName(document_statements(held))


def strip_spaces(df: DataFrame, text: str = "text") -> DataFrame:
    """df without the blanks of its texts."""
    return df.withColumn(text, F.translate(text, " ", ""))


def unspaced(statements: DataFrame) -> tuple[DataFrame, DataFrame]:
    """Statements without blanks, and the reference tokens (lang, stmt_id, tok_no, token) from before the blanks were taken out: what a script without blanks is scored against."""
    from ..operators import baselines

    return strip_spaces(statements).where("text <> ''"), baselines.reference_tokens(statements)


def bucket_share(df: DataFrame, key: str, of: int, takes: list[int]) -> DataFrame:
    """The rows whose key falls into the given residues: a sample that can be repeated."""
    return df.where((F.col(key) % of).isin(takes))


#: What of a page is no text.
HIDDEN = r"(?is)<(script|style)\b.*?</\1\s*>|<!--.*?-->"
#: Elements that give lines; a paragraph also ends where the next one begins or what holds it ends.
ELEMENTS = {
    "title": r"(?is)<title(?:\s[^>]*)?>(.*?)</title\s*>",
    "heading": r"(?is)<h[1-6](?:\s[^>]*)?>(.*?)</h[1-6]\s*>",
    "paragraph": r"(?is)<p(?:\s[^>]*)?>(.*?)(?=</?p[\s>]|</(?:article|body|html)[\s>]|\z)",
}
ENTITIES = {"&lt;": "<", "&gt;": ">", "&quot;": '"', "&#39;": "'", "&amp;": "&"}


def untagged(html: Column) -> Column:
    """The text of a piece of HTML: tags are taken out, the five common entities decoded, runs of white space made one blank."""
    bare = F.regexp_replace(html, r"<[^>]*>", "")
    for entity, symbol in ENTITIES.items():
        bare = F.replace(bare, F.lit(entity), F.lit(symbol))
    return F.trim(F.regexp_replace(bare, r"[ \t\r\n\f]+", " "))


def html_lines(pages: DataFrame, html: str = "html", key: str = "page_id") -> DataFrame:
    """key, kind, line: the titles, headings and paragraphs of pages, whatever tags they hold, each a line of its own. One pass over a page."""
    seen = pages.select(key, F.regexp_replace(html, HIDDEN, "").alias("h"))
    found = F.array(*(F.struct(F.lit(kind).alias("kind"), F.regexp_extract_all("h", F.lit(p), F.lit(1)).alias("parts")) for kind, p in ELEMENTS.items()))
    each = seen.select(key, F.inline(found)).select(key, "kind", F.explode("parts").alias("part"))
    return each.select(key, "kind", untagged(F.col("part")).alias("line")).where("line <> ''")


def json_lines(records: DataFrame, json: str, fields: list[str], *keys: str) -> DataFrame:
    """keys, field, line: the named text fields of JSON records, each a line of its own."""
    pairs = F.array(*(F.struct(F.lit(f).alias("field"), F.get_json_object(json, f"$.{f}").alias("line")) for f in fields))
    return records.select(*keys, F.inline(pairs)).where("line is not null and line <> ''")


def text_lines(spark: SparkSession, path: str) -> DataFrame:
    """line of plain text files."""
    return spark.read.text(path).select(F.col("value").alias("line")).where("line <> ''")


def read_lexicon(spark: SparkSession, path: str) -> DataFrame:
    """word, freq of CSV files with that header."""
    return spark.read.schema("word string, freq long").option("header", True).csv(path)


def write_lexicon(lexicon: DataFrame, path: str) -> None:
    lexicon.select("word", "freq").write.mode("overwrite").option("header", True).csv(path)


def sequences(df: DataFrame, entity: str, order: list[str], symbol: Column) -> DataFrame:
    """entity, line: one symbol for each row, in order. Rows are dealt out by ranges of entity and order, so one with very many rows lies in several tasks; each strings together what it has, and the pieces of an entity, as many as tasks at most, are put together."""
    rows = df.select(F.col(entity), *(F.col(c) for c in order), symbol.alias("__s")).where(F.col("__s").isNotNull())
    dealt = rows.repartitionByRange(entity, *order).sortWithinPartitions(entity, *order)

    def run(batches):
        now, parts = None, []
        for batch in batches:
            names, symbols = batch.column(0).to_pylist(), batch.column(1).to_pylist()
            for name, part in groupby(zip(names, symbols, strict=True), key=lambda x: x[0]):
                if parts and name != now:
                    yield piece(now, parts, batch)
                    parts = []
                now = name
                parts.append("".join(s for _, s in part))
        if parts:
            yield piece(now, parts, batch)

    def piece(name, parts, like):
        return pa.RecordBatch.from_arrays([pa.array([name], like.schema.field(0).type), pa.array(["".join(parts)], pa.string())], [entity, "piece"])

    made = dealt.select(entity, "__s").mapInArrow(run, f"`{entity}` {rows.schema[entity].dataType.simpleString()}, piece string").withColumn("no", F.spark_partition_id())
    whole = F.array_sort(F.collect_list(F.struct("no", "piece")))
    return made.groupBy(entity).agg(F.array_join(F.transform(whole, lambda x: x["piece"]), "").alias("line"))


def event_sequences(spark: SparkSession, sf_dir: str) -> DataFrame:
    """user_id, line: a user's events in order of time, the first letter of each type."""
    return sequences(table(spark, sf_dir, "events"), "user_id", ["ts", "event_id"], F.left("event_type", F.lit(1)))
