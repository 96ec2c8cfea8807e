"""The gram model: counts of grams (vertices) and of what follows and precedes them (edges).

One window of up to n + 1 symbols is counted for each place of a line; a gram's count is the sum over the windows that
begin with it, and an edge is a longer gram split in two. So text is read once and shuffled as counted windows only.
A model is keyed by `lang`; any other name of a corpus can stand there.
"""

from __future__ import annotations

from functools import reduce
from itertools import chain

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions import kernels
from . import packed

KEYS = ("lang", "n", "gram")
#: Symbols that are counted in arrays at once.
BATCH_SYMBOLS = 1_000_000
#: Distinct windows, of 16 bytes each, that a task holds before it lets go of their counts.
HELD_WINDOWS = 6_000_000
#: Grams of so many symbols are many to a task, so they are shuffled in packed arrays.
PACKED_FROM = 5


def windows(lines: DataFrame, most: int) -> DataFrame:
    """lang, w: at each place of each line the next `most` symbols, fewer at the end. One linear scan of a line in the JVM."""
    return lines.select("lang", F.explode(F.regexp_extract_all("line", F.lit(rf"(?s)(?=(.{{1,{most}}}))."), F.lit(1))).alias("w"))


def count_grams(lines: DataFrame, n_max: int) -> DataFrame:
    """lang, n, gram, cnt for n from 1 to n_max. From PACKED_FROM symbols on see `packed.count_grams`. Else a task counts the windows of all its lines in arrays and takes the shorter grams from them, so each of a task's grams is shuffled once, or as often as more than HELD_WINDOWS have to be let go. Lines without a language are left out."""
    if n_max >= PACKED_FROM:
        return packed.count_grams(lines, n_max)

    def rows(lang, n, grams, counts):
        return pa.RecordBatch.from_arrays([pa.array([lang], pa.string()).take(pa.array(np.zeros(len(grams), np.int32))), pa.array(np.full(len(grams), n, np.int32)), grams, pa.array(counts)], ["lang", "n", "gram", "c"])

    def taken_apart(lang, lines):
        """Of lines with too many symbols."""
        w, c = kernels.count_windows(lines, n_max)
        w, c = pa.array(w, pa.string()), pa.array(c)
        for n in range(1, n_max + 1):
            whole = pc.greater_equal(pc.utf8_length(w), n)
            got = pa.table({"w": pc.utf8_slice_codeunits(w.filter(whole), 0, n), "c": c.filter(whole)}).group_by("w").aggregate([("c", "sum")]).combine_chunks()
            for part in got.to_batches():
                yield rows(lang, n, part.column("w"), part.column("c_sum").to_numpy())

    def run(batches):
        held, own, size = kernels.WindowCounts(n_max), {}, 0
        for batch in chain(batches, [None]):
            if batch is not None:
                langs = batch.column("lang").dictionary_encode()
                at, texts = langs.indices.to_numpy(zero_copy_only=False), batch.column("line")
                for k, lang in enumerate(langs.dictionary.to_pylist()):
                    some = texts.filter(pa.array(at == k)).to_pylist()
                    own.setdefault(lang, []).extend(some)
                    size += sum(map(len, some))
            if batch is None or size > BATCH_SYMBOLS:
                for lang, some in own.items():
                    if not held.add(lang, some):
                        yield from (rows(*x) for x in held.grams())
                        held = kernels.WindowCounts(n_max)
                        if not held.add(lang, some):
                            yield from taken_apart(lang, some)
                own, size = {}, 0
            if batch is None or len(held) > HELD_WINDOWS:
                yield from (rows(*x) for x in held.grams())

    made = lines.select("lang", "line").where(F.col("lang").isNotNull() & F.col("line").isNotNull()).mapInArrow(run, "lang string, n int, gram string, c long")
    return made.groupBy("lang", "n", "gram").agg(F.sum("c").alias("cnt"))


def count_grams_once(lines: DataFrame, n_max: int) -> DataFrame:
    """As count_grams in a single aggregation, for streams: every window is taken apart before it is counted."""
    each = windows(lines, n_max).select("lang", "w", F.explode(F.sequence(F.lit(1), F.length("w"))).alias("n"))
    return each.groupBy("lang", "n", F.expr("left(w, n)").alias("gram")).agg(F.count("*").alias("cnt"))


def symbol_edges(grams: DataFrame, dir_: str) -> DataFrame:
    """lang, n, dir, gram, nbr, cnt: the symbols after (dir_ "f") or before ("b") each gram, as projections of the longer grams."""
    longer = grams.where("n > 1")
    if dir_ == "f":
        gram, nbr = F.expr("left(gram, n - 1)"), F.expr("right(gram, 1)")
    else:
        gram, nbr = F.expr("substring(gram, 2)"), F.expr("left(gram, 1)")
    return longer.select("lang", (F.col("n") - 1).alias("n"), F.lit(dir_).alias("dir"), gram.alias("gram"), nbr.alias("nbr"), "cnt")


def edges(grams: DataFrame) -> DataFrame:
    """Symbol edges of both directions."""
    return symbol_edges(grams, "f").unionByName(symbol_edges(grams, "b"))


def gram_edges(lines: DataFrame, n: int, dir_: str) -> DataFrame:
    """lang, n, dir, gram, nbr, cnt where nbr is the gram of n symbols next to a gram of n symbols."""
    counted = windows(lines, 2 * n).where(F.length("w") == 2 * n).groupBy("lang", "w").agg(F.count("*").alias("cnt"))
    head, tail = F.left("w", F.lit(n)), F.right("w", F.lit(n))
    gram, nbr = (head, tail) if dir_ == "f" else (tail, head)
    return counted.select("lang", F.lit(n).alias("n"), F.lit(dir_).alias("dir"), gram.alias("gram"), nbr.alias("nbr"), "cnt")


def wide_edges(grams: DataFrame, ranks) -> DataFrame:
    """lang, n, dir, gram, nbr, cnt of both directions where nbr is as long as gram, as projections of the grams of twice the ranks."""
    each = grams.where(F.col("n").isin([2 * n for n in ranks])).withColumn("n", (F.col("n") / 2).cast("int"))
    head, tail = F.expr("left(gram, n)"), F.expr("substring(gram, n + 1)")
    ways = F.array(F.struct(F.lit("f").alias("dir"), head.alias("gram"), tail.alias("nbr")), F.struct(F.lit("b").alias("dir"), tail.alias("gram"), head.alias("nbr")))
    return each.select("lang", "n", F.inline(ways), "cnt")


def merge(*parts: DataFrame) -> DataFrame:
    """The gram counts of the corpora together: counts add up, so no corpus is read again."""
    return reduce(DataFrame.unionByName, parts).groupBy(*KEYS).agg(F.sum("cnt").alias("cnt"))


def vertex_max(vertices: DataFrame) -> DataFrame:
    """lang, n, vmax: a row for each language and rank."""
    return vertices.groupBy("lang", "n").agg(F.max("cnt").alias("vmax"), F.sum("cnt").alias("vsum"))


def probability(vertices: DataFrame, scale: str = "max") -> DataFrame:
    """vertices with p, relative to the largest count of the rank ("max") or to their sum ("sum")."""
    return vertices.join(F.broadcast(vertex_max(vertices)), ["lang", "n"]).select(*KEYS, "cnt", (F.col("cnt") / F.col(f"v{scale}")).alias("p"))


def conditional(edge_rows: DataFrame, vertices: DataFrame) -> DataFrame:
    """Edges with cp, their share of the gram's count."""
    own = vertices.select(*KEYS, F.col("cnt").alias("c"))
    return edge_rows.join(own, list(KEYS)).select(*KEYS, "dir", "nbr", "cnt", (F.col("cnt") / F.col("c")).alias("cp"))


def freedom(edge_rows: DataFrame) -> DataFrame:
    """lang, n, gram, dir, tf, emax, esum: edges are distinct, so a count is the number of continuations."""
    return edge_rows.groupBy(*KEYS, "dir").agg(F.count("*").alias("tf"), F.max("cnt").alias("emax"), F.sum("cnt").alias("esum"))


def both_ways(free: DataFrame) -> DataFrame:
    """lang, n, gram, tf_f, tf_b with 0 where nothing follows or precedes."""
    way = lambda d: F.coalesce(F.max(F.when(F.col("dir") == d, F.col("tf"))), F.lit(0)).cast("long").alias(f"tf_{d}")
    return free.groupBy(*KEYS).agg(way("f"), way("b"))


def as_graph(vertices: DataFrame, edge_rows: DataFrame) -> tuple[DataFrame, DataFrame]:
    """Vertices (id, weight) and edges (src, dst, dir, weight) of the weighted graph. A gram's neighbour is a symbol, itself a vertex of rank 1."""
    key = lambda n, g: F.concat_ws("\u0001", "lang", n, g)
    return vertices.select(key("n", "gram").alias("id"), F.col("cnt").alias("weight")), edge_rows.select(
        key("n", "gram").alias("src"), key(F.lit("1"), "nbr").alias("dst"), "dir", F.col("cnt").alias("weight")
    )


def degree(vertices: DataFrame, edge_rows: DataFrame) -> DataFrame:
    """id, out_degree, in_degree of every vertex of the graph: how many symbols follow and precede it."""
    ways = edge_rows.groupBy(*KEYS).agg(F.count_if(F.col("dir") == "f").alias("out_degree"), F.count_if(F.col("dir") == "b").alias("in_degree"))
    zero = lambda c: F.coalesce(c, F.lit(0)).cast("long").alias(c)
    return vertices.join(ways, list(KEYS), "left").select(F.concat_ws("\u0001", "lang", "n", "gram").alias("id"), zero("out_degree"), zero("in_degree"))


def freedom_sketch(lines: DataFrame, n: int, lg_k: int = 12) -> DataFrame:
    """lang, n, gram, tf_f: approximate forward freedom, a mergeable sketch for each gram, for ranks whose edges are too many to count."""
    w = windows(lines, n + 1).where(F.length("w") == n + 1)
    gram = F.left("w", F.lit(n)).alias("gram")
    made = w.select("lang", F.lit(n).alias("n"), gram, F.right("w", F.lit(1)).alias("x")).groupBy(*KEYS).agg(F.hll_sketch_agg("x", F.lit(lg_k)).alias("s"))
    return made.select(*KEYS, F.hll_sketch_estimate("s").alias("tf_f"))


def save(grams: DataFrame, path: str) -> None:
    """Parquet by language and rank, so a lookup reads only the ranks it needs. Rows are dealt out by ranges, so the grams of a large rank lie in several tasks and files."""
    grams.repartitionByRange("lang", "n", "gram").write.mode("overwrite").partitionBy("lang", "n").parquet(path)


def load(spark: SparkSession, path: str) -> DataFrame:
    return spark.read.schema("gram string, cnt long, lang string, n int").parquet(path).select(*KEYS, "cnt")
