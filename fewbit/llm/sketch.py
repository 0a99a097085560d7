"""Document fingerprints by a threshold-scaled sketch: every shingle hash below a fixed share of the hash range is kept.

Sketches of any two documents, however unequal, hold the same share of their shingles, so unions, intersections and
containment follow from the sketches alone. A text with fewer than LEAST hashes below the threshold keeps its LEAST
smallest ones (all, if it has no more), so short texts have sketches too. Sketches stay mergeable: the sketch of a union
is the union of sketches cut by the same rule. Everything is DataFrame and SQL functions.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import Window

from fewbit.llm._store import stored, table
from fewbit.llm.pii import let

WORDS = 5
#: One hash in SCALE is kept.
SCALE = 8
#: Hashes that a sketch holds at least, if the text has as many.
LEAST = 16
#: Hashes are of 31 bits.
TOP = 2**31


def threshold(scale: int = SCALE) -> int:
    return TOP // scale


def sketch_sql(text: str, words: int = WORDS, scale: int = SCALE, least: int = LEAST) -> str:
    """SQL for the sorted int array of a text expression; empty for texts without words.

    Words are runs of non-space characters after lower-casing; a text with fewer words than a shingle is one shingle.
    """
    shingle = ", ".join(f"w[i + {k}]" for k in range(words))
    hashes = (
        f"transform(sequence(0, size(w) - {words}), i -> int(xxhash64({shingle}) & 2147483647L))"
    )
    return let(
        "w",
        f"filter(split(lower({text}), '\\\\s+'), x -> x <> '')",
        "CASE WHEN size(w) = 0 THEN CAST(array() AS array<int>) ELSE "
        + let(
            "h",
            f"CASE WHEN size(w) < {words} THEN array(int(xxhash64(array_join(w, ' ')) & 2147483647L)) ELSE {hashes} END",
            let(
                "below",
                f"array_sort(array_distinct(filter(h, x -> x < {threshold(scale)})))",
                f"CASE WHEN size(below) >= {least} THEN below ELSE slice(array_sort(array_distinct(h)), 1, {least}) END",
            ),
        )
        + " END",
    )


def as_text(sketch: Column) -> Column:
    """A sketch as fixed-width hexadecimal, eight digits a hash."""
    return F.array_join(F.transform(sketch, lambda x: F.lpad(F.lower(F.hex(x)), 8, "0")), "")


def _told(a: str, scale: int, least: int) -> str:
    """SQL for the hash up to which a sketch knows all of its text's hashes."""
    return f"(CASE WHEN size({a}) < {least} THEN {TOP} ELSE greatest(element_at({a}, -1), {threshold(scale) - 1}) END)"


def _compared(a: str, b: str, body: str, scale: int, least: int) -> Column:
    """body over p.a and p.b: the hashes of both sketches up to the greatest hash up to which both know all of theirs."""
    top = f"least({_told('s.a', scale, least)}, {_told('s.b', scale, least)})"
    kept = "named_struct('a', filter(s.a, x -> x <= top), 'b', filter(s.b, x -> x <= top))"
    return F.expr(let("s", f"named_struct('a', {a}, 'b', {b})", let("top", top, let("p", kept, body))))


def likeness(a: str, b: str, scale: int = SCALE, least: int = LEAST) -> Column:
    """Estimated Jaccard similarity of the texts of two sketch columns; exact where both hold all hashes. Two empty ones are alike."""
    body = let("n", "size(array_intersect(p.a, p.b))", "CASE WHEN size(p.a) + size(p.b) = 0 THEN double(size(s.a) = size(s.b)) ELSE n / double(size(p.a) + size(p.b) - n) END")
    return _compared(a, b, body, scale, least)


def containment(a: str, b: str, scale: int = SCALE, least: int = LEAST) -> Column:
    """Estimated share of a's shingles that b has; an empty a is contained in all."""
    return _compared(a, b, "CASE WHEN size(p.a) = 0 THEN double(size(s.a) = 0) ELSE size(array_intersect(p.a, p.b)) / double(size(p.a)) END", scale, least)


def merge(sketches: Column, scale: int = SCALE, least: int = LEAST) -> Column:
    """Aggregate: the sketch of the union of documents, the very one that all their shingles together would have."""
    union = F.array_sort(F.array_distinct(F.flatten(F.collect_list(sketches))))
    return F.filter(union, lambda x, i: (x < threshold(scale)) | (i < least))


def fingerprints(docs: DataFrame, text_col: str = "text", id_col: str = "doc_id") -> DataFrame:
    """(id, fingerprint int array), one row per row of docs; null text has the empty sketch."""
    return docs.select(id_col, F.expr(sketch_sql(f"coalesce(`{text_col}`, '')")).alias("fingerprint"))


def successors(ids: DataFrame, id_col: str = "doc_id") -> DataFrame:
    """(id, next_id, prev_id): the next and former distinct id in descending order, round the end; null ids are left out.

    Ids are range-partitioned and kept; each stretch is ordered by itself, and its ends meet those of the neighbouring
    stretches in a table of one row per partition.
    """
    laid = stored(ids.select(F.col(id_col).alias("i")).where("i IS NOT NULL").distinct().repartitionByRange(F.desc("i")).withColumn("p", F.spark_partition_id()))
    ends = laid.groupBy("p").agg(F.max("i").alias("top"), F.min("i").alias("low"))
    by_p = Window.orderBy("p")
    whole = by_p.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    ends = ends.select(
        "p",
        F.coalesce(F.lead("top").over(by_p), F.first("top").over(whole)).alias("after"),
        F.coalesce(F.lag("low").over(by_p), F.last("low").over(whole)).alias("before"),
    )
    order = Window.partitionBy("p").orderBy(F.desc("i"))
    inner = laid.select("p", "i", F.lead("i").over(order).alias("n"), F.lag("i").over(order).alias("b"))
    return inner.join(F.broadcast(ends), "p").select(
        F.col("i").alias(id_col), F.coalesce("n", "after").alias("next_id"), F.coalesce("b", "before").alias("prev_id")
    )


def edited_pairs(docs: DataFrame) -> DataFrame:
    """(doc_id, n_chars, edited, fingerprint, edited_fingerprint, next_fingerprint) of each distinct doc_id.

    The edited text swaps a document's last half for the beginning of the next document in descending doc_id. Rows
    that repeat a doc_id count as one, with the text of the smallest hash; a null text counts as empty, and rows
    without doc_id are left out. An empty table gives an empty one; other columns are not read.
    Each document sends its first half to its own row and only as much of its beginning as its predecessor needs to
    that one's, so whole texts move once and halves once more.
    """
    base = docs.select("doc_id", F.coalesce("text", F.lit("")).alias("text"))
    near = successors(base)
    sizes = stored(base.groupBy("doc_id").agg(F.min(F.struct(F.xxhash64("text").alias("h"), F.length("text").alias("n"))).alias("s")))
    need = near.join(sizes.select("doc_id", "s.h"), "doc_id").join(
        sizes.select(F.col("doc_id").alias("prev_id"), F.expr("s.n div 2").cast("int").alias("need")), "prev_id"
    ).select("doc_id", "h", "prev_id", "need")
    both = base.join(need, "doc_id").where(F.xxhash64("text") == F.col("h")).withColumn("n_chars", F.length("text").cast("long"))
    sent = both.withColumn("fp", F.expr(sketch_sql("text")))
    own = F.struct(
        F.col("doc_id").alias("to"), F.lit(True).alias("own"), F.expr("substring(text, 1, int(n_chars - n_chars div 2))").alias("part"), "n_chars", "fp"
    )
    other = F.struct(F.col("prev_id").alias("to"), F.lit(False).alias("own"), F.expr("substring(text, 1, need)").alias("part"), "n_chars", "fp")
    parts = sent.select(F.explode(F.array(own, other)).alias("s")).select("s.*")
    row = F.struct("part", "n_chars", "fp")
    met = parts.groupBy(F.col("to").alias("doc_id")).agg(
        F.min(F.when(F.col("own"), row)).alias("a"), F.min(F.when(~F.col("own"), row)).alias("b")
    )
    edited = met.select("doc_id", F.col("a.n_chars").alias("n_chars"), F.concat("a.part", "b.part").alias("edited"), F.col("a.fp").alias("fingerprint"), F.col("b.fp").alias("next_fingerprint"))
    return edited.withColumn("edited_fingerprint", F.expr(sketch_sql("edited")))


def op9_scaled_sketch(spark, sf_dir):
    pairs = edited_pairs(table(spark, sf_dir, "documents"))
    return pairs.select(
        "doc_id",
        "n_chars",
        F.sha2(F.col("edited").cast("binary"), 256).alias("edited_sha256"),
        as_text(F.col("fingerprint")).alias("fingerprint"),
        as_text(F.col("edited_fingerprint")).alias("edited_fingerprint"),
        likeness("fingerprint", "edited_fingerprint").alias("near_edited"),
        likeness("fingerprint", "next_fingerprint").alias("near_next"),
        containment("fingerprint", "edited_fingerprint").alias("contained_in_edited"),
    )
