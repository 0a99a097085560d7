"""Line dedup: winnowed line fingerprints find repeated runs of lines; all but the first copy of a run are deleted.

A window is a smallest stretch of whole lines with at least `min_words` words, taken forward from each line and backward
from each line. Its line of least hash is its anchor, so two texts that share a window choose the same anchor in it: any
run of equal lines with min_words words holds a whole window and is found for certain. A fingerprint is the anchor's hash
with the window's, so that a common line in other surroundings is another fingerprint. Each fingerprint is joined to the
position where it comes first, matches are extended both ways line by line, and the later run goes.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from fewbit.llm._shingles import U, mix, text_stretches
from fewbit.llm._store import Stored, sifted, table
from fewbit.llm._worker import fresh, release

MIN_WORDS = 50
_BASE = 0xD6E8FEB86659FD93


def line_windows(hashes: np.ndarray, words: np.ndarray, min_words: int) -> tuple[np.ndarray, ...]:
    """(fingerprint, anchor line, first line, last line) of every window of a text."""
    n = len(hashes)
    cum = np.concatenate([[0], np.cumsum(words)])
    line = np.arange(n)
    ahead = np.searchsorted(cum, cum[:-1] + min_words, "left") - 1
    back = np.searchsorted(cum, cum[1:] - min_words, "right") - 1
    # windows begin and end with words: lines without any between them are in it, so that no line is in many windows
    told = words > 0
    front, rear = told & (ahead < n), told & (back >= 0)
    lo = np.concatenate([line[front], back[rear]])
    hi = np.concatenate([ahead[front], line[rear]])
    if not len(lo):
        return (np.zeros(0, np.int64),) * 4
    both = np.unique(lo * n + hi)
    lo, hi = both // n, both % n
    up = np.multiply.accumulate(np.concatenate([[U(1)], np.full(n, _BASE, U)]))
    down = np.multiply.accumulate(np.concatenate([[U(1)], np.full(n, pow(_BASE, -1, 1 << 64), U)]))
    total = np.concatenate([[U(0)], np.cumsum(hashes * up[:n], dtype=U)])
    content = (total[hi + 1] - total[lo]) * down[lo]
    anchor = np.fromiter((a + int(hashes[a : b + 1].argmin()) for a, b in zip(lo.tolist(), hi.tolist(), strict=True)), np.int64, len(lo))
    return mix(hashes[anchor] ^ mix(content + (hi - lo).astype(U))).view(np.int64), anchor, lo, hi


def _fingerprints(min_words: int):
    """(doc, line hashes as bytes, windows) from (doc, text)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        names = ["doc", "lines", "windows"]
        kind = pa.list_(pa.struct([("fp", pa.int64()), ("at", pa.int64()), ("lo", pa.int64()), ("hi", pa.int64())]))
        fresh()
        for batch in batches:
            for lo, texts in text_stretches(batch.column(1)):
                raw, windows = [], []
                for text in texts:
                    parts = text.split(b"\n")
                    hashes = np.fromiter(map(xxhash.xxh3_64_intdigest, parts), U, len(parts))
                    words = np.fromiter((len(p.split()) for p in parts), np.int64, len(parts))
                    raw.append(hashes.tobytes())
                    windows.append(line_windows(hashes, words, min_words))
                sizes = np.cumsum([0, *(len(w[0]) for w in windows)]).astype(np.int32)
                flat = [pa.array(np.concatenate([w[i] for w in windows])) for i in range(4)]
                made = pa.ListArray.from_arrays(sizes, pa.StructArray.from_arrays(flat, fields=list(kind.value_type)))
                yield pa.RecordBatch.from_arrays([batch.column(0).slice(lo, len(texts)), pa.array(raw, pa.binary()), made], names)
            release()

    return run


def _extend(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """(doc, [(lo, hi)]) from (doc, source, shift, spans, lines of doc, lines of source): spans grown while lines are equal."""
    fresh()
    for batch in batches:
        out = []
        shifts = batch.column(2).to_pylist()
        for shift, spans, own, other in zip(shifts, batch.column(3).to_pylist(), batch.column(4), batch.column(5), strict=True):
            a, b = np.frombuffer(own.as_py(), U), np.frombuffer(other.as_py(), U)
            first = max(0, shift)
            n = min(len(a), len(b) + shift) - first
            odd = np.flatnonzero(a[first : first + n] != b[first - shift : first - shift + n]) + first
            runs = set()
            for s in spans:
                k = int(np.searchsorted(odd, s["lo"]))
                runs.add((int(odd[k - 1]) + 1 if k else first, int(odd[k]) - 1 if k < len(odd) else first + n - 1))
            out.append([{"lo": lo, "hi": hi} for lo, hi in sorted(runs)])
        kind = pa.list_(pa.struct([("lo", pa.int64()), ("hi", pa.int64())]))
        yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(out, kind)], ["doc", "runs"])


def repeated_runs(docs: DataFrame, min_words: int = MIN_WORDS) -> DataFrame:
    """(doc, runs array of (lo, hi) line numbers from 0) of documents with lines to delete; runs may overlap."""
    own = docs.select(F.col("doc_id").cast("long").alias("doc"), "text").where("doc IS NOT NULL AND text IS NOT NULL")
    kind = "doc long, lines binary, windows array<struct<fp:long,at:long,lo:long,hi:long>>"
    marked = Stored(own.mapInArrow(_fingerprints(min_words), kind)).df
    windows = marked.select("doc", F.explode("windows").alias("w")).select("doc", "w.*")
    firsts = windows.groupBy("fp").agg(F.min(F.struct("doc", "at")).alias("s"), F.count("*").alias("n")).where("n > 1").select("fp", "s")
    matches = windows.join(firsts, "fp").where(F.struct("doc", "at") > F.col("s"))
    lanes = matches.groupBy("doc", F.col("s.doc").alias("source"), (F.col("at") - F.col("s.at")).alias("shift")).agg(
        F.collect_set(F.struct("lo", "hi")).alias("spans")
    )
    lines = marked.select("doc", "lines")
    met = lanes.join(lines, "doc").join(lines.withColumnRenamed("doc", "source").withColumnRenamed("lines", "other"), "source")
    grown = met.select("doc", "source", "shift", "spans", "lines", "other").mapInArrow(_extend, "doc long, runs array<struct<lo:long,hi:long>>")
    return grown.groupBy("doc").agg(F.array_sort(F.array_distinct(F.flatten(F.collect_list("runs")))).alias("runs"))


def _merged(runs: list[dict]) -> list[tuple[int, int]]:
    """Disjoint runs in order, of runs sorted by their first lines."""
    out: list[tuple[int, int]] = []
    for r in runs:
        if out and r["lo"] <= out[-1][1] + 1:
            out[-1] = out[-1][0], max(out[-1][1], r["hi"])
        else:
            out.append((r["lo"], r["hi"]))
    return out


def _cut(names: list[str]):
    """Rows with their text cut by their runs, the last column, which n_removed and removed replace; null runs cut nothing."""
    at = names.index("text")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        fresh()
        for batch in batches:
            text, gone, said = [], [], []
            for i, runs in enumerate(batch.column(len(names)).to_pylist()):
                own = batch.column(at)[i].as_py()
                if own is None or not runs:
                    text.append(own)
                    gone.append(0)
                    said.append("")
                    continue
                lines, merged, kept, last = own.split("\n"), _merged(runs), [], 0
                for lo, hi in merged:
                    kept += lines[last:lo]
                    last = hi + 1
                text.append("\n".join(kept + lines[last:]))
                gone.append(sum(hi - lo + 1 for lo, hi in merged))
                said.append(",".join(f"{lo}-{hi}" for lo, hi in merged))
            columns = [*batch.columns[:-1], pa.array(gone, pa.int64()), pa.array(said, pa.string())]
            columns[at] = pa.array(text, pa.string())
            yield pa.RecordBatch.from_arrays(columns, [*names, "n_removed", "removed"])
            del text, columns
            release()

    return run


def dedup_lines(docs: DataFrame, min_words: int = MIN_WORDS) -> DataFrame:
    """docs with the later copies of repeated runs cut from the text, and columns n_lines, n_removed, removed.

    A line goes if it lies in a run of consecutive lines, with min_words words together at least, that equals an earlier
    run (of a smaller doc_id, or further up in the text); every line's first copy stays. Lines are parted by "\\n" and
    compared as they are. `removed` lists the deleted stretches as lo-hi. Null texts stay null and rows without doc_id stay
    as they are; repeated doc_ids are one source but each row is cut. Clashing columns of the three names are replaced.
    Texts without anything to delete are not shuffled.
    """
    base = docs.drop("n_lines", "n_removed", "removed")
    base = base.withColumn("n_lines", F.size(F.split("text", "\n", -1)).cast("long"))
    runs = Stored(repeated_runs(docs, min_words)).df.withColumnRenamed("doc", "__doc").withColumnRenamed("runs", "__runs")
    flagged = sifted(base, runs.select("__doc"), "doc_id")
    whole = [F.lit(0).cast("long").alias("n_removed"), F.lit("").alias("removed")]
    names, quoted = base.columns, [F.col(f"`{c}`") for c in base.columns]
    clean = flagged.where("NOT __maybe").select(*quoted, *whole)
    met = flagged.where("__maybe").join(runs, F.col("doc_id") == F.col("__doc"), "left").select(*quoted, "__runs")
    schema = T.StructType([*base.schema.fields, T.StructField("n_removed", T.LongType()), T.StructField("removed", T.StringType())])
    return clean.unionByName(met.mapInArrow(_cut(names), schema))


def without_repeats(docs: DataFrame, min_words: int = MIN_WORDS) -> DataFrame:
    """docs with repeated runs cut, n_chars to match, and without the documents of which nothing but space is left."""
    cut = dedup_lines(docs, min_words).where("n_removed = 0 OR trim(text) <> ''")
    if "n_chars" in docs.columns:
        changed = F.when(F.col("n_removed") > 0, F.length("text")).otherwise(F.col("n_chars"))
        cut = cut.withColumn("n_chars", changed.cast(docs.schema["n_chars"].dataType))
    return cut.select(*[F.col(f"`{c}`") for c in docs.columns])


def op4_line_winnowing(spark, sf_dir):
    return dedup_lines(table(spark, sf_dir, "documents").select("doc_id", "text"))
