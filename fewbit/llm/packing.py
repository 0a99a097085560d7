"""Best-two-fit packing of tokenised documents into sequences of a fixed length.

A sequence is filled greedily with the longest pieces that fit; then its shortest piece gives way to two unpacked ones if
these fill the widened gap more tightly. Pieces of one length are alike, so the plan is made on the histogram of lengths:
each step packs one pattern of lengths as often as the histogram allows, which exhausts a length. The plan's size follows
from the sequence length alone, and the pieces find their places by their rank among those of their length.
"""

from __future__ import annotations

import json
import re
from array import array
from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import public_tokenizers
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from fewbit.llm._shingles import text_stretches
from fewbit.llm._store import stored, table
from fewbit.llm._worker import kept, release

LENGTH = 4096
END = 1
CACHE = 270_000
#: Rows that one window task ranks, about.
SHARE = 100_000


def pack_histogram(counts: dict[int, int], length: int) -> list[tuple[list[int], int]]:
    """(lengths of one sequence, how many such sequences), until all pieces are packed."""
    left = np.zeros(length + 1, np.int64)
    for size, n in counts.items():
        left[size] = n
    out = []
    while (sizes := np.flatnonzero(left)).size:
        taken: Counter = Counter()
        pattern, gap = [], length
        while True:
            k = int(np.searchsorted(sizes, gap, "right")) - 1
            while k >= 0 and taken[int(sizes[k])] >= left[sizes[k]]:
                k -= 1
            if k < 0:
                break
            size = int(sizes[k])
            pattern.append(size)
            taken[size] += 1
            gap -= size
        if len(pattern) > 1 and gap:
            least = pattern[-1]
            pair = _best_two(sizes, left, taken, gap + least)
            if pair and sum(pair) > least:
                pattern[-1:] = pair
        need = Counter(pattern)
        times = min(int(left[size]) // n for size, n in need.items())
        for size, n in need.items():
            left[size] -= n * times
        out.append((pattern, times))
    return out


def _best_two(sizes: np.ndarray, left: np.ndarray, taken: Counter, room: int) -> list[int] | None:
    """The two unpacked pieces that fill the room best, the larger first."""
    free = left[sizes] - np.fromiter((taken[s] for s in sizes.tolist()), np.int64, len(sizes))
    open_, free = sizes[free > 0], free[free > 0]
    big = open_[open_ < room]
    if not len(big):
        return None
    k = np.minimum(np.searchsorted(open_, room - big, "right") - 1, np.arange(len(big)))
    alone = (k == np.arange(len(big))) & (free[: len(big)] < 2)
    k = np.where(alone, k - 1, k)
    total = np.where(k >= 0, big + open_[np.maximum(k, 0)], 0)
    best = len(total) - 1 - int(total[::-1].argmax())
    return [int(big[best]), int(open_[k[best]])] if total[best] else None


@dataclass
class Plan:
    """By length, in order of rank: first rank of a run of places, its first sequence, the offset in each."""

    runs: dict[int, tuple[np.ndarray, np.ndarray, np.ndarray]]
    sequences: int

    @classmethod
    def of(cls, counts: dict[int, int], length: int) -> Plan:
        used: Counter = Counter()
        runs: dict[int, list[tuple[int, int, int]]] = {}
        base = 0
        for pattern, times in pack_histogram(counts, length):
            offset = 0
            for size in pattern:
                runs.setdefault(size, []).append((used[size], base, offset))
                used[size] += times
                offset += size
            base += times
        return cls({size: tuple(np.array(r).T) for size, r in runs.items()}, base)


#: What a byte of a text may be to PlainChunks.
SPACE, LETTER, DIGIT, MARK, OTHER = range(5)


def _kinds(plain: bool) -> np.ndarray:
    out = np.full(256, OTHER, np.uint8)
    if plain:
        for kind, those in ((LETTER, r"[A-Za-z]"), (DIGIT, r"[0-9]"), (MARK, r"[!-&(-/:;=>?@\[-`{}~]")):
            out[[b for b in range(128) if re.fullmatch(those, chr(b))]] = kind
    out[[32, *range(9, 14)]] = SPACE
    return out


_LOWER = np.frombuffer(bytes(range(256)).lower(), np.uint8)


class PlainChunks:
    """Ids of chunks of Latin-1 letters, digits and ASCII marks by the tokenizer's model alone, piece by piece.

    On such text the normaliser only lower-cases and the splitter's classes are short ranges, so both are done here; pieces
    are far fewer than chunks. It serves tokenizers of that one shape; for others, and other chunks, it has no answer.
    """

    #: How the tokenizer file must normalise and split.
    SHAPE = ["NFC", "Replace", "Lowercase"], ["Split", "ByteLevel"], r"'s|'t|'re|'ve|'m|'ll|'d|[\p{L}]+|[\p{N}]|[^\s\p{L}\p{N}]+"
    # without what the names of special tokens are made of
    WHOLE = re.compile(r"[A-Za-z0-9\u00c0-\u00d6\u00d8-\u00f6\u00f8-\u00ff!-/:;=>?@\[-`{}~]+").fullmatch
    PIECES = re.compile(r"'s|'t|'re|'ve|'m|'ll|'d|[a-z\u00df-\u00f6\u00f8-\u00ff]+|[0-9]|[^a-z\u00df-\u00f6\u00f8-\u00ff0-9]+").findall

    def __init__(self, text: str, inner, cache: int):
        norm, split = (json.loads(text).get(k) or {} for k in ("normalizer", "pre_tokenizer"))
        norms, splits = norm.get("normalizers", []), split.get("pretokenizers", [])
        regexp = splits[0].get("pattern", {}).get("Regex") if splits else None
        self.fits = ([n["type"] for n in norms], [x["type"] for x in splits], regexp) == self.SHAPE and not splits[1]["add_prefix_space"]
        self.tokenize, self.limit = inner.model.tokenize, cache
        # the splitter writes each byte as one character; ASCII marks and letters stand for themselves
        self.bytes = {c: inner.pre_tokenizer.pre_tokenize_str(chr(c))[0][0] for c in range(0xDF, 0x100) if c != 0xF7} if self.fits else {}
        self.kinds = _kinds(self.fits)
        self.seen: dict[str, bytes] = {}
        self.old: dict[str, bytes] = {}

    def parted(self, raw: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(the bytes, plain chunks in lower case; where pieces begin) of bytes that end with a space.

        Plain chunks are parted as the splitter does it; a chunk with anything else, or an apostrophe, is one piece, and so
        is the space between two chunks.
        """
        kind, low = self.kinds[raw], _LOWER[raw]
        if self.fits and len(lead := np.flatnonzero(raw == 0xC3)):
            # letters of two bytes: all of that lead but two signs
            after = raw[lead + 1]
            good = (after >= 0x80) & (after <= 0xBF) & (after != 0x97) & (after != 0xB7)
            lead, after = lead[good], after[good]
            kind[lead] = kind[lead + 1] = LETTER
            low[lead + 1] = np.where(after <= 0x9E, after + 0x20, after)
        begin = np.ones(len(raw), bool)
        np.not_equal(kind[1:], kind[:-1], out=begin[1:])
        begin |= kind == DIGIT
        if len(other := np.flatnonzero(kind == OTHER)):
            gaps = np.flatnonzero(kind == SPACE)
            k = np.unique(np.searchsorted(gaps, other))
            lo, hi = np.where(k > 0, gaps[k - 1] + 1, 0), gaps[k]
            inside = np.zeros(len(raw), np.int8)
            inside[lo] = 1
            inside[hi] = -1
            inside = np.cumsum(inside, dtype=np.int8).view(bool)
            begin[inside] = False
            begin[lo] = True
            low[inside] = raw[inside]
        return low, np.flatnonzero(begin)

    def ids(self, chunks: list[bytes]) -> tuple[dict[bytes, bytes], list[tuple[bytes, str]]]:
        """(ids by chunk, the others with their text); chunks hold no ASCII space."""
        done, rest = {}, []
        if not chunks:
            return done, rest
        joined = b"\n".join(chunks).decode("utf-8", "replace")
        for chunk, text, low in zip(chunks, joined.split("\n"), joined.lower().split("\n"), strict=True):
            if not self.fits or not ((letters := text.isascii() and text.isalpha()) or self.WHOLE(text)):
                rest.append((chunk, text))
            elif letters or low.isalpha():
                # kept by the caller
                done[chunk] = self._made(low)
            else:
                done[chunk] = b"".join([self.seen.get(p) or self._piece(p) for p in self.PIECES(low)])
        return done, rest

    def _made(self, piece: str) -> bytes:
        return array("I", [t.id for t in self.tokenize(piece if piece.isascii() else piece.translate(self.bytes))]).tobytes()

    def _piece(self, piece: str) -> bytes:
        found = self.old.get(piece)
        if found is None:
            found = self._made(piece)
        if len(self.seen) >= self.limit:
            self.old, self.seen = self.seen, {}
        self.seen[piece] = found
        return found


class ChunkTokenizer:
    """Ids of texts by a tokenizer whose normaliser and splitter never join what ASCII space parts; pieces are cached."""

    def __init__(self, path_or_json: str, cache: int = CACHE):
        from tokenizers import Tokenizer

        self.inner = Tokenizer.from_str(path_or_json)
        self.plain = PlainChunks(path_or_json, self.inner, cache // 2)
        # two generations: what is used again survives when the younger one is full
        self.seen: dict[bytes, bytes] = {}
        self.old: dict[bytes, bytes] = {}
        # more texts at a time are quicker, and hold more on the way
        self.limit, self.step = cache, max(64, cache // 270)

    def encode(self, texts: list[bytes]) -> Iterator[bytes]:
        """Ids as unsigned 32-bit words. Texts are parted by numpy and put together by Arrow, so Python sees distinct pieces."""
        for lo in range(0, len(texts), self.step):
            some = texts[lo : lo + self.step]
            raw = np.frombuffer(b" ".join([*some, b""]), np.uint8)
            low, begins = self.plain.parted(raw)
            bounds = pa.py_buffer(np.append(begins, len(raw)))
            pieces = pa.LargeBinaryArray.from_buffers(pa.large_binary(), len(begins), [None, bounds, pa.py_buffer(low)]).dictionary_encode()
            made = pa.array(self._ids(pieces.dictionary.to_numpy(zero_copy_only=False).tolist()), pa.large_binary()).take(pieces.indices)
            _, ends, held = made.buffers()
            # what parts two texts is a piece without ids, or in one
            at = np.searchsorted(begins, np.cumsum([0, *(len(t) + 1 for t in some)]))
            at = np.frombuffer(ends, np.int64)[at]
            ids = memoryview(held or b"")
            for i in range(len(some)):
                yield bytes(ids[at[i] : at[i + 1]])

    def _ids(self, chunks: list[bytes]) -> list[bytes]:
        if len(self.seen) > self.limit:
            self.old, self.seen = self.seen, {}
        words = set(chunks).difference(self.seen)
        self.seen.update((w, self.old[w]) for w in words & self.old.keys())
        words = words.difference(self.old)
        spaces = {w for w in words if w.isspace()}
        self.seen.update(dict.fromkeys(spaces, b""))
        done, rest = self.plain.ids(list(words - spaces))
        self.seen.update(done)
        for at in range(0, len(rest), 1_000):
            some = rest[at : at + 1_000]
            found = self.inner.encode_batch_fast([t for _, t in some], add_special_tokens=False)
            self.seen.update((w, array("I", e.ids).tobytes()) for (w, _), e in zip(some, found, strict=True))
        return list(map(self.seen.__getitem__, chunks))


def _cut(tokenizer: str, length: int, end: int, cache: int):
    """Pieces (row, doc, piece, start, length, ids) of each document; row tells stored pieces apart."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        import gc
        import os

        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        gc.disable()  # nothing here is cyclic, and walking the caches costs a tenth of the time
        encoder, last = kept(("tokenizer", tokenizer, cache), lambda: ChunkTokenizer(tokenizer, cache)), np.array([end], "<u4").tobytes()
        row = TaskContext.get().partitionId() << 33
        names = ["row", "doc_id", "piece", "start", "length", "ids"]
        for batch in batches:
            every = (raw for _, texts in text_stretches(batch.column(1)) for raw in encoder.encode(texts))
            doc, piece, start, ids, held = [], [], [], [], 0

            def rows():
                size = np.array([len(i) // 4 for i in ids], np.int64)
                number = np.arange(row, row + len(ids), dtype=np.int64)
                of = pa.array(doc, batch.schema[0].type)
                return pa.RecordBatch.from_arrays([pa.array(number), of, pa.array(piece, pa.int32()), pa.array(start, pa.int64()), pa.array(size), pa.array(ids, pa.binary())], names)

            for i, raw in zip(batch.column(0).to_pylist(), every, strict=True):
                raw += last
                for n, at in enumerate(range(0, len(raw), 4 * length)):
                    doc.append(i)
                    piece.append(n)
                    start.append(at // 4)
                    ids.append(raw[at : at + 4 * length])
                held += len(raw)
                if held > 1 << 20:
                    yield rows()
                    row += len(ids)
                    doc, piece, start, ids, held = [], [], [], [], 0
            if ids:
                yield rows()
                row += len(ids)
            del doc, piece, start, ids, every
            release()
        gc.enable()

    return run


def ranked(pieces: DataFrame) -> DataFrame:
    """(row, length, rank): rank from 0 among the pieces of a length; a frequent length is dealt to many tasks."""
    parts = max(1, -(-pieces.count() // SHARE)) * 16
    slim = pieces.select("row", "length").withColumn("part", F.pmod(F.xxhash64("row"), F.lit(parts)))
    before = Window.partitionBy("length").orderBy("part").rowsBetween(Window.unboundedPreceding, -1)
    counts = slim.groupBy("length", "part").count().withColumn("ahead", F.coalesce(F.sum("count").over(before), F.lit(0)))
    inside = slim.withColumn("k", F.row_number().over(Window.partitionBy("length", "part").orderBy("row")) - 1)
    return inside.join(counts, ["length", "part"]).select("row", "length", (F.col("ahead") + F.col("k")).alias("rank"))


@dataclass
class Packed:
    """pieces (row, doc_id, piece, start, length, ids) and places (row, sequence_id, offset)."""

    pieces: DataFrame
    places: DataFrame

    def rows(self) -> DataFrame:
        return self.pieces.join(self.places, "row")

    def sequences(self) -> DataFrame:
        """(sequence_id, ids binary): the sequences themselves; one holds `length` ids at most."""
        held = self.rows().groupBy("sequence_id").agg(F.array_sort(F.collect_list(F.struct("offset", "ids"))).alias("p"))
        return held.select("sequence_id", F.expr("aggregate(p, X'', (a, x) -> concat(a, x.ids))").alias("ids"))


def pack(docs: DataFrame, path: str, length: int = LENGTH, end: int = END, cache: int = CACHE) -> Packed:
    """Tokenises whole texts, ends each document with id `end`, cuts the longer ones and packs all pieces.

    Null and empty texts are the one id `end`. Rows that repeat a doc_id, or have none, are documents of their own. Ties
    between equal lengths fall by row number. Other columns are not read; an empty table gives no sequence. path: a
    tokenizer file, read on the driver. cache: pieces of text whose ids a worker remembers, about 200 bytes each in two
    generations; it changes time and memory, never the result.
    """
    with open(path, encoding="utf-8") as file:
        tokenizer = file.read()
    own = docs.select("doc_id", "text")
    kind = f"row long, doc_id {own.schema['doc_id'].dataType.simpleString()}, piece int, start long, length long, ids binary"
    shared = docs.sparkSession.sparkContext.broadcast(tokenizer)

    def cut(batches):
        return _cut(shared.value, length, end, cache)(batches)

    pieces = stored(own.mapInArrow(cut, kind))
    # at most `length` rows, whatever the input
    counts = {r["length"]: r["n"] for r in pieces.groupBy("length").agg(F.count("*").alias("n")).collect()}
    plan = docs.sparkSession.sparkContext.broadcast(Plan.of(counts, length))

    def place(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            size, rank = batch.column(1).to_numpy(), batch.column(2).to_numpy()
            sequence, offset = np.zeros(len(size), np.int64), np.zeros(len(size), np.int64)
            for s in np.unique(size):
                first, base, at = plan.value.runs[int(s)]
                some = size == s
                k = np.searchsorted(first, rank[some], "right") - 1
                sequence[some], offset[some] = base[k] + rank[some] - first[k], at[k]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(sequence), pa.array(offset)], ["row", "sequence_id", "offset"])

    return Packed(pieces, ranked(pieces).mapInArrow(place, "row long, sequence_id long, offset long"))


def packed_rows(packed: Packed) -> DataFrame:
    slim = packed.pieces.select("row", "doc_id", "piece", "start", "length", F.crc32("ids").alias("ids_crc32"))
    return slim.join(packed.places, "row").drop("row")


def op3_best_two_fit(spark, sf_dir):
    return packed_rows(pack(table(spark, sf_dir, "documents"), public_tokenizers.path("word_bpe_49k.json")))
