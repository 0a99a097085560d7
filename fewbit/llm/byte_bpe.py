"""Byte-level BPE encoding and decoding in two tiers.

A minimal perfect hash over the vocabulary resolves whole pre-tokens; a pre-token that isn't in it is merged with a heap
over its linked bytes. Chunks of text between single spaces are pre-tokenised alike wherever they stand, so each worker
keeps what it has encoded in a cache of bounded size.
"""

from __future__ import annotations

import base64
import heapq
from array import array
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import public_tokenizers
import regex
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from fewbit.llm._store import table
from fewbit.llm._worker import kept, release

CACHE = 200_000
#: Bytes of ids that are given on at a time, about; a longer text is given on by itself.
STRETCH = 4 << 20


def read_ranks(path: str) -> dict[bytes, int]:
    """Token bytes to id, of a file with a base64 token and its rank in each line."""
    with open(path, "rb") as lines:
        return {base64.b64decode(a): int(b) for a, b in (line.split() for line in lines if line.strip())}


class PerfectHash:
    """Minimal perfect hash of fixed keys: buckets of keys, placed from the fullest on, each displaced until it fits."""

    def __init__(self, keys: list[bytes]):
        n = self.n = max(1, len(keys))
        self.buckets = max(1, n // 2)
        groups: list[list[int]] = [[] for _ in range(self.buckets)]
        digests = [xxhash.xxh3_64_intdigest(k) for k in keys]
        for i, d in enumerate(digests):
            groups[d % self.buckets].append(i)
        self.shift, self.slots = [0] * self.buckets, [-1] * n
        order = sorted(range(self.buckets), key=lambda b: -len(groups[b]))
        free = None
        for b in order:
            group = groups[b]
            if not group:
                break
            if len(group) == 1:
                # the rest are singles: any free slot will do, named directly by a negative shift
                free = free if free is not None else [s for s in range(n) if self.slots[s] < 0]
                slot = free.pop()
                self.shift[b], self.slots[slot] = -1 - slot, group[0]
                continue
            shift = 1
            while True:
                at = {self._slot(digests[i], shift) for i in group}
                if len(at) == len(group) and all(self.slots[s] < 0 for s in at):
                    break
                shift += 1
            self.shift[b] = shift
            for i in group:
                self.slots[self._slot(digests[i], shift)] = i

    def _slot(self, digest: int, shift: int) -> int:
        return ((digest >> 20) * (2 * shift + 1) + (digest * shift >> 7)) % self.n

    def __call__(self, key: bytes) -> int:
        """Number of the only key that this one can be."""
        digest = xxhash.xxh3_64_intdigest(key)
        shift = self.shift[digest % self.buckets]
        return self.slots[-1 - shift if shift < 0 else self._slot(digest, shift)]


def merge_bytes(piece: bytes, ranks: dict[bytes, int]) -> list[int]:
    """Ids of a pre-token: the pair of lowest rank, of equals the leftmost, is merged until no pair has a rank.

    ends[i] is where the part that begins at byte i ends, so it is also where the next part begins; starts[j] is where the
    part that ends at byte j begins. A heap entry is stale if its two parts have changed since.
    """
    n = len(piece)
    rank = ranks.get
    ends, starts = list(range(1, n + 1)), list(range(-1, n))
    # an entry is rank, first byte and end as one number, in that order of weight
    bits = n.bit_length() + 1
    heap = [((r << bits) + i << bits) + i + 2 for i in range(n - 1) if (r := rank(piece[i : i + 2])) is not None]
    heapq.heapify(heap)
    push, pop, low = heapq.heappush, heapq.heappop, (1 << bits) - 1
    while heap:
        entry = pop(heap)
        i, end = entry >> bits & low, entry & low
        mid = ends[i]
        if mid < 0 or mid >= n or ends[mid] != end:
            continue
        ends[i], ends[mid], starts[end] = end, -1, i
        if end < n and (r := rank(piece[i : ends[end]])) is not None:
            push(heap, ((r << bits) + i << bits) + ends[end])
        if i and (r := rank(piece[(b := starts[i]) : end])) is not None:
            push(heap, ((r << bits) + b << bits) + end)
    out, i = [], 0
    while i < n:
        out.append(ranks[piece[i : ends[i]]])
        i = ends[i]
    return out


class Encoder:
    def __init__(self, ranks: dict[bytes, int], pattern: str, cache: int = CACHE):
        self.ranks, self.limit = ranks, cache
        self.keys = list(ranks)
        self.ids = list(ranks.values())
        self.tokens = dict(zip(self.ids, self.keys, strict=True))
        self.whole = PerfectHash(self.keys)
        # the class as in the Unicode table, whatever the regular expression library takes for space
        space = r"\p{White_Space}"
        own = pattern.replace(r"[^\s", f"[^{space}").replace(r"\S", rf"\P{{White_Space}}").replace(r"\s", space)
        self.pieces = regex.compile(own).findall
        self.odd = regex.compile(f" {space}|{space} ").search
        self.seen: dict[str, bytes] = {}
        self.seen_old: dict[str, bytes] = {}
        self.merged: dict[str, list[int]] = {}
        self.merged_old: dict[str, list[int]] = {}

    def piece(self, piece: str) -> list[int]:
        """Ids of a pre-token. Each cache has a young and an old half: what is used again survives a full one."""
        found = self.merged.get(piece)
        if found is None:
            found = self.merged_old.get(piece)
            if found is None:
                raw = piece.encode()
                at = self.whole(raw)
                found = [self.ids[at]] if self.keys[at] == raw else merge_bytes(raw, self.ranks)
            if len(self.merged) >= self.limit:
                self.merged_old, self.merged = self.merged, {}
            self.merged[piece] = found
        return found

    def spaced(self, chunk: str) -> bytes:
        """Ids, as unsigned 32-bit words, of a chunk after a single space; no pre-token crosses its ends."""
        found = self.seen_old.get(chunk)
        if found is None:
            found = self.plain(" " + chunk)
        if len(self.seen) >= self.limit:
            self.seen_old, self.seen = self.seen, {}
        self.seen[chunk] = found
        return found

    def plain(self, text: str) -> bytes:
        return array("I", [i for p in self.pieces(text) for i in self.piece(p)]).tobytes()

    def encode(self, text: str) -> bytes:
        if not text:
            return b""
        if self.odd(text):
            return self.plain(text)
        first, *rest = text.split(" ")
        made = [self.plain(first)]
        for chunk in rest:
            found = self.seen.get(chunk)
            made.append(self.spaced(chunk) if found is None else found)
        return b"".join(made)


def _encoded(batches: Iterator[pa.RecordBatch], encoder: Encoder, id_col: str) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        made, held, lo = [], 0, 0
        for text in batch.column(1).cast(pa.binary()):
            made.append(encoder.encode((text.as_py() or b"").decode("utf-8", "replace")))
            held += len(made[-1])
            if held > STRETCH:
                yield _lists(batch.column(0).slice(lo, len(made)), made, id_col)
                lo, made, held = lo + len(made), [], 0
        yield _lists(batch.column(0).slice(lo, len(made)), made, id_col)
        del made, batch
        release()


def _decoded(batches: Iterator[pa.RecordBatch], token: dict[int, bytes], id_col: str) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        decoded = [b"".join(map(token.__getitem__, x.values.to_numpy().tolist())) if x.is_valid else None for x in batch.column(1)]
        yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(decoded, pa.binary())], [id_col, "ids", "decoded"])
        del decoded, batch
        release()


def _lists(ids: pa.Array, made: list[bytes], id_col: str) -> pa.RecordBatch:
    ends = np.cumsum([0, *(len(m) // 4 for m in made)]).astype(np.int32)
    return pa.RecordBatch.from_arrays([ids, pa.ListArray.from_arrays(ends, pa.array(np.frombuffer(b"".join(made), np.int32)))], [id_col, "ids"])


def _encoder(path: str, pattern: str, ranks: dict[bytes, int]) -> Encoder:
    return kept((path, pattern, len(ranks)), lambda: Encoder(ranks, pattern))


def encode_bpe(docs: DataFrame, path: str, pattern: str = public_tokenizers.PATTERN, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(id, ids array<int>), one row per row of docs; null and empty texts have no ids.

    path: rank file, read on the driver; its size is that of the vocabulary. Whole texts are encoded, without special
    tokens: their names in a text are ordinary text. Other columns are not read; an empty table gives an empty one.
    """
    own = docs.select(id_col, text_col)
    shared = docs.sparkSession.sparkContext.broadcast(read_ranks(path))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        return _encoded(batches, _encoder(path, pattern, shared.value), id_col)

    return own.mapInArrow(run, f"`{id_col}` {own.schema[id_col].dataType.simpleString()}, ids array<int>")


def decode_bpe(encoded: DataFrame, path: str, id_col: str = "doc_id") -> DataFrame:
    """encoded's id and ids, with `decoded binary`: the bytes that the ids stand for; null ids give null."""
    own = encoded.select(id_col, "ids")
    shared = encoded.sparkSession.sparkContext.broadcast(read_ranks(path))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        return _decoded(batches, {i: t for t, i in shared.value.items()}, id_col)

    return own.mapInArrow(run, f"`{id_col}` {own.schema[id_col].dataType.simpleString()}, ids array<int>, decoded binary")


def round_trip(docs: DataFrame, path: str, pattern: str = public_tokenizers.PATTERN, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """What decode_bpe gives for what encode_bpe gives, by one Python worker a task instead of two; rows as in encode_bpe."""
    own = docs.select(id_col, text_col)
    shared = docs.sparkSession.sparkContext.broadcast(read_ranks(path))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encoder = _encoder(path, pattern, shared.value)
        return _decoded(_encoded(batches, encoder, id_col), encoder.tokens, id_col)

    return own.mapInArrow(run, f"`{id_col}` {own.schema[id_col].dataType.simpleString()}, ids array<int>, decoded binary")


def op5_two_tier_bpe(spark, sf_dir):
    path = public_tokenizers.path("byte_bpe_50k.tiktoken")
    both = round_trip(table(spark, sf_dir, "documents"), path)
    return both.select(
        "doc_id",
        F.size("ids").cast("long").alias("n_tokens"),
        F.sha2(F.array_join(F.col("ids").cast("array<string>"), " ").cast("binary"), 256).alias("ids_sha256"),
        F.sha2("decoded", 256).alias("decoded_sha256"),
    )
