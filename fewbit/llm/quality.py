"""Quality classifier by attention-based multiple-instance learning.

A document is a bag of passages. Each passage is encoded by a learned layer over its byte statistics; a gated attention,
learned from the labels of whole documents, weighs the passages; the score is a logistic function of the weighted mean.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from fewbit.llm._shingles import text_stretches
from fewbit.llm._store import stored, table
from fewbit.llm._worker import fresh, release

PASSAGE_WORDS = 64
PAIRS = 256
HIDDEN = 24
#: Labelled documents, and bytes of their texts in all, that the model is fitted on at most.
SAMPLE, SAMPLE_BYTES = 3000, 16 << 20
EPOCHS = 40
RATE = 0.01
SEED = 11
CUT = 0.7
_EXTRA = 6
WIDTH = 256 + PAIRS + _EXTRA
_CHUNK = 1 << 18


def _word_starts(data: np.ndarray, cuts: np.ndarray) -> np.ndarray:
    """Bytes at which words begin; cuts: bytes at which a document begins."""
    space = (data == 32) | ((data >= 9) & (data <= 13))
    after = np.empty(len(data), bool)
    after[:1], after[1:] = True, space[:-1]
    after[cuts] = True
    return np.flatnonzero(~space & after)


def _features(data: np.ndarray, begin: np.ndarray, opens: np.ndarray, ends: np.ndarray) -> np.ndarray:
    """Features of passages: begin, the words' first bytes; opens, the first word of each passage; ends, the byte behind each passage."""
    n = len(opens)
    starts, words = begin[opens], np.diff(np.append(opens, len(begin)))
    size = (ends - starts).astype(np.float32)
    ones, twos = np.zeros((n, 256), np.float32), np.zeros((n, PAIRS), np.float32)
    # bytes are counted in slices, so that a passage of one endless word takes no more memory than its bytes
    for lo in range(int(starts[0]), int(ends[-1]), _CHUNK):
        hi = min(lo + _CHUNK, int(ends[-1]))
        first, last = np.searchsorted(ends, lo, "right"), np.searchsorted(starts, hi, "left")
        inside = np.concatenate([np.arange(max(lo, s), min(hi, e)) for s, e in zip(starts[first:last].tolist(), ends[first:last].tolist(), strict=True)])
        at = np.repeat(np.arange(first, last), np.minimum(ends[first:last], hi) - np.maximum(starts[first:last], lo))
        byte = data[inside].astype(np.int64)
        ones[first:last] += np.bincount((at - first) * 256 + byte, minlength=(last - first) * 256).reshape(-1, 256)
        paired = inside + 1 < ends[at]
        one, other, at = byte[paired], data[inside[paired] + 1].astype(np.int64), at[paired]
        pair = ((one * 31 + other * 17) ^ (other >> 3)) % PAIRS
        twos[first:last] += np.bincount((at - first) * PAIRS + pair, minlength=(last - first) * PAIRS).reshape(-1, PAIRS)
    # a word's first bytes and its length tell repeated words
    number = np.repeat(np.arange(n), words)
    until = np.append(begin[1:], ends[-1])
    until[np.append(opens[1:], len(begin)) - 1] = ends
    second = data[np.minimum(begin + 1, len(data) - 1)].astype(np.int64)
    sign = data[begin].astype(np.int64) + 256 * np.where(begin + 1 < until, second, 0) + 65536 * (until - begin)
    extra = np.zeros((n, _EXTRA), np.float32)
    extra[:, 0] = size / np.maximum(words, 1) / 8
    extra[:, 1] = words / PASSAGE_WORDS
    for k in (1, 2, 3):
        again = (sign[k:] == sign[:-k]) & (number[k:] == number[:-k])
        extra[:, 1 + k] = np.bincount(number[k:][again], minlength=n) / np.maximum(words, 1)
    extra[:, 5] = np.log1p(size) / 8
    scale = np.maximum(size, 1)[:, None]
    return np.concatenate([np.sqrt(ones / scale), np.sqrt(twos / scale), extra], axis=1)


def _joined(texts: list[bytes]) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """(features, document) of the passages of short texts, computed together; each passage runs up to the next or the text's end."""
    data = np.frombuffer(b" ".join(texts), np.uint8)
    cuts = np.cumsum([0, *(len(t) + 1 for t in texts)])
    begin = _word_starts(data, cuts[:-1][cuts[:-1] < len(data)])
    of = np.searchsorted(cuts, begin, "right") - 1
    nth = np.arange(len(begin)) - np.searchsorted(of, of)
    opens = np.flatnonzero(nth % PASSAGE_WORDS == 0)
    bare = np.setdiff1d(np.arange(len(texts)), of)
    x, owner = np.zeros((0, WIDTH), np.float32), of[opens]
    if len(opens):
        ends = np.minimum(np.append(begin[opens[1:]], len(data)), cuts[owner + 1] - 1)
        x = _features(data, begin, opens, ends)
    if len(bare):
        x, owner = np.concatenate([x, np.zeros((len(bare), WIDTH), np.float32)]), np.concatenate([owner, bare])
        order = np.argsort(owner, kind="stable")
        x, owner = x[order], owner[order]
    yield x, owner


def _streamed(text: bytes) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """(features, zeros) of one long text, some passages at a time."""
    data, lo, size, found = np.frombuffer(text, np.uint8), 0, _CHUNK, False
    while lo < len(data):
        part = data[lo : lo + size]
        begin = _word_starts(part, np.zeros(1, np.int64))
        final = lo + size >= len(data)
        # the last word may go on behind the stretch, and so may the last passage
        whole = len(begin) if final else max(len(begin) - 1, 0) // PASSAGE_WORDS * PASSAGE_WORDS
        if not whole and not final:
            size *= 2
            continue
        if whole:
            opens = np.arange(0, whole, PASSAGE_WORDS)
            stop = len(part) if final else int(begin[whole])
            found = True
            yield (x := _features(part, begin[:whole], opens, np.append(begin[opens[1:]], stop))), np.zeros(len(x), np.int64)
        lo, size = len(data) if final else lo + int(begin[whole]), _CHUNK
    if not found:
        yield np.zeros((1, WIDTH), np.float32), np.zeros(1, np.int64)


def encode_passages(texts: list[bytes]) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """(features, document number) of all passages in order, a bounded number at a time; each document has one at least.

    A document longer than a stretch comes in several successive pieces.
    """
    lo = 0
    while lo < len(texts):
        hi, size = lo, 0
        while hi < len(texts) and (hi == lo or size + len(texts[hi]) < _CHUNK):
            size += len(texts[hi]) + 1
            hi += 1
        for x, owner in _streamed(texts[lo]) if size > _CHUNK else _joined(texts[lo:hi]):
            yield x, owner + lo
        lo = hi


@dataclass
class AttentionModel:
    """Weights by name: encoder E, e; attention V, U, a; output o, b; mean and spread scale the features."""

    weights: dict[str, np.ndarray]

    def forward(self, x: np.ndarray, first: np.ndarray) -> dict[str, np.ndarray]:
        """x: passages in document order; first: the first passage of each document."""
        w = self.weights
        count = np.diff(np.append(first, len(x)))
        h = np.tanh(((x - w["mean"]) / w["spread"]) @ w["E"] + w["e"])
        t, g = np.tanh(h @ w["V"]), 1 / (1 + np.exp(-(h @ w["U"])))
        raw = (t * g) @ w["a"]
        top = np.maximum.reduceat(raw, first)
        power = np.exp(raw - np.repeat(top, count))
        total = np.add.reduceat(power, first)
        share = power / np.repeat(total, count)
        z = np.add.reduceat(h * share[:, None], first)
        return {"h": h, "t": t, "g": g, "share": share, "top": top, "total": total, "z": z, "score": 1 / (1 + np.exp(-(z @ w["o"] + w["b"]))), "count": count}

    def score(self, texts: list[bytes]) -> np.ndarray:
        """Score of each text; a text that comes in pieces is weighed up piece by piece, as one sum of all its passages."""
        w, out = self.weights, np.zeros(len(texts))
        top, total, z = np.full(len(texts), -np.inf), np.zeros(len(texts)), np.zeros((len(texts), HIDDEN))
        for x, owner in encode_passages(texts):
            first = np.flatnonzero(np.concatenate([[True], owner[1:] != owner[:-1]]))
            f, doc = self.forward(x, first), owner[first]
            high = np.maximum(top[doc], f["top"])
            old, new = np.exp(top[doc] - high), np.exp(f["top"] - high) * f["total"]
            z[doc] = z[doc] * old[:, None] + f["z"] * new[:, None]
            total[doc], top[doc] = total[doc] * old + new, high
        if len(texts):
            out = 1 / (1 + np.exp(-((z / total[:, None]) @ w["o"] + w["b"])))
        return out


def train(texts: list[bytes], labels: np.ndarray, epochs: int = EPOCHS, batch: int = 64) -> AttentionModel:
    """Fits by Adam on the logistic loss of document labels. Without documents of both labels the score is their share, 0.5 if none."""
    rng = np.random.default_rng(SEED)
    scale = lambda *s: (rng.standard_normal(s) / np.sqrt(s[0])).astype(np.float32)
    share = float(labels.mean()) if len(labels) else 0.5
    w = {
        "mean": np.zeros(WIDTH, np.float32), "spread": np.ones(WIDTH, np.float32), "E": scale(WIDTH, HIDDEN), "e": np.zeros(HIDDEN, np.float32),
        "V": scale(HIDDEN, HIDDEN), "U": scale(HIDDEN, HIDDEN), "a": scale(HIDDEN), "o": np.zeros(HIDDEN, np.float32), "b": np.zeros(1, np.float32),
    }
    model = AttentionModel(w)
    edge = min(max(share, 0.01), 0.99)
    w["b"][0] = np.log(edge / (1 - edge))
    if not len(labels) or not 0 < share < 1:
        return model
    parts = list(encode_passages(texts))
    x, owner = np.concatenate([p[0] for p in parts]), np.concatenate([p[1] for p in parts])
    w["mean"], w["spread"] = x.mean(0), x.std(0) + 0.02
    first = np.flatnonzero(np.concatenate([[True], owner[1:] != owner[:-1]]))
    ends = np.append(first, len(x))
    names = ["E", "e", "V", "U", "a", "o", "b"]
    m, v = {k: np.zeros_like(w[k]) for k in names}, {k: np.zeros_like(w[k]) for k in names}
    step = 0
    for epoch in range(epochs):
        order = rng.permutation(len(labels))
        for lo in range(0, len(order), batch):
            some = np.sort(order[lo : lo + batch])
            rows = np.concatenate([np.arange(ends[i], ends[i + 1]) for i in some])
            size = ends[some + 1] - ends[some]
            grad = _gradient(model, x[rows], np.cumsum(size) - size, labels[some])
            step += 1
            rate = RATE * 0.5 * (1 + np.cos(np.pi * epoch / epochs))
            for k in names:
                g = grad[k] + (1e-4 * w[k] if w[k].ndim > 1 else 0)
                m[k] = 0.9 * m[k] + 0.1 * g
                v[k] = 0.999 * v[k] + 0.001 * g * g
                w[k] = (w[k] - rate * (m[k] / (1 - 0.9**step)) / (np.sqrt(v[k] / (1 - 0.999**step)) + 1e-8)).astype(np.float32)
    return model


def _gradient(model: AttentionModel, x: np.ndarray, first: np.ndarray, y: np.ndarray) -> dict[str, np.ndarray]:
    w, f = model.weights, model.forward(x, first)
    h, t, g, share = f["h"], f["t"], f["g"], f["share"]
    d = (f["score"] - y) / len(y)
    dz = np.repeat(d[:, None] * w["o"], f["count"], axis=0)
    dshare = (dz * h).sum(1)
    draw = share * (dshare - np.repeat(np.add.reduceat(share * dshare, first), f["count"]))
    dt, dg = draw[:, None] * w["a"] * g * (1 - t * t), draw[:, None] * w["a"] * t * g * (1 - g)
    dh = (dz * share[:, None] + dt @ w["V"].T + dg @ w["U"].T) * (1 - h * h)
    xs = (x - w["mean"]) / w["spread"]
    return {"E": xs.T @ dh, "e": dh.sum(0), "V": h.T @ dt, "U": h.T @ dg, "a": (t * g).T @ draw, "o": f["z"].T @ d, "b": np.array([d.sum()])}


def held_out(id_col: str = "doc_id"):
    """Whether a document is kept from training."""
    return F.crc32(F.col(id_col).cast("string").cast("binary")) % 4 == 2


def fit_quality(docs: DataFrame, labels: DataFrame, sample: int = SAMPLE, most: int = SAMPLE_BYTES) -> AttentionModel:
    """A model of labels.quality, from labelled documents that aren't held out.

    What reaches the driver is bounded by `sample` documents and by `most` bytes of text in all: documents in the order of
    a hash of their id, one row each (that of the smallest text hash), but for those that the bytes left don't hold. Null
    texts count as empty; rows without quality or doc_id aren't used, a document with two labels has the larger.
    """
    usable = labels.select("doc_id", "quality").where("doc_id IS NOT NULL AND quality IS NOT NULL").where(~held_out())
    chosen = usable.groupBy("doc_id").agg(F.max("quality").alias("quality")).orderBy(F.xxhash64("doc_id"), "doc_id").limit(sample)
    text = F.coalesce("text", F.lit(""))
    labelled = docs.select("doc_id", text.alias("text"), F.xxhash64(text).alias("h")).join(F.broadcast(chosen), "doc_id")
    sizes = labelled.groupBy("doc_id", "quality").agg(F.min(F.struct("h", F.octet_length("text").alias("n"))).alias("s")).orderBy(F.xxhash64("doc_id"), "doc_id").collect()
    taken, left = {}, most
    for r in sizes:
        if r.s.n <= left:
            taken[r.doc_id, r.s.h] = r.quality
            left -= r.s.n
    if not taken:
        return train([], np.zeros(0, np.float32))
    kind = f"doc_id {docs.schema['doc_id'].dataType.simpleString()}, h long"
    some = F.broadcast(docs.sparkSession.createDataFrame(list(taken), kind))
    rows = labelled.join(some, ["doc_id", "h"]).groupBy("doc_id", "h").agg(F.min("text").alias("text")).collect()
    rows.sort(key=lambda r: (r.doc_id, r.h))
    return train([r.text.encode() for r in rows], np.array([taken[r.doc_id, r.h] for r in rows], np.float32))


def score_quality(docs: DataFrame, model: AttentionModel, text_col: str = "text") -> DataFrame:
    """docs with `score double`; every whole text is read, null texts as empty; a clashing column is replaced."""
    base = docs.drop("score")
    kept = base.columns
    at = kept.index(text_col)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        fresh()
        for batch in batches:
            scores = [np.zeros(0), *(model.score(texts) for _, texts in text_stretches(batch.column(at)))]
            yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(np.concatenate(scores))], [*kept, "score"])
            del batch, scores
            release()

    schema = T.StructType([*base.schema.fields, T.StructField("score", T.DoubleType())])
    return base.mapInArrow(run, schema)


def keep_good(docs: DataFrame, labels: DataFrame, cut: float = CUT) -> DataFrame:
    """docs whose score is at least cut, same columns and rows; null and empty texts have a score like any other."""
    model = fit_quality(docs, labels)
    scored = score_quality(docs, model)
    return scored.where(F.col("score") >= cut).select(*[F.col(f"`{c}`") for c in docs.columns])


def op6_attention_quality(spark, sf_dir):
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    model = fit_quality(docs, table(spark, sf_dir, "labels"))
    scored = stored(score_quality(docs, model).select("doc_id", "score"))
    return scored.select("doc_id", held_out().alias("held_out"), "score", (F.col("score") >= CUT).cast("int").alias("predicted"))
