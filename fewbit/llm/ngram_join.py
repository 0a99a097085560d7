"""N-gram Jaccard join: an exact set-similarity self-join by pigeonhole over a partitioned shingle universe.

Two sets of sizes l <= l' with 100 |A & B| >= percent |A | B| differ in at most H shingles, H following from the sizes.
Sizes are cut in bands so that partners lie in one band or in neighbouring ones; each band has its own partition of the
universe into m segments by hash. A segment matches if both sets hold the same shingles there, or, in the q designated
segments, sets one deletion apart. If at most k segments matched, the sets would differ in more than H shingles, so
partners match in k + 1 segments at least. (m, q, k) are allocated for each band by a cost estimate.

A segment that holds nothing would match between any two sets, so it is no key. A set with more than k such segments has
as keys all subsets of k + 1 of them: partners that match in void segments alone share one of these. Nothing is lost.

Documents under one key are tied to the key's first one; connected ties are families. Every pair of a family is then
verified exactly, in blocks of bounded size, each pair once.
"""

from __future__ import annotations

import math
from collections.abc import Iterator
from dataclasses import dataclass
from itertools import combinations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from fewbit.llm._components import components, spanning_forest
from fewbit.llm._shingles import U, WordHasher, mix, shingle_set, text_stretches, word_hashes
from fewbit.llm._store import Stored, sifted, table
from fewbit.llm._worker import fresh, release

WORDS, PERCENT = 5, 80
#: Shingles that one block of a family holds, about.
BLOCK = 1_000_000
#: Shingles of a set too small for comparing by a part.
SMALL = 200
#: For the cost estimate: chance that a shingle is shared with some other document of the band; cost of a candidate in keys.
SHARED, CANDIDATE = 0.02, 1.0


@dataclass(frozen=True)
class Allocation:
    """How one band is partitioned: m segments, the first q of them with one-deletion neighbourhoods, slack k."""

    m: int
    q: int = 0
    k: int = 0


def band_starts(percent: int, largest: int) -> list[int]:
    """First size of each band up to that of `largest`, and of one more; partners of a band's sizes lie in it or the next."""
    out = [1]
    while out[-1] <= largest:
        out.append(out[-1] * 100 // percent + 1)
    return out


def largest_difference(percent: int, last: int) -> int:
    """Most shingles in which partners differ if the smaller has at most `last`."""
    return (100 - percent) * (last + last * 100 // percent) // (100 + percent)


def _cost(m: int, q: int, k: int, size: float, rows: float) -> float:
    """Keys that a set of `size` shingles emits, plus the candidates it meets among `rows` sets, each as CANDIDATE keys."""
    each = size / m
    # expected subsets of k + 1 void segments, in one set and in both of a pair
    subsets = math.lgamma(m + 1) - math.lgamma(k + 2) - math.lgamma(m - k) if m > k else -math.inf
    one, both = (math.exp(min(subsets - i * (k + 1) * each, 50.0)) for i in (1, 2))
    shared = (m - q) * SHARED**each + q * (1 + each) * SHARED ** max(each - 1, 1)
    return m + q * each + one + CANDIDATE * rows * (shared + both)


def allocate(percent: int, first: int, last: int, rows: float) -> Allocation:
    """The cheapest partition of a band, for its smallest sets."""
    h = largest_difference(percent, last)
    if h == 0:
        return Allocation(1)
    best, least = None, math.inf
    for k in sorted({*range(9), *(h * i // 32 for i in range(1, 17))}):
        options = {(h + 1 + k, 0)}
        for share in (0.25, 0.5, 1.0):
            m = max(math.ceil((h + 1 + 2 * k) / (1 + share)), k)
            options.add((m, min(m, max(h + 1 + 2 * k - m, k))))
        for m, q in options:
            if (m + q - 2 * k if q >= k else m - k) >= h + 1 and (cost := _cost(m, q, k, first, rows)) < least:
                best, least = Allocation(m, q, k), cost
    return best


def band_plan(percent: int, counts: dict[int, int], largest: int) -> tuple[list[int], list[Allocation]]:
    """Band starts and the allocation of each band; counts: documents by size, estimated is enough (cost only)."""
    starts = band_starts(percent, max(largest, 1))
    rows = np.zeros(len(starts))
    for size, n in counts.items():
        rows[np.searchsorted(starts, max(size, 1), "right") - 1] += n
    return starts, [allocate(percent, a, b - 1, rows[i] + (rows[i + 1] if i + 1 < len(rows) else 0)) for i, (a, b) in enumerate(zip(starts, starts[1:], strict=False))]


def band_keys(shingles: np.ndarray, band: int, plan: Allocation) -> np.ndarray:
    """All keys of a set under one band's partition."""
    m = plan.m
    value = mix(shingles ^ U(0xA5A5A5A5A5A5A5A5))
    segment = ((shingles >> U(32)) * U(m)) >> U(32)
    # sets are sorted by hash, so segments (the high bits) are in order already
    begin = np.flatnonzero(np.concatenate([[True], segment[1:] != segment[:-1]]))
    total, here = np.add.reduceat(value, begin), segment[begin]
    tag = mix(here + U((band + 1) << 40))
    keys = [mix(total ^ tag)]
    void = np.ones(m, bool)
    void[here.astype(np.int64)] = False
    if plan.q:
        size = np.diff(np.concatenate([begin, [len(shingles)]]))
        void[here[(size == 1) & (here < plan.q)].astype(np.int64)] = True
        of = np.repeat(np.arange(len(begin)), size)
        drop = (segment < plan.q) & (size[of] > 1)
        keys.append(mix((total[of[drop]] - value[drop]) ^ tag[of[drop]]))
    empty = np.flatnonzero(void)
    if len(empty) > plan.k:
        folds = []
        for some in combinations(empty.tolist(), plan.k + 1):
            x = U((band + 1) << 40 | plan.k)
            for s in some:
                x = mix(np.array([x], U) + U(s + 1))[0]
            folds.append(x)
        keys.append(np.array(folds, U))
    return np.concatenate(keys)


def _key_rows(words: int, starts: list[int], plans: list[Allocation]):
    """Rows (key, doc, 0) for the keys of documents, and one row (hash of the whole set, doc, size + 1) for each.

    Documents of one task that share a key are tied there, as rows (first, doc, -1), and only the first keeps the key; a
    key that very many documents have is so thinned out before anything is shuffled.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        fresh()
        hasher = WordHasher()
        for batch in batches:
            ids = batch.column(0).to_numpy(zero_copy_only=False)
            key, doc, n, held = [], [], [], 0
            every = (h for _, texts in text_stretches(batch.column(1)) for h in word_hashes(texts, hasher))
            for i, hashes in zip(ids, every, strict=True):
                found = shingle_set(hashes, words)
                own = [np.array([np.add.reduce(mix(found), dtype=U)], U)]
                if len(found):
                    band = int(np.searchsorted(starts, len(found), "right")) - 1
                    own += [band_keys(found, b, plans[b]) for b in (band, band - 1) if b >= 0]
                size = sum(map(len, own))
                key += own
                doc.append(np.full(size, i))
                n.append(np.zeros(size, np.int64))
                n[-1][0] = len(found) + 1
                held += size
                if held > 100_000:
                    yield _rows(key, doc, n)
                    key, doc, n, held = [], [], [], 0
            if held:
                yield _rows(key, doc, n)
            del key, doc, n, every
            release()

    return run


def _rows(key, doc, n) -> pa.RecordBatch:
    key, doc, n = np.concatenate(key).view(np.int64), np.concatenate(doc), np.concatenate(n)
    bare = np.flatnonzero(n == 0)
    order = bare[np.lexsort((doc[bare], key[bare]))]
    again = np.flatnonzero(key[order[1:]] == key[order[:-1]]) + 1
    if len(again):
        new = np.ones(len(order), bool)
        new[again] = False
        first = doc[order[np.maximum.accumulate(np.where(new, np.arange(len(order)), 0))[again]]]
        tied = first != doc[order[again]]
        ties = np.unique(np.stack([first[tied], doc[order[again]][tied]]), axis=1)
        stay = np.ones(len(key), bool)
        stay[order[again]] = False
        key, doc, n = np.concatenate([key[stay], ties[0]]), np.concatenate([doc[stay], ties[1]]), np.concatenate([n[stay], np.full(ties.shape[1], -1)])
    return pa.RecordBatch.from_arrays([pa.array(key), pa.array(doc), pa.array(n)], ["key", "doc", "n"])


def _tie(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Of rows sorted by key and doc: (doc, first doc of its key, null, null) for the others of a key; ties and set rows as they are."""
    last_key, last_doc = None, None
    for batch in batches:
        key, doc, n = (c.to_numpy(zero_copy_only=False) for c in batch.columns)
        whole = n > 0
        if whole.any():
            none = pa.nulls(int(whole.sum()), pa.int64())
            yield pa.RecordBatch.from_arrays([pa.array(doc[whole]), none, pa.array(n[whole] - 1), pa.array(key[whole])], ["doc", "first", "n", "sig"])
        ready = n < 0
        if ready.any():
            none = pa.nulls(int(ready.sum()), pa.int64())
            yield pa.RecordBatch.from_arrays([pa.array(doc[ready]), pa.array(key[ready]), none, none], ["doc", "first", "n", "sig"])
        bare = n == 0
        key, doc = key[bare], doc[bare]
        if not len(key):
            continue
        new = np.concatenate([[last_key is None or key[0] != last_key], key[1:] != key[:-1]])
        at = np.maximum.accumulate(np.where(new, np.arange(len(key)), -1))
        first = np.where(at >= 0, doc[np.maximum(at, 0)], last_doc if last_doc is not None else 0)
        last_key, last_doc = key[-1], first[-1]
        tied = first != doc
        if tied.any():
            pairs = np.unique(np.stack([doc[tied], first[tied]]), axis=1)
            none = pa.nulls(pairs.shape[1], pa.int64())
            yield pa.RecordBatch.from_arrays([pa.array(pairs[0]), pa.array(pairs[1]), none, none], ["doc", "first", "n", "sig"])


def _sets(words: int, part: int):
    """The same rows with the shingle set as bytes in place of the text, the last column; of it, the first of `part` equal
    ranges of the universe."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        fresh()
        hasher = WordHasher()
        for batch in batches:
            names = [*batch.schema.names[:-1], "shingles"]
            made, lo, held = [], 0, 0
            for hashes in (h for _, texts in text_stretches(batch.column(len(names) - 1)) for h in word_hashes(texts, hasher)):
                found = shingle_set(hashes, words)
                made.append(found[: np.searchsorted(found, U(((1 << 64) - 1) // part), "right")].tobytes())
                held += len(made[-1])
                if held > 4 << 20:
                    yield pa.RecordBatch.from_arrays([*(c.slice(lo, len(made)) for c in batch.columns[:-1]), pa.array(made, pa.binary())], names)
                    lo, made, held = lo + len(made), [], 0
            if made:
                yield pa.RecordBatch.from_arrays([*(c.slice(lo, len(made)) for c in batch.columns[:-1]), pa.array(made, pa.binary())], names)
            del made
            release()

    return run


def linked_pairs(
    ids: np.ndarray, sets: list[np.ndarray], side: np.ndarray, percent: int, whole: np.ndarray | None = None
) -> tuple[np.ndarray, np.ndarray]:
    """A spanning forest of the links among sets: all pairs if side is one value, else pairs between the two sides.

    With the sizes of the whole sets, `sets` hold a part of each, and a pair stays unless the parts alone differ in more
    shingles than linked sets can.
    """
    two = side.min() != side.max()
    others = np.flatnonzero(side == side.max())
    sizes = np.fromiter(map(len, sets), np.int64, len(sets))
    flat = np.concatenate([sets[i] for i in others])
    owner = np.repeat(others, sizes[others])
    order = np.argsort(flat, kind="stable")
    flat, owner = flat[order], owner[order]
    a, b = [], []
    for i in np.flatnonzero(side == side.min()):
        lo, hi = np.searchsorted(flat, sets[i], "left"), np.searchsorted(flat, sets[i], "right")
        n = hi - lo
        total = int(n.sum())
        if whole is None and total <= (0 if two else len(sets[i])):
            continue
        at = np.repeat(lo - np.cumsum(n) + n, n) + np.arange(total)
        common = np.bincount(owner[at], minlength=len(sets))
        if whole is None:
            hit = np.flatnonzero((100 * common >= percent * (sizes[i] + sizes - common)) & (common > 0))
        else:
            hit = np.flatnonzero((sizes[i] + sizes - 2 * common) * (100 + percent) <= (whole[i] + whole) * (100 - percent))
        hit = hit[side[hit] == side.max()] if two else hit[hit > i]
        a.append(np.full(len(hit), ids[i]))
        b.append(ids[hit])
    if not a:
        return np.zeros(0, np.int64), np.zeros(0, np.int64)
    return spanning_forest(np.concatenate(a).astype(np.int64), np.concatenate(b).astype(np.int64))


def _verify(percent: int, partly: bool):
    """Links of each (family, span, i, j) block pair, of rows sorted by those four; a block pair is held as a whole."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        fresh()
        at, ids, sides, whole, sets = None, [], [], [], []

        def links():
            u, v = linked_pairs(np.array(ids), sets, np.array(sides), percent, np.array(whole) if partly else None)
            return pa.RecordBatch.from_arrays([pa.array(u), pa.array(v)], ["a", "b"])

        for batch in batches:
            rows = zip(*(batch.column(c).to_pylist() for c in range(4)), strict=True)
            docs, side, n, raw = *(batch.column(c).to_pylist() for c in (4, 5, 6)), batch.column(7)
            for r, here in enumerate(rows):
                if here != at:
                    if len(ids) > 1:
                        yield links()
                    at, ids, sides, whole, sets = here, [], [], [], []
                ids.append(docs[r])
                sides.append(side[r])
                whole.append(n[r])
                sets.append(np.frombuffer(raw[r].as_py(), U))
            del rows, docs, side, raw
            release()
        if len(ids) > 1:
            yield links()

    return run


def _block_links(texts: DataFrame, copies: DataFrame, words: int, percent: int, block: int, part: int) -> DataFrame:
    """(a, b): a forest of the links in each family of copies (doc, family, n, span); with part > 1, of the pairs that one range in `part` can't tell apart."""
    held = copies.groupBy("family", "span").agg(F.count("*").alias("docs"), F.ceil(F.sum("n") / (block * part)).cast("int").alias("own"))
    beside = lambda step, name: F.coalesce(F.max(F.when(F.col("near") == step, F.col("blocks"))), F.lit(0)).alias(name)
    met = held.select("family", F.explode(F.array(*[F.struct((F.col("span") - k).alias("span"), F.lit(k).alias("near")) for k in (-1, 0, 1)])).alias("m"), F.col("own").alias("blocks"), "docs")
    met = met.select("family", "m.*", "blocks", "docs").groupBy("family", "span").agg(
        beside(0, "own"), beside(1, "above"), beside(-1, "below"), F.max(F.when(F.col("near") == 0, F.col("docs"))).alias("docs")
    )
    met = met.where("own > 0 AND (docs > 1 OR above > 0 OR below > 0)").drop("docs")
    chosen = Stored(copies.join(met, ["family", "span"]).select("doc", "n", "family", "span", "own", "above", "below")).df
    near_texts = sifted(texts, chosen.select("doc"), "doc").where("__maybe").drop("__maybe")
    kind = "doc long, n long, family long, span int, own int, above int, below int"
    sets = near_texts.join(chosen, "doc").select(*chosen.columns, "text").mapInArrow(_sets(words, part), f"{kind}, shingles binary")
    # each document meets every block of its own span, and those of the spans beside it; 2 * span + 1 names two spans' pairs
    places = """concat(
        transform(sequence(0, own - 1), o -> struct(2 * span AS span, least(mine, o) AS i, greatest(mine, o) AS j, mine AS side)),
        transform(filter(sequence(0, above), o -> o < above), o -> struct(2 * span + 1 AS span, mine AS i, o AS j, 0 AS side)),
        transform(filter(sequence(0, below), o -> o < below), o -> struct(2 * span - 1 AS span, o AS i, mine AS j, 1 AS side)))"""
    pairs = sets.withColumn("mine", F.pmod(F.xxhash64("doc"), F.col("own")).cast("int")).withColumn("p", F.explode(F.expr(places)))
    pairs = pairs.select("family", "p.span", "p.i", "p.j", "doc", "p.side", "n", "shingles")
    pairs = pairs.repartition("family", "span", "i", "j").sortWithinPartitions("family", "span", "i", "j")
    return pairs.mapInArrow(_verify(percent, part > 1), "a long, b long")


def ngram_groups(docs: DataFrame, words: int = WORDS, percent: int = PERCENT, block: int = BLOCK, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(id, n_shingles long, component_id long) of every document; components are those of the exact link graph.

    Words are `[^\\x20\\x09-\\x0D]+` after lower-casing A-Z; a set has the distinct shingles of `words` words, of a text
    with fewer words the whole sequence as one. Null, empty and wordless texts have empty sets, linked with nothing.
    Rows that repeat an id belong to one document with all their links, and give a row each if their sizes differ.
    Rows without id are left out. Ties need no order: a component is named by its smallest id. An empty table gives an
    empty one. Only the two named columns are read.
    """
    spark = docs.sparkSession
    own = docs.select(F.col(id_col).cast("long").alias("doc"), F.col(text_col).alias("text")).where("doc IS NOT NULL")
    near = F.floor(F.log(1.1, F.greatest(F.length("text") / 6, F.lit(1.0)))).cast("int")
    sizes = own.groupBy(near.alias("s")).agg(F.count("*").alias("c"), F.max(F.octet_length("text")).alias("top")).collect()
    largest = max([1, *(r.top or 0 for r in sizes)])
    starts, plans = band_plan(percent, {round(1.1 ** (r.s or 0)): r.c for r in sizes}, largest)

    keyed = own.mapInArrow(_key_rows(words, starts, plans), "key long, doc long, n long")
    dealt = keyed.repartition("key").sortWithinPartitions("key", "doc")
    tied = Stored(dealt.mapInArrow(_tie, "doc long, first long, n long, sig long")).df
    base = tied.where("n IS NOT NULL").select("doc", "n", "sig").distinct()
    family = components(tied.where("first IS NOT NULL"), "doc", "first")
    family = family.unionByName(family.select(F.col("component").alias("node"), "component").distinct())

    members = Stored(base.join(family.withColumnRenamed("node", "doc"), "doc").withColumnRenamed("component", "family")).df
    copies = members.groupBy("family", "sig", "n").agg(F.min("doc").alias("doc"), F.count("*").alias("c"))
    same = members.join(copies.where("c > 1").withColumnRenamed("doc", "first"), ["family", "sig", "n"]).select(F.col("doc").alias("a"), F.col("first").alias("b"))
    # a quarter of the sets tells unlike documents apart; those that may have a partner are then compared whole
    # partners lie in one span of sizes or in successive ones; the ratio is a little wide for the logarithm's rounding
    ratio = math.log(100 / percent * 1.0001)
    sized = copies.where("n > 0").withColumn("span", F.floor(F.log(F.col("n").cast("double")) / ratio).cast("int"))
    # small sets are compared whole at once, and so are those that may have a small partner
    small = math.floor(math.log(SMALL) / ratio)
    rough = Stored(_block_links(own, sized.where(F.col("span") > small), words, percent, block, 4)).df
    some = rough.select(F.col("a").alias("doc")).union(rough.select("b")).union(sized.where(F.col("span") <= small + 1).select("doc")).distinct()
    # stored, so that no task runs the workers of two operators at a time
    links = Stored(_block_links(own, sized.join(some, "doc", "left_semi"), words, percent, block, 1)).df
    joined = components(same.unionByName(links), "a", "b")
    return base.join(joined, F.col("doc") == F.col("node"), "left").select(
        F.col("doc").alias(id_col), F.col("n").alias("n_shingles"), F.coalesce("component", "doc").alias("component_id")
    )


def keep_one(docs: DataFrame, words: int = WORDS, percent: int = PERCENT) -> DataFrame:
    """docs without those that a smaller doc_id of their component stands for; rows without doc_id stay."""
    gone = Stored(ngram_groups(docs, words, percent).where("component_id <> doc_id").select("doc_id").distinct()).df
    flagged = sifted(docs, gone, "doc_id")
    certain = flagged.where("NOT __maybe").select(*docs.columns)
    return certain.unionByName(flagged.where("__maybe").join(gone, "doc_id", "left_anti").select(*docs.columns))


def op2_ngram_jaccard(spark, sf_dir):
    return ngram_groups(table(spark, sf_dir, "documents"), words=4, percent=85)
