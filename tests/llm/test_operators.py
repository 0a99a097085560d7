"""The operators of the training-data pipeline beside plain versions, and on awkward rows."""

import hashlib
import itertools
import re
import zlib

import numpy as np
import pyarrow as pa
import public_tokenizers as P
import pytest

from fewbit.llm import byte_bpe, embedding_dedup, line_dedup, ngram_join, packing, pii, quality, sharding, sketch, url_filter
from fewbit.llm._components import components

DOC = "doc_id long, text string, lang string, source string, n_chars long"
LONG = " ".join(f"w{i % 977}x{i % 31}" for i in range(30_000))
PASSAGE = " ".join(f"p{i}" for i in range(60))
TEXTS = [
    "The quick brown fox jumps over the lazy dog and runs away from here to there again",
    "The quick brown fox jumps over the lazy dog and runs away from here to there again",
    None, "", "   ", "one", "Mail a.b@c.example.org or +1 (706) 555-3138, card 4539 1488 0343 6467 at 10.0.0.255!",
    f"first own line\n{PASSAGE}\nlast", f"other start\n{PASSAGE}\nlast", LONG, LONG + " end", "Ünïcode ünïcode  two\tspaces\n\nline ’s don't",
]


def rows(texts):
    return [(i, t, "en", f"src{i % 2}", len(t or "")) for i, t in enumerate(texts)]


@pytest.fixture(scope="module")
def docs(spark):
    """Awkward documents, with extra columns whose names clash with those the operators make."""
    extra = "shard int, score double, component_id string, rank long, `key` string, block int, removed string, ids string, host string"
    return spark.createDataFrame([(*r, 1, 0.5, "x", 7, "k", 1, "r", "i", "h") for r in rows(TEXTS)], f"{DOC}, {extra}")


@pytest.fixture(scope="module")
def none(spark):
    return spark.createDataFrame([], DOC)


def words_of(t):
    low = "".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in t or "")
    return re.findall(r"[^\x20\x09-\x0D]+", low)


def set_of(t, k):
    w = words_of(t)
    return {tuple(w[i : i + k]) for i in range(len(w) - k + 1)} if len(w) >= k else ({tuple(w)} if w else set())


def groups(n, linked):
    up = list(range(n))

    def root(x):
        while up[x] != x:
            x = up[x]
        return x

    for a, b in itertools.combinations(range(n), 2):
        if linked(a, b):
            x, y = root(a), root(b)
            up[max(x, y)] = min(x, y)
    return [root(i) for i in range(n)]


def test_components_of_chains_and_stars(spark):
    links = [(i, i + 1) for i in range(100, 180)] + [(5, i) for i in range(6, 60)] + [(7, 7), (None, 3), (300, 299)]
    got = {r.node: r.component for r in components(spark.createDataFrame(links, "a long, b long")).collect()}
    assert got == {i: 100 for i in range(101, 181)} | {i: 5 for i in range(6, 60)} | {300: 299}
    assert components(spark.createDataFrame([], "a long, b long")).count() == 0


@pytest.mark.parametrize(("k", "percent"), [(4, 85), (5, 80)])
def test_ngram_join_is_exact(spark, k, percent):
    rng = np.random.default_rng(3)
    texts = list(TEXTS)
    for _ in range(8):
        base = [f"t{x}" for x in rng.integers(0, 60, rng.integers(3, 120))]
        for _ in range(6):
            copy = list(base)
            for _ in range(int(rng.integers(0, 4))):
                copy[int(rng.integers(0, len(copy)))] = "new"
            texts.append(" ".join(copy))
    sets = [set_of(t, k) for t in texts]
    want = groups(len(texts), lambda a, b: bool(sets[a]) and 100 * len(sets[a] & sets[b]) >= percent * len(sets[a] | sets[b]))
    df = spark.createDataFrame(rows(texts), DOC)
    got = sorted(tuple(r) for r in ngram_join.ngram_groups(df, k, percent).collect())
    assert got == [(i, len(s), want[i]) for i, s in enumerate(sets)]
    small = sorted(tuple(r) for r in ngram_join.ngram_groups(df, k, percent, block=500).collect())
    assert small == got


def test_every_allocation_finds_every_pair():
    """Pairs at the very threshold share a key under deletions, slack and void subsets alike."""
    from fewbit.llm._shingles import U, mix

    rng = np.random.default_rng(1)
    for plan_of in (lambda h: ngram_join.Allocation(h + 1), lambda h: ngram_join.Allocation(h + 4, 0, 3), lambda h: ngram_join.Allocation(-(-(h + 1) // 2), -(-(h + 1) // 2)), lambda h: ngram_join.Allocation(h + 1, 2, 1)):
        for n in (6, 9, 20, 47):
            starts = ngram_join.band_starts(80, n)
            band = len(starts) - 2
            h = ngram_join.largest_difference(80, starts[band + 1] - 1)
            for _ in range(60):
                pool = mix(rng.integers(1, 2**62, 2 * n).astype(U))
                common = -(-80 * 2 * n // 180)
                a, b = np.unique(pool[:n]), np.unique(np.concatenate([pool[:common], pool[n : 2 * n - common]]))
                assert 100 * common >= 80 * (2 * n - common)
                assert np.intersect1d(ngram_join.band_keys(a, band, plan_of(h)), ngram_join.band_keys(b, band, plan_of(h))).size


def test_allocation_follows_costs():
    few, many = ngram_join.allocate(85, 20, 23, 10), ngram_join.allocate(85, 20, 23, 1e9)
    assert few.q == 0 and many.q > 0


def test_embeddings(spark):
    rng = np.random.default_rng(0)
    centre = rng.standard_normal((30, 16))
    x = (centre[rng.integers(0, 30, 400)] + 0.12 * rng.standard_normal((400, 16))).astype(np.float32)
    data = [(i, [float(v) for v in x[i]], 0) for i in range(400)]
    data += [(400, None, 1), (401, [0.0] * 16, 1), (402, [], 1), (403, [float("nan")] * 16, 1), (404, [None] * 16, 1), (405, data[3][1], 1), (406, [1.0, 0.0], 1)]
    got = {r[0]: tuple(r) for r in embedding_dedup.embedding_groups(spark.createDataFrame(data, "vec_id long, embedding array<float>, label int")).collect()}
    u = x.astype(float)
    u = np.vstack([u, u[3]])
    u /= np.linalg.norm(u, axis=1, keepdims=True)
    near = u @ u.T >= 0.9
    comp = groups(401, lambda a, b: near[a, b])
    ids = [*range(400), 405]
    for a, i in enumerate(ids):
        assert got[i] == (i, int(near[a].sum()) - 1, ids[comp[a]], comp[a] == a)
    for i in (400, 401, 402, 403, 404, 406):
        assert got[i] == (i, 0, i, True)
    assert embedding_dedup.embedding_groups(spark.createDataFrame([], "vec_id long, embedding array<float>")).count() == 0


def test_more_passes_for_more_vectors():
    assert embedding_dedup.passes_for(100) == 1 < embedding_dedup.passes_for(10**5) < embedding_dedup.passes_for(10**8)


def removed(texts, least):
    """Lines in a run of equal lines, with enough words, that begins earlier somewhere."""
    lines = [(t or "").split("\n") for t in texts]
    at = [(i, j) for i, ls in enumerate(lines) for j in range(len(ls)) if texts[i] is not None]
    gone = set()
    for (a, p), (b, q) in itertools.combinations(at, 2):
        n = 0
        while p + n < len(lines[a]) and q + n < len(lines[b]) and lines[a][p + n] == lines[b][q + n]:
            n += 1
        if n and sum(len(x.split()) for x in lines[b][q : q + n]) >= least:
            gone |= {(b, q + k) for k in range(n)}
    return ["\n".join(x for j, x in enumerate(ls) if (i, j) not in gone) if texts[i] is not None else None for i, ls in enumerate(lines)]


@pytest.mark.parametrize("least", [6, 50])
def test_line_dedup(spark, docs, least):
    rng = np.random.default_rng(5)
    texts = list(TEXTS)
    pool = [" ".join(f"l{rng.integers(0, 40)}" for _ in range(int(rng.integers(0, 5)))) for _ in range(12)]
    texts += ["\n".join(pool[int(i)] for i in rng.integers(0, 12, int(rng.integers(1, 14)))) for _ in range(25)]
    df = spark.createDataFrame(rows(texts), DOC)
    got = [r.text for r in line_dedup.dedup_lines(df, least).orderBy("doc_id").collect()]
    assert got == removed(texts, least)
    kept = line_dedup.without_repeats(docs)
    assert kept.columns == docs.columns and {r.doc_id for r in kept.collect()} >= {0, 2, 3, 4, 7, 8}


def test_packing(spark, docs, none):
    from tokenizers import Tokenizer

    path = P.path("word_bpe_49k.json")
    tok = Tokenizer.from_file(path)
    packed = packing.pack(docs, path, length=64)
    got = sorted(packing.packed_rows(packed).collect(), key=lambda r: (r.doc_id, r.piece))
    want = []
    for i, t in enumerate(TEXTS):
        ids = [*tok.encode(t or "", add_special_tokens=False).ids, 1]
        want += [(i, n, a, len(ids[a : a + 64]), zlib.crc32(np.array(ids[a : a + 64], "<u4").tobytes())) for n, a in enumerate(range(0, len(ids), 64))]
    assert [(r.doc_id, r.piece, r.start, r.length, r.ids_crc32) for r in got] == want
    at = {}
    for r in sorted(got, key=lambda r: (r.sequence_id, r.offset)):
        assert r.offset == at.get(r.sequence_id, 0)
        at[r.sequence_id] = r.offset + r.length
    assert max(at.values()) <= 64 and len(at) <= -(-sum(at.values()) // 64) + 2
    whole = {r.sequence_id: len(r.ids) // 4 for r in packed.sequences().collect()}
    assert whole == at
    assert packing.packed_rows(packing.pack(none, path)).count() == 0


def test_best_two_fit_replaces_the_smallest():
    assert packing.pack_histogram({60: 1, 30: 1, 21: 1, 19: 1}, 100)[0] == ([60, 21, 19], 1)
    plan = packing.pack_histogram({7: 10**9, 3: 5}, 10)
    assert plan[0] == ([7, 3], 5) and sum(n for _, n in plan) == 10**9


def test_bytes(spark, docs, none):
    import tiktoken

    path = P.path("byte_bpe_50k.tiktoken")
    ranks = byte_bpe.read_ranks(path)
    plain = tiktoken.Encoding("own", pat_str=P.PATTERN, mergeable_ranks=ranks, special_tokens={})
    out = byte_bpe.decode_bpe(byte_bpe.encode_bpe(docs, path), path).collect()
    for r in out:
        text = TEXTS[r.doc_id] or ""
        assert list(r.ids) == plain.encode_ordinary(text) and bytes(r.decoded).decode() == text
    assert sorted(byte_bpe.round_trip(docs, path).collect()) == sorted(out) and byte_bpe.round_trip(none, path).count() == 0
    encoder = byte_bpe.Encoder(ranks, P.PATTERN, cache=50)
    rng = np.random.default_rng(2)
    bits = ["'s", " ", "  ", "\n", "a", "É", "1", "!", "\t", "don't", " word", "　", "😀", "'", "<|endoftext|>", "\x1c", "é" * 40, "ab" * 30]
    for _ in range(1500):
        s = "".join(bits[i] for i in rng.integers(0, len(bits), rng.integers(0, 9)))
        assert np.frombuffer(encoder.encode(s), "<u4").tolist() == plain.encode_ordinary(s)
    assert {encoder.whole(k) for k in encoder.keys} == set(range(len(encoder.keys)))
    # a batch whose ids exceed a stretch is given on in several, and no row is lost or cut
    long = pa.record_batch([pa.array(range(5)), pa.array(["word " * 600_000, None, "", "word " * 600_000, "end"])], ["doc_id", "text"])
    parts = list(byte_bpe._decoded(byte_bpe._encoded(iter([long]), encoder, "doc_id"), encoder.tokens, "doc_id"))
    rows = [r for part in parts for r in part.to_pylist()]
    assert [len(part) for part in parts] == [4, 1] and [r["doc_id"] for r in rows] == list(range(5))
    assert [r["decoded"].decode() for r in rows] == [t or "" for t in long.column(1).to_pylist()]
    assert byte_bpe.encode_bpe(none, path).count() == 0


def test_quality(spark, docs, none):
    good = [f"the cat number {i} sat on the mat and looked at the other cats with calm eyes" for i in range(80)]
    bad = [f"BUY!! NOW!! {i}!! $$$ CHEAP!! $$$ CLICK!! HERE!!" for i in range(80)]
    data = spark.createDataFrame(rows(good + bad), DOC)
    labels = spark.createDataFrame([(i, int(i < 80), 0) for i in range(160)] + [(None, 1, 0), (3, None, 0)], "doc_id long, quality int, toxic int")
    model = quality.fit_quality(data, labels)
    scored = quality.score_quality(data, model).withColumn("held_out", quality.held_out()).collect()
    assert all((r.score >= 0.7) == (r.doc_id < 80) for r in scored if r.held_out)
    assert all(r.held_out == (zlib.crc32(str(r.doc_id).encode()) % 4 == 2) for r in scored)
    odd = quality.score_quality(docs, model).collect()
    assert len(odd) == len(TEXTS) and all(0 <= r.score <= 1 for r in odd)
    assert quality.score_quality(none, model).count() == 0
    flat = quality.fit_quality(data, spark.createDataFrame([], "doc_id long, quality int"))
    assert flat.score([b"any text", b""]).tolist() == pytest.approx([0.5, 0.5])


def test_attention_gradient_is_right():
    rng = np.random.default_rng(0)
    model = quality.train([b"one two three " * 30, b"four! five! " * 90, b"six"], np.array([1.0, 0.0, 1.0]), epochs=1)
    for k in ("E", "e", "V", "U", "a", "o", "b"):
        model.weights[k] = rng.standard_normal(model.weights[k].shape) * 0.3
    x, owner = next(quality.encode_passages([b"one two three " * 50, b"four! five! " * 90]))
    first = np.flatnonzero(np.concatenate([[True], owner[1:] != owner[:-1]]))
    y = np.array([1.0, 0.0])
    loss = lambda: float(-np.mean(y * np.log(s := model.forward(x, first)["score"]) + (1 - y) * np.log(1 - s)))
    grad = quality._gradient(model, x, first, y)
    for k, at in (("E", (3, 2)), ("V", (1, 1)), ("U", (0, 2)), ("a", (1,)), ("o", (4,)), ("b", (0,)), ("e", (5,))):
        w, step = model.weights[k], 1e-5
        w[at] += step
        up = loss()
        w[at] -= 2 * step
        down = loss()
        w[at] += step
        assert grad[k][at] == pytest.approx((up - down) / (2 * step), rel=2e-3, abs=1e-7)


def test_sharding(spark, docs, none):
    many = spark.createDataFrame(rows([f"text {i % 70} " * (i % 9) for i in range(300)]), DOC)
    for df, n in ((many, 300), (docs, len(TEXTS))):
        out = sharding.hilbert_shards(df, shards=7).collect()
        assert len(out) == n
        slots = {}
        for r in out:
            slots.setdefault(r.shard, []).append(r.slot)
        sizes = [len(s) for s in slots.values()]
        assert max(sizes) - min(sizes) <= 1 and all(sorted(s) == list(range(len(s))) for s in slots.values()) and set(slots) == set(range(7))
        for r in out:
            text = (TEXTS[r.doc_id] if n == len(TEXTS) else f"text {r.doc_id % 70} " * (r.doc_id % 9)) or ""
            assert (r["size"], r.text_crc32) == (len(text.encode()) + 16, zlib.crc32(text.encode()))
    assert sharding.hilbert_shards(none).count() == 0


def test_hilbert_curve_is_a_curve():
    cells = np.array(list(itertools.product(range(8), repeat=3)))
    at = sharding.hilbert_index(cells, 3)
    assert sorted(at) == list(range(512))
    assert (np.abs(np.diff(cells[np.argsort(at)], axis=0)).sum(1) == 1).all()


URLS = [
    "https://a.example.net/en/x?q#f", "http://EXAMPLE.com/de/", "https://x.org/fr/1", "https://net/", "https://foo.net", "https://barexample.com/de/x", None, "", "nourl", "ftp://y.net:80/p?x",
    "https://evil.com/x.example.net/en/", "a://b://c.net/", "https://ex.org#/fr/", "https://é.net/ü", "https://sub.example.net/en/" + "a" * 5000,
]


def test_urls(spark):
    got = {r.page_id: r for r in url_filter.judge_urls(spark.createDataFrame(list(enumerate(URLS)), "page_id long, url string")).collect()}
    for i, u in enumerate(URLS):
        host = path = ""
        if u and "://" in u:
            rest = u.split("://", 1)[1]
            host = re.match(r"[^/?#]*", rest)[0]
            path = re.match(r"[^?#]*", rest[len(host) :])[0]
            host = "".join(c.lower() if "A" <= c <= "Z" else c for c in host)
        fits = [r for r in url_filter.RULES if (host == r.host or host.endswith("." + r.host)) and path.startswith(r.path)]
        best = max(fits, key=lambda r: len(r.name), default=None)
        assert (got[i].host, got[i].path, got[i].rule, got[i].verdict) == (host, path, best and best.name, best.verdict if best else "allow")
    assert url_filter.judge_urls(spark.createDataFrame([], "page_id long, url string")).count() == 0


def test_automaton_against_fnmatch():
    import fnmatch

    rng = np.random.default_rng(4)
    globs = ["".join(rng.choice(list("ab*"), int(rng.integers(1, 14)))) for _ in range(60)]
    texts = ["".join(rng.choice(list("ab"), int(rng.integers(0, 12)))) for _ in range(200)]
    hit = url_filter.GlobAutomaton([g.encode() for g in globs]).run([t.encode() for t in texts])
    for i, t in enumerate(texts):
        for j, g in enumerate(globs):
            assert hit[i, j] == fnmatch.fnmatchcase(t, g)


def test_sketches(spark, docs, none):
    out = {r.doc_id: r for r in sketch.edited_pairs(docs).collect()}
    order = sorted(range(len(TEXTS)), reverse=True)
    for a, b in zip(order, order[1:] + order[:1], strict=True):
        t, nxt = TEXTS[a] or "", TEXTS[b] or ""
        edited = t[: len(t) - len(t) // 2] + nxt[: len(t) // 2]
        assert out[a].edited == edited and out[a].n_chars == len(t) and out[a].next_fingerprint == out[b].fingerprint
    assert out[0].fingerprint == out[1].fingerprint and out[2].fingerprint == out[3].fingerprint == []
    a, b = out[9].fingerprint, out[10].fingerprint
    s = set_of(LONG, 5)
    assert len(a) == pytest.approx(len(s) / sketch.SCALE, rel=0.2) and len(set(a) ^ set(b)) <= 2
    union = docs.where("doc_id IN (9, 10)").groupBy().agg(sketch.merge(sketch.F.expr(sketch.sketch_sql("text"))).alias("m")).first().m
    assert set(union) == set(a) | set(b)
    assert sketch.edited_pairs(none).count() == 0
    twice = docs.unionByName(docs)
    assert sketch.edited_pairs(twice).count() == len(TEXTS)


def luhn(d):
    return sum(int(c) if i % 2 == 0 else sum(divmod(2 * int(c), 10)) for i, c in enumerate(reversed(d))) % 10 == 0


BASE = {
    "email": r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+",
    "ip": r"[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)",
    "card": r"[0-9]([\x20-]?[0-9])+",
    "phone": r"\+[0-9][\x20().0-9-]+[0-9]",
}


def base_spans(t):
    out = []
    for rank, (kind, p) in enumerate(BASE.items()):
        for m in re.finditer(p, t):
            d = re.sub("[^0-9]", "", m[0])
            tests = {"email": lambda: True, "ip": lambda: all(int(x) <= 255 for x in m[0].split(".")), "card": lambda: 14 <= len(d) <= 19 and luhn(d), "phone": lambda: 10 <= len(d) <= 15}
            if tests[kind]():
                out.append((m.start(), rank, m.end(), kind))
    return sorted(out)


def test_personal_data(spark, docs, none):
    rng = np.random.default_rng(9)
    bits = ["a@b.co", "a@b.co_c@d.ef", "@", ".", " ", "-", "+", "1.2.3.4", "300.1.1.1", "4539148803436467", "4539 1488 0343 6467", "+49 (30) 1234-56789", "é😀", "x", "12", "(", "\n", "1.2.3.4.5.6.7.8", "000.001.02.255"]
    texts = TEXTS + ["".join(bits[i] for i in rng.integers(0, len(bits), 14)) for _ in range(300)] + ["9" * 20_000, "a" * 50_000, "a@b.c " * 900]
    df = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    names = list(BASE)
    for r in pii.find_pii(df).collect():
        got = [(s.start, s["rank"], s.end, s.kind) for s in r.pii_spans if s.kind in names]
        assert got == base_spans(texts[r.doc_id] or "")
    more = ["IBAN GB82WEST12345698765432 of my bank", "GB82WEST12345698765433", "ssn 123-45-6789", "part 123-45-6789"]
    found = pii.find_pii(spark.createDataFrame(list(enumerate(more)), "doc_id long, text string")).orderBy("doc_id").collect()
    assert [[s.kind for s in r.pii_spans] for r in found] == [["iban"], [], ["social"], []]
    clean = pii.redact_pii(docs)
    assert clean.columns == docs.columns
    kept = {r.doc_id: r.text for r in clean.collect()}
    assert kept[6] == "Mail [EMAIL] or [PHONE], card [CARD] at [IP]!" and kept[2] is None and kept[9] == LONG
    assert pii.find_pii(none).count() == 0


def test_query_digests(spark, sf):
    from fewbit.llm.queries import queries

    texts = {r.doc_id: r.text for r in spark.read.parquet(f"{sf}/documents.parquet").select("doc_id", "text").collect()}
    for r in queries()["op10_pii"](spark, sf).collect():
        own = ",".join(f"{k}:{a}:{b}" for a, _, b, k in base_spans(texts[r.doc_id]))
        assert r.base_sha256 == hashlib.sha256(own.encode()).hexdigest()
