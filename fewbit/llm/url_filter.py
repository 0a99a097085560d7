"""URL filter: glob rules packed in one bit-parallel automaton that reads each canonical URL once."""

from __future__ import annotations

from collections.abc import Iterator, Sequence
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from fewbit.llm._store import table

#: Parts host from path in a canonical URL; UTF-8 has no such byte, so no wildcard can cross it twice.
BOUND = b"\xff"
_ROWS = 4096


@dataclass(frozen=True)
class Rule:
    host: str
    path: str
    verdict: str

    @property
    def name(self) -> str:
        return self.host + self.path

    def globs(self) -> list[bytes]:
        tail = BOUND + self.path.encode() + b"*"
        return [self.host.encode() + tail, b"*." + self.host.encode() + tail]


RULES = (
    Rule("net", "/", "block"),
    Rule("example.net", "/en/", "allow"),
    Rule("example.com", "/de/", "block"),
    Rule("org", "/fr/", "allow"),
)


class GlobAutomaton:
    """All globs as one Shift-And machine over 64-bit words; `*` stands for any run of bytes.

    Each glob owns a stretch of bits: one for its start, one for each literal byte. A step moves every live bit up by
    one where the byte read leads into it, and keeps the bits at which a `*` waits.
    """

    def __init__(self, globs: Sequence[bytes]):
        start, into, stay, ends, n = [], [], [], [], 0
        for glob in globs:
            start.append(n)
            here = n
            n += 1
            for byte in glob:
                if byte == 0x2A:
                    stay.append(here)
                else:
                    into.append((n, byte))
                    here = n
                    n += 1
            ends.append(here)
        self.words = max(1, -(-n // 64))
        self.step = np.zeros((256, self.words), np.uint64)
        for bit, byte in into:
            self.step[byte, bit // 64] |= np.uint64(1 << bit % 64)
        self.begin, self.stay = self._mask(start), self._mask(stay)
        self.ends = ends

    def _mask(self, bits: Sequence[int]) -> np.ndarray:
        out = np.zeros(self.words, np.uint64)
        for bit in bits:
            out[bit // 64] |= np.uint64(1 << bit % 64)
        return out

    def run(self, texts: Sequence[bytes]) -> np.ndarray:
        """Boolean matrix: text by glob, whether the glob matches the whole text."""
        out = np.zeros((len(texts), len(self.ends)), bool)
        lengths = np.fromiter(map(len, texts), np.int64, len(texts))
        order = np.argsort(-lengths, kind="stable")
        for lo in range(0, len(texts), _ROWS):
            some = order[lo : lo + _ROWS]
            size, flat = lengths[some], np.frombuffer(b"".join(texts[i] for i in some), np.uint8)
            at = np.cumsum(size) - size
            state = np.repeat(self.begin[None, :], len(some), 0)
            live = len(some)
            for k in range(int(size[0]) if len(size) else 0):
                while size[live - 1] <= k:
                    live -= 1
                now = state[:live]
                moved = now << np.uint64(1)
                if self.words > 1:
                    moved[:, 1:] |= now[:, :-1] >> np.uint64(63)
                state[:live] = (moved & self.step[flat[at[:live] + k]]) | (now & self.stay)
            for g, bit in enumerate(self.ends):
                out[some, g] = (state[:, bit // 64] >> np.uint64(bit % 64)) & np.uint64(1)
        return out


def canonical(url: str = "url") -> tuple[Column, Column]:
    """Host (A-Z lower-cased) and path of a URL column; both empty for null or where `://` is missing."""
    has = f"instr(`{url}`, '://') > 0"
    rest = f"substring(`{url}`, instr(`{url}`, '://') + 3)"
    upper, lower = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"
    host = F.expr(f"CASE WHEN {has} THEN translate(regexp_extract({rest}, '^[^/?#]*', 0), '{upper}', '{lower}') ELSE '' END")
    path = F.expr(f"CASE WHEN {has} THEN regexp_extract({rest}, '^[^/?#]*([^?#]*)', 1) ELSE '' END")
    return host, path


def judge_urls(pages: DataFrame, rules: Sequence[Rule] = RULES, default: str = "allow", id_col: str = "page_id", url_col: str = "url") -> DataFrame:
    """(id, host, path, rule string, verdict string), one row per input row; only the two named columns are read.

    A rule fits its host and that host's subdomains where the URL's path starts with the rule's; the longest fitting
    rule wins (of equals, the first listed), and `default` holds where none fits. Null, empty and scheme-less URLs have
    empty host and path, which no rule fits. Repeated rows are judged one by one; an empty table gives an empty one.
    """
    rules = tuple(rules)
    globs = [g for r in rules for g in r.globs()]
    rank = sorted(range(len(rules)), key=lambda i: (-len(rules[i].name), i))
    names = [r.name for r in rules]
    verdicts = [r.verdict for r in rules]
    host, path = canonical(url_col)
    cut = pages.select(F.col(id_col), host.alias("host"), path.alias("path"))
    schema = f"`{id_col}` {cut.schema[id_col].dataType.simpleString()}, host string, path string, rule string, verdict string"

    def judge(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        machine = GlobAutomaton(globs)
        for batch in batches:
            hosts, paths = batch.column(1).to_pylist(), batch.column(2).to_pylist()
            hit = machine.run([h.encode() + BOUND + p.encode() for h, p in zip(hosts, paths, strict=True)])
            best = np.full(len(hosts), -1)
            for i in rank:
                best[(best < 0) & hit[:, 2 * i : 2 * i + 2].any(axis=1)] = i
            found = best.tolist()
            yield pa.RecordBatch.from_arrays(
                [
                    *batch.columns,
                    pa.array([names[i] if i >= 0 else None for i in found], pa.string()),
                    pa.array([verdicts[i] if i >= 0 else default for i in found], pa.string()),
                ],
                [id_col, "host", "path", "rule", "verdict"],
            )

    return cut.mapInArrow(judge, schema)


def op8_url_filter(spark, sf_dir):
    return judge_urls(table(spark, sf_dir, "pages"))


OP8_SQL = r"""
WITH u AS (SELECT page_id, CASE WHEN strpos(url, '://') > 0 THEN substr(url, strpos(url, '://') + 3) END AS rest FROM pages),
p AS (SELECT page_id,
    coalesce(translate(regexp_extract(rest, '^[^/?#]*'), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '') AS host,
    coalesce(regexp_extract(rest, '^[^/?#]*([^?#]*)', 1), '') AS path FROM u),
r(h, s, v) AS (VALUES ('net', '/', 'block'), ('example.net', '/en/', 'allow'), ('example.com', '/de/', 'block'), ('org', '/fr/', 'allow')),
m AS (SELECT page_id, arg_max(h || s, length(h || s)) AS rule, arg_max(v, length(h || s)) AS v
    FROM p, r WHERE (host = h OR ends_with(host, '.' || h)) AND starts_with(path, s) GROUP BY page_id)
SELECT p.page_id, host, path, rule, coalesce(v, 'allow') AS verdict FROM p LEFT JOIN m USING (page_id)
"""
