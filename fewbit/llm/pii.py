"""Personal data: regular expressions propose spans, checksums confirm them, nearby words adjust their score.

Everything is a SQL expression over one row: no shuffle, no Python worker.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from fewbit.llm._store import table

CHUNK = 64
NEAR = 40


@dataclass(frozen=True)
class Kind:
    """pattern proposes; `valid` is SQL over the match `m`; `score` changes by `boost` where a whole word of `context` is near.

    Kinds that aren't base need ACCEPT: those that begin below it are taken for what they are by their surroundings alone.
    """

    name: str
    pattern: str
    hint: str
    valid: str = "true"
    score: float = 0.6
    boost: float = 0.3
    context: str = ""
    base: bool = True


def let(name: str, value: str, body: str) -> str:
    """SQL that evaluates value once and calls it name in body."""
    return f"transform(array({value}), {name} -> {body})[0]"


_DIGITS = "regexp_replace(m, '[^0-9]', '')"
_LUHN = let(
    "d",
    _DIGITS,
    "length(d) BETWEEN 14 AND 19 AND aggregate(transform(split(reverse(d), ''), (c, i) -> "
    "CASE WHEN i % 2 = 0 THEN int(c) WHEN int(c) > 4 THEN 2 * int(c) - 9 ELSE 2 * int(c) END), 0, (s, x) -> s + x) % 10 = 0",
)
_OCTET = "(?:0*(?:[0-9]{1,2}|1[0-9]{2}|2[0-4][0-9]|25[0-5]))"
_MOD97 = let(
    "r",
    "concat(substring(replace(m, ' '), 5), substring(m, 1, 4))",
    "aggregate(split(array_join(transform(split(r, ''), c -> CASE WHEN c >= 'A' THEN string(ascii(c) - 55) ELSE c END), ''), ''), "
    "0, (s, x) -> (s * 10 + int(x)) % 97) = 1",
)

# letters and digits, and not few of them only
_MIXED = "m RLIKE '[0-9]' AND m RLIKE '[A-Za-z]' AND size(array_distinct(split(m, ''))) >= 8"

# The base patterns may only begin where a run of their first class begins or where the last match ended: a start inside
# such a run can't succeed where the run's own start has failed. With possessive runs this finds the same leftmost spans
# in linear time, and no repeated group recurses on very long runs.
_EMAIL = r"(?:(?<![A-Za-z0-9._%+-])|\G)[A-Za-z0-9._%+-]++@[A-Za-z0-9-]++(?:\.[A-Za-z0-9-]++)++"
_IP = r"(?:(?<![0-9])|\G)[0-9]++\.[0-9]++\.[0-9]++\.[0-9]++"
_CARD = r"[0-9](?:[\x20-]?[0-9])++"
_PHONE = r"\+[0-9][\x20().0-9-]+[0-9]"

#: The length of an IBAN by country, by the public registry.
IBAN_LENGTHS = (
    "AD24 AE23 AL28 AT20 AZ28 BA20 BE16 BG22 BH22 BR29 BY28 CH21 CR22 CY28 CZ24 DE22 DK18 DO28 EE20 EG29 ES24 FI18 FO18 FR27 GB22 GE22 GI23 GL18 GR27 GT28 "
    "HR21 HU28 IE22 IL23 IS26 IT27 JO30 KW30 KZ20 LB28 LI21 LT20 LU20 LV21 MC27 MD24 ME22 MK19 MR27 MT31 MU30 NL18 NO15 PK24 PL28 PS29 PT25 QA29 RO24 RS22 "
    "SA24 SC31 SE24 SI19 SK24 SM27 TN24 TR26 UA29 VA22 VG24 XK20"
)


def iban_pattern() -> str:
    """IBANs as written, with a space after every four characters or without; each country's own length."""
    by_length: dict[int, list[str]] = {}
    for item in IBAN_LENGTHS.split():
        by_length.setdefault(int(item[2:]), []).append(item[:2])
    forms = []
    for length, countries in sorted(by_length.items()):
        fours, rest = divmod(length - 4, 4)
        tail = rf"\x20?[A-Z0-9]{{{rest}}}" if rest else ""
        forms.append(rf"(?:{'|'.join(countries)})[0-9]{{2}}(?:\x20?[A-Z0-9]{{4}}){{{fours}}}{tail}")
    return rf"(?<![A-Za-z0-9])(?:{'|'.join(forms)})(?![A-Za-z0-9])"


# keys that say what they are by their first letters, and long runs that only their surroundings can call a secret
_KEY = r"(?<![A-Za-z0-9])(?:AKIA[A-Z0-9]{16}|gh[oprsu]_[A-Za-z0-9]{36}|sk-[A-Za-z0-9_-]{20,}+|xox[abps]-[A-Za-z0-9-]{10,}+|-----BEGIN (?:[A-Z]+ )?PRIVATE KEY-----)"
_SECRET = r"(?<![A-Za-z0-9+/_-])[A-Za-z0-9+/_-]{16,}+=*+"
_SOCIAL = r"(?<![0-9-])[0-9]{3}-[0-9]{2}-[0-9]{4}(?![0-9-])"

KINDS = (
    Kind("email", _EMAIL, "instr(t, '@') > 0", score=0.9, boost=0.1, context="e-?mails?|mail|contact|write"),
    Kind("ip", _IP, "t RLIKE '[0-9][.][0-9]'", f"m RLIKE '^{_OCTET}([.]{_OCTET}){{3}}$'", context="ip|host|server|address"),
    Kind("card", _CARD, "t RLIKE '[0-9]'", _LUHN, score=0.8, boost=0.2, context="card|visa|credit|pay"),
    Kind("phone", _PHONE, "instr(t, '+') > 0", f"length({_DIGITS}) BETWEEN 10 AND 15", context="phone|call|tel|fax"),
    Kind("iban", iban_pattern(), "t RLIKE '[A-Z][0-9]{2}'", _MOD97, score=0.8, boost=0.2, context="iban|bank|account", base=False),
    Kind("social", _SOCIAL, "t RLIKE '[0-9]-[0-9]'", score=0.3, context="ssn|social|security", base=False),
    Kind("key", _KEY, "t RLIKE '[a-zA-Z]{2}[A-Z_-]'", score=0.9, boost=0.1, context="key|token|secret", base=False),
    Kind("secret", _SECRET, "t RLIKE '[A-Za-z0-9+/_-]{16}'", _MIXED, score=0.2, boost=0.5, context="secrets?|tokens?|passwords?|passwd|pwd|credentials?|(?:api|access|private)?[_-]?keys?", base=False),
)
ACCEPT = 0.5


def _quoted(pattern: str) -> str:
    return "'" + pattern.replace("\\", "\\\\").replace("'", "\\'") + "'"


def _spans(kind: Kind, rank: int) -> str:
    """SQL array of (start, rank, end, kind, score) of one kind in the text `t`.

    The text between matches and the matches themselves give all places by running sums, taken in chunks so that a
    text with very many matches costs little more than one with few.
    """
    p = _quoted(kind.pattern)
    score = f"{kind.score}D"
    if kind.context:
        # the words just before and after, within the neighbouring stretches between matches
        words = _quoted(f"(?i)(?<![A-Za-z])(?:{kind.context})(?![A-Za-z])")
        near = f"(right(seg[i], {NEAR}) RLIKE {words} OR left(seg[i + 1], {NEAR}) RLIKE {words})"
        score = f"CASE WHEN {near} THEN {kind.score}D + {kind.boost}D ELSE {kind.score}D END"
    start = f"base[int(i div {CHUNK})] + aggregate(slice(len, int(i - i % {CHUNK}) + 1, int(i % {CHUNK})), 0, (s, x) -> s + x) + length(seg[i])"
    made = (
        f"filter(transform(found, (m, i) -> CASE WHEN {kind.valid} THEN "
        + let("b", start, f"named_struct('start', b, 'rank', {rank}, 'end', b + length(m), 'kind', '{kind.name}', 'score', {score})")
        + " END), x -> x IS NOT NULL)"
    )
    chunks = f"transform(sequence(0, int(size(len) div {CHUNK})), c -> aggregate(slice(len, c * {CHUNK} + 1, {CHUNK}), 0, (s, x) -> s + x))"
    body = let(
        "len",
        "transform(found, (m, i) -> length(seg[i]) + length(m))",
        let("sums", chunks, let("base", "transform(sums, (y, c) -> aggregate(slice(sums, 1, c), 0, (s, x) -> s + x))", made)),
    )
    none = "CAST(array() AS array<struct<start:int,rank:int,end:int,kind:string,score:double>>)"
    return (
        f"CASE WHEN {kind.hint} THEN "
        + let("found", f"regexp_extract_all(t, {p}, 0)", f"CASE WHEN size(found) = 0 THEN {none} ELSE {let('seg', f'split(t, {p}, -1)', body)} END")
        + f" ELSE {none} END"
    )


def spans_sql(text: str) -> str:
    """SQL array of all accepted spans of a text expression, by start, then kind as listed. Places count code points."""
    parts = ", ".join(_spans(k, i) for i, k in enumerate(KINDS))
    base = "(" + ", ".join(f"'{k.name}'" for k in KINDS if k.base) + ")"
    return let("t", text, f"array_sort(filter(concat({parts}), s -> s.kind IN {base} OR s.score >= {ACCEPT}D))")


def find_pii(docs: DataFrame, text_col: str = "text", spans_col: str = "pii_spans") -> DataFrame:
    """docs with one array column of (start, rank, end, kind, score) structs; a clashing column of that name is replaced.

    Base kinds (email, ip, card, phone) stay whatever their score; the added kinds (iban by mod-97, social and secret by
    context, key by its first letters) need ACCEPT. Kinds are searched apart, so spans of two kinds may overlap. Null and empty texts have no spans.
    """
    return docs.withColumn(spans_col, F.expr(spans_sql(f"coalesce(`{text_col}`, '')")))


def redacted(text_col: str, spans_col: str) -> Column:
    """The text with each stretch that spans cover replaced by [KIND] of its first span."""
    merged = (
        f"aggregate({spans_col}, CAST(array() AS array<struct<start:int,end:int,kind:string>>), (a, s) -> "
        "CASE WHEN size(a) > 0 AND s.start < element_at(a, -1).end THEN concat(slice(a, 1, size(a) - 1), "
        "array(named_struct('start', element_at(a, -1).start, 'end', greatest(element_at(a, -1).end, s.end), 'kind', element_at(a, -1).kind))) "
        "ELSE concat(a, array(named_struct('start', s.start, 'end', s.end, 'kind', s.kind))) END)"
    )
    pieces = (
        "concat(array_join(transform(z, (s, i) -> concat(substring(t, CASE WHEN i = 0 THEN 1 ELSE z[i - 1].end + 1 END, "
        "s.start - CASE WHEN i = 0 THEN 0 ELSE z[i - 1].end END), '[', upper(s.kind), ']')), ''), substring(t, element_at(z, -1).end + 1))"
    )
    return F.expr(f"CASE WHEN size({spans_col}) > 0 THEN {let('t', f'`{text_col}`', let('z', merged, pieces))} ELSE `{text_col}` END")


def redact_pii(docs: DataFrame, text_col: str = "text") -> DataFrame:
    """docs, same columns and rows, with personal data in the text replaced by its kind in brackets; null text stays null."""
    marked = find_pii(docs, text_col, "__pii")
    out = marked.withColumn(text_col, redacted(text_col, "__pii")).drop("__pii")
    if "n_chars" in docs.columns:
        out = out.withColumn("n_chars", F.coalesce(F.length(text_col), F.lit(0)).cast(docs.schema["n_chars"].dataType))
    return out.select(*[F.col(f"`{c}`") for c in docs.columns])


def op10_pii(spark, sf_dir):
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    found = find_pii(docs).select("doc_id", "pii_spans")
    names = "(" + ", ".join(f"'{k.name}'" for k in KINDS if k.base) + ")"
    joined = "array_join(transform({a}, s -> concat(s.kind, ':', s.start, ':', s.end)), ',')"
    base = joined.format(a=f"filter(pii_spans, s -> s.kind IN {names})")
    return found.select(
        "doc_id",
        *[F.expr(f"bigint(size(filter(pii_spans, s -> s.kind = '{k.name}')))").alias(f"n_{k.name}") for k in KINDS if k.base],
        F.size("pii_spans").cast("long").alias("n_spans"),
        F.expr(f"sha2({base}, 256)").alias("base_sha256"),
        F.expr(joined.format(a="pii_spans")).alias("spans"),
        F.expr("array_join(transform(pii_spans, s -> string(round(s.score, 2))), ',')").alias("scores"),
    )
