"""Secret scans with DataFrame functions only.

Base spans come from three patterns (assign, access, hex). Further spans come from
candidate strings: runs of 20 or more characters of a key alphabet. A window of 20
characters slides over a candidate with the counts c of its characters, of which a step changes two:
that of the character that enters and that of the one that leaves. So does the sum
of c * log2(c), and the window's
Shannon entropy is log2(20) - sum / 20. A candidate counts if the highest entropy
reaches the bound of its character class, if it mixes digits and letters, if no
base span holds it and if nothing on the allow list fits it.

Positions are code points, ends exclusive. Null text is empty. A text of any length
is scanned whole: one pass picks the texts in which anything can match, and match
positions are summed up block by block, so that many matches stay affordable.
Repeated rows are scanned alike; an empty table gives an empty one.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import common

# The patterns of the kinds, in the order in which kinds are listed.
ASSIGN = r"""(?i:password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)"""
ACCESS = r"AKIA[A-Z0-9]{16,}"
HEX = r"[0-9a-f]{24,}"
CANDIDATE = r"(?<![A-Za-z0-9+/_=-])[A-Za-z0-9+/_=-]{20,}"
ANY = rf"""(?i:password|passwd|secret|token|api_?key)["']?\x20*[:=]|AKIA[A-Z0-9]{{16}}|(?<![0-9a-f])[0-9a-f]{{24}}|{CANDIDATE[:-5]}{{20}}"""
KINDS = ("assign", "access", "hex", "entropy")

WINDOW = 20
#: Bits that a window must reach, by character class: hexadecimal digits, letters and digits of one case, all others.
BOUNDS = (3.0, 3.4, 3.6)
#: Strings that look random and are known not to be: identifiers, runs, placeholders, words joined by dashes or slashes.
ALLOWED = (
    r"^[0-9a-fA-F]{8}-[0-9a-fA-F]{4}-[0-9a-fA-F]{4}-[0-9a-fA-F]{4}-[0-9a-fA-F]{12}$",
    r"(?i)0123456789|9876543210|abcdefghij|qwertyuiop",
    r"(?i)example|sample|dummy|placeholder|changeme|your[_-]",
    r"^[A-Za-z]{2,}([/_=+-]+([A-Za-z]{2,}|[0-9]{1,4}))*$",
    r"^[0-9]{4}-?[0-9]{2}-?[0-9]{2}[0-9T_-]*$",
)

#: Match positions summed up at a time.
_BLOCK = 500


def _quote(pattern: str) -> str:
    return "'" + pattern.replace("\\", "\\\\").replace("'", "\\'") + "'"


def _places(pattern: str, group: int) -> str:
    """SQL for an array of (start, end, value) of the matches of a pattern in ``text``."""
    p = _quote(pattern)
    steps = f"zip_with(zip_with(slice(split(text, {p}), 1, size(regexp_extract_all(text, {p}, 0))), regexp_extract_all(text, {p}, 0), (g, m) -> struct(char_length(g) AS gap, char_length(m) AS len)), regexp_extract_all(text, {p}, {group}), (a, v) -> struct(a.gap AS gap, a.len AS len, v AS value))"
    none = "cast(array() AS array<struct<start: int, end: int, value: string>>)"
    inner = f"""aggregate(slice(s, k * {_BLOCK} + 1, {_BLOCK}), struct(acc.at AS at, {none} AS out),
        (b, x) -> struct(b.at + x.gap + x.len AS at, concat(b.out, array(struct(b.at + x.gap AS start, b.at + x.gap + x.len AS end, x.value AS value))) AS out))"""
    return f"""transform(array({steps}), s -> aggregate(sequence(0, size(s) div {_BLOCK}), struct(0 AS at, {none} AS out),
        (acc, k) -> transform(array({inner}), i -> struct(i.at AS at, concat(acc.out, i.out) AS out))[0], acc -> acc.out))[0]"""


def _weight(count: str) -> str:
    return f"CASE WHEN {count} > 1 THEN {count} * log2({count}) ELSE 0D END"


def _entropy(value: str) -> str:
    """SQL for the highest entropy of a window of a string.

    ``counts`` holds how often each distinct character of the string stands in the window; a step
    adds one for the character that enters and takes one for that which leaves.
    """
    c_in, c_out = "acc.counts[p.entering - 1]", "acc.counts[p.leaving - 1]"
    added = f"{_weight(f'({c_in} + 1)')} - {_weight(c_in)}"
    taken = f"CASE WHEN p.leaving = 0 THEN 0D ELSE {_weight(c_out)} - {_weight(f'({c_out} - 1)')} END"
    places = f"struct(array_position(ids, ch[i - 1]) AS entering, CASE WHEN i > {WINDOW} THEN array_position(ids, ch[i - 1 - {WINDOW}]) ELSE 0L END AS leaving)"
    counts = "transform(acc.counts, (c, k) -> c + CASE WHEN k + 1 = p.entering THEN 1 WHEN k + 1 = p.leaving THEN -1 ELSE 0 END)"
    total = f"CASE WHEN p.entering = p.leaving THEN acc.sum ELSE acc.sum + {added} - {taken} END"
    step = f"""transform(array({places}), p -> transform(array({total}), t -> struct(t AS sum,
        CASE WHEN i < {WINDOW} THEN 0D ELSE greatest(acc.best, log2({WINDOW}D) - t / {WINDOW}D) END AS best,
        CASE WHEN p.entering = p.leaving THEN acc.counts ELSE {counts} END AS counts))[0])[0]"""
    start = "struct(0D AS sum, 0D AS best, array_repeat(0, size(ids)) AS counts)"
    return f"transform(array(split({value}, '')), ch -> transform(array(array_distinct(ch)), ids -> aggregate(sequence(1, size(ch)), {start}, (acc, i) -> {step}, acc -> acc.best))[0])[0]"


def scanned(docs: DataFrame) -> DataFrame:
    """docs with two more columns, ``_scan_base`` and ``_scan_found``: spans of each whole text,
    as arrays of (start, rank of kind, end), sorted; the second holds base spans and those
    of high entropy. Texts without any have empty arrays. Other columns stay."""
    none = "cast(array() AS array<struct<start: int, kind: int, end: int>>)"
    may = "(text IS NOT NULL AND text RLIKE " + _quote(ANY) + ")"
    as_kind = lambda places, kind, keep="true": f"transform(filter({places}, x -> {keep}), x -> struct(x.start AS start, {kind} AS kind, x.end AS end))"
    value = "x.value"
    good = " AND ".join([f"x.value RLIKE '[0-9]' AND x.value RLIKE '[A-Za-z]'", *(f"NOT x.value RLIKE {_quote(a)}" for a in ALLOWED)])
    bound = f"CASE WHEN x.value RLIKE '^([0-9a-f]+|[0-9A-F]+)$' THEN {BOUNDS[0]}D WHEN x.value RLIKE '^([0-9a-z]+|[0-9A-Z]+)$' THEN {BOUNDS[1]}D ELSE {BOUNDS[2]}D END"
    rows = docs.withColumn("_scan_may", F.expr(may))
    rows = rows.withColumn("_scan_base", F.expr(f"""CASE WHEN _scan_may THEN array_sort(concat(
        {as_kind(_places(ASSIGN, 1), 0, "char_length(x.value) >= 6")},
        {as_kind(_places(ACCESS, 0), 1)},
        {as_kind(_places(HEX, 0), 2)})) ELSE {none} END"""))
    held = "exists(_scan_base, b -> b.start <= x.start AND x.end <= b.end)"
    more = as_kind(_places(CANDIDATE, 0), 3, f"NOT {held} AND {good} AND {_entropy(value)} >= {bound}")
    return rows.withColumn("_scan_found", F.expr(f"CASE WHEN _scan_may THEN array_sort(concat(_scan_base, {more})) ELSE {none} END")).drop("_scan_may")


def _joined(spans: str) -> str:
    names = "array(" + ", ".join(f"'{k}'" for k in KINDS) + ")"
    return f"array_join(transform({spans}, x -> concat_ws(':', {names}[x.kind], x.start, x.end)), ',')"


def scan(docs: DataFrame) -> DataFrame:
    """One row per document: doc_id, numbers of base spans by kind, SHA-256 of the
    base spans, and all spans as text."""
    n = lambda kind: F.expr(f"cast(size(filter(_scan_base, x -> x.kind = {kind})) AS long)")
    rows = scanned(common.columns(docs, ["doc_id", "text"]))
    return rows.select("doc_id", n(0).alias("n_assign"), n(1).alias("n_access"), n(2).alias("n_hex"), F.expr(f"sha2({_joined('_scan_base')}, 256)").alias("base_sha256"), F.expr(_joined("_scan_found")).alias("spans"))


def redact(docs: DataFrame, mark: str = "[SECRET]") -> DataFrame:
    """docs with every found span of ``text`` replaced by a mark; overlapping spans by one."""
    parts = """aggregate(_scan_found, struct(0 AS at, cast(array() AS array<string>) AS out), (acc, x) ->
        CASE WHEN x.end <= acc.at THEN acc
             WHEN x.start < acc.at THEN struct(x.end AS at, acc.out AS out)
             ELSE struct(x.end AS at, concat(acc.out, array(substring(text, acc.at + 1, x.start - acc.at), MARK)) AS out) END,
        acc -> concat(array_join(acc.out, ''), substring(text, acc.at + 1)))""".replace("MARK", _quote(mark))
    names = docs.columns
    return scanned(docs).withColumn("text", F.expr(f"CASE WHEN size(_scan_found) > 0 THEN {parts} ELSE text END")).select(*names)
