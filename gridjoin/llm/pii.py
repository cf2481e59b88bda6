"""Operator 6, personal data: patterns propose spans, checks confirm them, words near by move the score. [native]

Four base kinds are always reported where their pattern and check hold: email, ip (parts at most 255), card (14 to 19
digits, Luhn) and phone (10 to 15 digits). Two further kinds are reported when their score reaches ``ACCEPT``: iban
(mod-97 makes 80 of 100 points) and ssn (the pattern alone makes 40, a whole context word in the 32 characters before it 40
more). Spans are code points, end exclusive, leftmost and not overlapping within a kind.

Positions come from one split and one extract of the same pattern: the lengths of the gaps and of the matches, summed in
turn. Everything is a row-wise JVM expression, so there is no shuffle and a hot source costs nothing.

Defined cases: null or empty text has no spans (empty string, SHA-256 of the empty string). A table without rows gives no
rows. Repeated rows are reported each. Spans of one start are in the order of the kinds. Columns other than doc_id and text are not read. Texts of any length are
scanned whole; the patterns are anchored and possessive where that finds the same spans, so a long run of digits or
letters costs linear time.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import table, text_or_empty

#: The kinds in their order.
BASE = ("email", "ip", "card", "phone")
ADDED = ("iban", "ssn")

#: Java patterns. They match what the plain patterns of SQL below match; a start is tried only where a run of the class begins
#: or where the last match ended.
PATTERNS = {
    "email": r"(?:(?<![A-Za-z0-9._%+-])|\G)[A-Za-z0-9._%+-]++@[A-Za-z0-9-]++(?:\.[A-Za-z0-9-]++)++",
    "ip": r"(?<![0-9])[0-9]++\.[0-9]++\.[0-9]++\.[0-9]++",
    "card": r"[0-9](?:[\x20-]?[0-9])++",
    "phone": r"\+[0-9][\x20().0-9-]+[0-9]",
    "iban": r"\b[A-Z]{2}[0-9]{2}[A-Z0-9]{11,30}\b",
    "ssn": r"\b[0-9]{3}-[0-9]{2}-[0-9]{4}\b",
}
#: A text without this character has no span of the kind.
NEEDS = {"email": "@", "ip": ".", "phone": "+", "ssn": "-"}
#: Points of a confirmed span before its context is read, and the words that add CONTEXT points.
POINTS = {"email": 90, "ip": 60, "card": 80, "phone": 60, "iban": 80, "ssn": 40}
WORDS = {
    "email": "mail|contact|write",
    "ip": "ip|host|server|address",
    "card": "card|visa|credit|payment",
    "phone": "phone|tel|call|mobile|fax",
    "iban": "iban|account|bank",
    "ssn": "ssn|social|security",
}
CONTEXT, NEAR, ACCEPT = 40, 32, 60


def _context(kind: str) -> str:
    """A whole word before the span; what is read begins one character earlier, so that a cut word does not count."""
    return f"[^a-z]({WORDS[kind]})([^a-z]|$)"


def _digits(m: Column) -> Column:
    return F.regexp_replace(m, "[^0-9]", "")


def _mod97(m: Column) -> Column:
    moved = F.concat(F.substring(m, 5, 64), F.substring(m, 1, 4))
    value = lambda c: F.when(c < "A", F.ascii(c) - 48).otherwise(F.ascii(c) - 55)
    step = lambda r, c: (r * F.when(c < "A", 10).otherwise(100) + value(c)) % 97
    return F.aggregate(F.split(moved, ""), F.lit(0), lambda r, c: F.when(c == "", r).otherwise(step(r, c)))


def confirmed(kind: str, m: Column) -> Column:
    if kind == "ip":
        return F.forall(F.split(m, r"\."), lambda p: (F.length(F.regexp_replace(p, "^0+", "")) <= 3) & (F.coalesce(p.try_cast("int"), F.lit(999)) <= 255))
    if kind == "card":
        d = _digits(m)
        return F.length(d).between(14, 19) & F.call_function("luhn_check", d)
    if kind == "phone":
        return F.length(_digits(m)).between(10, 15)
    if kind == "iban":
        return _mod97(m) == 1
    return F.lit(True)


def spans_of(kind: str, text: Column) -> Column:
    """array<struct<s,e,k,p>> of one kind: start, end, rank of the kind, points."""
    pattern, rank = PATTERNS[kind], (BASE + ADDED).index(kind)
    gaps, found = F.split(text, pattern, -1), F.regexp_extract_all(text, F.lit(pattern), F.lit(0))
    none = F.expr("cast(array() as array<struct<s:int,e:int,k:int,p:int>>)")

    def step(acc: Column, x: Column) -> Column:
        start = acc["pos"] + F.length(x["g"])
        end = start + F.length(x["m"])
        before = F.lower(F.when(start > NEAR, F.substring(text, start - NEAR, F.lit(NEAR + 1))).otherwise(F.concat(F.lit(" "), F.substring(text, F.lit(1), start))))
        points = F.lit(POINTS[kind]) + F.when(before.rlike(_context(kind)), CONTEXT).otherwise(0)
        keep = confirmed(kind, x["m"])
        if kind in ADDED:
            keep = keep & (points >= ACCEPT)
        one = F.array(F.struct(start.alias("s"), end.alias("e"), F.lit(rank).alias("k"), points.alias("p")))
        return F.struct(end.alias("pos"), F.when(keep, F.concat(acc["out"], one)).otherwise(acc["out"]).alias("out"))

    pairs = F.zip_with(found, F.slice(gaps, F.lit(1), F.size(found)), lambda m, g: F.struct(g.alias("g"), m.alias("m")))
    spans = F.aggregate(pairs, F.struct(F.lit(0).alias("pos"), none.alias("out")), step)["out"]
    present = F.contains(text, F.lit(NEEDS[kind])) if kind in NEEDS else text.rlike("[0-9]")
    return F.when(present, spans).otherwise(none)


def _joined(spans: Column) -> Column:
    names = F.array(*[F.lit(k) for k in BASE + ADDED])
    one = lambda x: F.concat_ws(":", F.element_at(names, x["k"] + 1), x["s"].cast("string"), x["e"].cast("string"))
    return F.concat_ws(",", F.transform(spans, one))


def find_pii(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row for each row of docs: counts of each kind, the joined spans and their highest score."""
    text = F.col("t")
    df = docs.select(F.col(id_col), text_or_empty(text_col).alias("t")).withColumns({k: spans_of(k, text) for k in BASE + ADDED})
    by_start = lambda *kinds: F.array_sort(F.transform(F.concat(*kinds), lambda x: F.struct(x["s"], x["k"], x["e"], x["p"])))
    df = df.select(id_col, *BASE, *ADDED, by_start(*BASE).alias("base"), by_start(*BASE, *ADDED).alias("every"))
    return df.select(
        F.col(id_col),
        *[F.size(k).cast("long").alias(f"n_{k}") for k in BASE + ADDED],
        F.sha2(_joined(F.col("base")), 256).alias("base_sha256"),
        _joined(F.col("every")).alias("spans"),
        F.coalesce(F.array_max(F.transform("every", lambda x: x["p"])), F.lit(0)).cast("long").alias("max_points"),
    )


def op6_pii(spark: SparkSession, sf_dir: str) -> DataFrame:
    return find_pii(table(spark, sf_dir, "documents"))


def oracle() -> str:
    """The same in DuckDB, with plain patterns (RE2 is linear whatever the pattern)."""
    plain = {
        "email": r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+",
        "ip": r"[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)",
        "card": r"[0-9]([\x20-]?[0-9])+",
        "phone": r"\+[0-9][\x20().0-9-]+[0-9]",
        "iban": PATTERNS["iban"],
        "ssn": PATTERNS["ssn"],
    }
    digits = "regexp_replace(m, '[^0-9]', '', 'g')"
    luhn = (
        f"list_sum(list_transform(range(1, length({digits}) + 1), lambda i: CASE WHEN (length({digits}) - i) % 2 = 0 THEN CAST(substr({digits}, i, 1) AS INT) "
        f"ELSE CASE WHEN CAST(substr({digits}, i, 1) AS INT) > 4 THEN 2 * CAST(substr({digits}, i, 1) AS INT) - 9 ELSE 2 * CAST(substr({digits}, i, 1) AS INT) END END)) % 10 = 0"
    )
    mod97 = "list_reduce(list_transform(string_split(substr(m, 5) || substr(m, 1, 4), ''), lambda c: CASE WHEN c < 'A' THEN ascii(c) - 48 ELSE ascii(c) - 55 END), lambda r, v: (r * CASE WHEN v > 9 THEN 100 ELSE 10 END + v) % 97) = 1"
    holds = {
        "email": "true",
        "ip": "len(list_filter(string_split(m, '.'), lambda p: coalesce(TRY_CAST(p AS HUGEINT), 999) > 255)) = 0",
        "card": f"length({digits}) BETWEEN 14 AND 19 AND {luhn}",
        "phone": f"length({digits}) BETWEEN 10 AND 15",
        "iban": mod97,
        "ssn": "true",
    }
    found = " UNION ALL ".join(
        f"SELECT doc_id, t, '{k}' AS kind, {i} AS k, unnest(regexp_extract_all(t, '{p}')) AS m, unnest(range(1, len(regexp_extract_all(t, '{p}')) + 1)) AS i, regexp_split_to_array(t, '{p}') AS g, "
        f"regexp_extract_all(t, '{p}') AS ms FROM d"
        for i, (k, p) in enumerate(plain.items())
    )
    check = " ".join(f"WHEN '{k}' THEN {v}" for k, v in holds.items())
    points = " ".join(f"WHEN '{k}' THEN {POINTS[k]} + CASE WHEN regexp_matches(b, '{_context(k)}') THEN {CONTEXT} ELSE 0 END" for k in plain)
    counts = ", ".join(f"count(*) FILTER (kind = '{k}') AS n_{k}" for k in plain)
    zero = ", ".join(f"coalesce(n_{k}, 0) AS n_{k}" for k in plain)
    return f"""
    WITH d AS (SELECT doc_id, coalesce(text, '') AS t FROM documents),
    f AS ({found}),
    p AS (SELECT doc_id, t, kind, k, m, CAST(list_sum(list_transform(g[1:i], lambda x: length(x))) + coalesce(list_sum(list_transform(ms[1:i - 1], lambda x: length(x))), 0) AS BIGINT) AS s FROM f),
    c AS (SELECT doc_id, kind, k, s, s + length(m) AS e, lower(CASE WHEN s > {NEAR} THEN substr(t, s - {NEAR}, {NEAR + 1}) ELSE ' ' || substr(t, 1, s) END) AS b FROM p WHERE CASE kind {check} END),
    q AS (SELECT *, CASE kind {points} END AS points FROM c),
    a AS (SELECT * FROM q WHERE k < {len(BASE)} OR points >= {ACCEPT}),
    r AS (SELECT doc_id, {counts}, coalesce(string_agg(kind || ':' || s || ':' || e, ',' ORDER BY s, k) FILTER (k < {len(BASE)}), '') AS base, string_agg(kind || ':' || s || ':' || e, ',' ORDER BY s, k) AS spans, max(points) AS max_points FROM a GROUP BY doc_id)
    SELECT d.doc_id, {zero}, sha256(coalesce(base, '')) AS base_sha256, coalesce(spans, '') AS spans, CAST(coalesce(max_points, 0) AS BIGINT) AS max_points
    FROM d LEFT JOIN r ON d.doc_id = r.doc_id
    """
