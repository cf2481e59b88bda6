"""SQL over the multiway join: SELECT list FROM a JOIN b USING (..) JOIN c USING (..) [WHERE ..] [GROUP BY ..].

The inner equi-join core becomes a JoinQuery over (SELECT ..) AS name atoms; what stands above it, a filter, an aggregate or an order, is
left to Spark over the joined relation. Other shapes fall back to spark.sql, and the reason is returned.
"""

from __future__ import annotations

import re

from pyspark.sql import DataFrame, SparkSession

from .covermix import cover_mix_join
from .query import JoinQuery

_ATOM = re.compile(r"\s*(?:\((?P<sub>(?:[^()]|\((?:[^()]|\([^()]*\))*\))*)\)|(?P<table>\w+))\s+(?:AS\s+)?(?P<name>\w+)\s*(?:USING\s*\((?P<using>[^)]*)\))?\s*", re.I | re.S)


def split_core(text: str) -> tuple[str, list[tuple[str, str, list[str]]], str] | str:
    """Select list, atoms (name, query, USING), and the rest; or the reason why the text has another shape."""
    m = re.match(r"\s*SELECT\s+(.*?)\s+FROM\s+", text, re.I | re.S)
    if not m or re.match(r"\s*WITH\b", text, re.I):
        return "not a plain SELECT"
    at, atoms = m.end(), []
    while True:
        a = _ATOM.match(text, at)
        if not a:
            return "a FROM item is not a named relation"
        atoms.append((a["name"], a["sub"] or f"SELECT * FROM {a['table']}", [x.strip() for x in (a["using"] or "").split(",") if x.strip()]))
        at = a.end()
        j = re.compile(r"(?:INNER\s+)?JOIN\b", re.I).match(text, at)
        if not j:
            break
        at = j.end()
    rest = text[at:].strip().rstrip(";")
    if rest and not re.match(r"(WHERE|GROUP|ORDER|HAVING|LIMIT)\b", rest, re.I):
        return "only inner joins with USING are taken"
    if len(atoms) < 2 or any(not u for _, _, u in atoms[1:]):
        return "no equi-join"
    return m[1], atoms, rest


def run_sql(spark: SparkSession, text: str, p: int = 32) -> tuple[DataFrame, str]:
    """The result, and "multiway" or the reason for the fall-back. Set semantics: each atom counts its tuples once."""
    core = split_core(text)
    if isinstance(core, str):
        return spark.sql(text), core
    select, atoms, rest = core
    frames, seen = {}, set()
    for name, sub, using in atoms:
        df = spark.sql(sub)
        if set(using) != (set(df.columns) & seen) and seen:
            return spark.sql(text), "USING does not name all shared columns"
        seen |= set(df.columns)
        frames[name] = df
    joined = cover_mix_join(JoinQuery(frames), p)
    return spark.sql(f"SELECT {select} FROM {{core}} {rest}", core=joined), "multiway"
