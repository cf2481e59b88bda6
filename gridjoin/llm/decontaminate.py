"""Operator 2, benchmark decontamination by spaced seeds. [native]

A seed is a window of SPAN words under a fixed mask: only the selected positions are hashed, so a substituted word under an
ignored position does not break the hit. Seeds of the benchmark meet the seeds of every document position on their hash; around
each hit the words are compared along the same diagonal, and a document is contaminated by an item when some window of
min(WINDOW, length of the item) words that covers the hit has at least SHARE percent equal words.

Words are runs of letters and digits in lower case. Items of MIN_ITEM to SPAN - 1 words are hashed whole, for each length that
occurs; shorter items are too short to tell and match nothing.

Plan: the documents are scanned once, positions are generated, hashed and probed within one generated stage, against the
benchmark's seeds as a broadcast table while these number at most MAX_BROADCAST (the count is taken first). Above that the
positions are shuffled by hash and the words are fetched for the hits only. Only hits leave the stage; they are reduced to one row
for each document and item before the shuffle, so a passage in a third of the documents is no hot key.

Defined cases: null or empty text, or a null item, matches nothing. Empty tables give no rows. Repeated documents or
items with one id give one row. Of several windows of a pair the best counts, and equal ones are one row, so ties have no part in the result. Other
columns are not read, whatever their names. Whole texts are read, however long.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import table, without

#: The masks. Each selects 7 of 11 words.
MASKS = ("11101001101", "11010111001", "10111010011")
SPAN, WINDOW, SHARE, MIN_ITEM = 11, 15, 80, 5
MAX_BROADCAST = 400_000
NOT_WORD = r"[^\p{L}\p{N}]+"


def _words(text: Column) -> Column:
    """An empty string may stand first or last; no item has one."""
    return F.split(F.lower(text.cast("string")), NOT_WORD)


def _seed(words: Column, at: Column, mask: str) -> Column:
    return F.xxhash64(F.lit(mask), *[F.get(words, at + k) for k, on in enumerate(mask) if on == "1"])


def benchmark_seeds(items: DataFrame, masks: list[str]) -> DataFrame:
    """h, item_id, j (place of the seed), lo and ctx (the words around it from place lo), n (words of the item)."""
    df = items.select("item_id", F.filter(_words(F.col("text")), lambda w: w != "").alias("iw")).where("item_id IS NOT NULL").withColumn("n", F.size("iw"))
    parts = []
    for mask in masks:
        k = len(mask)
        whole = (F.col("n") == k) if k < SPAN else (F.col("n") >= k)
        part = df.where(whole).select("item_id", "iw", "n", F.explode(F.sequence(F.lit(0), F.col("n") - k)).alias("j"))
        parts.append(part.select("item_id", "iw", "n", "j", F.lit(k).alias("k"), _seed(F.col("iw"), F.col("j"), mask).alias("h")))
    out = parts[0]
    for part in parts[1:]:
        out = out.unionByName(part)
    out = out.withColumn("win", F.least(F.lit(WINDOW), F.col("n"))).withColumn("lo", F.greatest(F.lit(0), F.col("j") + F.col("k") - F.col("win")))
    return out.select("h", "item_id", "j", "k", "n", "win", "lo", F.slice("iw", F.col("lo") + 1, F.least(F.col("n"), F.col("j") + F.col("win")) - F.col("lo")).alias("ctx"))


def masks_for(items: DataFrame) -> list[str]:
    """The masks, and one without gaps for each short length that occurs (at most SPAN - MIN_ITEM of them)."""
    n = F.size(F.filter(_words(F.col("text")), lambda w: w != ""))
    short = items.select(n.alias("n")).where(f"n >= {MIN_ITEM} AND n < {SPAN}").distinct().collect()
    return [*MASKS, *("1" * r["n"] for r in sorted(short))]


def _best() -> Column:
    """Most equal words in a window that covers the hit; w: the document's words, i: the hit's place there."""
    same = F.transform("ctx", lambda x, p: F.coalesce(F.get("w", F.col("i") - F.col("j") + F.col("lo") + p) == x, F.lit(False)).cast("int"))
    starts = F.sequence(F.lit(1), F.size("ctx") - F.col("win") + 1)
    return F.array_max(F.transform(starts, lambda s: F.aggregate(F.slice(same, s, F.col("win")), F.lit(0), lambda a, x: a + x)))


def find_overlaps(docs: DataFrame, items: DataFrame, id_col: str = "doc_id", max_broadcast: int = MAX_BROADCAST) -> DataFrame:
    """doc_id, item_id, overlap (most equal words of a window), win (words of that window)."""
    masks = masks_for(items)
    seeds = benchmark_seeds(items, masks)
    places = F.explode(F.sequence(F.lit(0), F.size("w") - min(map(len, masks)))).alias("i")
    base = docs.select(F.col(id_col).alias("doc_id"), _words(F.col("text")).alias("w")).where(F.size("w") >= min(map(len, masks)))
    hashes = F.explode(F.array(*[_seed(F.col("w"), F.col("i"), m) for m in masks])).alias("h")
    if seeds.count() <= max_broadcast:
        hits = base.select("doc_id", "w", places).select("doc_id", "w", "i", hashes).join(F.broadcast(seeds), "h")
    else:
        found = base.select("doc_id", "w", places).select("doc_id", "i", hashes).join(seeds, "h").drop("h").dropDuplicates(["doc_id", "item_id", "i", "j", "k"])
        hits = found.join(base, "doc_id")
    pairs = hits.select("doc_id", "item_id", "win", _best().alias("best")).groupBy("doc_id", "item_id").agg(F.max("best").alias("overlap"), F.max("win").alias("win"))
    return pairs.where(F.col("overlap") * 100 >= F.col("win") * SHARE).select("doc_id", "item_id", F.col("overlap").cast("long"), F.col("win").cast("long"))


def drop_contaminated(docs: DataFrame, items: DataFrame) -> DataFrame:
    """The documents without a verified overlap, with their columns; a null doc_id is never contaminated."""
    return without(docs, find_overlaps(docs, items))


def op2_decontaminate(spark: SparkSession, sf_dir: str) -> DataFrame:
    return find_overlaps(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"))


def overlaps_sql(docs: str = "documents") -> str:
    """DuckDB SQL of find_overlaps(); seeds are compared as strings."""
    seed = lambda w, at, mask: "concat_ws(' ', " + ", ".join(f"{w}[{at} + {k + 1}]" for k, on in enumerate(mask) if on == "1") + ")"
    masks = [*MASKS, *("1" * k for k in range(MIN_ITEM, SPAN))]
    item_seeds = " UNION ALL ".join(
        f"SELECT item_id, iw, n, j, {len(m)} AS k, {i} AS m, {seed('iw', 'j', m)} AS h FROM (SELECT *, unnest(range(0, n - {len(m)} + 1)) AS j FROM it WHERE n {'=' if len(m) < SPAN else '>='} {len(m)})"
        for i, m in enumerate(masks)
    )
    doc_seeds = " UNION ALL ".join(f"SELECT doc_id, w, i, {n} AS m, {seed('w', 'i', m)} AS h FROM dp WHERE i <= len(w) - {len(m)}" for n, m in enumerate(masks))
    return f"""
    WITH it AS (SELECT item_id, iw, CAST(len(iw) AS INT) AS n FROM (SELECT item_id, list_filter(regexp_split_to_array(lower(text), '{NOT_WORD}'), lambda x: x <> '') AS iw FROM benchmark WHERE item_id IS NOT NULL)),
    ms AS (SELECT *, least({WINDOW}, n) AS win, greatest(0, j + k - least({WINDOW}, n)) AS lo FROM ({item_seeds})),
    dw AS (SELECT doc_id, regexp_split_to_array(lower(text), '{NOT_WORD}') AS w FROM {docs} WHERE text IS NOT NULL),
    dp AS (SELECT doc_id, w, unnest(range(0, len(w) - {MIN_ITEM} + 1)) AS i FROM dw),
    ds AS ({doc_seeds}),
    hits AS (SELECT doc_id, item_id, win, list_transform(range(lo, least(n, j + win)), lambda p: CASE WHEN w[i - j + p + 1] = iw[p + 1] AND i - j + p >= 0 THEN 1 ELSE 0 END) AS same FROM ds JOIN ms USING (m, h)),
    best AS (SELECT doc_id, item_id, max(win) AS win, max(list_max(list_transform(range(1, len(same) - win + 2), lambda s: list_sum(same[s:s + win - 1])))) AS overlap FROM hits GROUP BY doc_id, item_id)
    SELECT doc_id, item_id, CAST(overlap AS BIGINT) AS overlap, CAST(win AS BIGINT) AS win FROM best WHERE overlap * 100 >= win * {SHARE}
    """


def oracle() -> str:
    return overlaps_sql()
