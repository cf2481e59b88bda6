"""Operator 9, line deduplication by winnowing over line hashes. [native]

A document's units are its lines that hold a word. The gram at a unit is the fewest units from it on that reach GRAM words; the window at a unit is the
fewest that reach RUN words. Of the grams that begin in a window's first RUN - GRAM words (all of these lie inside it) the one of least hash is
its fingerprint. A window's fingerprint hangs on its text alone, so equal windows select equal fingerprints at equal places.

1. Fingerprints are joined by value: those that stand at one place of the corpus only are passed over, and with them all windows that selected them.
2. A fingerprint may stand in an earlier text that shares the gram and not the run. So the first place is looked up for each
   fingerprint with its window, by a hash of the whole window: the earliest place that has the window, not merely the gram.
3. Matches are extended both ways: to the left by the windows of the units before, to the right by the block from the window's first
   unit on that ends with a later unit and would have fewer than RUN words without its first. Each is matched with its own first place.

A repeated run of at least RUN words is covered by its windows and by the extension of its last window, so a unit goes exactly when some run of
at least RUN words around it stands at an earlier place (doc_id, then line) too, whatever surrounds the run and wherever parts
of it stood before. The first occurrence stays, within one document too.

Plan: line hashes are made from the text (no text is shuffled for them), windows run within a document, fingerprints are counted with a partial
aggregate, and only windows of repeated fingerprints go on, through a written table. A passage that a third of the documents share is linked to its
first place only, never in pairs. The tables of first places and of lines to delete are broadcast while they are small; above that, joins are left to
AQE's splitting of skewed partitions. The text is read again for the result.

Defined cases: null text stays null and has no lines; empty text is one empty line, never deleted. Rows that repeat both doc_id and
text are one document, deleted from alike. Of equal runs in rows of one doc_id and different texts the one of least text hash comes first. Null doc_id
sorts first and is a document as others. Texts may be of any length; a document's units meet in one task. Empty tables give no rows.
Other columns pass through dedup_lines() unread, but for those named as its results, which are replaced.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .common import WORD, settled, stored, table

GRAM, RUN = 20, 50
#: Rows up to which the table of first places, and that of the lines to delete, are broadcast; a row of these has at most ten lines on average then.
MAX_BROADCAST = 400_000


def _hash(text: Column) -> Column:
    """60 bits of MD5, which SQL has too."""
    return F.conv(F.substring(F.md5(text), 1, 15), 16, 10).cast("long")


def _lines(text: Column) -> Column:
    return F.split(text, "\n", -1)


def line_units(docs: DataFrame) -> DataFrame:
    """doc_id, th (hash of the text), ln (line, from 0), h (hash of the trimmed line), nw (words)."""
    df = docs.where("text IS NOT NULL").select("doc_id", F.xxhash64("text").alias("th"), _lines(F.col("text")).alias("lines"))
    df = df.select("doc_id", "th", F.posexplode("lines").alias("ln", "line"))
    df = df.select("doc_id", "th", "ln", _hash(F.trim("line")).alias("h"), F.regexp_count("line", F.lit(WORD)).cast("long").alias("nw"))
    return df.where("nw > 0").repartition("doc_id", "th")


def windows(units: DataFrame) -> DataFrame:
    """doc_id, th, fp (the fingerprint), at (the unit where it begins), lo and hi (first and last line), k1 and k2 (two hashes of the line hashes) of each
    unit's window, and of the blocks that extend a window to the right."""
    units = units.dropDuplicates(["doc_id", "th", "ln"])
    by_line = Window.partitionBy("doc_id", "th").orderBy("ln")
    df = units.select("doc_id", "th", "ln", "h", "nw", F.sum("nw").over(by_line).alias("ce")).withColumn("cb", F.col("ce") - F.col("nw"))
    from_here = Window.partitionBy("doc_id", "th").orderBy("cb")
    gram, window, starts = (from_here.rangeBetween(0, n) for n in (GRAM - 1, RUN - 1, RUN - GRAM))
    upto = Window.partitionBy("doc_id", "th").orderBy("ce").rangeBetween(1 - RUN, 0)
    df = df.withColumn("g", F.struct(F.xxhash64(F.collect_list("h").over(gram)).alias("fp"), F.col("ln").alias("at")))
    df = df.withColumn("least", F.min("g").over(starts))

    def block(w, enough: Column, least: Column) -> Column:
        hs = F.collect_list("h").over(w)
        return F.when(F.sum("nw").over(w) >= enough, F.struct(least.alias("g"), F.min("ln").over(w).alias("lo"), F.max("ln").over(w).alias("hi"), F.xxhash64(hs).alias("k1"), F.hash(hs).alias("k2")))

    # a block up to a unit that is a window too is left out: without its last unit it must reach RUN words, or it ends a window
    df = df.select("doc_id", "th", block(window, F.lit(RUN), F.col("least")).alias("a"), block(upto, F.col("nw") + RUN, F.first("least").over(upto)).alias("b"))
    df = df.select("doc_id", "th", F.explode(F.filter(F.array("a", "b"), lambda x: x.isNotNull())).alias("x"))
    return df.select("doc_id", "th", "x.g.fp", "x.g.at", "x.lo", "x.hi", "x.k1", "x.k2")


def repeated_lines(docs: DataFrame) -> DataFrame:
    """doc_id, th, gone (the lines of repeated runs; lines without a word among them stay)."""
    found = windows(line_units(docs))
    place = F.struct("doc_id", "th", "at")
    repeated = found.groupBy("fp").agg(F.min(place).alias("one"), F.max(place).alias("two")).where("one <> two").select("fp")
    met = stored(found.join(repeated, "fp").select("doc_id", "th", "lo", "hi", "k1", "k2"), "met")
    first = stored(met.groupBy("k1", "k2").agg(F.min(F.struct("doc_id", "th", "lo")).alias("f"), F.count("*").alias("n")).where("n > 1").select("k1", "k2", "f"), "first")
    few = F.broadcast if first.count() <= MAX_BROADCAST else (lambda d: d)
    here = (F.col("doc_id").eqNullSafe(F.col("f.doc_id"))) & (F.col("th") == F.col("f.th")) & (F.col("lo") == F.col("f.lo"))
    hits = met.join(few(first), ["k1", "k2"]).where(~here).select("doc_id", "th", "lo", "hi")
    before = Window.partitionBy("doc_id", "th").orderBy("lo", "hi")
    hits = hits.withColumn("top", F.max("hi").over(before.rowsBetween(Window.unboundedPreceding, -1)))
    hits = hits.select("doc_id", "th", F.greatest("lo", F.coalesce(F.col("top") + 1, "lo")).alias("lo"), "hi").where("lo <= hi")  # each line once
    return settled(hits.groupBy("doc_id", "th").agg(F.sort_array(F.flatten(F.collect_list(F.sequence("lo", "hi")))).alias("gone")), "gone", met, first)


#: What dedup_lines() adds.
ADDED = ("n_lines", "n_deleted", "kept_text")


def dedup_lines(docs: DataFrame) -> DataFrame:
    """The rows of docs with the columns n_lines, n_deleted and kept_text added; columns of docs with these names are replaced."""
    docs = docs.drop(*ADDED)
    gone = repeated_lines(docs).select(F.col("doc_id").alias("__d"), F.col("th").alias("__t"), F.col("gone").alias("__gone"))
    size = gone.agg(F.count("*"), F.coalesce(F.sum(F.size("__gone")), F.lit(0))).first()
    gone = F.broadcast(gone) if size[0] <= MAX_BROADCAST and size[1] <= 10 * MAX_BROADCAST else gone
    df = docs.join(gone, F.col("doc_id").eqNullSafe(F.col("__d")) & (F.xxhash64("text") == F.col("__t")), "left")
    lines = _lines(F.col("text"))
    gone = F.filter("__gone", lambda i: F.regexp_like(F.get(lines, i), F.lit(WORD)))
    kept = F.array_except(F.sequence(F.lit(0), F.size(lines) - 1), gone)
    text = F.when(F.col("__gone").isNull(), F.col("text")).otherwise(F.array_join(F.transform(kept, lambda i: F.get(lines, i)), "\n"))
    return df.select(
        *[F.col(f"`{c}`") for c in docs.columns],
        F.when(F.col("text").isNull(), 0).otherwise(F.size(lines)).cast("long").alias("n_lines"),
        F.coalesce(F.size(gone), F.lit(0)).cast("long").alias("n_deleted"),
        text.alias("kept_text"),
    )


def op9_line_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    return dedup_lines(docs).select("doc_id", "n_lines", "n_deleted", F.col("kept_text").alias("text"))


def dedup_sql(docs: str = "documents") -> str:
    """DuckDB SQL of the plain definition, without fingerprints: doc_id, n_lines, n_deleted, kept_text. docs has one row for each doc_id.
    Runs are compared as the text of their line hashes."""
    return f"""
    WITH l AS (SELECT doc_id, unnest(string_split(text, chr(10))) AS line, unnest(range(0, len(string_split(text, chr(10))))) AS ln FROM {docs} WHERE text IS NOT NULL),
    un AS (SELECT doc_id, ln, substr(md5(trim(line, ' ')), 1, 15) AS h, CAST(len(regexp_extract_all(line, '{WORD}')) AS BIGINT) AS nw FROM l WHERE regexp_matches(line, '{WORD}')),
    c AS (SELECT *, CAST(sum(nw) OVER (PARTITION BY doc_id ORDER BY ln) AS BIGINT) AS ce, ce - nw AS cb FROM un),
    x AS (SELECT doc_id, ln AS lo, max(ln) OVER w AS hi, sum(nw) OVER w AS nw, string_agg(h, ',') OVER w AS run FROM c WINDOW w AS (PARTITION BY doc_id ORDER BY cb RANGE BETWEEN CURRENT ROW AND {RUN - 1} FOLLOWING)
          UNION
          SELECT doc_id, min(ln) OVER w AS lo, ln AS hi, sum(nw) OVER w AS nw, string_agg(h, ',') OVER w AS run FROM c WINDOW w AS (PARTITION BY doc_id ORDER BY ce RANGE BETWEEN {RUN - 1} PRECEDING AND CURRENT ROW)),
    b AS (SELECT doc_id, lo, hi, min({{'d': doc_id, 'l': lo}}) OVER (PARTITION BY md5(run)) AS f FROM x WHERE nw >= {RUN}),
    gone AS (SELECT DISTINCT u.doc_id, u.ln FROM (SELECT DISTINCT doc_id, lo, hi FROM b WHERE doc_id <> f.d OR lo <> f.l) r JOIN un u ON u.doc_id = r.doc_id AND u.ln BETWEEN r.lo AND r.hi),
    n AS (SELECT doc_id, count(*) AS n FROM gone GROUP BY doc_id),
    t AS (SELECT l.doc_id, string_agg(line, chr(10) ORDER BY l.ln) AS kept FROM l ANTI JOIN gone ON l.doc_id = gone.doc_id AND l.ln = gone.ln GROUP BY l.doc_id)
    SELECT d.doc_id, CASE WHEN text IS NULL THEN 0 ELSE len(string_split(text, chr(10))) END AS n_lines, coalesce(n.n, 0) AS n_deleted,
           CASE WHEN n.n IS NULL THEN text ELSE coalesce(kept, '') END AS kept_text FROM {docs} d LEFT JOIN n ON d.doc_id = n.doc_id LEFT JOIN t ON d.doc_id = t.doc_id
    """


def oracle() -> str:
    return f"SELECT doc_id, n_lines, n_deleted, kept_text AS text FROM ({dedup_sql()})"
