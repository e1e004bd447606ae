"""Quality rules with adaptive thresholds.

Fixed rules reject very short and very repetitive texts. The other measures have no
fixed cutoff: for each language and source their distribution is kept as a sketch, a
histogram with 32 buckets to an octave, which is merged by adding counts (so from
tasks to sources, from sources to languages, from languages to the whole). A threshold
is a fence: the upper quartile of the sketch and REACH times the distance between its
quartiles. Where more than half of a group has the same value, as with measures that are
mostly zero, the quartiles may meet; then the distance is the measure's GRAIN, so that a
single symbol or line is not taken for an outlier. A source of few documents takes the
sketch of its language, a language of few that of the whole. Documents meet the
thresholds in a join. A sketch's buckets are exact integers, so results do not depend on
partitions.

Only DataFrame functions are used.

Defined results: a null text counts as empty, has no words and fails the base rules;
texts are measured whole; null languages and sources are groups of their own; repeated
rows are each measured; an empty table gives an empty result; further columns are
ignored or, by `keep_good`, kept.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from strata.llm.common import materialize

#: What separates words, and the characters that count as symbols.
GAP, SYMBOLS = r"[\x20\x09-\x0D]+", r"[#*$%&|<>]"
#: Measures with adaptive thresholds, and the least distance that their quartiles are taken to have.
GRAIN = {"symbols_per_mille": 15, "dup_lines_per_mille": 80, "word_length_x100": 8}
#: Times the distance between the quartiles that a fence lies over the upper one.
REACH = 6
#: Leading bits of a number that its bucket keeps.
KEPT_BITS = 6
#: Documents that a group needs for thresholds of its own.
LEAST_DOCS = 100
#: Number of groups up to which the threshold table is broadcast.
FEW_GROUPS = 20_000

WINDOW = 5


def measured(docs: DataFrame, text_column: str = "text") -> DataFrame:
    """The documents with n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words and n_lines."""
    text = F.coalesce(F.col(text_column), F.lit(""))
    d = docs.withColumn("_words", F.array_remove(F.split(text, GAP), ""))
    d = d.withColumn("_lines", F.filter(F.split(text, "\n"), lambda x: x.rlike(r"[^\x20\x09-\x0D]")))
    n = F.size("_words")
    at = F.sequence(F.lit(1), n - (WINDOW - 1))
    d = d.withColumn("_hashes", F.when(n >= WINDOW, F.transform(at, lambda k: F.xxhash64(F.slice("_words", k, WINDOW)))))
    again = F.size(F.array_distinct("_hashes")) < F.size("_hashes")
    # equal hashes only select the texts whose windows are then compared as text
    spelled = F.transform(at, lambda k: F.struct(F.array_join(F.slice("_words", k, WINDOW), " ").alias("g"), k.alias("k")))
    d = d.withColumn("_sorted", F.when(again, F.sort_array(spelled)))
    same = lambda x, k: F.get("_sorted", k)["g"] == x["g"]
    d = d.withColumn("_starts", F.sort_array(F.transform(F.filter("_sorted", lambda x, k: F.coalesce(same(x, k - 1), F.lit(False)) | F.coalesce(same(x, k + 1), F.lit(False))), lambda x: x["k"])))
    zero = F.struct(F.lit(0).alias("end"), F.lit(0).alias("n"))
    covered = F.aggregate("_starts", zero, lambda a, k: F.struct((k + WINDOW).alias("end"), (a["n"] + k + WINDOW - F.greatest(k, a["end"])).alias("n")))
    return d.select(
        *docs.columns,
        n.cast("long").alias("n_words"),
        F.length(F.array_join("_words", "")).cast("long").alias("word_chars"),
        F.when(text.rlike(SYMBOLS), F.length(text) - F.length(F.regexp_replace(text, SYMBOLS, ""))).otherwise(0).cast("long").alias("n_symbols"),
        (F.size("_lines") - F.size(F.array_distinct("_lines"))).cast("long").alias("n_dup_lines"),
        F.coalesce(covered["n"], F.lit(0)).cast("long").alias("n_repeat_words"),
        F.size("_lines").cast("long").alias("n_lines"),
    )


def base_failed() -> Column:
    return (F.col("n_words") < 10) | (100 * F.col("n_repeat_words") > 20 * F.col("n_words"))


def with_ratios(d: DataFrame) -> DataFrame:
    """The adaptive measures, as integers."""
    words = F.greatest("n_words", F.lit(1))
    return d.withColumns({
        "symbols_per_mille": (1000 * F.col("n_symbols") / words).cast("long"),
        "dup_lines_per_mille": (1000 * F.col("n_dup_lines") / F.greatest("n_lines", F.lit(1))).cast("long"),
        "word_length_x100": (100 * F.col("word_chars") / words).cast("long"),
    })


def bucket(v: Column) -> Column:
    """The least value of a number's bucket: small numbers are their own, larger ones keep their leading bits."""
    low = F.length(F.bin(v)) - KEPT_BITS
    return F.when(v < 1 << KEPT_BITS, v).otherwise(F.expr("1L") * F.floor(v / F.pow(F.lit(2), low)) * F.pow(F.lit(2), low).cast("long")).cast("long")


def sketches(d: DataFrame) -> DataFrame:
    """(level, lang, source, measure, value, n): the merged sketches of sources, languages and the whole."""
    pairs = F.explode(F.array(*(F.struct(F.lit(m).alias("measure"), bucket(F.col(m)).alias("value")) for m in GRAIN)))
    own = d.select("lang", "source", pairs.alias("p")).groupBy("lang", "source", F.col("p.measure").alias("measure"), F.col("p.value").alias("value")).agg(F.count("*").alias("n"))
    levels = own.withColumn("level", F.explode(F.array(F.lit(0), F.lit(1), F.lit(2))))
    lang, source = F.when(F.col("level") < 2, F.col("lang")), F.when(F.col("level") < 1, F.col("source"))
    return levels.groupBy("level", lang.alias("lang"), source.alias("source"), "measure", "value").agg(F.sum("n").alias("n"))


def fences(sketch: DataFrame) -> DataFrame:
    """(level, lang, source, docs, and one fence per measure)."""
    from pyspark.sql import Window

    keys = ["level", "lang", "source", "measure"]
    w = Window.partitionBy(*keys)
    upto = F.sum("n").over(w.orderBy("value"))
    ranked = sketch.withColumn("upto", upto).withColumn("docs", F.sum("n").over(w))
    at = lambda num, den: F.min(F.when(F.col("upto") * den >= F.col("docs") * num, F.col("value")))
    q = ranked.groupBy(*keys).agg(F.max("docs").alias("docs"), at(1, 4).alias("q25"), at(3, 4).alias("q75"))
    grain = F.coalesce(*(F.when(F.col("measure") == m, F.lit(v)) for m, v in GRAIN.items()))
    q = q.withColumn("fence", F.col("q75") + REACH * F.greatest(grain, F.col("q75") - F.col("q25")))
    return q.groupBy("level", "lang", "source").agg(F.max("docs").alias("docs"), *(F.max(F.when(F.col("measure") == m, F.col("fence"))).alias(f"most_{m}") for m in GRAIN))


def thresholds(d: DataFrame) -> DataFrame:
    """(lang, source, most_*): each source's fences, or those of its language or of all where it has few documents."""
    f = materialize(fences(sketches(d)))
    most = [f"most_{m}" for m in GRAIN]
    part = lambda level, tag: f.filter(F.col("level") == level).select(*(F.col(c).alias(f"{tag}{c}") for c in ("lang", "source", "docs", *most)))
    a, b, c = part(0, "a"), part(1, "b"), part(2, "c")
    j = a.join(b, F.col("alang").eqNullSafe(F.col("blang"))).crossJoin(F.broadcast(c))  # the whole is one row
    pick = lambda m: F.when(F.col("adocs") >= LEAST_DOCS, F.col(f"a{m}")).when(F.col("bdocs") >= LEAST_DOCS, F.col(f"b{m}")).otherwise(F.col(f"c{m}"))
    return j.select(F.col("alang").alias("_lang"), F.col("asource").alias("_source"), *(pick(m).alias(m) for m in most))


def judged(d: DataFrame, limits: DataFrame) -> DataFrame:
    """Rows of `with_ratios` with base_failed and kept."""
    if limits.count() <= FEW_GROUPS:
        limits = F.broadcast(limits)
    j = d.join(limits, F.col("lang").eqNullSafe(F.col("_lang")) & F.col("source").eqNullSafe(F.col("_source")), "left")
    within = F.lit(True)
    for m in GRAIN:
        within = within & F.coalesce(F.col(m) <= F.col(f"most_{m}"), F.lit(True))
    return j.withColumn("base_failed", base_failed()).withColumn("kept", ~base_failed() & within)


MEASURES = ("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "n_lines")


def verdicts(docs: DataFrame, id_column: str = "doc_id", text_column: str = "text") -> DataFrame:
    """One row per document: id, the measures, base_failed and kept."""
    light = docs.select(F.col(id_column), F.col("lang"), F.col("source"), F.col(text_column).alias("_text"))
    d = materialize(with_ratios(measured(light, "_text").drop("_text")))
    return judged(d, materialize(thresholds(d))).select(id_column, *MEASURES, "base_failed", "kept")


def keep_good(docs: DataFrame, text_column: str = "text") -> DataFrame:
    """The documents that pass, with their columns. Texts are read twice, which spares a shuffle of them; the first time,
    only what the sketches need is measured."""
    own = F.struct(*docs.columns)
    light = docs.select(F.col("lang"), F.col("source"), F.col(text_column).alias("_text"))
    limits = materialize(thresholds(materialize(with_ratios(measured(light, "_text")).select("lang", "source", *GRAIN))))
    whole = docs.select(own.alias("_doc"), F.col("lang"), F.col("source"), F.col(text_column).alias("_text"))
    # a filter is not pushed below a row number, and so does not repeat the measures' expressions
    once = with_ratios(measured(whole, "_text").drop("_text").withColumn("_row", F.monotonically_increasing_id()))
    return judged(once, limits).filter("kept and _row >= 0").select("_doc.*")


ORACLE_SQL = r"""
WITH w AS (SELECT doc_id, lang, source, coalesce(text, '') t, list_filter(regexp_split_to_array(coalesce(text, ''), '[\x20\x09-\x0D]+'), lambda x: x <> '') ws FROM documents),
g AS (SELECT doc_id, k, array_to_string(ws[k:k+4], ' ') g FROM (SELECT doc_id, ws, unnest(generate_series(1, len(ws) - 4)) k FROM w)),
c AS (SELECT doc_id, k FROM (SELECT doc_id, k, count(*) OVER (PARTITION BY doc_id, g) n FROM g) WHERE n > 1),
r AS (SELECT doc_id, count(DISTINCT k + o) n_repeat_words FROM c, (SELECT unnest([0,1,2,3,4]) o) GROUP BY 1),
l AS (SELECT doc_id, count(*) n_lines, count(*) - count(DISTINCT x) n_dup_lines FROM (SELECT doc_id, unnest(string_split(t, chr(10))) x FROM w) WHERE regexp_matches(x, '[^\x20\x09-\x0D]') GROUP BY 1),
m AS (SELECT w.doc_id, lang, source, len(ws)::BIGINT n_words, length(array_to_string(ws, ''))::BIGINT word_chars,
  length(t) - length(regexp_replace(t, '[#*$%&|<>]', '', 'g')) n_symbols, coalesce(n_dup_lines, 0)::BIGINT n_dup_lines,
  coalesce(n_repeat_words, 0)::BIGINT n_repeat_words, coalesce(n_lines, 0)::BIGINT n_lines
  FROM w LEFT JOIN r USING (doc_id) LEFT JOIN l USING (doc_id)),
v AS (SELECT *, (1000 * n_symbols) // greatest(n_words, 1) s, (1000 * n_dup_lines) // greatest(n_lines, 1) d, (100 * word_chars) // greatest(n_words, 1) h FROM m),
p AS (SELECT lang, source, 's' measure, 15 grain, s x FROM v UNION ALL SELECT lang, source, 'd', 80, d FROM v UNION ALL SELECT lang, source, 'h', 8, h FROM v),
b AS (SELECT *, CASE WHEN x < 64 THEN x ELSE (x >> (length(bin(x)) - 6)) << (length(bin(x)) - 6) END value FROM p),
lv AS (SELECT level, CASE WHEN level < 2 THEN lang END lang, CASE WHEN level < 1 THEN source END source, measure, grain, value FROM b, (SELECT unnest([0,1,2]) level)),
n AS (SELECT level, lang, source, measure, grain, value, count(*) n FROM lv GROUP BY ALL),
k AS (SELECT *, sum(n) OVER (PARTITION BY level, lang, source, measure ORDER BY value) upto, sum(n) OVER (PARTITION BY level, lang, source, measure) docs FROM n),
q AS (SELECT level, lang, source, measure, grain, max(docs) docs, min(value) FILTER (upto * 4 >= docs) q25, min(value) FILTER (upto * 4 >= docs * 3) q75 FROM k GROUP BY ALL),
f AS (SELECT level, lang, source, max(docs) docs, max(q75 + 6 * greatest(grain, q75 - q25)) FILTER (measure = 's') s, max(q75 + 6 * greatest(grain, q75 - q25)) FILTER (measure = 'd') d,
  max(q75 + 6 * greatest(grain, q75 - q25)) FILTER (measure = 'h') h FROM q GROUP BY ALL),
z AS (SELECT a.lang, a.source, CASE WHEN a.docs >= 100 THEN a.s WHEN b.docs >= 100 THEN b.s ELSE c.s END ms, CASE WHEN a.docs >= 100 THEN a.d WHEN b.docs >= 100 THEN b.d ELSE c.d END md,
  CASE WHEN a.docs >= 100 THEN a.h WHEN b.docs >= 100 THEN b.h ELSE c.h END mh FROM f a JOIN f b ON a.level = 0 AND b.level = 1 AND a.lang IS NOT DISTINCT FROM b.lang JOIN f c ON c.level = 2)
SELECT v.doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, n_lines,
  n_words < 10 OR 100 * n_repeat_words > 20 * n_words AS base_failed,
  NOT (n_words < 10 OR 100 * n_repeat_words > 20 * n_words) AND s <= ms AND d <= md AND h <= mh AS kept
FROM v JOIN z ON v.lang IS NOT DISTINCT FROM z.lang AND v.source IS NOT DISTINCT FROM z.source
"""
