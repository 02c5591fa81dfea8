"""Quality rules: per-document counts and cross-document line frequency, in DataFrame functions only.

Lines are normalised (ASCII white space runs to one space, trimmed, lower case, digits to 0) and hashed. For each host
(column ``source``) a line counts once for each distinct document text, so exact copies of one document count once and a
group of copies can't make its own lines look like boilerplate. A line found in more distinct documents than
``max(min_docs, share * documents of the host)`` is removed; a document that loses more than ``depleted_share`` of its words
is rejected.

Frequent lines are few beside the documents. Up to ``LITERAL_LINES`` of them stand in the plan as a hash set, so a document's lines are looked up where
they are; more are joined by (host, line), with the lines of distinct documents as rows and only places coming back, so that neither a
host nor its list is ever gathered in one place.

Edge cases: a null text has no words and no lines; a null source is the host ''; repeated rows get equal results; an empty
table gives an empty result; lines without a word never count. Other columns are never looked at.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from lincompress.llm.common import WORD, let, materialise, read

MIN_DOCS, SHARE, DEPLETED_SHARE = 10, 0.01, 0.5
#: Frequent lines up to this number are a set in the plan (8 bytes each); more are joined by shuffle.
LITERAL_LINES = 20_000
SPACE_RUN = r"[\x20\x09-\x0D]+"


def normal_line(line: Column) -> Column:
    return F.regexp_replace(F.lower(F.trim(F.regexp_replace(line, SPACE_RUN, " "))), "[0-9]", "0")


def word_lines(text: Column) -> Column:
    return F.filter(F.split(text, "\n"), lambda x: x.rlike(WORD))


def base_counts(docs: DataFrame) -> DataFrame:
    """Adds n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words to rows with a non-null text."""
    words = F.regexp_extract_all("text", F.lit(WORD), F.lit(0))
    df = docs.withColumn("_w", words).withColumn("n_words", F.size("_w").cast("long"))

    def covered(pos: Column) -> Column:
        n = F.size(pos)
        return F.aggregate(
            F.transform(pos, lambda p, k: F.when(k == n - 1, 3).otherwise(F.least(F.lit(3), F.get(pos, k + 1) - p))),
            F.lit(0), lambda a, x: a + x,
        )

    def repeated(marks: Column) -> Column:
        """Start positions, in order, of windows whose hash stands beside an equal one in the sorted array."""
        n = F.size(marks)
        same = F.filter(
            marks,
            lambda m, k: ((k > 0) & (F.get(marks, k - 1)["h"] == m["h"])) | ((k < n - 1) & (F.get(marks, k + 1)["h"] == m["h"])),
        )
        return F.sort_array(F.transform(same, lambda m: m["i"]))

    grams = F.when(
        F.col("n_words") >= 3,
        F.transform(F.sequence(F.lit(0), (F.col("n_words") - 3).cast("int")), lambda i: F.xxhash64(F.get("_w", i), F.get("_w", i + 1), F.get("_w", i + 2))),
    ).otherwise(F.array().cast("array<bigint>"))
    df = df.withColumn("_g", grams)
    marks = F.sort_array(F.transform("_g", lambda h, i: F.struct(h.alias("h"), i.alias("i"))))
    repeat = F.when(F.size(F.array_distinct("_g")) < F.size("_g"), let(let(marks, repeated), covered)).otherwise(0)
    lines = word_lines(F.col("text"))
    return df.withColumns({
        "word_chars": F.length(F.regexp_replace("text", SPACE_RUN, "")).cast("long"),
        "n_symbols": F.length(F.regexp_replace("text", r"[^#*$%&|<>]+", "")).cast("long"),
        "n_dup_lines": let(lines, lambda x: F.size(x) - F.size(F.array_distinct(x))).cast("long"),
        "n_repeat_words": repeat.cast("long"),
    }).drop("_w", "_g")


def frequent_lines(docs: DataFrame, min_docs: int = MIN_DOCS, share: float = SHARE) -> DataFrame:
    """(host, line hash) of lines in too many distinct documents of the host. docs: text and host."""
    base = docs.select("_host", "text", F.xxhash64("text").alias("_doc"))
    sizes = base.select("_host", "_doc").distinct().groupBy("_host").agg(F.count(F.lit(1)).alias("n"))
    lines = base.select("_host", "_doc", F.explode(F.array_distinct(F.transform(word_lines(F.col("text")), lambda x: F.xxhash64(normal_line(x))))).alias("_line"))
    counts = lines.distinct().groupBy("_host", "_line").agg(F.count(F.lit(1)).alias("docs")).where(F.col("docs") > min_docs)
    return counts.join(sizes, "_host").where(F.col("docs") > F.greatest(F.lit(float(min_docs)), F.col("n") * share)).select("_host", "_line")


def _line_key(host: Column, line: Column) -> Column:
    return F.xxhash64(host, F.xxhash64(normal_line(line)))


def mark_lines(docs: DataFrame, bad: DataFrame, literal_lines: int = LITERAL_LINES) -> DataFrame:
    """Adds _gone: the places of frequent lines among all lines of the text. docs: text and _host; bad: _host, _line."""
    named = bad.select(F.xxhash64("_host", "_line").alias("_key"))
    if bad.count() <= literal_lines:
        keys = [r[0] for r in named.collect()]
        if not keys:
            return docs.withColumn("_gone", F.array().cast("array<int>"))
        among = f"IN ({','.join(f'{k}L' if k > -(1 << 63) else 'cast(-9223372036854775808 AS bigint)' for k in keys)})"
        lines = docs.withColumn("_keys", F.transform(F.split("text", "\n"), lambda x: F.when(x.rlike(WORD), _line_key(F.col("_host"), x))))
        return lines.withColumn("_gone", F.expr(f"filter(transform(_keys, (k, i) -> if(k {among}, i, null)), i -> i is not null)")).drop("_keys")
    rows = docs.withColumn("_text", F.xxhash64("text"))
    lines = rows.select("_host", "_text", F.posexplode(F.transform(F.split("text", "\n"), lambda x: F.when(x.rlike(WORD), _line_key(F.col("_host"), x)))).alias("_at", "_key"))
    # of equal texts one is enough, and a line of all of them comes once
    met = lines.where("_key is not null").distinct().join(named, "_key", "left_semi").groupBy("_host", "_text").agg(F.sort_array(F.collect_list("_at")).alias("_gone"))
    out = rows.join(met, ["_host", "_text"], "left").drop("_text")
    return out.withColumn("_gone", F.coalesce("_gone", F.array().cast("array<int>")))


def judge(docs: DataFrame, min_docs: int = MIN_DOCS, share: float = SHARE, depleted_share: float = DEPLETED_SHARE, keep: list[str] = ()) -> DataFrame:
    """doc_id, the base counts, base_failed, removed_lines, removed_words, kept, clean_text and the columns named in keep."""
    rows = docs.select("doc_id", F.coalesce("text", F.lit("")).alias("text"), F.coalesce(F.col("source").cast("string"), F.lit("")).alias("_host"), *[F.col(f"`{c}`").alias(f"keep_{c}") for c in keep])
    bad = materialise(frequent_lines(rows.select("text", "_host"), min_docs, share), "lines")
    found = mark_lines(base_counts(rows), bad)
    found = found.withColumns({
        "removed_lines": F.size("_gone").cast("long"),
        "removed_words": F.when(F.size("_gone") > 0, F.size(F.regexp_extract_all(let(F.split("text", "\n"), lambda lines: F.array_join(F.transform("_gone", lambda i: F.get(lines, i)), "\n")), F.lit(WORD), F.lit(0)))).otherwise(0).cast("long"),
        "base_failed": (F.col("n_words") < 50) | (100 * F.col("n_repeat_words") > 50 * F.col("n_words")),
    })
    clean = F.when(F.size("_gone") > 0, F.array_join(F.filter(F.split("text", "\n"), lambda x, i: ~F.array_contains("_gone", i)), "\n")).otherwise(F.col("text"))
    return found.select(
        "doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "removed_lines", "removed_words",
        (~F.col("base_failed") & (F.col("removed_words") <= depleted_share * F.col("n_words"))).alias("kept"), clean.alias("clean_text"), *[F.col(f"`keep_{c}`") for c in keep],
    )


def op1_quality_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    return judge(read(spark, sf_dir, "documents")).drop("clean_text")


def stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The kept documents without their removed lines, in the columns of the input."""
    others = [c for c in docs.columns if c not in ("doc_id", "text")]
    # the row number keeps Spark from repeating the counts, lambdas and all, inside a filter below them
    good = judge(docs, keep=others).withColumn("_row", F.monotonically_increasing_id()).where("kept and _row >= 0")
    given = {"doc_id": F.col("doc_id"), "text": F.col("clean_text")} | {c: F.col(f"`keep_{c}`") for c in others}
    if "n_chars" in given:
        given["n_chars"] = F.when(F.col("removed_lines") > 0, F.length("clean_text").cast("long")).otherwise(F.col("keep_n_chars")).cast(docs.schema["n_chars"].dataType)
    return good.select(*[given[c].alias(c) for c in docs.columns])


SQL = rf"""
WITH d AS (SELECT doc_id, coalesce(text, '') AS text, coalesce(source, '') AS host FROM documents),
w AS (SELECT doc_id, regexp_extract_all(text, '[^\x20\x09-\x0D]+') AS ws, text FROM d),
g AS (SELECT doc_id, i, ws[i] AS a, ws[i + 1] AS b, ws[i + 2] AS c FROM (SELECT doc_id, ws, unnest(range(1, greatest(len(ws) - 1, 1))) AS i FROM w)),
r AS (SELECT doc_id, i FROM (SELECT doc_id, i, count(*) OVER (PARTITION BY doc_id, a, b, c) AS n FROM g) WHERE n > 1),
rep AS (SELECT doc_id, count(DISTINCT p) AS n_repeat_words FROM (SELECT doc_id, i + unnest([0, 1, 2]) AS p FROM r) GROUP BY doc_id),
ln AS (SELECT doc_id, host, text AS t, line FROM (SELECT doc_id, host, text, unnest(string_split(text, chr(10))) AS line FROM d) WHERE regexp_matches(line, '[^\x20\x09-\x0D]')),
dup AS (SELECT doc_id, count(*) - count(DISTINCT line) AS n_dup_lines FROM ln GROUP BY doc_id),
nl AS (SELECT doc_id, host, t, len(regexp_extract_all(line, '[^\x20\x09-\x0D]+')) AS nw,
  regexp_replace(lower(trim(regexp_replace(line, '[\x20\x09-\x0D]+', ' ', 'g'))), '[0-9]', '0', 'g') AS z FROM ln),
hs AS (SELECT host, count(DISTINCT text) AS n FROM d GROUP BY host),
bad AS (SELECT host, z FROM (SELECT host, z, count(DISTINCT t) AS k FROM nl GROUP BY host, z) JOIN hs USING (host) WHERE k > greatest({MIN_DOCS}, n * {SHARE})),
gone AS (SELECT doc_id, count(*) AS removed_lines, sum(nw) AS removed_words FROM nl JOIN bad USING (host, z) GROUP BY doc_id),
f AS (SELECT w.doc_id, len(ws) AS n_words, length(regexp_replace(text, '[\x20\x09-\x0D]+', '', 'g')) AS word_chars,
  length(regexp_replace(text, '[^#*$%&|<>]+', '', 'g')) AS n_symbols, coalesce(n_dup_lines, 0) AS n_dup_lines, coalesce(n_repeat_words, 0) AS n_repeat_words,
  coalesce(removed_lines, 0) AS removed_lines, coalesce(removed_words, 0) AS removed_words
  FROM w LEFT JOIN dup USING (doc_id) LEFT JOIN rep USING (doc_id) LEFT JOIN gone USING (doc_id))
SELECT doc_id, n_words::BIGINT AS n_words, word_chars::BIGINT AS word_chars, n_symbols::BIGINT AS n_symbols, n_dup_lines::BIGINT AS n_dup_lines,
  n_repeat_words::BIGINT AS n_repeat_words, (n_words < 50 OR 100 * n_repeat_words > 50 * n_words) AS base_failed,
  removed_lines::BIGINT AS removed_lines, removed_words::BIGINT AS removed_words,
  NOT (n_words < 50 OR 100 * n_repeat_words > 50 * n_words) AND removed_words <= {DEPLETED_SHARE} * n_words AS kept
FROM f
"""
