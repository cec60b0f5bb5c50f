"""Line dedup by a log-template tree, in DataFrame functions alone.

A line's words with digits become a wildcard. The tree's first level is the number of words, the next are the leading
words; a leaf then generalises: where its lines differ, a word that no second template of the leaf has at that place is
a wildcard too, as long as four fifths of the words stay. A template that recurs in another document is dropped, but
for its lines in the document of smallest id; a document that loses all its lines goes.

`like_lines` has the whole of look-alikes: templates of a leaf are alike where four fifths of their places agree, pair by
pair, however many variants a leaf has and however often a varying word repeats. A line goes if its template or one alike
is in a document of smaller id. Of m places that may differ, m + 1 bands leave one untouched, so only templates that share
a band are compared; each with the earliest of its bands first, and what that leaves open with all earlier ones. Lines of
every length take part, and words end at any white space. Of lines of fewer than three words only runs of digits become
wildcards, and only beside a letter: one long word of a script without spaces is not lost to its digits.

Lines end at a line feed. In `recurring`, the plainer rule, words end at a space and lines of fewer than `min_words` words
stay. Blank lines stay. A null text stays null, an empty one empty; rows with a null id stay as they are and count as no
document; rows of one id, equal or not, are one document. Of equal lines in several documents that of the smallest id
stays. A line of any length is one row's work. An empty table gives an empty one.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import saved

DEPTH, MIN_WORDS, SIMILARITY = 3, 3, 0.8
WILDCARD = "<*>"
#: Two bits of each word's hash, by its place: templates that differ in m places differ in no more than 2 m of them.
BITS = "aggregate(transform(words, (w, i) -> shiftleft(w & 3L, cast(2 * i % 64 as int))), 0L, (s, x) -> s ^ x)"
#: Templates of a band that one key of the second comparison holds, about; lines that make a template a hot one.
BLOCK, HOT = 1000, 1_000_000
#: White space but for U+0020, for regular expressions of Java and of DuckDB.
WHITE = r"\t\x0b\x0c\r\x1c-\x1f\x{85}\x{a0}\x{1680}\x{2000}-\x{200a}\x{2028}\x{2029}\x{202f}\x{205f}\x{3000}"


def masked(line: Column) -> Column:
    """The line with each word that holds a digit as a wildcard; possessive, so long words are read once."""
    return F.when(line.rlike("[0-9]"), F.regexp_replace(line, r"(?<![^ ])[^ 0-9]*+[0-9][^ ]*+", WILDCARD)).otherwise(line)


def _lines(docs: DataFrame) -> DataFrame:
    """doc_id, line, mask, n of all lines that take part."""
    rows = docs.where("doc_id IS NOT NULL AND text IS NOT NULL").select("doc_id", F.explode(F.array_distinct(F.split("text", "\n"))).alias("line"))
    rows = rows.where(F.trim("line") != "").select("doc_id", "line", masked(F.col("line")).alias("mask"))
    return rows.withColumn("n", F.size(F.split("mask", " ")))


def _all_lines(docs: DataFrame) -> DataFrame:
    """As _lines, with any white space between words, and short lines by their runs of digits."""
    rows = docs.where("doc_id IS NOT NULL AND text IS NOT NULL").select("doc_id", F.explode(F.array_distinct(F.split("text", "\n"))).alias("line"))
    rows = rows.where(F.col("line").rlike(f"[^ {WHITE}]"))
    tidy, line = F.trim(F.regexp_replace("line", f"[ {WHITE}]+", " ")), F.col("line")
    # few ranges, so most lines are told at little cost; what they let through needs no change
    untidy = line.rlike(r"[^ -\x{84}\x{86}-\x{9f}\x{a1}-\x{167f}]") | line.contains("  ") | line.startswith(" ") | line.endswith(" ")
    rows = rows.withColumn("tidy", F.when(untidy, tidy).otherwise(line))
    rows = rows.withColumn("n", F.size(F.split("tidy", " ")))
    short = F.regexp_replace("tidy", "[0-9]+", WILDCARD)
    short = F.when(F.col("tidy").rlike("[0-9]") & short.rlike(r"\p{L}"), short).otherwise(F.col("tidy"))
    return rows.select("doc_id", "line", F.when(F.col("n") < MIN_WORDS, short).otherwise(masked(F.col("tidy"))).alias("mask"), "n")


def _leaf() -> Column:
    return F.xxhash64("n", F.substring_index("mask", " ", DEPTH))


def recurring(docs: DataFrame, similarity: float = SIMILARITY, min_words: int = MIN_WORDS) -> DataFrame:
    """doc_id and `lines`, hashes of the lines that it loses."""
    lines = _lines(docs).where(F.col("n") >= min_words)
    seen = saved(lines.select("doc_id", F.xxhash64("line").alias("line"), _leaf().alias("leaf"), F.xxhash64("mask").alias("template"), "n"), "lines")
    ends = [F.min("doc_id").alias("lo"), F.max("doc_id").alias("hi")]
    templates = saved(seen.groupBy("leaf", "template", "n").agg(*ends), "templates")
    # leaves that more than one template and more than one document share
    open_leaves = templates.groupBy("leaf").agg(F.count("*").alias("k"), F.min("lo").alias("a"), F.max("hi").alias("b")).where("k > 1 AND a < b").select("leaf")
    one_each = templates.join(open_leaves, "leaf", "left_semi").select(F.col("lo").alias("doc_id"))
    words = _lines(docs.select("doc_id", "text").join(one_each, "doc_id", "left_semi")).where(F.col("n") >= min_words)
    words = words.select("doc_id", "mask", "n", _leaf().alias("leaf"), F.xxhash64("mask").alias("template"))
    words = words.join(templates.join(open_leaves, "leaf", "left_semi").select("leaf", "template", F.col("lo").alias("doc_id")), ["leaf", "template", "doc_id"], "left_semi")
    words = words.dropDuplicates(["leaf", "template"]).select("leaf", "template", "n", F.posexplode(F.split("mask", " ")).alias("pos", "word"))
    words = saved(words.select("leaf", "template", "n", "pos", F.xxhash64("word").alias("word")), "words")
    steady = words.groupBy("leaf", "pos", "word").agg(F.count("*").alias("c")).where("c > 1").select("leaf", "pos", "word")
    general = words.join(steady, ["leaf", "pos", "word"], "left_semi").groupBy("leaf", "template", "n")
    general = general.agg(F.count("*").alias("fixed"), F.bit_xor(F.xxhash64("pos", "word")).alias("shape"))
    general = general.where((F.col("fixed") >= similarity * F.col("n")) & (F.col("fixed") < F.col("n"))).select("leaf", "template", F.xxhash64("fixed", "shape").alias("shape"))
    widened = templates.join(general, ["leaf", "template"], "left").withColumn("final", F.coalesce("shape", "template"))
    spread = widened.groupBy("leaf", "final").agg(F.min("lo").alias("first"), F.max("hi").alias("last")).where("first < last").select("leaf", "final", "first")
    lost = widened.select("leaf", "template", "final").join(spread, ["leaf", "final"]).select("leaf", "template", "first")
    return seen.join(lost, ["leaf", "template"]).where("doc_id > first").groupBy("doc_id").agg(F.collect_set("line").alias("lines"))


def like_lines(docs: DataFrame, similarity: float = SIMILARITY) -> DataFrame:
    """doc_id and `lines`, hashes of the lines whose template, or one alike, is in a document of smaller id."""
    lines = _all_lines(docs)
    seen = saved(lines.select("doc_id", F.xxhash64("line").alias("line"), _leaf().alias("leaf"), F.xxhash64("mask").alias("template"), "n"), "lines")
    templates = saved(seen.groupBy("leaf", "template", "n").agg(F.min("doc_id").alias("lo"), F.max("doc_id").alias("hi"), F.count("*").alias("c")), "templates")
    most = (F.col("n") - F.ceil(similarity * F.col("n"))).cast("int")  # places that may differ
    leaves = templates.where(most > 0).groupBy("leaf").agg(F.count("*").alias("k"), F.min("lo").alias("a"), F.max("lo").alias("b")).where("k > 1 AND a < b").select("leaf")
    open_ones = templates.where(most > 0).join(leaves, "leaf", "left_semi").select("template", F.col("lo").alias("doc_id"))
    words = _all_lines(docs.select("doc_id", "text").join(open_ones.select("doc_id"), "doc_id", "left_semi"))
    words = words.select("doc_id", "mask", "n", _leaf().alias("leaf"), F.xxhash64("mask").alias("template")).join(open_ones, ["template", "doc_id"], "left_semi")
    hashes = F.transform(F.split("mask", " "), lambda x: F.xxhash64(x)).alias("words")
    words = words.dropDuplicates(["template"]).select("template", F.col("doc_id").alias("lo"), "leaf", "n", hashes)
    words = saved(words.withColumn("bits", F.expr(BITS)), "words")
    rest = F.greatest(F.col("n") - DEPTH, F.lit(0))
    start = lambda j: F.floor(rest * j / (most + 1)).cast("int")
    band = lambda j: F.xxhash64("leaf", j, F.slice("words", start(j) + DEPTH + 1, start(j + 1) - start(j)))
    bands = words.select("template", "lo", "n", "bits", F.explode(F.transform(F.sequence(F.lit(0), most), band)).alias("band"))
    shared = bands.groupBy("band").agg(F.min(F.struct("lo", "template", "bits")).alias("head"), F.max("lo").alias("b"), F.count("*").alias("k")).where("head.lo < b").select("band", "head", "k")
    members = saved(bands.join(shared, "band"), "bands")
    near = lambda x, y: F.bit_count(F.col(x).bitwiseXOR(F.col(y))) <= 2 * most
    later = members.where("lo > head.lo")
    like = _alike(later.where(near("bits", "head.bits")).select("template", F.col("head.template").alias("other")).distinct(), words, similarity)
    like = saved(like, "like")
    # a long band is met in parts, and pairs that the bits rule out are never rows
    parts = F.ceil(F.col("k") / BLOCK).cast("int")
    open_later = later.join(like, "template", "left_anti").select("template", "lo", "n", "bits", "band", F.explode(F.sequence(F.lit(0), parts - 1)).alias("part"))
    earlier = members.where("template <> head.template").select("band", F.pmod(F.xxhash64("template"), parts).cast("int").alias("part"), F.col("template").alias("other"), F.col("lo").alias("other_lo"), F.col("bits").alias("other_bits"))
    more = open_later.join(earlier, ["band", "part"]).where((F.col("other_lo") < F.col("lo")) & near("bits", "other_bits"))
    more = _alike(more.select("template", "other").distinct(), words, similarity)
    lost = templates.where("lo < hi").select("template", F.col("lo").alias("first")).unionByName(like).unionByName(more)
    lost = lost.groupBy("template").agg(F.min("first").alias("first")).join(templates.select("template", (F.col("c") > HOT).alias("hot")), "template")
    return _rows_of(seen, lost).where("doc_id > first").groupBy("doc_id").agg(F.collect_set("line").alias("lines"))


def _rows_of(seen: DataFrame, lost: DataFrame) -> DataFrame:
    """doc_id, line, first of the lines of lost templates. A template of more than HOT lines would be one key of many rows:
    there is at most one for each HOT lines of the corpus, so these few are broadcast, and the rows of the others joined."""
    hot = lost.where("hot").select("template", "first")
    rows = seen.select("doc_id", "line", "template")
    others = rows.join(F.broadcast(hot.select("template")), "template", "left_anti").join(lost.where("NOT hot").select("template", "first"), "template")
    return rows.join(F.broadcast(hot), "template").unionByName(others)


def _alike(pairs: DataFrame, words: DataFrame, similarity: float) -> DataFrame:
    """template and `first`, the smallest document of its others that agree in enough places."""
    others = words.select(F.col("template").alias("other"), F.col("lo").alias("first"), F.col("words").alias("other_words"))
    both = pairs.join(words.select("template", "n", "words"), "template").join(others, "other")
    same = F.size(F.filter(F.zip_with("words", "other_words", lambda x, y: x == y), lambda x: x))
    return both.where(same >= similarity * F.col("n")).groupBy("template").agg(F.min("first").alias("first"))


def _free(columns: list[str], *names: str) -> list[str]:
    """The names, each with as many underscores before it as no column of a table needs."""
    held, out = {c.lower() for c in columns}, []
    for name in names:
        while name.lower() in held:
            name = f"_{name}"
        out.append(name)
    return out


def drop_recurring(docs: DataFrame, report: bool = False, by: Callable[..., DataFrame] = recurring, **how) -> DataFrame:
    """docs without recurring lines, all its columns under their names, whatever those are; a document that loses all its
    lines goes, and n_chars (if it is there) follows the text. With `report`: doc_id, text, n_lines, n_dropped of all rows,
    those left empty too."""
    own_id, gone, left_lines = _free(docs.columns, "_id", "_lost", "_kept")
    lost = by(docs.select("doc_id", "text"), **how).withColumnRenamed("doc_id", own_id).withColumnRenamed("lines", gone)
    joined = docs.join(lost, F.col("doc_id") == F.col(own_id), "left")
    split, same = F.split("text", "\n"), F.col(gone).isNull()
    joined = joined.withColumn(left_lines, F.when(same, split).otherwise(F.filter(split, lambda x: ~F.array_contains(gone, F.xxhash64(x)))))
    text = F.when(same, F.col("text")).otherwise(F.array_join(left_lines, "\n"))
    if report:
        count = lambda c: F.coalesce(F.size(c), F.lit(0)).cast("bigint")
        n_lines = F.when(F.col("text").isNull(), F.lit(0)).otherwise(count(split)).cast("bigint")
        n_kept = F.when(F.col("text").isNull(), F.lit(0)).otherwise(count(F.col(left_lines))).cast("bigint")
        return joined.select("doc_id", text.alias("text"), n_lines.alias("n_lines"), (n_lines - n_kept).alias("n_dropped"))
    left = same | (F.trim(F.array_join(left_lines, "")) != "")
    fields = [F.col(c) for c in docs.columns]
    if "n_chars" in docs.columns:
        fields = [F.when(same, F.col(c)).otherwise(F.length(text)).cast(docs.schema[c].dataType).alias(c) if c == "n_chars" else F.col(c) for c in docs.columns]
    fields = [text.alias("text") if c == "text" else f for c, f in zip(docs.columns, fields, strict=True)]
    return joined.where(left).select(*fields)


#: The report for DuckDB, with the texts of templates in place of their hashes.
ORACLE_SQL = f"""
WITH base AS (
  SELECT DISTINCT doc_id, line, regexp_replace(line, '[^ ]*[0-9][^ ]*', '{WILDCARD}', 'g') AS mask
  FROM (SELECT doc_id, unnest(string_split(text, chr(10))) AS line FROM documents WHERE doc_id IS NOT NULL)
  WHERE trim(line) <> ''
), lines AS (
  SELECT doc_id, line, mask, w, len(w) AS n, array_to_string(w[1:{DEPTH}], ' ') AS lead
  FROM (SELECT *, string_split(mask, ' ') AS w FROM base) WHERE len(w) >= {MIN_WORDS}
), templates AS (SELECT n, lead, mask, any_value(w) AS w, min(doc_id) AS lo, max(doc_id) AS hi FROM lines GROUP BY ALL),
open_leaves AS (SELECT n, lead FROM templates GROUP BY ALL HAVING count(*) > 1 AND min(lo) < max(hi)),
words AS (
  SELECT t.n, t.lead, mask, unnest(range(1, t.n + 1)) AS pos, unnest(w) AS word FROM templates t JOIN open_leaves USING (n, lead)
), steady AS (SELECT n, lead, pos, word FROM words GROUP BY ALL HAVING count(*) > 1),
general AS (
  SELECT n, lead, mask, string_agg(pos || ':' || word, ' ' ORDER BY pos) AS shape
  FROM words JOIN steady USING (n, lead, pos, word) GROUP BY ALL HAVING count(*) >= {SIMILARITY} * n AND count(*) < n
), widened AS (
  SELECT t.n, t.lead, t.mask, lo, hi, CASE WHEN shape IS NULL THEN 'm' || t.mask ELSE 's' || shape END AS final
  FROM templates t LEFT JOIN general g ON t.n = g.n AND t.lead = g.lead AND t.mask = g.mask
), spread AS (SELECT n, lead, final, min(lo) AS first FROM widened GROUP BY ALL HAVING min(lo) < max(hi)),
lost AS (
  SELECT DISTINCT l.doc_id, l.line FROM lines l JOIN widened w ON l.n = w.n AND l.lead = w.lead AND l.mask = w.mask
  JOIN spread s ON w.n = s.n AND w.lead = s.lead AND w.final = s.final WHERE l.doc_id > s.first
), gone AS (SELECT doc_id, list(line) AS gone FROM lost GROUP BY doc_id)
SELECT d.doc_id,
  CASE WHEN gone IS NULL THEN text ELSE array_to_string(list_filter(string_split(text, chr(10)), lambda x: NOT list_contains(gone, x)), chr(10)) END AS text,
  coalesce(len(string_split(text, chr(10))), 0)::BIGINT AS n_lines,
  CASE WHEN gone IS NULL OR text IS NULL THEN 0 ELSE len(list_filter(string_split(text, chr(10)), lambda x: list_contains(gone, x))) END::BIGINT AS n_dropped
FROM documents d LEFT JOIN gone ON d.doc_id = gone.doc_id
"""

#: The same for `like_lines`.
LIKE_SQL = f"""
WITH split AS (
  SELECT doc_id, line, trim(regexp_replace(line, '[ {WHITE}]+', ' ', 'g')) AS tidy
  FROM (SELECT DISTINCT doc_id, unnest(string_split(text, chr(10))) AS line FROM documents WHERE doc_id IS NOT NULL)
), base AS (
  SELECT *, len(string_split(tidy, ' ')) AS n, regexp_replace(tidy, '[0-9]+', '{WILDCARD}', 'g') AS short,
    regexp_replace(tidy, '[^ ]*[0-9][^ ]*', '{WILDCARD}', 'g') AS long
  FROM split WHERE tidy <> ''
), lines AS (
  SELECT *, string_split(mask, ' ') AS w, array_to_string(string_split(mask, ' ')[1:{DEPTH}], ' ') AS lead
  FROM (SELECT doc_id, line, n, CASE WHEN n >= {MIN_WORDS} THEN long WHEN regexp_matches(short, '\\p{{L}}') THEN short ELSE tidy END AS mask FROM base)
), templates AS (SELECT n, lead, mask, any_value(w) AS w, min(doc_id) AS lo FROM lines GROUP BY ALL),
alike AS (
  SELECT a.mask, b.lo FROM templates a JOIN templates b ON a.n = b.n AND a.lead = b.lead AND b.lo < a.lo
  WHERE len(list_filter(range(1, a.n + 1), lambda i: a.w[i] = b.w[i])) >= {SIMILARITY} * a.n
), firsts AS (SELECT mask, min(lo) AS first FROM (SELECT mask, lo FROM templates UNION ALL SELECT mask, lo FROM alike) GROUP BY mask),
gone AS (SELECT doc_id, list(DISTINCT line) AS gone FROM lines JOIN firsts USING (mask) WHERE doc_id > first GROUP BY doc_id)
SELECT d.doc_id,
  CASE WHEN gone IS NULL THEN text ELSE array_to_string(list_filter(string_split(text, chr(10)), lambda x: NOT list_contains(gone, x)), chr(10)) END AS text,
  coalesce(len(string_split(text, chr(10))), 0)::BIGINT AS n_lines,
  CASE WHEN gone IS NULL OR text IS NULL THEN 0 ELSE len(list_filter(string_split(text, chr(10)), lambda x: list_contains(gone, x))) END::BIGINT AS n_dropped
FROM documents d LEFT JOIN gone ON d.doc_id = gone.doc_id
"""
