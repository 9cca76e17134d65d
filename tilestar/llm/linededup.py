"""Line dedup across a corpus, by a deletion-neighbourhood join.

A line's key is the line without white space at its ends. A line goes if an earlier line, in order of
(doc_id, line number), has the same key, or a key within one edit (insertion, deletion or substitution). Blank lines always
stay. The first of its kind stays. Edits count at every length; `min_chars` asks for so many code points in both keys, by default none.

How: keys are reduced to their first occurrence. Two keys within one edit agree outside one of four segments, so each key
emits a hash of the rest for each segment; keys whose rest nobody shares cannot have a neighbour. The others emit
every variant with one code point deleted inside that segment, and themselves, as hashes with the place of the deletion.
Equal variants with an equal place are substitutions; a variant that equals a whole key is an insertion. Each group
needs its earliest member only, so groups are aggregated and no pairs are listed. Edit distance is verified against
that earliest member.

Defined results: null text stays null with no lines; repeated rows (equal id and text) count as one document and are treated alike; rows with one doc_id and
different texts are documents of their own, in order of a hash of the text; a null doc_id sorts first; columns
of the input are kept, and the new ones take the given names; an empty table gives an empty table.

Shuffles: line keys as 128-bit hashes, never texts, except those of lines that have a candidate. Aggregations combine before the
shuffle, so a line that a third of all documents share costs a task one row. The table of kept lines meets the documents by
broadcast if its written size is within runtime.BROADCAST_BYTES, by a shuffled join otherwise.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from tilestar.llm.words import trimmed
from tilestar.runtime import Scratch, let

#: Least length of keys that may differ by an edit; 0: any.
MIN_CHARS = 0
#: Deletions are looked for in one of so many segments.
SEGMENTS = 4


def _quarter(n: Column) -> Column:
    """Length of the agreed outer segments for a key of n code points; it grows in steps, so neighbours mostly agree on it."""
    return F.floor(n / 8).cast("int") * 2


def _rests(key: Column, n: Column) -> Column:
    """For each segment, what lies outside it: struct(rest, low, high), deletions to be tried at [low, high).

    Keys of n and n+1 code points must share a quarter, so the quarter of n-1 is used too where it differs.
    """

    def at(q: Column) -> Column:
        def rest(tag: int, before: Column, after: Column) -> Column:
            text = F.xxhash64(F.lit(tag), q, F.substr(key, F.lit(1), before), F.substr(key, n - after + 1, after))
            return F.struct(text.alias("rest"), before.cast("int").alias("low"), (n - after).cast("int").alias("high"))

        zero = F.lit(0)
        whole = F.array(rest(0, zero, zero))  # too short for segments
        return F.when(q == 0, whole).otherwise(F.array(rest(0, zero, 3 * q), rest(1, q, 2 * q), rest(2, 2 * q, q), rest(3, 3 * q, zero)))

    q, q0 = _quarter(n), _quarter(n - 1)
    return F.when(q == q0, at(q)).otherwise(F.concat(at(q), at(q0)))


def _identity(doc: str, text: str) -> Column:
    """What documents are told apart and ordered by."""
    return F.struct(F.col(doc).alias("id"), F.xxhash64(F.col(text)).alias("hash"))


def _lines(df: DataFrame, doc: str, text: str) -> DataFrame:
    line = F.posexplode(F.split(F.col(text), "\n")).alias("line_no", "line")
    return df.select(_identity(doc, text).alias("doc"), line).select("doc", "line_no", trimmed(F.col("line")).alias("key")).filter("key <> ''")


def kept_lines(df: DataFrame, scratch: Scratch, doc: str = "doc_id", text: str = "text", min_chars: int = MIN_CHARS) -> DataFrame:
    """One row per document with kept lines: doc (its id and the hash of its text), kept (sorted array of line numbers)."""
    n = F.length("key")
    lines = _lines(df, doc, text)
    rests = F.when(n >= min_chars, F.transform(let(n, lambda k: _rests(F.col("key"), k)), lambda r: r["rest"]))
    hashed = lines.select(F.xxhash64("key").alias("h"), F.xxhash64(F.lit(7), "key").alias("g"), F.struct("doc", "line_no").alias("at"), rests.alias("rests"))
    firsts = scratch.save(hashed.groupBy("h", "g").agg(F.min("at").alias("at"), F.first("rests").alias("rests")), "firsts")
    shared = firsts.select("h", F.explode("rests").alias("rest"))
    crowded = shared.groupBy("rest").agg(F.min("h").alias("a"), F.max("h").alias("b")).filter("a <> b").select("rest")
    active = firsts.select("at", F.explode("rests").alias("rest")).join(crowded, "rest").groupBy("at").agg(F.collect_set("rest").alias("shared"))
    active = scratch.save(active.groupBy(F.col("at.doc").alias("active_doc")).agg(F.map_from_entries(F.collect_list(F.struct("at.line_no", "shared"))).alias("wanted")), "active")
    near = scratch.save(_near(df, scratch.small(active, "active"), doc, text, scratch), "near")
    kept = firsts.select("at").join(near, "at", "left_anti").groupBy("at.doc").agg(F.sort_array(F.collect_list("at.line_no")).alias("kept"))
    kept = scratch.save(kept, "kept")
    scratch.drop("firsts", "active", "near", "texts", "variants", "whole")
    return kept


def _near(df: DataFrame, active: DataFrame, doc: str, text: str, scratch: Scratch) -> DataFrame:
    """Places (`at`) of first occurrences that have an earlier neighbour within one edit."""
    wanted = df.select(_identity(doc, text).alias("doc"), F.col(text).alias("text")).join(active, F.col("doc").eqNullSafe(F.col("active_doc"))).select("doc", "text", "wanted")
    rows = wanted.select("doc", F.split("text", "\n").alias("lines"), F.explode("wanted").alias("line_no", "shared"))
    rows = rows.select(F.struct("doc", "line_no").alias("at"), trimmed(F.get("lines", F.col("line_no"))).alias("key"), "shared").filter("key is not null")
    texts = scratch.save(rows.groupBy("at").agg(F.min("key").alias("key"), F.first("shared").alias("shared")), "texts")
    n = F.length("key")
    spans = F.filter(let(n, lambda k: _rests(F.col("key"), k)), lambda r: F.array_contains("shared", r["rest"]))
    tasks = int(df.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    parts = texts.repartition(tasks, "at").select("at", "key", F.explode(spans).alias("r"))
    parts = parts.select("at", "r.rest", F.substr("key", F.col("r.low") + 1, F.col("r.high") - F.col("r.low")).alias("part"))
    deleted = parts.filter("part <> ''").select("at", "rest", "part", F.explode(F.sequence(F.lit(0), F.length("part") - 1)).alias("place"))
    # the rest's hash stands for the text outside the segment
    variants = deleted.select("at", "place", F.xxhash64("rest", F.concat(F.substr("part", F.lit(1), F.col("place")), F.substr("part", F.col("place") + 2, F.length("part")))).alias("variant"))
    variants = scratch.save(variants, "variants")
    whole = scratch.save(parts.select("at", F.xxhash64("rest", "part").alias("variant")), "whole")
    # substitutions: equal variants, equal place
    first = variants.groupBy("variant", "place").agg(F.min("at").alias("witness"), F.max("at").alias("last")).filter("witness < last").select("variant", "place", "witness")
    found = variants.join(first, ["variant", "place"]).filter("witness < at").select("at", "witness")
    # insertions: a variant that is a whole key
    ends = variants.groupBy("variant").agg(F.min("at").alias("longest"))
    found = found.union(whole.join(ends, "variant").filter("longest < at").select("at", F.col("longest").alias("witness")))
    found = found.union(variants.join(whole.select("variant", F.col("at").alias("witness")), "variant").filter("witness < at").select("at", "witness"))
    pairs = found.distinct().join(texts.select("at", F.col("key").alias("mine")), "at").join(texts.select(F.col("at").alias("witness"), F.col("key").alias("other")), "witness")
    return pairs.filter(F.levenshtein("mine", "other", 1) >= 0).select("at").distinct()


def dedup_lines(df: DataFrame, doc: str = "doc_id", text: str = "text", min_chars: int = MIN_CHARS, out: str | None = None, counts: tuple[str, str] | None = None) -> DataFrame:
    """df with duplicate lines taken out of `text` (put into column `out`, by default in place); counts: names for lines and removed lines."""
    spark = df.sparkSession
    scratch = Scratch(spark, "linededup")
    kept = scratch.small(kept_lines(df, scratch, doc, text, min_chars), "kept").select(F.col("doc").alias("__line_doc"), F.col("kept").alias("__line_kept"))
    joined = df.join(kept, _identity(doc, text).eqNullSafe(F.col("__line_doc")), "left")
    joined = joined.withColumn("__line_lines", F.split(F.col(text), "\n"))
    blank = F.filter(F.transform(F.col("__line_lines"), lambda x, i: F.when(trimmed(x) == "", i)), lambda i: i.isNotNull())
    joined = joined.withColumn("__line_numbers", F.sort_array(F.array_union(F.coalesce("__line_kept", F.array().cast("array<int>")), blank)))
    chosen = let(F.col("__line_lines"), lambda a: F.transform(F.filter(F.col("__line_numbers"), lambda i: i < F.size(a)), lambda i: F.get(a, i)))
    made = {out or text: F.array_join(chosen, "\n")}
    if counts:
        made[counts[0]] = F.coalesce(F.size("__line_lines"), F.lit(0)).cast("bigint")
        made[counts[1]] = F.coalesce(F.size("__line_lines") - F.size("__line_numbers"), F.lit(0)).cast("bigint")
    return joined.withColumns(made).drop("__line_doc", "__line_kept", "__line_lines", "__line_numbers")


def op4_line_dedup(df: DataFrame) -> DataFrame:
    out = dedup_lines(df.select("doc_id", "text"), out="__kept_text", counts=("n_lines", "n_removed"))
    return out.select("doc_id", "n_lines", "n_removed", F.sha2(F.coalesce("__kept_text", F.lit("")), 256).alias("kept_sha256"))


#: Edits are of code points; DuckDB's own levenshtein counts bytes, so the place of the edit is looked for.
SQL = f"""
WITH l AS (SELECT doc_id, i - 1 AS line_no, ls[i] AS line, trim(ls[i], ' ' || chr(9) || chr(10) || chr(11) || chr(12) || chr(13)) AS key
           FROM (SELECT doc_id, ls, unnest(range(1, len(ls) + 1)) AS i FROM (SELECT doc_id, string_split(text, chr(10)) AS ls FROM documents))),
f AS (SELECT key, min({{'d': doc_id, 'n': line_no}}) AS spot, length(key) AS n FROM l WHERE key <> '' GROUP BY key),
h AS (SELECT key, spot, n, b, s FROM f, (VALUES (0), (1)) t(b), (VALUES ('p'), ('s')) u(s) WHERE n >= {MIN_CHARS}),
k AS (SELECT key, spot, n, n - b AS base, s, CASE s WHEN 'p' THEN substr(key, 1, (n - b) // 2) ELSE right(key, (n - b) - (n - b) // 2) END AS half FROM h),
near AS (SELECT DISTINCT x.spot FROM k x JOIN k y ON x.base = y.base AND x.s = y.s AND x.half = y.half
         WHERE y.spot < x.spot AND least(x.n, y.n) = x.base AND len(list_filter(range(1, greatest(x.n, y.n) + 1), lambda i:
           substr(x.key, 1, i - 1) = substr(y.key, 1, i - 1) AND substr(x.key, CASE WHEN x.n < y.n THEN i ELSE i + 1 END) = substr(y.key, CASE WHEN y.n < x.n THEN i ELSE i + 1 END))) > 0),
kept AS (SELECT spot FROM f WHERE spot NOT IN (SELECT spot FROM near)),
r AS (SELECT l.*, key = '' OR {{'d': doc_id, 'n': line_no}} IN (SELECT spot FROM kept) AS stays FROM l)
SELECT d.doc_id, coalesce(count(r.line), 0)::BIGINT AS n_lines, coalesce(sum(CASE WHEN NOT stays THEN 1 ELSE 0 END), 0)::BIGINT AS n_removed,
       sha256(coalesce(string_agg(line, chr(10) ORDER BY line_no) FILTER (stays), '')) AS kept_sha256
FROM documents d LEFT JOIN r ON d.doc_id = r.doc_id GROUP BY d.doc_id
"""
