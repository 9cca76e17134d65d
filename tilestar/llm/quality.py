"""Quality rules as a bitmask ledger.

Every rule is evaluated once per document. The ledger holds the measurements and one long whose bit k
says that rule k failed. A policy is a versioned mask: a document passes if it fails no rule of the mask,
so policies are compared, and rules ablated, by bit operations on the ledger alone.

Defined results: null text counts as empty; an empty text has no words, fails "too_few_words" and all its
measurements are 0; repeated rows are judged separately and alike; an empty table gives an empty ledger;
columns of the input are kept, and measurements go into columns whose names start with the given prefix,
so names cannot clash unless the caller asks for it.

Cost: one pass, no shuffle, no Python. Windows are hashed (64 bits) inside the row; only documents in which some
window hash repeats are sorted, so a text of n words costs O(n log n) at worst.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from tilestar.llm.words import WHITE_RUN, words_of
from tilestar.runtime import let

WINDOW = 8
MEASURES = ("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "n_lines", "n_stutter", "n_upper")

#: Rule k sets bit k. Each is a predicate over the measurements; integers only, so that engines agree.
RULES: tuple[tuple[str, str], ...] = (
    ("too_few_words", "n_words < 20"),
    ("repeated_windows", "100 * n_repeat_words > 30 * n_words"),
    ("symbols", "20 * n_symbols > word_chars"),
    ("repeated_lines", "2 * n_dup_lines > n_lines"),
    ("stutter", "5 * n_stutter > n_words"),
    ("shouting", "2 * n_upper > word_chars"),
    ("short_words", "word_chars < 3 * n_words"),
    ("long_words", "word_chars > 12 * n_words"),
)
BIT = {name: 1 << k for k, (name, _) in enumerate(RULES)}
BASE = BIT["too_few_words"] | BIT["repeated_windows"]
ALL = (1 << len(RULES)) - 1
#: Versioned policies; a new version is a new entry, so old decisions can be reproduced.
POLICIES: dict[str, int] = {"base": BASE, "v1": ALL & ~(BIT["short_words"] | BIT["long_words"]), "v2": ALL}
CURRENT = "v2"


def _window_hashes(words: Column, width: int) -> Column:
    """64-bit hashes of all runs of `width` words."""
    return let(
        F.transform(words, lambda w: F.xxhash64(w)),
        lambda h: F.when(F.size(h) >= width, F.transform(F.sequence(F.lit(1), F.size(h) - (width - 1)), lambda i: F.xxhash64(F.slice(h, i, width)))).otherwise(F.array().cast("array<bigint>")),
    )


def _covered(hashes: Column, width: int) -> Column:
    """Words that lie in a window whose hash occurs twice or more in the array."""
    sorted_pairs = F.sort_array(F.transform(hashes, lambda h, i: F.struct(h.alias("h"), i.alias("i"))))
    same = lambda a, b: F.coalesce(a["h"] == b["h"], F.lit(False))
    twice = let(sorted_pairs, lambda s: F.filter(s, lambda x, k: same(F.get(s, k - 1), x) | same(F.get(s, k + 1), x)))
    places = F.sort_array(F.transform(twice, lambda x: x["i"]))
    gaps = let(places, lambda p: F.transform(p, lambda x, k: F.least(F.lit(width), F.get(p, k + 1) - x)))
    return F.aggregate(gaps, F.lit(0).cast("bigint"), lambda acc, g: acc + g)


def repeat_words(words: Column, width: int = WINDOW) -> Column:
    return let(
        _window_hashes(words, width),
        lambda h: F.when(F.size(F.array_distinct(h)) == F.size(h), F.lit(0).cast("bigint")).otherwise(_covered(h, width)),
    )


def measure(df: DataFrame, text: str = "text", prefix: str = "") -> DataFrame:
    """df with one column for each of MEASURES, named prefix + measure."""
    t, w, lines = (f"__quality_{x}" for x in ("text", "words", "lines"))
    df = df.withColumn(t, F.coalesce(F.col(text).cast("string"), F.lit("")))
    df = df.withColumns({w: words_of(F.col(t)), lines: F.filter(F.split(F.col(t), "\n"), lambda x: x.rlike("[^\\x20\\x09-\\x0D]"))})
    removed = lambda rx: (F.length(t) - F.length(F.regexp_replace(t, rx, ""))).cast("bigint")
    stutter = let(F.col(w), lambda a: F.size(F.filter(a, lambda x, i: F.coalesce(F.get(a, i - 1) == x, F.lit(False)))))
    made = {
        "n_words": F.size(w),
        "word_chars": F.length(F.array_join(w, "")),
        "n_symbols": removed("[#*$%&|<>]"),
        "n_dup_lines": F.size(lines) - F.size(F.array_distinct(lines)),
        "n_repeat_words": repeat_words(F.col(w)),
        "n_lines": F.size(lines),
        "n_stutter": stutter,
        "n_upper": removed("\\p{Lu}"),
    }
    return df.withColumns({prefix + k: made[k].cast("bigint") for k in MEASURES}).drop(t, w, lines)


def failure_bits(prefix: str = "") -> Column:
    """The ledger's long: bit k set where rule k fails."""
    bits = F.lit(0).cast("bigint")
    for k, (_, rule) in enumerate(RULES):
        for m in MEASURES if prefix else ():
            rule = rule.replace(m, f"`{prefix}{m}`")
        bits = bits + F.when(F.expr(rule), F.lit(1 << k).cast("bigint")).otherwise(F.lit(0).cast("bigint"))
    return bits


def ledger(df: DataFrame, text: str = "text", prefix: str = "") -> DataFrame:
    """df with its measurements and fail_bits."""
    return measure(df, text, prefix).withColumn(f"{prefix}fail_bits", failure_bits(prefix))


def passes(bits: Column, policy: str = CURRENT) -> Column:
    return bits.bitwiseAND(F.lit(POLICIES[policy]).cast("bigint")) == 0


def keep(df: DataFrame, policy: str = CURRENT, text: str = "text") -> DataFrame:
    """The rows of df that a policy accepts, with df's own columns."""
    p = "__quality_ledger_"
    return ledger(df, text, p).filter(passes(F.col(f"{p}fail_bits"), policy)).select(*(F.col(f"`{c}`") for c in df.columns))


def ablation(led: DataFrame, policy: str = CURRENT) -> DataFrame:
    """For each rule of a policy: documents that fail it, that only it rejects, and that the policy keeps without it."""
    mask = POLICIES[policy]
    counts = led.groupBy(F.col("fail_bits").bitwiseAND(F.lit(mask).cast("bigint")).alias("bits")).agg(F.count("*").alias("n"))
    rules = led.sparkSession.createDataFrame([(name, k) for k, (name, _) in enumerate(RULES) if mask >> k & 1], "rule string, bit int")
    failed = F.getbit("bits", "bit") == 1
    alone = failed & (F.bit_count("bits") == 1)
    total = lambda c: F.coalesce(F.sum(F.when(c, F.col("n"))), F.lit(0)).cast("bigint")
    # at most 2^rules rows on one side and one row a rule on the other
    return rules.join(F.broadcast(counts), F.lit(True), "left").groupBy("rule").agg(total(failed).alias("n_failed"), total(alone).alias("n_only"), total(alone | (F.col("bits") == 0)).alias("n_kept_without"))


def op1_quality(df: DataFrame, policy: str = CURRENT) -> DataFrame:
    led = ledger(df.select("doc_id", "text"))
    base_failed = ~passes(F.col("fail_bits"), "base")
    return led.select("doc_id", *MEASURES[:5], base_failed.alias("base_failed"), passes(F.col("fail_bits"), policy).alias("kept"), *MEASURES[5:], "fail_bits")


SQL = r"""
WITH d AS (SELECT doc_id, coalesce(text, '') AS t FROM documents),
w AS (SELECT doc_id, t,
        list_filter(regexp_split_to_array(t, '[\x20\x09-\x0D]+'), lambda x: x <> '') AS ws,
        list_filter(string_split(t, chr(10)), lambda x: regexp_matches(x, '[^\x20\x09-\x0D]')) AS ls
      FROM d),
win AS (SELECT doc_id, i, ws[i:i + 7] AS g FROM (SELECT doc_id, ws, unnest(range(1, len(ws) - 6)) AS i FROM w)),
rep AS (SELECT doc_id, count(DISTINCT i + j) AS n
        FROM (SELECT doc_id, i, count(*) OVER (PARTITION BY doc_id, g) AS c FROM win) x, range(0, 8) r(j)
        WHERE c > 1 GROUP BY doc_id),
m AS (SELECT w.doc_id,
        len(ws)::BIGINT AS n_words,
        length(array_to_string(ws, ''))::BIGINT AS word_chars,
        (length(t) - length(regexp_replace(t, '[#*$%&|<>]', '', 'g')))::BIGINT AS n_symbols,
        (len(ls) - len(list_distinct(ls)))::BIGINT AS n_dup_lines,
        coalesce(rep.n, 0)::BIGINT AS n_repeat_words,
        len(ls)::BIGINT AS n_lines,
        len(list_filter(range(2, len(ws) + 1), lambda i: ws[i] = ws[i - 1]))::BIGINT AS n_stutter,
        (length(t) - length(regexp_replace(t, '\p{Lu}', '', 'g')))::BIGINT AS n_upper
      FROM w LEFT JOIN rep USING (doc_id)),
b AS (SELECT *, (CASE WHEN n_words < 20 THEN 1 ELSE 0 END
        + CASE WHEN 100 * n_repeat_words > 30 * n_words THEN 2 ELSE 0 END
        + CASE WHEN 20 * n_symbols > word_chars THEN 4 ELSE 0 END
        + CASE WHEN 2 * n_dup_lines > n_lines THEN 8 ELSE 0 END
        + CASE WHEN 5 * n_stutter > n_words THEN 16 ELSE 0 END
        + CASE WHEN 2 * n_upper > word_chars THEN 32 ELSE 0 END
        + CASE WHEN word_chars < 3 * n_words THEN 64 ELSE 0 END
        + CASE WHEN word_chars > 12 * n_words THEN 128 ELSE 0 END)::BIGINT AS fail_bits FROM m)
SELECT doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words,
       (fail_bits & 3) <> 0 AS base_failed, fail_bits = 0 AS kept, n_lines, n_stutter, n_upper, fail_bits
FROM b
"""
