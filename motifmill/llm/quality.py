"""Quality rules with host-level verdicts, in DataFrame functions only.

Every document gets counts from its whole text and a set of rule failures. The
failures are aggregated by host (``source``), each host's failure rate is shrunk
towards the corpus with a beta prior whose two parameters come from the hosts'
own rates (method of moments), and the host's verdict is joined back.

A document is kept when it passes the base rules and those of symbols and word
lengths, and its host's shrunk failure rate is not out of the ordinary. The limit comes
from the prior: ``HOST_SDS`` standard deviations of the hosts' rates above their mean and
``HOST_FACTOR`` times the mean at least, at most ``HOST_LIMIT``. Repeated lines alone
reject no document (good texts have refrains); they count for the host.

Windows of a text whose 64-bit hashes are equal are compared word by word.

Nulls: a null text has no words and fails; a null host has no host verdict.
Repeated rows count as often as they occur, ties of a rate with the limit pass. A very
long text is one row of one task. An empty table gives an empty result. Input columns
named like an output are replaced.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from motifmill.functions.scratch import materialise
from motifmill.llm.words import SEPARATORS, let, words_column

#: A host is rejected above this share of failing documents after shrinking, or above less: see ``host_limit``.
HOST_LIMIT, HOST_FACTOR, HOST_SDS = 0.5, 2.0, 3.0
#: Prior weights outside this range (in documents) are moved to its ends.
PRIOR_WEIGHT = (2.0, 10_000.0)
WINDOW = 5
#: Bytes of rejected hosts up to which they are broadcast.
HOSTS_BROADCAST = 16 << 20
COUNTS = ["n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words"]
RULES = ["fail_short", "fail_repeats", "fail_symbols", "fail_lines", "fail_lengths"]


def repeated_words(words: Column, width: int = WINDOW) -> Column:
    """Number of words inside windows of ``width`` words that occur twice or more in the array."""
    last = F.size(words) - width
    window = lambda i: F.xxhash64(*[F.get(words, i + k) for k in range(width)])
    hashes = F.transform(F.sequence(F.lit(0), last), window)

    def covered(at: Column) -> Column:
        gaps = F.transform(at, lambda p, i: F.least(F.lit(width), F.coalesce(F.get(at, i + 1) - p, F.lit(width))))
        return F.aggregate(gaps, F.lit(0), lambda a, x: a + x)

    def places(pairs: Column) -> Column:
        same = lambda p, j: F.coalesce((F.get(pairs, j)["h"] == p["h"]) & (F.get(pairs, j)["w"] == p["w"]), F.lit(False))
        twice = F.filter(pairs, lambda p, i: ((i > 0) & same(p, F.greatest(i - 1, F.lit(0)))) | same(p, i + 1))
        return F.sort_array(F.transform(twice, lambda p: p["i"]))

    def count(h: Column) -> Column:
        # only texts with two equal hashes come here; their windows are put in order with their words
        pairs = F.array_sort(F.transform(h, lambda x, i: F.struct(x.alias("h"), F.slice(words, i + 1, width).alias("w"), i.alias("i"))))
        return F.when(F.size(F.array_distinct(h)) == F.size(h), F.lit(0)).otherwise(let(let(pairs, places), covered))

    return F.when(last < 1, F.lit(0)).otherwise(let(hashes, count)).cast("long")


def document_counts(text: Column) -> Column:
    """Struct of the five counts and the number of lines that have a word."""
    whole = F.coalesce(text, F.lit(""))
    lines = F.filter(F.split(whole, "\n"), lambda x: F.regexp_like(x, F.lit(r"[^\x20\x09-\x0D]")))
    by_line = let(lines, lambda x: F.struct(F.size(x).cast("long").alias("lines"), (F.size(x) - F.size(F.array_distinct(x))).cast("long").alias("again")))
    by_word = let(words_column(text), lambda w: F.struct(F.size(w).cast("long").alias("n"), repeated_words(w).alias("again")))
    return let(
        F.struct(by_word.alias("w"), by_line.alias("l")),
        lambda x: F.struct(
            x["w"]["n"].alias("n_words"),
            F.length(F.regexp_replace(whole, SEPARATORS, "")).cast("long").alias("word_chars"),
            F.length(F.regexp_replace(whole, r"[^#*$%&|<>]+", "")).cast("long").alias("n_symbols"),
            x["l"]["again"].alias("n_dup_lines"),
            x["w"]["again"].alias("n_repeat_words"),
            x["l"]["lines"].alias("n_lines"),
        ),
    )


def rule_failures() -> dict[str, Column]:
    """The first two are the base rules."""
    c = {k: F.col(k) for k in [*COUNTS, "n_lines"]}
    return {
        "fail_short": c["n_words"] < 10,
        "fail_repeats": 100 * c["n_repeat_words"] > 20 * c["n_words"],
        "fail_symbols": 10 * c["n_symbols"] > c["n_words"],
        "fail_lines": 100 * c["n_dup_lines"] > 30 * c["n_lines"],
        "fail_lengths": (c["word_chars"] < 2 * c["n_words"]) | (c["word_chars"] > 20 * c["n_words"]),
    }


def host_rates(features: DataFrame, host: str = "source") -> DataFrame:
    """One row per host: documents, failures, the shrunk rate and the verdict ``host_failed``."""
    failed = F.greatest(*[F.col(r).cast("int") for r in RULES])
    hosts = features.where(F.col(host).isNotNull()).groupBy(host).agg(F.count("*").alias("host_docs"), F.sum(failed).alias("host_failures"))
    rate = F.col("host_failures") / F.col("host_docs")
    total = hosts.agg(
        F.sum("host_docs").alias("docs"),
        F.sum("host_failures").alias("failures"),
        F.count("*").alias("hosts"),
        F.sum(F.col("host_docs") * rate * rate).alias("squares"),
    ).first()
    alpha, beta = beta_prior(total["docs"] or 0, total["failures"] or 0, total["hosts"], total["squares"] or 0.0)
    shrunk = (F.col("host_failures") + alpha) / (F.col("host_docs") + alpha + beta)
    return hosts.withColumn("host_rate", shrunk).withColumn("host_failed", F.col("host_rate") > host_limit(alpha, beta))


def host_limit(alpha: float, beta: float) -> float:
    """The highest ordinary rate under the prior."""
    mean = alpha / (alpha + beta)
    spread = (mean * (1 - mean) / (alpha + beta + 1)) ** 0.5
    return min(HOST_LIMIT, max(HOST_FACTOR * mean, mean + HOST_SDS * spread))


def beta_prior(docs: int, failures: int, hosts: int, squares: float) -> tuple[float, float]:
    """Moments of the hosts' rates, each weighted by its documents, less what sampling adds to their spread."""
    if not docs:
        return 1.0, 1.0
    mean = min(max(failures / docs, 1e-6), 1 - 1e-6)
    spread = squares / docs - (failures / docs) ** 2 - mean * (1 - mean) * hosts / docs
    weight = mean * (1 - mean) / spread - 1 if spread > 0 else PRIOR_WEIGHT[1]
    weight = min(max(weight, PRIOR_WEIGHT[0]), PRIOR_WEIGHT[1])
    return mean * weight, (1 - mean) * weight


def quality_features(docs: DataFrame, text: str = "text", host: str = "source", key: str = "doc_id") -> DataFrame:
    """Counts and rule failures of every row, without the text."""
    counted = docs.select(F.col(key), F.col(host), document_counts(F.col(text)).alias("c")).select(key, host, "c.*")
    return counted.withColumns(rule_failures())


def quality_verdicts(docs: DataFrame, text: str = "text", host: str = "source", key: str = "doc_id") -> DataFrame:
    """Every row's counts, rule failures, host rate, ``base_failed`` and ``kept``."""
    features = materialise(quality_features(docs, text, host, key), "quality")
    hosts = host_rates(features, host)
    own = F.col("fail_symbols") | F.col("fail_lengths")
    base = F.col("fail_short") | F.col("fail_repeats")
    return features.join(hosts, host, "left").select(
        key, host, *COUNTS, "n_lines", *RULES, "host_docs", "host_rate",
        F.coalesce("host_failed", F.lit(False)).alias("host_failed"),
        base.alias("base_failed"),
        (~base & ~own & ~F.coalesce("host_failed", F.lit(False))).alias("kept"),
    )


def keep_good(docs: DataFrame, text: str = "text", host: str = "source", key: str = "doc_id") -> DataFrame:
    """The rows that pass, with the columns of ``docs``.

    Texts are counted once: the first pass writes the rows that pass by themselves, and of the others host and failure
    only. The rejected hosts are all that it has to deliver to the second. While they are few (their bytes are summed
    first) they are broadcast, and no text is shuffled.
    """
    counted = docs.select(F.struct(*[F.col(c) for c in docs.columns]).alias("__row"), F.col(host).alias("__host"), document_counts(F.col(text)).alias("__c"))
    within = {k: F.col(f"__c.{k}").alias(k) for k in [*COUNTS, "n_lines"]}
    judged = counted.select("__row", "__host", *within.values()).withColumns(rule_failures())
    own = F.greatest(*[F.col(r) for r in RULES if r != "fail_lines"])
    first = materialise(judged.select(F.when(~own, F.col("__row")).alias("__row"), "__host", *RULES), "judged")
    bad = materialise(host_rates(first, "__host").where("host_failed").select(F.col("__host").alias("__bad")), "bad-hosts")
    size = bad.agg(F.count("*").alias("rows"), F.sum(F.octet_length(F.col("__bad").cast("string"))).alias("bytes")).first()
    rows = first.where(F.col("__row").isNotNull())
    if size["rows"]:
        small = size["rows"] * 32 + size["bytes"] <= HOSTS_BROADCAST
        rows = rows.join(F.broadcast(bad) if small else bad, F.col("__host") == F.col("__bad"), "left_anti")
    return rows.select("__row.*")


def op3_quality_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Verdict on every document."""
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    return quality_verdicts(docs).select("doc_id", *COUNTS, "base_failed", "kept", "host_failed")


#: The same verdicts in DuckDB's dialect.
OP3_SQL = r"""
WITH t AS (SELECT doc_id, source, coalesce(text, '') AS text FROM documents),
w AS (
  SELECT doc_id, source, text, regexp_extract_all(text, '[^\x20\x09-\x0D]+') AS words,
         list_filter(string_split(text, chr(10)), lambda x: regexp_matches(x, '[^\x20\x09-\x0D]')) AS lines
  FROM t),
g AS (
  SELECT doc_id, i, count(*) OVER (PARTITION BY doc_id, win) AS times
  FROM (SELECT doc_id, i, list_slice(words, i, i + 4) AS win
        FROM (SELECT doc_id, words, unnest(range(1, len(words) - 3)) AS i FROM w))),
rep AS (SELECT doc_id, count(DISTINCT i + k) AS n_repeat_words
        FROM (SELECT doc_id, i FROM g WHERE times > 1), range(0, 5) r(k) GROUP BY doc_id),
c AS (
  SELECT doc_id, source, len(words)::BIGINT AS n_words,
         coalesce(list_sum(list_transform(words, lambda x: length(x))), 0)::BIGINT AS word_chars,
         length(regexp_replace(text, '[^#*$%&|<>]+', '', 'g'))::BIGINT AS n_symbols,
         (len(lines) - len(list_distinct(lines)))::BIGINT AS n_dup_lines,
         coalesce(n_repeat_words, 0)::BIGINT AS n_repeat_words, len(lines) AS n_lines
  FROM w LEFT JOIN rep USING (doc_id)),
f AS (
  SELECT *, n_words < 10 OR 100 * n_repeat_words > 20 * n_words AS base_failed,
         10 * n_symbols > n_words OR word_chars < 2 * n_words OR word_chars > 20 * n_words AS own_failed, 100 * n_dup_lines > 30 * n_lines AS lines_failed
  FROM c),
h AS (SELECT source, count(*)::DOUBLE AS n, sum((base_failed OR own_failed OR lines_failed)::INT)::DOUBLE AS k FROM f WHERE source IS NOT NULL GROUP BY source),
s AS (SELECT greatest(least(sum(k) / sum(n), 1 - 1e-6), 1e-6) AS m,
             sum(n * (k / n) * (k / n)) / sum(n) - (sum(k) / sum(n)) ** 2 AS v, count(*) / sum(n) AS inv FROM h),
p AS (SELECT m, CASE WHEN v - m * (1 - m) * inv > 0 THEN greatest(least(m * (1 - m) / (v - m * (1 - m) * inv) - 1, 10000), 2) ELSE 10000 END AS wt FROM s),
r AS (SELECT source, (k + m * wt) / (n + wt) AS rate, least(0.5, greatest(2 * m, m + 3 * sqrt(m * (1 - m) / (wt + 1)))) AS top FROM h, p)
SELECT doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, base_failed,
       NOT base_failed AND NOT own_failed AND NOT coalesce(rate > top, false) AS kept,
       coalesce(rate > top, false) AS host_failed
FROM f LEFT JOIN r USING (source)
"""
