"""URL verdicts: host and path rules first, then gradient-boosted trees on lexical features.

All row work is DataFrame expressions. The trees are fitted on the driver from a bounded
sample of labelled URLs (``TRAIN_ROWS``) and applied as CASE expressions.

Labels are weak ones, as no table holds labelled URLs: a list of host words (``SEED_WORDS``). The trees do not see words,
only lexical features and what other hosts under the same suffix are labelled; ``held_out`` measures them on hosts that
neither trees nor statistics have seen. URLs are looked at whole, however long.

Defined cases: a null URL, or one without ``://``, has empty host and path, fits no rule and
is judged by the trees like any other; repeated rows each get their verdict; with no labelled
URL of one class the trees are constant; extra columns are ignored.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from spanweave.llm import boosting
from spanweave.llm.batches import bounded_sample

#: Documented bound of the training sample: labelled URLs with the smallest hashes.
TRAIN_ROWS = 20_000

#: (host, path, verdict); fixed values of the contract.
RULES = (
    ("com", "/en/", "block"),
    ("example.com", "/en/7", "allow"),
    ("net", "/de/", "allow"),
    ("example.net", "/de/8", "block"),
    ("org", "/es/", "block"),
)

#: Host words that label a URL as unwanted for training; every other URL that no rule decides is labelled wanted.
SEED_WORDS = ("casino", "bets", "poker", "lottery", "ads", "track", "adult", "porn", "pills", "cheap", "spam", "loan", "win")

FEATURES = [
    "f_length", "f_host_length", "f_path_length", "f_depth", "f_labels", "f_digits", "f_host_digits", "f_hyphens",
    "f_entropy", "f_params", "f_query_length", "f_fragment", "f_secure", "f_suffix_rate", "f_suffix_rows", "f_suffix2_rate",
]


def ascii_lower(c: Column) -> Column:
    return F.translate(c, "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")


def with_parts(df: DataFrame, url: str = "url") -> DataFrame:
    """Adds ``host``, ``path`` and ``query`` as the contract cuts them."""
    at = F.locate("://", F.col(url))
    rest = F.when(at > 0, F.expr(f"substring(`{url}`, locate('://', `{url}`) + 3)")).otherwise(F.lit(""))
    df = df.withColumn("_rest", F.coalesce(rest, F.lit("")))
    df = df.withColumn("host", ascii_lower(F.regexp_extract("_rest", r"^([^/?#]*)", 1)))
    df = df.withColumn("path", F.regexp_extract("_rest", r"^[^/?#]*([^?#]*)", 1))
    df = df.withColumn("query", F.regexp_extract("_rest", r"^[^?#]*\?([^#]*)", 1))
    return df.drop("_rest")


def with_rule(df: DataFrame, rules=RULES) -> DataFrame:
    """Adds ``rule`` and ``rule_verdict`` of the longest rule that fits host (or a parent of it) and path; null where none does."""
    name = verdict = F.lit(None).cast("string")
    for host, path, says in sorted(rules, key=lambda r: (len(r[0]) + len(r[1]), r)):
        fits = ((F.col("host") == host) | F.endswith(F.col("host"), F.lit("." + host))) & F.startswith(F.col("path"), F.lit(path))
        name = F.when(fits, F.lit(host + path)).otherwise(name)
        verdict = F.when(fits, F.lit(says)).otherwise(verdict)
    return df.withColumn("rule", name).withColumn("rule_verdict", verdict)


def _entropy(c: Column) -> Column:
    """Bits per character."""
    chars = F.filter(F.split(c, ""), lambda x: x != "")
    total = F.size(chars).cast("double")

    def term(x):
        p = (F.length(c) - F.length(F.replace(c, x, F.lit("")))) / total
        return -p * F.log2(p)

    return F.when(total > 0, F.aggregate(F.array_distinct(chars), F.lit(0.0), lambda acc, x: acc + term(x))).otherwise(F.lit(0.0))


def with_lexical(df: DataFrame, url: str = "url") -> DataFrame:
    """Adds the features of a single URL and its host suffixes of one and two labels."""
    u, host, path, query = F.coalesce(F.col(url), F.lit("")), F.col("host"), F.col("path"), F.col("query")
    count = lambda c, ch: (F.length(c) - F.length(F.replace(c, F.lit(ch), F.lit("")))).cast("double")
    digits = lambda c: (F.length(c) - F.length(F.translate(c, "0123456789", ""))).cast("double")
    share = lambda part, c: part / F.greatest(F.length(c).cast("double"), F.lit(1.0))
    return df.withColumns({
        "f_length": F.length(u).cast("double"),
        "f_host_length": F.length(host).cast("double"),
        "f_path_length": F.length(path).cast("double"),
        "f_depth": count(path, "/"),
        "f_labels": count(host, "."),
        "f_digits": share(digits(u), u),
        "f_host_digits": share(digits(host), host),
        "f_hyphens": count(host, "-"),
        "f_entropy": _entropy(host),
        "f_params": F.when(query == "", F.lit(0.0)).otherwise(count(query, "&") + 1),
        "f_query_length": F.length(query).cast("double"),
        "f_fragment": F.contains(u, F.lit("#")).cast("double"),
        "f_secure": F.startswith(u, F.lit("https")).cast("double"),
        "suffix1": F.substring_index(host, ".", -1),
        "suffix2": F.substring_index(host, ".", -2),
    })


def label_by_words(df: DataFrame, words=SEED_WORDS) -> DataFrame:
    """Adds ``label``: null where a rule decides or there is no host; 1 where a host word is a seed word; else 0."""
    named = F.arrays_overlap(F.split("host", "[.-]"), F.array(*[F.lit(w) for w in words]))
    unknown = F.col("rule").isNotNull() | (F.col("host") == "")
    return df.withColumn("label", F.when(unknown, F.lit(None)).when(named, F.lit(1.0)).otherwise(F.lit(0.0)))


def with_statistics(df: DataFrame, labelled: DataFrame) -> DataFrame:
    """Adds what the labelled URLs of *other* hosts under the same suffix say: smoothed share of unwanted ones, log of rows.

    A host's own labels are taken out, in training as in judging: no feature holds the label that it is to predict."""
    sums = lambda key, out: labelled.groupBy(F.col(key).alias(f"_{out}")).agg(F.sum("label").alias(f"_{out}_s"), F.count("label").alias(f"_{out}_n"))
    for key, out in (("host", "h"), ("suffix1", "one"), ("suffix2", "two")):
        df = df.join(sums(key, out), F.col(key) == F.col(f"_{out}"), "left").drop(f"_{out}")
    mine = lambda c: F.coalesce(c, F.lit(0.0))
    bad = lambda out: mine(f"_{out}_s") - mine("_h_s")
    rows = lambda out: mine(f"_{out}_n") - mine("_h_n")
    df = df.withColumns({
        "f_suffix_rate": (bad("one") + 1.0) / (rows("one") + 2.0), "f_suffix_rows": F.log2(rows("one") + 1.0),
        "f_suffix2_rate": (bad("two") + 1.0) / (rows("two") + 2.0),
    })
    return df.drop(*[f"_{out}_{k}" for out in ("h", "one", "two") for k in "sn"])


def train(df: DataFrame, rows: int = TRAIN_ROWS, **options) -> boosting.Forest:
    """Fits trees to ``FEATURES`` and ``label`` of about ``rows`` labelled rows at most, those with the smallest hashes."""
    sample = bounded_sample(df.filter("label is not null"), rows, "page_id").select("label", *FEATURES)
    sample = sample.orderBy("label", *FEATURES).collect()
    x = np.array([[float(r[f]) for f in FEATURES] for r in sample]).reshape(len(sample), len(FEATURES))
    return boosting.fit(x, np.array([r["label"] for r in sample]), **({"trees": 20, "depth": 3, "rate": 0.3} | options))


def judge(pages: DataFrame, rules=RULES, *, threshold: float = 0.5, train_rows: int = TRAIN_ROWS) -> DataFrame:
    """page_id, host, path, rule, verdict, score of each page: the longest rule's verdict, else block from ``threshold`` on."""
    base = label_by_words(with_lexical(with_rule(with_parts(pages.select("page_id", "url")), rules)))
    full = with_statistics(base, base.filter("label is not null"))
    score = train(full, train_rows).as_column(FEATURES)
    by_trees = F.when(F.col("score") >= threshold, F.lit("block")).otherwise(F.lit("allow"))
    judged = full.withColumn("score", score).withColumn("verdict", F.coalesce("rule_verdict", by_trees))
    return judged.select("page_id", "host", "path", "rule", "verdict", "score")


def held_out(pages: DataFrame, rules=RULES, *, threshold: float = 0.5, folds: int = 5) -> DataFrame:
    """(label, blocked, rows) over the hosts of one fold, judged by trees and statistics of the other folds' hosts."""
    base = label_by_words(with_lexical(with_rule(with_parts(pages.select("page_id", "url")), rules))).filter("label is not null")
    out = F.pmod(F.xxhash64("host"), F.lit(folds)) == 0
    full = with_statistics(base, base.filter(~out))
    score = train(full.filter(~out)).as_column(FEATURES)
    judged = full.filter(out).select("label", (score >= threshold).alias("blocked"))
    return judged.groupBy("label", "blocked").agg(F.count(F.lit(1)).alias("rows"))
