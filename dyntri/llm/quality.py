"""Quality rules with host-level verdicts, in DataFrame functions only.

Every document gets measures and a severity: the largest of its measures, each divided by its rule's limit. Hosts (the
``source`` column) gather how many of their documents pass a limit; these rates are shrunk by a beta prior fitted to
all hosts by moments. A host's shrunk rate, held against the prior, sets the severity that its documents may have: better
hosts than most are given more room, worse ones less. A document without a fault stays, whatever its host.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from . import storage

BLANK = " \t\n\x0b\f\r"
SYMBOLS = "#*$%&|<>"
WINDOW = 5
MIN_WORDS = 10
MAX_REPEAT_PERCENT = 20
#: Limits of the rules: symbols per word, share of repeated lines, share of capitals, mean word length.
LIMITS = {"symbols": 0.2, "dup_lines": 0.5, "capitals": 0.4, "word_chars": 15.0}
#: Least and most strength of the prior in documents, severity that a standard deviation of it is worth, least and most severity allowed.
STRENGTH, ROOM, ALLOWED = (1.0, 10_000.0), 0.25, (0.75, 2.0)

MEASURES = ("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words")


def _less(text: Column, characters: str) -> Column:
    return F.length(F.translate(text, characters, ""))


def measured(docs: DataFrame) -> DataFrame:
    """docs with ``_q``, a struct of the measures and severity; no shuffle. Write it before filtering or grouping by
    ``_q``: the optimizer would else copy its expressions into each use.

    docs: text, source, any further columns, of whatever names (an earlier ``_q`` gives way). Words are runs of anything
    but space and \\x09-\\x0D; a null text has none. Repeated rows are measured each; an empty table gives none. Windows are
    told apart by 64-bit hashes.
    """
    text = F.coalesce(F.col("text"), F.lit(""))
    flat = F.translate(text, BLANK[1:], " " * (len(BLANK) - 1))
    lines = F.filter(F.split(text, "\n"), lambda x: F.length(F.trim(F.translate(x, BLANK[1:], " " * (len(BLANK) - 1)))) > 0)
    step = docs.select(storage.packed(docs), F.array_remove(F.split(flat, " "), "").alias("_w"), lines.alias("_l"), _less(text, BLANK).alias("_chars"), F.length(text).alias("_len"),
                       (F.length(text) - _less(text, SYMBOLS)).alias("_symbols"), (F.length(text) - F.length(F.regexp_replace(text, "[A-Z]", ""))).alias("_capitals"))
    n = F.size("_w")
    step = step.select("row", "_chars", "_len", "_symbols", "_capitals", n.alias("_n"), F.size("_l").alias("_lines"), (F.size("_l") - F.size(F.array_distinct("_l"))).alias("_dups"), F.transform("_w", lambda w: F.xxhash64(w)).alias("_h"))
    h = F.col("_h")
    windows = F.when(F.col("_n") >= WINDOW, F.transform(F.sequence(F.lit(0), F.col("_n") - WINDOW), lambda i: F.xxhash64(*[h[i + k] for k in range(WINDOW)])))
    step = step.select("row", "_chars", "_len", "_symbols", "_capitals", "_n", "_lines", "_dups", windows.alias("_g"))
    # most texts repeat no window; only the others are sorted
    repeats = F.size("_g") > F.size(F.array_distinct("_g"))
    spots = F.when(repeats, F.array_sort(F.transform("_g", lambda x, i: F.struct(x.alias("x"), i.alias("i")))))
    rest = ["_chars", "_len", "_symbols", "_capitals", "_n", "_lines", "_dups"]
    step = step.select("row", *rest, spots.alias("_s"))
    s, last = F.col("_s"), F.size("_s") - 1
    same = F.filter(
        F.sequence(F.lit(0), last),
        lambda k: F.when(k > 0, s[F.greatest(k - 1, F.lit(0))]["x"] == s[k]["x"]).otherwise(False) | F.when(k < last, s[F.least(k + 1, last)]["x"] == s[k]["x"]).otherwise(False),
    )
    step = step.select("row", *rest, F.when(s.isNotNull(), F.array_sort(F.transform(same, lambda k: s[k]["i"]))).alias("_p"))
    p = F.col("_p")
    gaps = F.aggregate(F.sequence(F.lit(0), F.size("_p") - 1), F.lit(0), lambda sum_, k: sum_ + F.when(k > 0, F.least(F.lit(WINDOW), p[k] - p[F.greatest(k - 1, F.lit(0))])).otherwise(WINDOW))
    covered = F.when(p.isNotNull(), gaps).otherwise(0)
    words = F.greatest(F.col("_n"), F.lit(1))
    severity = F.greatest(
        F.col("_symbols") / words / LIMITS["symbols"], F.col("_dups") / F.greatest("_lines", F.lit(1)) / LIMITS["dup_lines"],
        F.col("_capitals") / F.greatest("_len", F.lit(1)) / LIMITS["capitals"], F.col("_chars") / words / LIMITS["word_chars"],
    )
    failed = (F.col("_n") < MIN_WORDS) | (100 * covered > MAX_REPEAT_PERCENT * F.col("_n"))
    values = dict(zip(MEASURES, (F.col("_n"), F.col("_chars"), F.col("_symbols"), F.col("_dups"), covered)))
    measures = F.struct(*[v.cast("long").alias(k) for k, v in values.items()], severity.alias("severity"), failed.alias("base_failed")).alias("_q")
    return step.select(*[F.col("row")[c].alias(c) for c in docs.columns if c != "_q"], measures)


def host_verdicts(rows: DataFrame) -> DataFrame:
    """(source, n_docs, n_failed, rate, allowed) from measured rows; a null source is a host of its own, no rows give none.

    Failures: base failures and severities over 1. The prior is beta(m k, (1 - m) k): m is the rate of all documents, and
    k = m (1 - m) / v - 1 within STRENGTH, v being the variance of hosts' rates around m (hosts weighted by documents)
    less what chance alone gives hosts of these sizes. A host is allowed a severity of 1, less ROOM for each of the prior's
    standard deviations that its shrunk rate lies above m, or more below it, within ALLOWED. One partial aggregation by
    host, then one over hosts to a single row.
    """
    bad = (F.col("_q.base_failed") | (F.col("_q.severity") > 1)).cast("long")
    hosts = rows.groupBy("source").agg(F.count(F.lit(1)).alias("n_docs"), F.sum(bad).alias("n_failed"))
    sums = hosts.agg(F.sum("n_docs").alias("_n"), F.sum("n_failed").alias("_b"), F.sum(F.col("n_failed") * F.col("n_failed") / F.col("n_docs")).alias("_s"), F.count(F.lit(1)).alias("_hosts"))
    m = F.col("_m")
    spread = F.col("_s") / F.col("_n") - m * m - m * (1 - m) * (F.col("_hosts") - 1) / F.col("_n")
    prior = sums.withColumn("_m", F.col("_b") / F.col("_n")).withColumn("_v", spread)
    strength = F.when(F.col("_v") > 0, F.greatest(F.lit(STRENGTH[0]), F.least(F.lit(STRENGTH[1]), m * (1 - m) / F.col("_v") - 1))).otherwise(STRENGTH[1])
    prior = prior.select("_m", strength.alias("_k"))
    known = hosts.join(F.broadcast(prior), F.lit(True)).withColumn("rate", (F.col("n_failed") + m * F.col("_k")) / (F.col("n_docs") + F.col("_k")))
    above = F.when(m * (1 - m) > 0, (F.col("rate") - m) / F.sqrt(m * (1 - m) / (F.col("_k") + 1))).otherwise(0.0)
    return known.select("source", "n_docs", "n_failed", "rate", F.greatest(F.lit(ALLOWED[0]), F.least(F.lit(ALLOWED[1]), 1 - ROOM * above)).alias("allowed"))


def judged(rows: DataFrame, hosts: DataFrame) -> DataFrame:
    """Measured rows with ``_kept``: no base failure and a severity within what the host is allowed; 1 for unknown hosts.

    Columns may have any names (an earlier ``_kept`` gives way). hosts has one row per source. Spark broadcasts it only
    below its own size limit; beyond, both sides are shuffled by source and large sources split.
    """
    verdicts = hosts.select(F.col("source").alias("host"), "allowed")
    joined = rows.select(storage.packed(rows)).join(verdicts, F.col("row")["source"].eqNullSafe(F.col("host")), "left")
    q = F.col("row")["_q"]
    kept = ~q["base_failed"] & (q["severity"] <= F.coalesce("allowed", F.lit(1.0)))
    return joined.select(*[F.col("row")[c].alias(c) for c in rows.columns if c != "_kept"], kept.alias("_kept"))


def kept_rows(docs: DataFrame) -> DataFrame:
    """docs without the rejected rows, with docs' columns, whatever their names; repeated rows stay or go together.

    Measures are written once, without texts, under a 128-bit key of the row's id, source and text; rejected keys
    are then taken away from docs, which are shuffled once by key. An empty table gives none.
    """
    parts = [F.col("doc_id").isNull(), F.col("doc_id"), F.col("source").isNull(), F.col("source"), F.col("text").isNull(), F.col("text")]
    keys = [F.xxhash64(F.lit(seed), *parts).alias(f"key{seed}") for seed in (1, 2)]
    rows = storage.saved(measured(docs.select("source", "text", *keys)).drop("text"), "measured")
    found = judged(rows, storage.saved(host_verdicts(rows), "hosts"))
    rejected = found.where(~F.col("_kept")).select("key1", "key2").distinct()
    return docs.select(storage.packed(docs), *keys).join(rejected, ["key1", "key2"], "left_anti").select("row.*")
