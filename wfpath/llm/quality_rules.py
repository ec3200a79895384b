"""Operator 2: quality rules with risk-controlled thresholds.

Every rule is a ratio of a text's counts that is compared with a cutoff.  The cutoffs aren't set by
hand.  The labelled documents that pass the base rule are dealt into two parts by a hash of their id:

1. on the tuning part, with all of its rows, a *path* is laid: a sequence of settings of all rules, each
   sharper than the one before, the steps that catch the most bad documents for a good one first;
2. on the calibration part, with all of its rows, the path is followed in each stratum (language)
   from the mildest setting on, and left at the first one for which an exact binomial test can't
   prove that it rejects at most ``risk`` of the stratum's good documents.  The last proven setting
   is taken.

Testing in an order that was fixed before needs no correction over the settings; over strata the
error ``delta`` is divided (Bonferroni).  So with probability 1 - delta the rules reject at most
``risk`` of the good documents of every stratum.  A stratum with too few labels to prove that gets
no rule: with 5 % risk and four strata the first setting needs 86 good labels.

Nulls and edge cases: a null or empty text has all counts 0 and fails the base rule; a null
stratum is a stratum of its own; a document without a label, or with a null one, is not used for
the path or for calibration; without usable labels no rule is set; repeated rows are judged one by one; extra columns pass through ``filtered``.
"""

from __future__ import annotations

import math

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from wfpath.llm import shared, textstats

STATS = [*textstats.BASE, "n_lines", "n_upper", "n_alpha", "n_bang", "n_digits", "n_distinct_words", "n_bytes"]
#: rule -> (numerator, denominator, sign): sign 1 rejects high ratios, -1 low ones.
RULES = {
    "symbols": ("n_symbols", "n_words", 1),
    "capitals": ("n_upper", "n_alpha", 1),
    "exclamations": ("n_bang", "n_words", 1),
    "digits": ("n_digits", "n_bytes", 1),
    "repeated_lines": ("n_dup_lines", "n_lines", 1),
    "repeated_words": ("n_repeat_words", "n_words", 1),
    "long_words": ("word_chars", "n_words", 1),
    "few_words": ("n_distinct_words", "n_words", -1),
}
#: One part of how many the path is laid on, and how many times a step's share of bad documents has to be that of good ones.
FOLDS, WORTH = 4, 5.0
#: Candidate cutoffs, from mild to sharp.
GRIDS = {name: [round(1.5 ** -k, 6) for k in range(14)] for name in RULES}
GRIDS["exclamations"] = GRIDS["symbols"] = [round(2.0 * 1.5 ** -k, 6) for k in range(14)]
GRIDS["long_words"] = [round(20 - 0.75 * k, 6) for k in range(16)]
GRIDS["few_words"] = [round(0.05 * (k + 1), 6) for k in range(14)]


def binomial_tail(k: int, n: int, p: float) -> float:
    """P(Bin(n, p) <= k), summed from logarithms."""
    if k >= n:
        return 1.0
    i = np.arange(k + 1)
    log_choose = math.lgamma(n + 1) - np.array([math.lgamma(x + 1) + math.lgamma(n - x + 1) for x in i])
    logs = log_choose + i * math.log(p) + (n - i) * math.log1p(-p)
    top = logs.max()
    return float(min(1.0, math.exp(top) * np.exp(logs - top).sum()))


def proven(good: int, rejected: list[int], risk: float, delta: float) -> int:
    """How many settings of a path, from its start, are proven to reject at most ``risk`` of the good documents."""
    for i, r in enumerate(rejected):
        if good == 0 or r > risk * good or binomial_tail(r, good, risk) > delta:
            return i
    return len(rejected)


def path_of(grouped: dict[tuple[int, ...], tuple[int, int]], worth: float = WORTH) -> list[dict[str, float]]:
    """A path of settings from how many (bad, good) tuning rows cross how many cutoffs of each rule's grid.

    Grids go from mild to sharp, so a row that crosses n of a grid's cutoffs crosses the last n.
    Each step sharpens one rule to the cutoff of its grid that catches the most bad documents for a
    good one (counted as shares of both, with one good document added), as long as a bad one is caught and it is worth it.
    """
    names = list(RULES)
    first = np.array([len(GRIDS[r]) for r in names]) - np.array(list(grouped), int).reshape(-1, len(names))
    bad, good = np.array(list(grouped.values()), np.int64).reshape(-1, 2).T
    caught, setting, path = np.zeros(len(first), bool), dict.fromkeys(names, -1), []
    n_bad, n_good = max(1, int(bad.sum())), max(1, int(good.sum()))
    while True:
        best = None
        for i, r in enumerate(names):
            for k in range(setting[r] + 1, len(GRIDS[r])):
                new = (first[:, i] <= k) & ~caught
                gain, cost = bad[new].sum() / n_bad, (good[new].sum() + 1) / n_good
                if gain and gain >= worth * (cost - 1 / n_good) and (best is None or gain / cost > best[0]):
                    best = (gain / cost, r, k)
        if best is None:
            return path
        _, r, k = best
        setting[r] = k
        caught |= first[:, names.index(r)] <= k
        path.append({name: GRIDS[name][at] for name, at in setting.items() if at >= 0})


def laid(ratios: np.ndarray, bad: np.ndarray, worth: float = WORTH) -> list[dict[str, float]]:
    """The path of rows at hand (a column for each rule, NaN where it doesn't apply)."""
    crossed = [sum(((x > c) if RULES[r][2] > 0 else (x < c)).astype(int) for c in GRIDS[r]) for r, x in zip(RULES, ratios.T, strict=True)]
    grouped: dict[tuple[int, ...], tuple[int, int]] = {}
    for key, b in zip(zip(*(x.tolist() for x in crossed), strict=True), bad.tolist(), strict=True):
        n_bad, n_good = grouped.get(key, (0, 0))
        grouped[key] = (n_bad + b, n_good + (not b))
    return path_of(grouped, worth)


def ratio(rule: str):
    over, under, _ = RULES[rule]
    return F.when(F.col(under) > 0, F.col(over) / F.col(under)).otherwise(F.lit(None).cast("double"))


def rejects(rule: str, cutoff):
    """Whether the rule rejects at this cutoff; a text without the denominator is not rejected."""
    sign = RULES[rule][2]
    r = ratio(rule)
    return F.coalesce(r > cutoff if sign > 0 else r < cutoff, F.lit(False))


def measured(docs: DataFrame, id_col: str = "doc_id", stratum: str = "lang") -> DataFrame:
    """The counts of every whole text: one row a document."""
    keep = docs.select(F.col(id_col).alias("_id"), F.col(stratum).cast("string").alias("_stratum"), F.col("text").cast("string").alias("text"))
    schema = "_id " + keep.schema["_id"].dataType.simpleString() + ", _stratum string, " + ", ".join(f"{x} long" for x in STATS)
    return keep.mapInArrow(lambda it: textstats.by_batch(it, ["_id", "_stratum"], STATS), schema)


def base_rule():
    return (F.col("n_words") < 10) | (100 * F.col("n_repeat_words") > 20 * F.col("n_words"))


def tuned(labelled: DataFrame, worth: float = WORTH) -> list[dict[str, float]]:
    """The path, from all rows: counted by how many cutoffs of each grid they cross, as nothing else of a row matters."""
    crossed = [sum((rejects(r, c).cast("int") for c in GRIDS[r]), F.lit(0)).alias(r) for r in RULES]
    rows = labelled.select("_bad", *crossed).groupBy(*RULES).agg(F.sum(F.col("_bad").cast("long")).alias("bad"), F.sum((~F.col("_bad")).cast("long")).alias("good")).orderBy(*RULES).collect()
    return path_of({tuple(row[r] for r in RULES): (row["bad"], row["good"]) for row in rows}, worth)


def calibrated(stats: DataFrame, labels: DataFrame, risk: float = 0.05, delta: float = 0.05, id_col: str = "doc_id", path: list[dict[str, float]] | None = None) -> DataFrame:
    """The cutoffs: rows (stratum, rule, cutoff, good, rejected), for the rules of the last proven setting of each stratum.

    An id with labels of both kinds counts as bad.  A path that is given is tested on all labelled rows.
    """
    known = labels.where(F.col("quality").isin(0, 1)).groupBy(F.col(id_col).alias("_label_id")).agg((F.min("quality") == 0).alias("_bad"))
    labelled = stats.where(~base_rule()).join(known, stats["_id"] == known["_label_id"])
    fold = F.pmod(F.xxhash64(F.col("_id").cast("string")), F.lit(FOLDS)) == 0
    if path is None:
        path = tuned(labelled.where(fold))
        labelled = labelled.where(~fold)
    # how many settings leave the document: a rule's cutoffs only get sharper along the path
    first = [F.lit(len(path))]
    for r in RULES:
        at = [i for i, setting in enumerate(path) if r in setting]
        if at:
            crossed = [F.when(rejects(r, path[i][r]), F.lit(i)) for i in at if i == at[0] or path[i][r] != path[i - 1][r]]
            first.append(F.coalesce(*crossed, F.lit(len(path))))
    level = F.least(*first) if len(first) > 1 else first[0]
    held = labelled.where("NOT _bad").select("_stratum", level.alias("_level"))
    counted = held.groupBy("_stratum").agg(F.count(F.lit(1)).alias("good"), F.array(*[F.sum((F.col("_level") <= i).cast("long")) for i in range(len(path))]).cast("array<bigint>").alias("rejected"))
    n_strata = max(1, stats.select("_stratum").distinct().count())

    def choose(batches):
        for pdf in batches:
            rows = []
            for stratum, good, rejected in zip(pdf["_stratum"], pdf["good"], pdf["rejected"], strict=True):
                n = proven(int(good), [int(x) for x in rejected], risk, delta / n_strata)
                rows += [(stratum, r, cut, int(good), int(rejected[n - 1])) for r, cut in (path[n - 1] if n else {}).items()]
            yield pd.DataFrame(rows, columns=["stratum", "rule", "cutoff", "good", "rejected"])

    return counted.mapInPandas(choose, "stratum string, rule string, cutoff double, good long, rejected long")


def judged(stats: DataFrame, cutoffs: DataFrame) -> DataFrame:
    """Adds base_failed, kept and failed_rules to the statistics."""
    wide = cutoffs.groupBy("stratum").pivot("rule", list(RULES)).agg(F.first("cutoff"))
    wide = wide.select(F.col("stratum").alias("_s"), *[F.col(r).alias(f"_cut_{r}") for r in RULES])
    x = stats.join(wide, stats["_stratum"].eqNullSafe(wide["_s"]), "left")
    failed = F.filter(F.array(*[F.when(rejects(r, F.col(f"_cut_{r}")), F.lit(r)) for r in RULES]), lambda v: v.isNotNull())
    return x.withColumn("base_failed", base_rule()).withColumn("failed_rules", failed).withColumn("kept", ~F.col("base_failed") & (F.size("failed_rules") == 0)).drop("_s", *[f"_cut_{r}" for r in RULES])


def apply_rules(docs: DataFrame, labels: DataFrame, risk: float = 0.05, delta: float = 0.05) -> DataFrame:
    """Statistics and verdict of every document."""
    stats = shared.materialised(measured(docs))
    return judged(stats, calibrated(stats, labels, risk, delta))


def filtered(docs: DataFrame, labels: DataFrame, risk: float = 0.05, delta: float = 0.05) -> DataFrame:
    """The documents that the rules keep, all columns as they were (a repeated id stays if all its rows pass)."""
    bad = apply_rules(docs, labels, risk, delta).where(~F.col("kept")).select(F.col("_id").alias("_rejected")).distinct()
    return docs.join(bad, docs["doc_id"].eqNullSafe(bad["_rejected"]), "left_anti")


def op2_quality_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    """doc_id, n_words, the base counts, base_failed, kept, failed_rules of every document."""
    out = apply_rules(shared.load(spark, sf_dir, "documents").select("doc_id", "text", "lang"), shared.load(spark, sf_dir, "labels"))
    return out.select(F.col("_id").alias("doc_id"), *textstats.BASE, "base_failed", "kept", F.concat_ws(",", "failed_rules").alias("failed_rules"))
