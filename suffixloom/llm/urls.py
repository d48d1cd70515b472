"""URL filters: path rules, and gradient-boosted trees on lexical features, with column functions only.

Features are small whole numbers. Trees are grown level by level: one aggregation sums gradients and weights for
each node, feature and bin over the labelled sample, and the driver picks splits from that bounded table. Gradients are
rounded to whole numbers of 1e-6, so that sums and splits don't depend on partitions. A trained forest is a sum of CASE
expressions, evaluated where the rows are.

Defined results: a null url, or one without "://", has empty host and path and fits no rule; without labelled rows the
forest has no trees and allows; repeated rows get repeated results; only the named columns are read.
"""

from __future__ import annotations

import math
from dataclasses import dataclass, field

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import maybe_broadcast, stored

#: Rows of the labelled sample at most (those with the smallest hashes of their URL).
SAMPLE_ROWS = 20_000
BINS = 16
#: Folds in which the labels of suffixes are counted.
FOLDS = 5
FEATURES = ("length", "depth", "digits", "entropy", "params", "suffix_urls", "suffix_rate")


def host_and_path(url: Column) -> tuple[Column, Column]:
    pattern = r"(?s)^.*?://([^/?#]*)([^?#]*)"
    take = lambda i: F.coalesce(F.regexp_extract(url, pattern, i), F.lit(""))
    return F.translate(take(1), "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"), take(2)


@dataclass(frozen=True)
class PathRule:
    rule: str  # host/path-prefix
    verdict: str


def fitting_rule(host: Column, path: Column, rules: list[PathRule]) -> Column:
    """Struct (rule, verdict) of the longest rule that fits; null if none does."""
    out = F.lit(None).cast("struct<rule: string, verdict: string>")
    for r in sorted(rules, key=lambda r: (len(r.rule), r.rule)):
        name, _, prefix = r.rule.partition("/")
        fits = ((host == name) | host.endswith("." + name)) & path.startswith("/" + prefix)
        out = F.when(fits, F.struct(F.lit(r.rule).alias("rule"), F.lit(r.verdict).alias("verdict"))).otherwise(out)
    return out


def entropy(text: Column) -> Column:
    """Shannon entropy of the characters, in bits; 0 for an empty text."""
    chars = F.split(text, "")
    total = F.length(text)
    counted = F.transform(F.array_distinct(chars), lambda c: F.length(text) - F.length(F.replace(text, c)))
    bits = F.aggregate(counted, F.lit(0.0), lambda s, n: s - F.when(n > 0, n / total * F.log2(n / total)).otherwise(0.0))
    return F.when(total > 0, bits).otherwise(0.0)


def clipped(x: Column) -> Column:
    return F.least(F.greatest(F.coalesce(x, F.lit(0)).cast("int"), F.lit(0)), F.lit(BINS - 1))


def lexical_features(pages: DataFrame, id_col: str, url_col: str) -> DataFrame:
    """id, url, host, path, suffix and binned features but for those of the suffix."""
    url = F.coalesce(F.col(url_col).cast("string"), F.lit(""))
    host, path = host_and_path(url)
    base = pages.select(F.col(id_col).alias("id"), url.alias("url"), host.alias("host"), path.alias("path"))
    n = F.greatest(F.length("url"), F.lit(1))
    count = lambda c: F.length("url") - F.length(F.replace(F.col("url"), F.lit(c)))
    return base.select(
        "*",
        F.substring_index("host", ".", -2).alias("suffix"),
        clipped(F.length("url") / 8).alias("length"),
        clipped(F.length("path") - F.length(F.replace(F.col("path"), F.lit("/")))).alias("depth"),
        clipped(F.length(F.regexp_replace("url", "[^0-9]", "")) * BINS / n).alias("digits"),
        clipped(entropy(F.col("url")) * 3).alias("entropy"),
        clipped(F.when(F.contains("url", F.lit("?")), 1 + count("&")).otherwise(0)).alias("params"),
    )


@dataclass
class Forest:
    """Trees of splits {node: (feature, last bin to the left)} and leaf values; nodes as in a heap, root 1."""

    depth: int
    rate: float
    base: float = 0.0
    trees: list[tuple[dict[int, tuple[str, int]], dict[int, float]]] = field(default_factory=list)

    def node(self, splits: dict[int, tuple[str, int]], at: int = 1) -> Column:
        if at not in splits:
            return F.lit(at)
        name, last = splits[at]
        return F.when(F.col(name) <= last, self.node(splits, 2 * at)).otherwise(self.node(splits, 2 * at + 1))

    def value(self, splits: dict, leaves: dict[int, float], at: int = 1) -> Column:
        if at not in splits:
            return F.lit(float(leaves.get(at, 0.0)))
        name, last = splits[at]
        return F.when(F.col(name) <= last, self.value(splits, leaves, 2 * at)).otherwise(self.value(splits, leaves, 2 * at + 1))

    def score(self) -> Column:
        """Log-odds of label 1."""
        out = F.lit(self.base)
        for splits, leaves in self.trees:
            out = out + self.value(splits, leaves)
        return out


def best_split(bins: dict[tuple[str, int], tuple[float, float]], least_weight: float, shrink: float = 1.0) -> tuple[str, int] | None:
    """The split of most gain over (feature, bin) -> (gradient, weight)."""
    best, gain = None, 1e-9
    for name in FEATURES:
        own = [bins.get((name, b), (0.0, 0.0)) for b in range(BINS)]
        g_all, h_all = sum(g for g, _ in own), sum(h for _, h in own)
        g = h = 0.0
        for b in range(BINS - 1):
            g, h = g + own[b][0], h + own[b][1]
            if h >= least_weight and h_all - h >= least_weight:
                new = g * g / (h + shrink) + (g_all - g) ** 2 / (h_all - h + shrink) - g_all * g_all / (h_all + shrink)
                if new > gain:
                    best, gain = (name, b), new
    return best


def train(sample: DataFrame, trees: int = 8, depth: int = 3, rate: float = 0.3, least_weight: float = 4.0) -> Forest:
    """Fit on a stored sample with the columns FEATURES and label (0 or 1): depth + 1 small aggregations a tree."""
    forest = Forest(depth, rate)
    n, ones = sample.agg(F.count("*"), F.sum("label")).first()
    if not n:
        return forest
    share = min(max(ones / n, 1e-3), 1 - 1e-3)
    forest.base = math.log(share / (1 - share))
    for _ in range(trees):
        p = 1 / (1 + F.exp(-forest.score()))
        whole = lambda x: F.round(x * 1_000_000).cast("long")
        rows = sample.select(*FEATURES, whole(F.col("label") - p).alias("g"), whole(p * (1 - p)).alias("h"))
        splits: dict[int, tuple[str, int]] = {}
        frontier, sums = [1], {}
        for level in range(depth + 1):
            at = rows.withColumn("node", forest.node(splits))
            if level == depth or not frontier:
                break
            long = at.select("node", "g", "h", F.explode(F.array(*(F.struct(F.lit(f).alias("feature"), F.col(f).alias("bin")) for f in FEATURES))).alias("x"))
            table = long.groupBy("node", "x.feature", "x.bin").agg(F.sum("g").alias("g"), F.sum("h").alias("h")).collect()  # nodes x features x bins at most
            sums = {}
            for r in table:
                sums.setdefault(r["node"], {})[r["feature"], r["bin"]] = (r["g"] / 1e6, r["h"] / 1e6)
            new = {k: s for k in frontier if k in sums and (s := best_split(sums[k], least_weight))}
            splits |= new
            frontier = [c for k in new for c in (2 * k, 2 * k + 1)]
        leaves = {r["node"]: rate * (r["g"] / 1e6) / (r["h"] / 1e6 + 1.0) for r in rows.withColumn("node", forest.node(splits)).groupBy("node").agg(F.sum("g").alias("g"), F.sum("h").alias("h")).collect()}
        forest.trees.append((splits, leaves))
    return forest


def with_suffix_statistics(features: DataFrame, statistics: DataFrame) -> DataFrame:
    """Adds suffix_urls and suffix_rate; a hot suffix is split by AQE's skew join where the table isn't broadcast."""
    return features.join(maybe_broadcast(statistics, 64), "suffix", "left").withColumns({"suffix_urls": clipped(F.col("suffix_urls")), "suffix_rate": clipped(F.col("suffix_rate"))})


def rate_bin(ones: Column, n: Column, share: float) -> Column:
    """A bin of the share of label 1, drawn towards the share of all labelled rows where there are few."""
    return (F.coalesce(ones + 5 * F.lit(share), F.lit(5.0 * share)) / F.coalesce(n + 5, F.lit(5)) * BINS).cast("int")


@dataclass
class UrlModel:
    """A forest, what it knows of suffixes, and the labelled rows (features, label, fold) that it was fitted on."""

    forest: Forest
    statistics: DataFrame
    training: DataFrame

    def scored(self, features: DataFrame) -> DataFrame:
        return with_suffix_statistics(features, self.statistics).withColumn("score", 1 / (1 + F.exp(-self.forest.score())))


def fit_urls(features: DataFrame, labelled: DataFrame, sample_rows: int = SAMPLE_ROWS, only: Column | None = None) -> UrlModel:
    """The forest is fitted on at most sample_rows labelled rows; suffixes are counted over all rows of features.

    What a suffix's labels say of a training row comes from the other folds' rows only, so that no row's feature holds its
    own label. only: a condition on fold (0 to FOLDS - 1) for the rows to fit on.
    """
    picked = labelled.select("url", F.col("label").cast("int").alias("label")).where("url is not null and label in (0, 1)").orderBy(F.xxhash64("url"), "url", "label").limit(sample_rows)
    picked = picked.withColumn("fold", F.pmod(F.xxhash64("url", F.lit(1)), F.lit(FOLDS)).cast("int"))
    whole = lexical_features(picked.select("url").distinct().withColumn("row", F.lit(0)), "row", "url").join(picked, "url")
    whole = stored(whole.select("suffix", *FEATURES[:5], "label", "fold"), "urls-sample")
    sample = whole if only is None else whole.where(only)
    n, ones = sample.agg(F.count("*"), F.sum("label")).first()
    share = ones / n if n else 0.5
    counts = features.groupBy("suffix").agg(F.floor(F.log2(F.count("*"))).alias("suffix_urls"))
    by_fold = sample.groupBy("suffix", "fold").agg(F.sum("label").alias("ones"), F.count("*").alias("n"))
    totals = by_fold.groupBy("suffix").agg(F.sum("ones").alias("all_ones"), F.sum("n").alias("all_n"))
    statistics = stored(counts.join(totals, "suffix", "full").select("suffix", F.col("suffix_urls").cast("int"), rate_bin(F.col("all_ones"), F.col("all_n"), share).alias("suffix_rate")), "urls-suffixes")
    out_of_fold = by_fold.join(totals, "suffix").select("suffix", "fold", rate_bin(F.col("all_ones") - F.col("ones"), F.col("all_n") - F.col("n"), share).alias("own_rate"))
    training = with_suffix_statistics(sample, statistics).join(out_of_fold, ["suffix", "fold"]).withColumn("suffix_rate", clipped(F.col("own_rate")))
    return UrlModel(train(stored(training.select(*FEATURES, "label"), "urls-training")), statistics, whole)


def held_out_auc(features: DataFrame, labelled: DataFrame, sample_rows: int = SAMPLE_ROWS, fold: int = 0) -> float | None:
    """Area under the curve on one fold of a model fitted on the others: 0.5 says that URLs tell nothing of their labels.

    Scores are counted in a thousand bins, so what comes to the driver is bounded. None if the fold lacks a label.
    """
    model = fit_urls(features, labelled, sample_rows, F.col("fold") != fold)
    held = model.scored(model.training.where(F.col("fold") == fold))
    bins = held.groupBy(F.round(F.col("score") * 1000).cast("int").alias("bin")).agg(F.sum("label").alias("ones"), F.count("*").alias("n")).orderBy("bin").collect()
    ones, zeros, below, area = sum(r["ones"] for r in bins), sum(r["n"] - r["ones"] for r in bins), 0, 0.0
    for r in bins:
        area += r["ones"] * (below + (r["n"] - r["ones"]) / 2)
        below += r["n"] - r["ones"]
    return area / (ones * zeros) if ones and zeros else None


def judge_urls(pages: DataFrame, labelled: DataFrame, rules: list[PathRule], id_col: str = "page_id", url_col: str = "url", sample_rows: int = SAMPLE_ROWS, threshold: float = 0.5) -> DataFrame:
    """page_id, host, path, rule, verdict, score. labelled: (url, label), 1 for URLs to allow.

    A URL without a rule is allowed if its score, the forest's probability of label 1, reaches threshold: 0.5 where a wrong
    block costs as much as a wrong permission, and cost of permission / (both costs) in general.
    """
    features = lexical_features(pages, id_col, url_col)
    judged = fit_urls(features, labelled, sample_rows).scored(features)
    fit = fitting_rule(F.col("host"), F.col("path"), rules)
    judged = judged.select(F.col("id").alias("page_id"), "host", "path", fit.alias("fit"), "score")
    return judged.select("page_id", "host", "path", F.col("fit.rule").alias("rule"), F.coalesce("fit.verdict", F.when(F.col("score") >= threshold, "allow").otherwise("block")).alias("verdict"), "score")
