"""Quality classifier: a sparse ensemble of conjunctive rules, compiled to Spark columns.

Statistics of each text are Spark expressions. Shallow trees over a labelled sample give rules (every
path is a conjunction of thresholds); a lasso logistic regression keeps few of them; the kept rules become
one column expression, so scoring never leaves the JVM.
"""

from __future__ import annotations

from dataclasses import dataclass, field
from functools import reduce

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import fresh

#: Bound of the labelled sample (rows of smallest id hash); a fit needs no more.
SAMPLE_ROWS = 20_000


def statistics(text: str = "text") -> dict[str, Column]:
    """Numbers that tell prose from tables, loops, shouting and line noise; null counts as empty."""
    t = F.coalesce(F.col(text), F.lit(""))
    n = F.greatest(F.length(t), F.lit(1)).cast("double")
    words = F.filter(F.split(t, r"\s+"), lambda w: w != "")
    lines = F.filter(F.split(t, "\n"), lambda x: F.trim(x) != "")
    n_words = F.greatest(F.size(words), F.lit(1)).cast("double")
    n_lines = F.greatest(F.size(lines), F.lit(1)).cast("double")
    rate = lambda pattern: F.regexp_count(t, F.lit(pattern)) / n
    without = lambda s, c: F.replace(s, F.lit(c), F.lit(""))
    share = lambda *cs: (F.octet_length(t) - F.octet_length(reduce(without, cs, t))) / n  # noqa: E731  bytes are characters here
    return {
        "log_chars": F.log1p(F.length(t).cast("double")),
        "log_words": F.log1p(F.size(words).cast("double")),
        "word_length": F.length(t) / n_words,
        "longest_word": F.log1p(F.coalesce(F.array_max(F.transform(words, lambda w: F.length(w))), F.lit(0)).cast("double")),
        "distinct_words": F.size(F.array_distinct(words)) / n_words,
        "distinct_lines": F.size(F.array_distinct(lines)) / n_lines,
        "line_length": F.log1p(n / n_lines),
        "letters": rate(r"\p{L}"),
        "capitals": rate(r"\p{Lu}"),
        "digits": rate(r"[0-9]"),
        "symbols": rate(r"[#$%&*^~=+_<>{}\[\]@/\\|]"),
        "bars": share("|"),
        "shouts": share("!"),
        "stops": share(".", "?"),
        "commas": share(","),
    }


@dataclass
class RuleModel:
    """Rules are tuples of (statistic, is_greater, threshold); weights in log odds."""

    intercept: float = 0.0
    rules: list[tuple[tuple[tuple[str, bool, float], ...], float]] = field(default_factory=list)

    def column(self, prefix: str = "q_") -> Column:
        """The score as an expression over columns named prefix + statistic."""
        total = F.lit(float(self.intercept))
        for rule, w in self.rules:
            hit = F.lit(True)
            for name, more, cut in rule:
                hit = hit & ((F.col(prefix + name) > F.lit(cut)) if more else (F.col(prefix + name) <= F.lit(cut)))
            total = total + F.when(hit, F.lit(float(w))).otherwise(F.lit(0.0))
        return 1.0 / (1.0 + F.exp(-total))


def _tree(bins: np.ndarray, cuts: list[np.ndarray], y: np.ndarray, w: np.ndarray, features: np.ndarray, depth: int, rows: np.ndarray, path: tuple, out: set, least: float) -> None:
    """Grows one tree by Gini gain on binned features; every node's path joins ``out``."""
    if path:
        out.add(path)
    if depth == 0 or w[rows].sum() < 2 * least:
        return
    best = (1e-9, None, None)
    wt, wy = w[rows], w[rows] * y[rows]
    n, p = wt.sum(), wy.sum()
    base = p * (n - p) / n
    for f in features:
        m = len(cuts[f]) + 1
        a = np.cumsum(np.bincount(bins[rows, f], wt, m))[:-1]
        b = np.cumsum(np.bincount(bins[rows, f], wy, m))[:-1]
        if len(a):
            with np.errstate(divide="ignore", invalid="ignore"):
                gain = base - np.nan_to_num(b * (a - b) / a) - np.nan_to_num((p - b) * (n - a - p + b) / (n - a))
            gain[(a < least) | (n - a < least)] = -1
            k = int(gain.argmax())
            if gain[k] > best[0]:
                best = (gain[k], int(f), k)
    if best[1] is None:
        return
    _, f, k = best
    left = bins[rows, f] <= k
    for more, part in ((False, rows[left]), (True, rows[~left])):
        _tree(bins, cuts, y, w, features, depth - 1, part, (*path, (f, more, float(cuts[f][k]))), out, least)


def fit_rules(x: np.ndarray, y: np.ndarray, names: list[str], trees: int = 40, depth: int = 3, penalty: float = 2e-3, seed: int = 7) -> RuleModel:
    """Rules from bootstrap trees on random halves of the statistics, then lasso logistic weights by
    accelerated proximal gradient. One class only, or no rows: the constant prior (0.5 without rows)."""
    if not len(y) or y.min() == y.max():
        p = (y.sum() + 0.5) / (len(y) + 1.0)
        return RuleModel(float(np.log(p / (1 - p))))
    cuts = [np.unique(np.quantile(x[:, f], np.linspace(0, 1, 34)[1:-1])) for f in range(x.shape[1])]
    bins = np.stack([np.searchsorted(c, x[:, f], side="left") for f, c in enumerate(cuts)], axis=1)
    rng = np.random.default_rng(seed)
    found: set = set()
    balance = np.where(y == 1, 0.5 / y.mean(), 0.5 / (1 - y.mean()))
    for _ in range(trees):
        w = rng.poisson(1.0, len(y)) * balance
        features = rng.choice(x.shape[1], max(2, x.shape[1] // 2), replace=False)
        _tree(bins, cuts, y, w, features, depth, np.arange(len(y)), (), found, max(3.0, 0.002 * len(y)))
    rules = sorted(found, key=lambda r: (len(r), r))
    hit = np.stack([np.logical_and.reduce([(x[:, f] > c) if more else (x[:, f] <= c) for f, more, c in r]) for r in rules], axis=1).astype(float)
    _, first = np.unique(hit, axis=1, return_index=True)
    first.sort()
    rules, hit = [rules[i] for i in first], hit[:, first]
    mean = hit.mean(axis=0)
    size = np.maximum(hit.std(axis=0), 0.02)
    z = (hit - mean) / size
    step = 4.0 / max(np.linalg.norm(z, 2) ** 2 / len(y), 1e-9)
    beta, b0 = np.zeros(z.shape[1]), float(np.log(y.mean() / (1 - y.mean())))
    look, look0, t = beta.copy(), b0, 1.0
    for _ in range(800):
        p = 1 / (1 + np.exp(-np.clip(z @ look + look0, -40, 40)))
        g = p - y
        new = look - step * (z.T @ g) / len(y)
        new = np.sign(new) * np.maximum(np.abs(new) - step * penalty, 0)
        new0 = look0 - g.mean()
        t2 = (1 + np.sqrt(1 + 4 * t * t)) / 2
        look, look0 = new + (t - 1) / t2 * (new - beta), new0 + (t - 1) / t2 * (new0 - b0)
        beta, b0, t = new, new0, t2
    use = np.flatnonzero(np.abs(beta) > 1e-6)
    weight = beta[use] / size[use]
    named = [(tuple((names[f], bool(more), c) for f, more, c in rules[i]), float(v)) for i, v in zip(use, weight)]
    return RuleModel(float(b0 - (weight * mean[use]).sum()), named)


def fit(docs: DataFrame, labels: DataFrame, target: str = "quality", sample_rows: int = SAMPLE_ROWS) -> RuleModel:
    """Learns from labelled rows, at most ``sample_rows`` of smallest id hash. Null labels and ids go; an id
    labelled twice counts once, by its smallest label, and an id with several texts by one of them (the one of smallest hash), so
    no more than ``sample_rows`` rows reach the driver. Empty tables give the constant model."""
    chosen = (
        labels.select(F.col("doc_id").alias("lid"), F.col(target).cast("int").alias("y"))
        .where("lid is not null and y in (0, 1)").groupBy("lid").agg(F.min("y").alias("y"))
        .orderBy(F.xxhash64("lid"), "lid").limit(sample_rows)
    )
    picked = [(r["lid"], r["y"]) for r in chosen.collect()]
    if not picked:
        return RuleModel(0.0)
    small = docs.sparkSession.createDataFrame(picked, "lid long, y int")
    stats = statistics()
    texts = docs.select("doc_id", "text").join(F.broadcast(small), F.col("doc_id") == F.col("lid"))
    texts = texts.groupBy("lid").agg(F.min("y").alias("y"), F.min_by("text", F.xxhash64("text")).alias("text"))
    got = texts.select("y", *[c.alias(k) for k, c in stats.items()]).toPandas()
    got = got.sort_values(list(got.columns)).to_numpy(float)
    return fit_rules(got[:, 1:], got[:, 0], list(stats))


def score(docs: DataFrame, model: RuleModel, text: str = "text", names: tuple[str, str] = ("score", "predicted")) -> DataFrame:
    """Adds score and predicted (or other ``names``; columns so named are replaced) to every row; null and empty texts are
    scored like any other, repeated rows each on their own, an empty table gives an empty result. Statistics are computed once, in a step of their own, and dropped again."""
    stats, prefix = statistics(text), fresh(docs, "q_")
    with_stats = docs.select("*", *[c.cast("double").alias(prefix + k) for k, c in stats.items()])
    out = with_stats.withColumn(names[0], model.column(prefix))
    return out.withColumn(names[1], (F.col(names[0]) >= 0.5).cast("int")).drop(*[prefix + k for k in stats])


def held_out(doc_id: str = "doc_id") -> Column:
    return F.coalesce(F.crc32(F.col(doc_id).cast("string")) % 3 == 1, F.lit(False))


def quality_query(docs: DataFrame, labels: DataFrame) -> DataFrame:
    """The contract's columns for every row; nulls, repeats and empty tables as in ``fit`` and ``score``."""
    model = fit(docs.select("doc_id", "text"), labels.where(~held_out()))
    return score(docs.select("doc_id", "text"), model).select("doc_id", held_out().alias("held_out"), "score", "predicted")
