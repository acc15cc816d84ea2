"""Quality classifier: a sparse ensemble of rules.

Statistics of a text are Spark columns. Small boosted trees, fitted to a bounded sample of labelled
rows, yield their paths as conjunctive rules; a lasso-penalised logistic fit keeps a few of them. The
kept rules compile back into one Spark column, so that every text is scored inside Spark's own code.

The model is fitted on a sample of at most TRAIN_ROWS labelled rows, chosen by a hash of the id.

Defined results: a null text counts as empty and is scored as such; ids labelled several times count
with their mean label; without labels, or with labels of one kind only, every score is the share of
label 1 (0.5 if none); texts of any length are scored whole; repeated rows are scored alike; other columns are
not read.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from motifprune.llm import common

TRAIN_ROWS, TREES, DEPTH, BINS, MOST_RULES, PENALTY = 6000, 30, 3, 32, 40, 0.003


def statistics(text: Column) -> dict[str, Column]:
    """Named statistics of a text that is never null."""
    n = F.length(text).cast("double")
    share = lambda signs: (n - F.length(F.regexp_replace(text, f"{signs}+", ""))) / F.greatest(n, F.lit(1.0))
    words = F.split(text, r"\s+")
    lines = F.split(text, "\n")
    n_words = F.size(words).cast("double")
    return {
        "length": F.log1p(n),
        "upper": share(r"\p{Lu}"),
        "letters": share(r"\p{L}"),
        "digits": share(r"[0-9]"),
        "signs": share(r"[^\p{L}\p{N}\s.,;:'-]"),
        "stops": share(r"[.,;:]"),
        "sign_runs": F.regexp_count(text, F.lit(r"[^\p{L}\p{N}\s]{2,}")) / n_words,
        "lone_signs": F.regexp_count(text, F.lit(r"(?<!\S)[^\p{L}\p{N}\s]+(?!\S)")) / n_words,
        "word_length": n / n_words,
        "different_words": F.size(F.array_distinct(words)) / n_words,
        "repeated_words": F.regexp_count(text, F.lit(r"(?<!\S)(\S{1,40}) \1(?!\S)")) / n_words,
        "different_lines": F.size(F.array_distinct(lines)) / F.size(lines),
    }


Condition = tuple[int, bool, float]  # statistic, whether above, threshold


@dataclass(frozen=True)
class RuleModel:
    names: tuple[str, ...]
    bias: float
    rules: tuple[tuple[float, tuple[Condition, ...]], ...]

    def column(self) -> Column:
        """The score as a Spark column over columns of the statistics' names."""
        total = F.lit(self.bias)
        for weight, conditions in self.rules:
            holds = F.lit(True)
            for k, above, threshold in conditions:
                holds = holds & (F.col(self.names[k]) > threshold if above else F.col(self.names[k]) <= threshold)
            total = total + F.when(holds, weight).otherwise(0.0)
        return 1 / (1 + F.exp(-total))

    def score(self, x: np.ndarray) -> np.ndarray:
        total = np.full(len(x), self.bias)
        for weight, conditions in self.rules:
            total += weight * holds_on(conditions, x)
        return 1 / (1 + np.exp(-total))


def holds_on(conditions: tuple[Condition, ...], x: np.ndarray) -> np.ndarray:
    out = np.ones(len(x), dtype=bool)
    for k, above, threshold in conditions:
        out &= x[:, k] > threshold if above else x[:, k] <= threshold
    return out


def tree_rules(x: np.ndarray, y: np.ndarray, trees: int = TREES, depth: int = DEPTH, seed: int = 0) -> list[tuple[Condition, ...]]:
    """The paths, from the root to each node, of boosted trees fitted to random halves."""
    rng = np.random.default_rng(seed)
    edges = [np.unique(np.quantile(x[:, k], np.linspace(0, 1, BINS + 1)[1:-1])) for k in range(x.shape[1])]
    margin, found = np.zeros(len(y)), {}

    def grow(rows: np.ndarray, path: tuple[Condition, ...], gradient: np.ndarray, curve: np.ndarray) -> None:
        if path:
            found.setdefault(tuple(sorted(path)))
        best = (1e-6, None)
        g, h = gradient[rows].sum(), curve[rows].sum()
        if len(path) < depth and len(rows) >= 20:
            for k in range(x.shape[1]):
                if not len(edges[k]):
                    continue
                at = np.searchsorted(edges[k], x[rows, k], side="left")
                left_g = np.cumsum(np.bincount(at, gradient[rows], len(edges[k]) + 1))[:-1]
                left_h = np.cumsum(np.bincount(at, curve[rows], len(edges[k]) + 1))[:-1]
                gain = left_g**2 / (left_h + 1) + (g - left_g) ** 2 / (h - left_h + 1) - g**2 / (h + 1)
                b = int(gain.argmax())
                if gain[b] > best[0]:
                    best = (gain[b], (k, float(edges[k][b])))
        if best[1] is None:
            margin_step[rows] = 0.4 * g / (h + 1)
            return
        k, threshold = best[1]
        above = x[rows, k] > threshold
        grow(rows[~above], (*path, (k, False, threshold)), gradient, curve)
        grow(rows[above], (*path, (k, True, threshold)), gradient, curve)

    for _ in range(trees):
        p = 1 / (1 + np.exp(-margin))
        margin_step = np.zeros(len(y))
        half = rng.random(len(y)) < 0.5
        grow(np.arange(len(y)), (), (y - p) * half * 2, p * (1 - p) * half * 2)
        margin += margin_step
    return list(found)


def lasso_logistic(z: np.ndarray, y: np.ndarray, penalty: float = PENALTY, steps: int = 400) -> tuple[float, np.ndarray]:
    """Accelerated proximal gradient; the bias is not penalised."""
    n, m = z.shape
    full = np.hstack([np.ones((n, 1)), z])
    rate = 4 / (np.linalg.norm(full, 2) ** 2 / n + 1e-12)
    w = look = np.zeros(m + 1)
    t = 1.0
    for _ in range(steps):
        p = 1 / (1 + np.exp(-(full @ look)))
        step = look - rate * (full.T @ (p - y)) / n
        new = np.concatenate([step[:1], np.sign(step[1:]) * np.maximum(0, np.abs(step[1:]) - rate * penalty)])
        t, was = (1 + np.sqrt(1 + 4 * t * t)) / 2, t
        w, look = new, new + (was - 1) / t * (new - w)
    return float(w[0]), w[1:]


def fit_rules(names: tuple[str, ...], x: np.ndarray, y: np.ndarray) -> RuleModel:
    share = float(np.clip(y.mean(), 0.01, 0.99)) if len(y) else 0.5
    plain = RuleModel(names, float(np.log(share / (1 - share))), ())
    if len(y) < 20 or len(set(y.tolist())) < 2:
        return plain
    rules = tree_rules(x, y)
    if not rules:
        return plain
    z = np.stack([holds_on(r, x) for r in rules], axis=1).astype(np.float64)
    _, w = lasso_logistic(z, y)
    kept = np.argsort(-np.abs(w) * z.std(axis=0), kind="stable")[:MOST_RULES]
    kept = np.array([k for k in kept if w[k] != 0], dtype=int)
    bias, w = lasso_logistic(z[:, kept], y, PENALTY / 10)  # what is kept is fitted again with less shrinkage
    return RuleModel(names, bias, tuple((float(v), rules[k]) for v, k in zip(w, kept) if v))


def train(docs: DataFrame, labels: DataFrame, rows: int = TRAIN_ROWS) -> RuleModel:
    """docs: (doc_id, text); labels: (doc_id, label), of which a sample of at most about `rows` is used."""
    labels = labels.where("doc_id IS NOT NULL AND label IS NOT NULL")
    share = (rows << 30) // max(1, labels.count()) + 1
    sample = labels.where(F.pmod(F.xxhash64("doc_id", F.lit(3)), F.lit(1 << 30)) < min(share, 1 << 30))
    sample = sample.groupBy("doc_id").agg(F.avg("label").alias("label"))
    columns = statistics(F.col("text"))
    got = common.texts_of(docs).join(F.broadcast(sample), "doc_id").select("doc_id", "label", *(c.alias(k) for k, c in columns.items())).toPandas().sort_values(["doc_id", *columns], kind="stable")
    return fit_rules(tuple(columns), got[list(columns)].to_numpy(dtype=float), (got["label"].to_numpy() >= 0.5).astype(float))


def score(docs: DataFrame, model: RuleModel) -> DataFrame:
    """(doc_id, score, predicted) of every row."""
    columns = statistics(F.col("text"))
    used = sorted({k for _, conditions in model.rules for k, _, _ in conditions})
    measured = common.texts_of(docs).select("doc_id", *(columns[model.names[k]].alias(model.names[k]) for k in used))
    return measured.select("doc_id", model.column().alias("score")).withColumn("predicted", (F.col("score") >= 0.5).cast("int"))


def op3_quality_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = common.read_table(spark, sf_dir, "documents")
    held_out = common.remainder_of(F.col("doc_id"), 3) == 1
    labels = common.read_table(spark, sf_dir, "labels").select("doc_id", F.col("quality").alias("label"))
    model = train(docs, labels.where(~held_out))
    return score(docs, model).withColumn("held_out", held_out)
