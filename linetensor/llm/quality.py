"""Quality classifier: a sparse ensemble of rules.

Statistics of a text are Spark columns. Small boosted trees are grown on them, every path from a
root to a node becomes a conjunctive rule, a lasso-penalised logistic regression weighs the rules,
and those with a weight are compiled into one Spark column expression, so that scoring stays in
generated code.

The fit reads at most ``FIT_ROWS`` labelled rows, the first by a hash of the id; statistics and
scores cover every row and whole texts.

Cases: a null text reads as the empty one. Where labels are missing or all alike, the score is
their smoothed share (0.5 without any). An id that is labelled twice counts once, by its lowest
label. Rows that repeat are scored alike; extra columns are left alone; an empty table gives an
empty table; columns whose names clash are carried in a struct. Very long texts are scored whole, and
ties need no order. A score of 0.5 or more predicts 1.
"""

from __future__ import annotations

from dataclasses import dataclass, field

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .langid import held_out

#: Bound on the labelled rows that the fit reads.
FIT_ROWS = 20_000
TREES, DEPTH, RATE, BINS, LEAST_ROWS = 40, 3, 0.3, 32, 5
PENALTY, STEPS = 0.003, 400
#: Characters that are counted one by one.
MARKS = {"pipe": "|", "star": "*", "hash": "#", "dollar": "$", "percent": "%", "ampersand": "&", "bang": "!", "stop": ".", "comma": ",", "line": "\n"}
#: Statistics in the order of the model's columns.
NAMES = ("chars", "words", "word_length", "distinct_share", "longest_word", "upper_share", "digit_share", *[f"{m}_share" for m in MARKS], "mark_words", "repeats_share")


def _share(count: Column, of: Column) -> Column:
    return count.cast("double") / F.greatest(of, F.lit(1)).cast("double")


def statistics(df: DataFrame, text: str = "text") -> DataFrame:
    """df with a struct column ``stats`` of doubles, one field for each of NAMES."""
    t = F.col("`__text`")
    without = lambda mark: F.length(t) - F.length(F.replace(t, F.lit(mark)))
    first = df.withColumn("__text", F.coalesce(F.col(f"`{text}`"), F.lit("")))
    second = first.withColumn("__words", F.filter(F.split(t, r"\s+"), lambda w: w != "")).withColumn(
        "__counts",
        F.struct(
            F.length(t).alias("chars"),
            (F.length(t) - F.length(F.regexp_replace(t, r"[A-ZÀ-ÖØ-Þ]+", ""))).alias("upper"),
            (F.length(t) - F.length(F.regexp_replace(t, r"[0-9]+", ""))).alias("digits"),
            *[without(mark).alias(name) for name, mark in MARKS.items()],
        ),
    )
    third = second.withColumn(
        "__lengths",
        F.struct(
            F.size("__words").alias("words"),
            F.size(F.array_distinct("__words")).alias("distinct"),
            F.coalesce(F.array_max(F.transform("__words", F.length)), F.lit(0)).alias("longest"),
        ),
    )
    c, w = F.col("__counts"), F.col("__lengths")
    marks = sum((c[m] for m in ("pipe", "star", "hash", "dollar", "percent", "ampersand", "bang")), F.lit(0))
    values = {
        "chars": c["chars"].cast("double"),
        "words": w["words"].cast("double"),
        "word_length": _share(c["chars"], w["words"]),
        "distinct_share": _share(w["distinct"], w["words"]),
        "longest_word": w["longest"].cast("double"),
        "upper_share": _share(c["upper"], c["chars"]),
        "digit_share": _share(c["digits"], c["chars"]),
        **{f"{m}_share": _share(c[m], w["words"]) for m in MARKS},
        "mark_words": marks.cast("double"),
        "repeats_share": _share(w["words"] - w["distinct"], w["words"]) * F.log1p(w["words"].cast("double")),
    }
    return third.withColumn("stats", F.struct(*[F.coalesce(values[n], F.lit(0.0)).alias(n) for n in NAMES])).drop("__text", "__words", "__counts", "__lengths")


Condition = tuple[int, bool, float]  # statistic, whether above, threshold


@dataclass
class RuleEnsemble:
    """Rules with their weights; rules are conjunctions of conditions on statistics."""

    intercept: float = 0.0
    rules: list[tuple[tuple[Condition, ...], float]] = field(default_factory=list)

    def column(self, stats: str = "stats") -> Column:
        """The score as a Spark expression over the struct of statistics."""
        total = F.lit(float(self.intercept))
        for conditions, weight in self.rules:
            holds = F.lit(True)
            for which, above, threshold in conditions:
                value = F.col(f"{stats}.{NAMES[which]}")
                holds = holds & (value > threshold if above else value <= threshold)
            total = total + F.when(holds, F.lit(float(weight))).otherwise(F.lit(0.0))
        return F.lit(1.0) / (F.lit(1.0) + F.exp(-total))

    def score(self, x: np.ndarray) -> np.ndarray:
        """The same in NumPy, rows x statistics."""
        return 1 / (1 + np.exp(-self.intercept - _fires(x, [c for c, _ in self.rules]) @ np.array([w for _, w in self.rules])))


def _fires(x: np.ndarray, rules: list[tuple[Condition, ...]]) -> np.ndarray:
    out = np.ones((len(x), len(rules)))
    for k, conditions in enumerate(rules):
        for which, above, threshold in conditions:
            out[:, k] *= x[:, which] > threshold if above else x[:, which] <= threshold
    return out


def _grow(x: np.ndarray, edges: list[np.ndarray], binned: np.ndarray, gradient: np.ndarray, curvature: np.ndarray) -> tuple[list[tuple[Condition, ...]], np.ndarray]:
    """One tree by gain on binned statistics: the path of every node, and the step of every row."""
    paths: list[tuple[Condition, ...]] = []
    step = np.zeros(len(x))
    open_nodes: list[tuple[tuple[Condition, ...], np.ndarray]] = [((), np.arange(len(x)))]
    while open_nodes:
        path, rows = open_nodes.pop()
        g, h = gradient[rows].sum(), curvature[rows].sum()
        step[rows] = -g / (h + 1)
        if path:
            paths.append(path)
        if len(path) == DEPTH or len(rows) < 2 * LEAST_ROWS:
            continue
        best = (1e-6, -1, -1)
        for k in range(x.shape[1]):
            n = len(edges[k]) + 1
            if n == 1:
                continue
            b = binned[rows, k]
            gs, hs, cs = (np.bincount(b, weights=v, minlength=n).cumsum()[:-1] for v in (gradient[rows], curvature[rows], np.ones(len(rows))))
            gain = gs**2 / (hs + 1) + (g - gs) ** 2 / (h - hs + 1) - g**2 / (h + 1)
            gain[(cs < LEAST_ROWS) | (len(rows) - cs < LEAST_ROWS)] = -1
            at = int(gain.argmax())
            if gain[at] > best[0]:
                best = (float(gain[at]), k, at)
        _, k, at = best
        if k >= 0:
            below = binned[rows, k] <= at
            open_nodes.append(((*path, (k, False, float(edges[k][at]))), rows[below]))
            open_nodes.append(((*path, (k, True, float(edges[k][at]))), rows[~below]))
    return paths, step


def _lasso(f: np.ndarray, y: np.ndarray) -> tuple[float, np.ndarray]:
    """Logistic regression with an absolute-value penalty on all but the intercept, by accelerated proximal steps; f is not copied."""
    n, k = f.shape
    products = np.block([[np.full((1, 1), float(n)), f.sum(axis=0)[None]], [f.sum(axis=0)[:, None], f.T @ f]])
    pace = 1 / (0.25 * np.linalg.eigvalsh(products)[-1] / n + 1e-9)
    w = z = np.zeros(k + 1)
    t = 1.0
    for _ in range(STEPS):
        wrong = 1 / (1 + np.exp(-z[0] - f @ z[1:])) - y
        slope = np.concatenate([[wrong.sum()], wrong @ f]) / n
        moved = z - pace * slope
        new = np.sign(moved) * np.maximum(np.abs(moved) - pace * PENALTY, 0)
        new[0] = moved[0]
        t_new = (1 + np.sqrt(1 + 4 * t * t)) / 2
        z, w, t = new + (t - 1) / t_new * (new - w), new, t_new
    return float(w[0]), w[1:]


def fit_rules(x: np.ndarray, y: np.ndarray) -> RuleEnsemble:
    share = (y.sum() + 1) / (len(y) + 2)
    base = float(np.log(share / (1 - share)))
    if len(y) == 0 or y.min() == y.max():
        return RuleEnsemble(base)
    edges = [np.unique(np.quantile(c, np.linspace(0, 1, BINS + 1)[1:-1])) for c in x.T]
    edges = [e[e < c.max()] for e, c in zip(edges, x.T, strict=True)]
    binned = np.stack([np.searchsorted(e, c, side="left") for e, c in zip(edges, x.T, strict=True)], axis=1)
    total, paths = np.full(len(y), base), set()
    for _ in range(TREES):
        p = 1 / (1 + np.exp(-total))
        found, step = _grow(x, edges, binned, p - y, p * (1 - p))
        paths.update(tuple(sorted(path)) for path in found)
        total = total + RATE * step
    rules = sorted(paths)
    fires = _fires(x, rules)
    spread = fires.std(axis=0)
    if not spread.all():
        rules = [r for r, s in zip(rules, spread, strict=True) if s > 0]
        fires, spread = fires[:, spread > 0], spread[spread > 0]
    fires /= spread
    intercept, weights = _lasso(fires, y.astype(float))
    return RuleEnsemble(intercept, [(r, float(w / s)) for r, w, s in zip(rules, weights, spread, strict=True) if abs(w) > 1e-6])


def learn(docs: DataFrame, labels: DataFrame, key: str = "doc_id", text: str = "text", label: str = "quality", fit_rows: int = FIT_ROWS) -> RuleEnsemble:
    """Fit on labelled rows of docs, at most fit_rows of them; labels has key and label."""
    order = [F.xxhash64("label_key"), F.col("label_key")]
    chosen = labels.select(F.col(key).alias("label_key"), F.col(label).cast("int").alias("label")).where("label_key IS NOT NULL AND label IN (0, 1)")
    chosen = chosen.groupBy("label_key").agg(F.min("label").alias("label")).orderBy(*order).limit(fit_rows)
    rows = docs.select(F.col(key).alias("label_key"), F.col(text).alias("text")).join(F.broadcast(chosen), "label_key")
    sample = statistics(rows).select("label_key", "label", "stats").orderBy(*order, "stats").limit(fit_rows).collect()
    x = np.array([tuple(r["stats"]) for r in sample], float).reshape(len(sample), len(NAMES))
    return fit_rules(x, np.array([r["label"] for r in sample], int))


def score_rows(df: DataFrame, model: RuleEnsemble, text: str = "text") -> DataFrame:
    """One row per input row: ``row`` (its columns, whatever their names), ``score`` and ``predicted``."""
    rows = df.select(F.struct(*[F.col(f"`{c}`") for c in df.columns]).alias("row"), F.col(f"`{text}`").alias("text"))
    scored = statistics(rows).select("row", model.column().alias("score"))
    return scored.withColumn("predicted", F.when(F.col("score") >= 0.5, 1).otherwise(0))


def accepted(df: DataFrame, model: RuleEnsemble, text: str = "text") -> DataFrame:
    """The rows that the model predicts 1 for, with all columns.

    A generator drops the others: a filter would be pushed below the statistics, and the optimizer would
    write them out anew, texts split and all, in every condition of every rule.
    """
    kept = F.when(F.col("score") >= 0.5, F.array(F.struct("row")))
    return score_rows(df, model, text).select(F.inline(kept)).select("row.*")


def score_documents(df: DataFrame, model: RuleEnsemble, text: str = "text") -> DataFrame:
    """df with ``quality_score`` and ``quality_predicted``; columns of those names are replaced."""
    kept = [c for c in df.columns if c not in ("quality_score", "quality_predicted")]
    return score_rows(df, model, text).select(*[F.col(f"row.`{c}`").alias(c) for c in kept], F.col("score").alias("quality_score"), F.col("predicted").alias("quality_predicted"))


def classify(docs: DataFrame, labels: DataFrame) -> DataFrame:
    """Learn from the labels that are not held out and score every document."""
    model = learn(docs, labels.where(~held_out("doc_id", 3, 1)))
    done = score_documents(docs, model)
    return done.select("doc_id", held_out("doc_id", 3, 1).alias("held_out"), F.col("quality_score").alias("score"), F.col("quality_predicted").alias("predicted"))
