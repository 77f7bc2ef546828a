"""Quality by a sparse ensemble of rules over text statistics.

Boosted shallow trees over statistics of the labelled texts suggest rules: each path from a root to a
node is a conjunction of comparisons. Lasso-penalised logistic regression over the rules keeps few
of them, and those are compiled into column expressions, so scoring is a projection.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from reportgraph.llm.training import MAX_LABELLED, held_out, labelled_sample

#: Names of the statistics, in the order of the learner's columns.
STATISTICS = ("words", "chars_a_word", "letters", "capitals", "digits", "odd_signs", "stops", "distinct_words", "distinct_lines", "words_a_line")


def with_statistics(docs: DataFrame, text_col: str = "text") -> DataFrame:
    """Adds ``__stats``, a struct of the statistics of each whole text; shares are of all signs but white space."""
    t = F.coalesce(F.col(text_col), F.lit(""))

    def signs(pattern: str) -> Column:
        return F.length(F.regexp_replace(t, pattern, ""))

    words = F.filter(F.split(t, r"[ \t\n\x0B\f\r]+"), lambda w: w != "")
    lines = F.filter(F.split(t, "\n"), lambda x: x != "")
    counts = docs.withColumn(
        "__n",
        F.struct(
            F.size(words).alias("words"), F.size(F.array_distinct(words)).alias("own_words"), F.size(lines).alias("lines"), F.size(F.array_distinct(lines)).alias("own_lines"),
            signs(r"\s+").alias("signs"), signs(r"[\s\p{L}]+").alias("not_letters"), signs(r"[\s\P{Lu}]+").alias("capitals"), signs("[^0-9]+").alias("digits"),
            signs(r"[^%&$#*!|~^@=<>{}\[\]\\/_+]+").alias("odd"), signs("[^.,;:?]+").alias("stops"),
        ),
    )
    n = {k: F.col(f"__n.{k}").cast("double") for k in ("words", "own_words", "lines", "own_lines", "signs", "not_letters", "capitals", "digits", "odd", "stops")}

    def part(a: Column, b: Column) -> Column:
        return F.coalesce(F.try_divide(a, b), F.lit(0.0))

    letters = n["signs"] - n["not_letters"]
    values = (n["words"], part(n["signs"], n["words"]), part(letters, n["signs"]), part(n["capitals"], letters), part(n["digits"], n["signs"]), part(n["odd"], n["signs"]), part(n["stops"], n["words"]), part(n["own_words"], n["words"]), part(n["own_lines"], n["lines"]), part(n["words"], n["lines"]))
    return counts.withColumn("__stats", F.struct(*[v.alias(k) for k, v in zip(STATISTICS, values)])).drop("__n")


@dataclass(frozen=True)
class Rule:
    """Holds where every (statistic, above, limit) does: value > limit if ``above``, else value <= limit."""

    parts: tuple[tuple[int, bool, float], ...]

    def of(self, x: np.ndarray) -> np.ndarray:
        ok = np.ones(len(x), bool)
        for f, above, limit in self.parts:
            ok &= (x[:, f] > limit) == above
        return ok

    def column(self) -> Column:
        c = F.lit(True)
        for f, above, limit in self.parts:
            v = F.col(f"__stats.{STATISTICS[f]}")
            c = c & ((v > limit) if above else (v <= limit))
        return c

    def __str__(self) -> str:
        return " and ".join(f"{STATISTICS[f]} {'>' if above else '<='} {limit:.4g}" for f, above, limit in self.parts) or "always"


def grow(x: np.ndarray, residual: np.ndarray, limits: list[np.ndarray], depth: int, least: int) -> tuple[list[tuple], np.ndarray]:
    """One regression tree: the conjunctions of all its nodes but the root, and its fitted values."""
    paths: list[tuple] = []
    fitted = np.zeros(len(x))

    def split(rows: np.ndarray, parts: tuple, level: int) -> None:
        r = residual[rows]
        fitted[rows] = r.mean()
        if level == depth or len(rows) < 2 * least:
            return
        best = None
        for f, cuts in enumerate(limits):
            if not len(cuts):
                continue
            cell = np.searchsorted(cuts, x[rows, f], side="left")  # value <= cuts[cell]
            n = np.cumsum(np.bincount(cell, minlength=len(cuts) + 1))[:-1]
            s = np.cumsum(np.bincount(cell, weights=r, minlength=len(cuts) + 1))[:-1]
            ok = (n >= least) & (len(rows) - n >= least)
            gain = np.where(ok, s**2 / np.maximum(n, 1) + (r.sum() - s) ** 2 / np.maximum(len(rows) - n, 1), -np.inf)
            k = int(gain.argmax())
            if np.isfinite(gain[k]) and (best is None or gain[k] > best[0]):
                best = (gain[k], f, float(cuts[k]))
        if best is None or best[0] <= r.sum() ** 2 / len(rows) + 1e-12:
            return
        _, f, cut = best
        for above in (False, True):
            inner = parts + ((f, above, cut),)
            paths.append(inner)
            split(rows[(x[rows, f] > cut) == above], inner, level + 1)

    split(np.arange(len(x)), (), 0)
    return paths, fitted


def lasso_logistic(z: np.ndarray, y: np.ndarray, penalty: float, rounds: int = 400) -> tuple[float, np.ndarray]:
    """Intercept and weights by accelerated proximal steps; the intercept bears no penalty."""
    n, k = z.shape
    step = 4.0 / max(1.0, float((z**2).sum() / max(n, 1)) + 1.0)
    w, b = np.zeros(k), float(np.log(max(y.mean(), 1e-3) / max(1 - y.mean(), 1e-3)))
    vw, vb, t = w.copy(), b, 1.0
    for _ in range(rounds):
        miss = (1 / (1 + np.exp(-np.clip(z @ vw + vb, -60, 60))) - y) / max(n, 1)
        nb = vb - step * miss.sum()
        g = vw - step * (z.T @ miss)
        nw = np.sign(g) * np.maximum(np.abs(g) - step * penalty, 0)
        nt = (1 + np.sqrt(1 + 4 * t * t)) / 2
        vw, vb = nw + (t - 1) / nt * (nw - w), nb + (t - 1) / nt * (nb - b)
        w, b, t = nw, nb, nt
    return b, w


@dataclass
class RuleEnsemble:
    intercept: float
    rules: list[tuple[Rule, float]]

    def of(self, x: np.ndarray) -> np.ndarray:
        return 1 / (1 + np.exp(-np.clip(self.intercept + sum((w * r.of(x) for r, w in self.rules), np.zeros(len(x))), -60, 60)))

    def column(self) -> Column:
        """Score from ``__stats``."""
        total = F.lit(self.intercept)
        for rule, w in self.rules:
            total = total + F.when(rule.column(), F.lit(w)).otherwise(F.lit(0.0))
        return F.lit(1.0) / (F.lit(1.0) + F.exp(-total))


def fit(x: np.ndarray, y: np.ndarray, trees: int = 30, depth: int = 3, rate: float = 0.3, penalty: float = 2e-4, bins: int = 64) -> RuleEnsemble:
    """Rules from boosted trees, then lasso weights; without both classes only an intercept is left."""
    y = np.asarray(y, np.float64)
    share = float(np.clip(y.mean() if len(y) else 0.5, 1e-3, 1 - 1e-3))
    base = float(np.log(share / (1 - share)))
    if not len(y) or y.min() == y.max():
        return RuleEnsemble(base, [])
    limits = []
    for f in range(x.shape[1]):
        v = np.unique(np.quantile(x[:, f], np.linspace(0, 1, bins + 1)[1:-1], method="nearest"))
        above = np.unique(x[:, f])
        nxt = above[np.minimum(np.searchsorted(above, v, side="right"), len(above) - 1)]
        limits.append(np.unique((v + nxt) / 2))
    paths: dict[tuple, None] = {}
    f_now, least = np.full(len(y), base), max(5, len(y) // 500)
    for _ in range(trees):
        p = 1 / (1 + np.exp(-f_now))
        found, values = grow(x, y - p, limits, depth, least)
        paths.update(dict.fromkeys(tuple(sorted(p)) for p in found))
        f_now = f_now + rate * 4 * values
    rules: dict[bytes, Rule] = {}
    for p in sorted(paths, key=lambda p: (len(p), p)):
        rule = Rule(p)
        rules.setdefault(np.packbits(rule.of(x)).tobytes(), rule)
    kept = list(rules.values())
    b, w = lasso_logistic(np.stack([r.of(x) for r in kept], 1).astype(np.float64), y, penalty)
    return RuleEnsemble(b, [(r, float(v)) for r, v in zip(kept, w) if abs(v) > 1e-6])


def learn(docs: DataFrame, labels: DataFrame, label: str = "quality", max_rows: int = MAX_LABELLED, **options) -> RuleEnsemble:
    """Fits the rules on the driver from the statistics of at most ``max_rows`` labelled rows."""
    sample = with_statistics(labelled_sample(docs, labels, label, max_rows))
    rows = sample.select("doc_id", "__stats.*", "label").toPandas().sort_values("doc_id")
    return fit(rows[list(STATISTICS)].to_numpy(np.float64), rows["label"].to_numpy(), **options)


def score(docs: DataFrame, model: RuleEnsemble, threshold: float = 0.3, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``doc_id, held_out, score, predicted`` of every whole text, by column expressions alone.

    Null texts count as empty (all statistics zero); repeated rows stay repeated; an empty table gives no rows.
    """
    rows = with_statistics(docs.select(F.col(id_col).alias("doc_id"), F.col(text_col).alias("text")))
    rows = rows.select("doc_id", held_out(F.col("doc_id")).alias("held_out"), model.column().alias("score"))
    return rows.withColumn("predicted", (F.col("score") >= threshold).cast("int"))


def accepted(docs: DataFrame, model: RuleEnsemble, threshold: float = 0.3, text_col: str = "text") -> DataFrame:
    """The rows of ``docs`` whose score reaches ``threshold``, with their columns."""
    rows = with_statistics(docs.select(F.struct(*[F.col(f"`{c}`") for c in docs.columns]).alias("__d"), F.col(text_col).alias("__text")), "__text")
    return rows.where(model.column() >= threshold).select("__d.*")
