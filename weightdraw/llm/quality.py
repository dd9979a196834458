"""Quality classifier: a sparse ensemble of rules over text statistics (operator 2).

Boosted trees are grown on statistics of labelled training rows; every path from a root
is a conjunctive rule; an l1-penalised logistic regression keeps few of the rules; those
are compiled into Spark column expressions, so scoring is one scan with built-in
functions and no Python.

The fit uses at most ``SAMPLE`` labelled rows (a bound on rows of twelve numbers that
reach the driver); statistics and scores cover whole texts of all documents.

Defined results for odd rows: null and empty texts have the statistics of an empty text
and a score like any other; repeated rows are scored each; a null doc_id is scored and
counts as not held out; without labels of both classes the score is 1 (nothing is known
against any text); an empty table gives an empty result.  Extra columns are ignored by
``score`` and kept by ``add_score``.
"""

from __future__ import annotations

from dataclasses import dataclass
from functools import reduce

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import bounded_labelled, held_out, ship
from .trees import boost, lasso_logistic, sigmoid

MODULUS, REMAINDER, THRESHOLD = 4, 2, 0.7
#: Labelled rows that a model is fitted on, at most.
SAMPLE = 20_000
PENALTIES = (0.03, 0.01, 0.003, 0.001)
Rule = tuple[tuple[int, bool, float], ...]


def statistics(text: Column) -> Column:
    """A struct of statistics of a text, all from built-in functions.

    Text, words and lines are bound as a lambda's variable: whatever the optimiser does
    with the expression, the text is split once.
    """
    text = F.coalesce(text.cast("string"), F.lit(""))
    parts = F.struct(text.alias("text"), F.split(F.trim(text), r"\s+").alias("words"), F.split(text, "\n").alias("lines"))

    def of(p: Column) -> Column:
        size, n_words, n_lines = F.greatest(F.length(p["text"]), F.lit(1)), F.size(p["words"]), F.size(p["lines"])
        count = lambda pattern: F.regexp_count(p["text"], F.lit(pattern))
        found = {
            "n_words": n_words.cast("double"),
            "distinct_words": F.size(F.array_distinct(p["words"])) / n_words,
            "word_length": F.length(p["text"]) / n_words,
            "symbols": count(r"[#$%&*|~^<>{}\[\]=_+@\\]") / size,
            "bangs": count(r"[!?]") / n_words,
            "capitals": count(r"\p{Lu}") / size,
            "digits": count(r"\p{Nd}") / size,
            "stops": count(r"[.,;:]") / n_words,
            "pipes": count(r"(?: \| )") / n_words,
            "n_lines": n_lines / n_words,
            "distinct_lines": F.size(F.array_distinct(p["lines"])) / n_lines,
            "repeats": count(r"(?<!\S)(\S+) \1(?!\S)") / n_words,
        }
        return F.struct(*[c.alias(n) for n, c in found.items()])

    return F.transform(F.array(parts), of)


NAMES = ["n_words", "distinct_words", "word_length", "symbols", "bangs", "capitals", "digits", "stops", "pipes", "n_lines", "distinct_lines", "repeats"]


@dataclass
class RuleModel:
    """Intercept and weighted rules; ``None`` weights mean that nothing could be learnt."""

    intercept: float
    rules: list[tuple[Rule, float]]
    fitted: bool = True

    def compile(self, known: Column) -> Column:
        """The score as a Spark column over a struct of the statistics."""
        if not self.fitted:
            return F.lit(1.0)

        def holds(rule: Rule) -> Column:
            tests = [known[NAMES[f]] <= t if low else known[NAMES[f]] > t for f, low, t in rule]
            return reduce(lambda a, b: a & b, tests)

        total = reduce(lambda a, b: a + b, [F.when(holds(r), F.lit(w)).otherwise(F.lit(0.0)) for r, w in self.rules], F.lit(self.intercept))
        return 1 / (1 + F.exp(-total))

    def score(self, text: Column) -> Column:
        """The score of a text; its statistics are computed once, wherever the expression is moved."""
        return F.transform(statistics(text), self.compile)[0]


def _simplify(path: Rule) -> Rule:
    """The tightest bound per feature and side, in a fixed order."""
    best: dict[tuple[int, bool], float] = {}
    for f, low, t in path:
        held = best.get((f, low))
        best[f, low] = t if held is None else min(held, t) if low else max(held, t)
    return tuple(sorted((f, low, t) for (f, low), t in best.items()))


def _matches(rule: Rule, x: np.ndarray) -> np.ndarray:
    return np.logical_and.reduce([x[:, f] <= t if low else x[:, f] > t for f, low, t in rule])


def fit_rules(x: np.ndarray, y: np.ndarray) -> RuleModel:
    if len(np.unique(y)) < 2:
        return RuleModel(0.0, [], fitted=False)
    _, trees = boost(x, y, rounds=40, depth=3, rate=0.3)
    rules = sorted({_simplify(p) for t in trees for p in t.paths()})
    r = np.stack([_matches(rule, x) for rule in rules], axis=1).astype(float) if rules else np.zeros((len(y), 0))
    varied = r.std(axis=0) > 0
    rules, r = [rule for rule, v in zip(rules, varied, strict=True) if v], r[:, varied]
    check = np.arange(len(y)) % 5 == 0
    loss = {}
    for penalty in PENALTIES:
        b, w = lasso_logistic(r[~check], y[~check], penalty)
        p = np.clip(sigmoid(b + r[check] @ w), 1e-6, 1 - 1e-6)
        loss[penalty] = -(y[check] * np.log(p) + (1 - y[check]) * np.log(1 - p)).mean()
    b, w = lasso_logistic(r, y, min(PENALTIES, key=lambda k: loss[k]))
    return RuleModel(b, [(rule, float(v)) for rule, v in zip(rules, w, strict=True) if abs(v) > 1e-4])


def fit(docs: DataFrame, labels: DataFrame, sample: int = SAMPLE) -> RuleModel:
    rows = bounded_labelled(docs, labels, "quality", MODULUS, REMAINDER, sample)
    table = rows.select("doc_id", "y", F.inline(statistics(F.col("text")))).toPandas().sort_values("doc_id", kind="stable")
    return fit_rules(table[NAMES].to_numpy(float), table["y"].to_numpy(float))


def add_score(docs: DataFrame, model: RuleModel, name: str = "_score") -> DataFrame:
    """The documents, all columns, with a score (a column of that name is replaced)."""
    return docs.withColumn(name, model.score(F.col("text")))


def keep(docs: DataFrame, model: RuleModel) -> DataFrame:
    """The documents, all columns and no other, that reach the threshold."""
    return docs.where(model.score(F.col("text")) >= THRESHOLD)


def score(docs: DataFrame, labels: DataFrame) -> DataFrame:
    """doc_id, held_out, score, predicted of every document."""
    scored = add_score(docs.select("doc_id", "text"), fit(docs, labels))
    return scored.select("doc_id", held_out(F.col("doc_id"), MODULUS, REMAINDER).alias("held_out"), F.col("_score").alias("score"), F.when(F.col("_score") >= THRESHOLD, 1).otherwise(0).alias("predicted"))


ship(__name__)
