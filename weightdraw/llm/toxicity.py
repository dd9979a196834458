"""Toxicity: boosted trees over dense features, with isotonic calibration (operator 7).

A lexicon of words and word beginnings (beginnings catch inflected forms in languages
other than English) is learnt from labelled training rows by smoothed log odds.  The
features are lexicon densities, lexicon words near a second-person pronoun, capitals,
punctuation, and words that become lexicon words once digits, symbols or separators
inside them are undone.  Features are built-in functions over whole texts; the trees see
a dozen numbers per row in Arrow batches.

The fit uses at most ``SAMPLE`` labelled rows.  Calibration is isotonic on predictions of
folds that a row did not train.

Defined results for odd rows: null and empty texts have the features of an empty text;
repeated rows are scored each; a null doc_id is scored and counts as not held out;
without labels of both classes the score is 0 (nothing is known against any text); an
empty table gives an empty result.  Extra columns are ignored by ``score`` and kept by
``add_score``.
"""

from __future__ import annotations

from dataclasses import dataclass
from functools import reduce

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import bounded_labelled, held_out, share, ship, unused
from .trees import Tree, boost, isotonic, margin

MODULUS, REMAINDER, THRESHOLD = 5, 0, 0.5
#: Labelled rows that lexicon and trees are fitted on, and lexicon entries, at most.
SAMPLE, ENTRIES = 12_000, 400
#: Second-person words of the languages served: fixed values.
SECOND = (
    "you your yours yourself u ur "
    "du dich dir dein deine deinen deiner ihr euch euer sie ihnen "
    "tu te toi ton ta tes vous votre vos "
    "tú ti usted ustedes vosotros vuestro tus"
).split()
NEAR = 3
STEMS = (4, 5, 6, 7)
FEATURES = ["lexicon", "lexicon_hits", "lexicon_kinds", "stem", "stem_hits", "near_you", "capitals", "bangs", "stops", "hidden", "spaced", "n_words"]


def words_of(text: Column) -> Column:
    return F.regexp_extract_all(F.lower(F.coalesce(text.cast("string"), F.lit(""))), F.lit(r"\p{L}+"), F.lit(0))


@dataclass
class ToxicityModel:
    words: list[str]
    stems: list[str]
    base: float
    trees: list[Tree]
    knots: tuple[np.ndarray, np.ndarray]
    fitted: bool = True

    def probability(self, x: np.ndarray) -> np.ndarray:
        return np.interp(margin(self.base, self.trees, x), *self.knots)


def learn_lexicon(train: DataFrame, entries: int = ENTRIES) -> tuple[list[str], list[str]]:
    """(words, beginnings of STEMS letters) that mark label 1; ``train`` has text and y."""
    train = train.dropDuplicates(["text"])  # copies say a thing once
    words = F.filter(F.array_distinct(words_of(F.col("text"))), lambda w: F.length(w) >= 3)
    heads = lambda n: F.transform(F.filter("words", lambda w: F.length(w) > n), lambda w: F.concat(F.substring(w, 1, n), F.lit("-")))
    each = train.select("y", words.alias("words")).select("y", F.explode(F.array_distinct(F.concat("words", *map(heads, STEMS)))).alias("entry"))
    total = train.agg(F.sum("y").alias("bad"), F.count("*").alias("all")).first()
    least = max(3, 0.01 * (total["bad"] or 0))
    count = each.groupBy("entry").agg(F.sum("y").alias("bad"), F.count("*").alias("all")).where(F.col("bad") >= least)
    good = max((total["all"] or 0) - (total["bad"] or 0), 1)
    odds = F.log((F.col("bad") + 0.1) / (total["bad"] or 1)) - F.log((F.col("all") - F.col("bad") + 0.1) / good)
    rows = count.withColumn("odds", odds).where(F.col("odds") >= float(np.log(12))).orderBy(F.desc(F.col("odds") * F.sqrt("bad")), "entry").limit(entries).collect()
    return [r.entry for r in rows if r.entry[-1] != "-"], [r.entry[:-1] for r in rows if r.entry[-1] == "-"]


def features(text: Column, own: str, words: list[str], stems: list[str]) -> dict[str, Column]:
    """The features; ``own`` begins the names of the bound columns: its words, its lexicon words."""
    said, hits = own + "words", own + "hits"
    text = F.coalesce(text.cast("string"), F.lit(""))
    low = F.lower(text)
    listed = lambda w: w.isin(words) if words else F.lit(False)
    stemmed = lambda w: reduce(lambda a, b: a | b, [F.substring(w, 1, n).isin([s for s in stems if len(s) == n]) for n in STEMS if any(len(s) == n for s in stems)], F.lit(False))
    near = lambda i: F.exists(F.slice(said, F.greatest(i - NEAR + 1, F.lit(1)), 2 * NEAR + 1), lambda x: x.isin(SECOND))
    n, size = F.greatest(F.size(said), F.lit(1)), F.greatest(F.length(text), F.lit(1))
    count = lambda pattern: F.regexp_count(text, F.lit(pattern))
    # possessive and anchored at word starts, so a word of a million letters is one pass
    masked = F.regexp_extract_all(low, F.lit(r"(?<!\p{L})\p{L}++[0-9@$*][\p{L}0-9@$*]*\p{L}"), F.lit(0))
    hidden = F.size(F.filter(masked, lambda w: listed(F.translate(w, "013457@$*", "oieastas")) | listed(F.regexp_replace(w, r"[^\p{L}]", ""))))
    apart = F.regexp_extract_all(low, F.lit(r"(?<!\p{L})\p{L}(?:[ ._*-]\p{L}(?!\p{L})){3,}+"), F.lit(0))
    spaced = F.size(F.filter(apart, lambda w: listed(F.regexp_replace(w, r"[^\p{L}]", ""))))
    return {
        "lexicon": F.size(hits) / n,
        "lexicon_hits": F.size(hits).cast("double"),
        "lexicon_kinds": F.size(F.array_distinct(hits)).cast("double"),
        "stem": F.size(F.filter(said, stemmed)) / n,
        "stem_hits": F.size(F.filter(said, stemmed)).cast("double"),
        "near_you": F.size(F.filter(said, lambda w, i: listed(w) & near(i))).cast("double"),
        "capitals": count(r"\p{Lu}") / size,
        "bangs": count(r"[!?]") / n,
        "stops": count(r"[.,;:]") / n,
        "hidden": hidden.cast("double"),
        "spaced": spaced.cast("double"),
        "n_words": F.size(said).cast("double"),
    }


def with_features(docs: DataFrame, own: str, words: list[str], stems: list[str]) -> DataFrame:
    """``docs`` with one column a feature, its name prefixed with ``own``."""
    said, hits = own + "words", own + "hits"
    docs = docs.withColumn(said, words_of(F.col("text")))
    docs = docs.withColumn(hits, F.filter(said, lambda w: w.isin(words)) if words else F.array().cast("array<string>"))
    return docs.withColumns({own + n: c for n, c in features(F.col("text"), own, words, stems).items()}).drop(said, hits)


def fit(docs: DataFrame, labels: DataFrame, sample: int = SAMPLE) -> ToxicityModel:
    train = bounded_labelled(docs, labels, "toxic", MODULUS, REMAINDER, sample)
    words, stems = learn_lexicon(train)
    prefix = "t_"
    table = with_features(train, prefix, words, stems).select("doc_id", "y", *[prefix + n for n in FEATURES]).toPandas().sort_values("doc_id", kind="stable")
    x, y = table[[prefix + n for n in FEATURES]].to_numpy(float), table["y"].to_numpy(float)
    if len(np.unique(y)) < 2:
        return ToxicityModel([], [], 0.0, [], (np.zeros(1), np.zeros(1)), fitted=False)
    base, trees = boost(x, y)
    fold = np.arange(len(y)) % 5
    out = np.zeros(len(y))
    for k in range(5):
        own = fold != k
        out[~own] = margin(*boost(x[own], y[own]), x[~own]) if len(np.unique(y[own])) > 1 else base
    return ToxicityModel(words, stems, base, trees, isotonic(out, y))


def add_score(docs: DataFrame, model: ToxicityModel, name: str = "_score") -> DataFrame:
    """The documents, all columns, with a calibrated score (a column of that name is replaced)."""
    if not model.fitted:
        return docs.withColumn(name, F.lit(0.0))
    held = share(docs.sparkSession, model)

    def run(*columns: pd.Series) -> pd.Series:
        return pd.Series(held().probability(np.stack([c.to_numpy(float) for c in columns], axis=1)))

    udf = F.pandas_udf(run, "double")
    own = unused(docs, "_t_")
    names = [own + n for n in FEATURES]
    return with_features(docs, own, model.words, model.stems).withColumn(name, udf(*names)).drop(*names)


def keep(docs: DataFrame, model: ToxicityModel) -> DataFrame:
    """The documents, all columns and no other, that stay below the threshold."""
    name = unused(docs, "_toxicity")
    return add_score(docs, model, name).where(F.col(name) < THRESHOLD).drop(name)


def score(docs: DataFrame, labels: DataFrame) -> DataFrame:
    """doc_id, held_out, score, predicted of every document."""
    scored = add_score(docs.select("doc_id", "text"), fit(docs, labels))
    return scored.select("doc_id", held_out(F.col("doc_id"), MODULUS, REMAINDER).alias("held_out"), F.col("_score").alias("score"), F.when(F.col("_score") >= THRESHOLD, 1).otherwise(0).alias("predicted"))


ship(__name__)
