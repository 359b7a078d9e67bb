"""Toxicity: boosted trees over dense features of whole texts, with isotonic calibration."""

from __future__ import annotations

import re

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from signedcluster.llm.boosting import BoostedTrees, calibrated, isotonic
from signedcluster.llm.common import doc_frame, fold, map_rows, texts

#: Common abusive words and second-person words (fixed values).
ABUSIVE = frozenset("idiot stupid moron loser trash pathetic worthless disgusting scum clown dumb fool jerk garbage hate ugly shut vile".split())
SECOND = frozenset("you your yours yourself u ur du dich dir dein deine ihr euch tu te toi ton ta vous votre tú ti usted vosotros".split())
#: Digits and signs written for letters (fixed values).
SWAPPED = str.maketrans("013457@$!", "oleastasi")

WORD = re.compile(r"[^\W\d_]+")
HIDDEN = re.compile(r"(?<![\w@$*])(?=\w*[^\W\d_])[\w]*[0-9@$!*][\w@$!*]*[^\W_](?![\w@$*])")
SHOUT = re.compile(r"[!?]")
CAPITAL = re.compile(r"[A-ZÀ-ÖØ-Þ]")
PUNCT = re.compile(r"[^\w\s]")
STEMS = (3, 4, 5, 6)
FEATURES = 16


def terms_of(text: str) -> set[str]:
    """Words and, marked by a hyphen, their beginnings."""
    words = set(WORD.findall(text.lower()))
    return words | {w[:k] + "-" for w in words for k in STEMS if len(w) > k}


def features_of(text: str | None, learned: dict[str, float]) -> list[float]:
    """Densities of the fixed and the learned lexicon, second-person proximity, capitals, punctuation, obfuscation."""
    if not text:
        return [0.0] * FEATURES
    words = WORD.findall(text.lower())
    n = max(len(words), 1)
    weights = learned.get
    fixed = [k for k, w in enumerate(words) if w in ABUSIVE]
    whole = [(k, v) for k, w in enumerate(words) if (v := weights(w))]
    stems = [v for w in words if (v := max((weights(w[:j] + "-", 0.0) for j in STEMS), default=0.0))]
    second = np.array([k for k, w in enumerate(words) if w in SECOND])
    hits = np.array(sorted({*fixed, *(k for k, _ in whole)}))
    near = 0
    if len(hits) and len(second):
        at = np.searchsorted(second, hits)
        gap = np.minimum(np.abs(hits - second[np.maximum(at - 1, 0)]), np.abs(second[np.minimum(at, len(second) - 1)] - hits))
        near = int((gap <= 5).sum())
    hidden = HIDDEN.findall(text) if not text.isalpha() else []
    unmasked = sum(x.lower().translate(SWAPPED) in ABUSIVE for x in hidden)
    letters = sum(map(len, words))
    capitals = len(CAPITAL.findall(text))
    return [
        len(fixed) / n,
        np.log1p(len(fixed)),
        len(whole) / n,
        np.log1p(len(whole)),
        max((v for _, v in whole), default=0.0),
        sum(v for _, v in whole) / n,
        len(stems) / n,
        np.log1p(len(stems)),
        sum(stems) / n,
        near / n,
        capitals / max(letters, 1),
        len(PUNCT.findall(text)) / len(text),
        len(SHOUT.findall(text)) / n,
        len(hidden) / n,
        np.log1p(unmasked),
        np.log1p(n),
    ]


def learn(docs: DataFrame, labels: DataFrame, most_rows: int = 20_000, most_terms: int = 3_000, id_col: str = "doc_id", text_col: str = "text"):
    """(lexicon, trees, calibration knots) from ``labels(doc_id, toxic)``.

    At most ``most_rows`` labelled rows, the first by a hash of the id, are used: two fifths to learn the lexicon
    (log odds of words and word beginnings, at most ``most_terms``), two fifths for the trees, one fifth to calibrate.
    Labels of one id that disagree count as toxic; null labels are left out. Returns None without labels of both kinds.
    """
    sample = (
        labels.where("toxic is not null and doc_id is not null")
        .groupBy(F.col("doc_id").cast("long").alias("label_id"))
        .agg(F.max("toxic").cast("int").alias("toxic"))
        .orderBy(F.xxhash64("label_id"), "label_id")
        .limit(most_rows)
        .withColumn("part", F.pmod(F.xxhash64("label_id", F.lit(3)), F.lit(5)).cast("int"))
    )
    frame = doc_frame(docs, id_col, text_col)
    rows = frame.join(F.broadcast(sample), F.col("doc_id") == F.col("label_id")).select("text", "toxic", "part", "label_id")

    def count(batches):
        seen: dict[str, list[int]] = {}
        n = [0, 0]
        for batch in batches:
            kinds = batch.column("toxic").to_pylist()
            for row, t in texts(batch):
                n[kinds[row]] += 1
                for term in terms_of(t or ""):
                    seen.setdefault(term, [0, 0])[kinds[row]] += 1
        yield {"term": [*seen, None], "clean": [*(v[0] for v in seen.values()), n[0]], "toxic": [*(v[1] for v in seen.values()), n[1]]}

    terms = map_rows(rows.where("part < 2"), count, "term string, clean long, toxic long").groupBy("term").agg(F.sum("clean").alias("c"), F.sum("toxic").alias("t"))
    totals = terms.where("term is null").first()
    if not totals or not totals["c"] or not totals["t"]:
        return None
    odds = F.log((F.col("t") + 0.5) / (totals["t"] + 1)) - F.log((F.col("c") + 0.5) / (totals["c"] + 1))
    found = terms.where("term is not null and t >= 3").withColumn("odds", odds).where("odds > 2").orderBy(F.desc("odds"), "term").limit(most_terms)
    learned = {r["term"]: float(r["odds"]) for r in found.collect()}

    def measure(batches):
        for batch in batches:
            yield {"id": batch.column("label_id"), "part": batch.column("part"), "toxic": batch.column("toxic"), "x": [features_of(t, learned) for _, t in texts(batch)]}

    got = sorted(map_rows(rows.where("part >= 2"), measure, "id long, part int, toxic int, x array<double>").collect())
    x, y, part = np.array([r["x"] for r in got]), np.array([r["toxic"] for r in got], float), np.array([r["part"] for r in got])
    fit, rest = part < 4, part == 4
    if len(got) == 0 or not 0 < y[fit].mean() < 1:
        return None
    trees = BoostedTrees().fit(x[fit], y[fit])
    return learned, trees, isotonic(trees.margin(x[rest]), y[rest])


def score(docs: DataFrame, model, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``doc_id, score, predicted`` of every row and whole text; null and empty texts have all features zero.

    Without a model every score is 0.
    """

    def step(batches):
        for batch in batches:
            if model is None:
                p = np.zeros(batch.num_rows)
            else:
                learned, trees, knots = model
                x = np.array([features_of(t, learned) for _, t in texts(batch)]).reshape(-1, FEATURES)
                p = calibrated(trees.margin(x), knots)
            yield {"doc_id": batch.column("doc_id"), "score": p, "predicted": (p >= 0.5).astype(np.int32)}

    return map_rows(doc_frame(docs, id_col, text_col), step, "doc_id long, score double, predicted int")


def toxicity(docs: DataFrame, labels: DataFrame, held_out_of: int = 5, **options) -> DataFrame:
    """Learn from labels outside fold 0 of ``held_out_of``, score all of ``docs``."""
    model = learn(docs, labels.where(fold(F.col("doc_id"), held_out_of) != 0), **options)
    return score(docs, model).withColumn("held_out", fold(F.col("doc_id"), held_out_of) == 0)
