"""Quality from weak labels: expectation-maximisation over heuristic labellers, then a hashed linear scorer."""

from __future__ import annotations

import re
import zlib
from collections import Counter

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from signedcluster.llm.common import bounded_sample, doc_frame, map_rows, texts

SLOTS = 1 << 14
LABELLERS = ("symbols", "capitals", "distinct", "commonest", "lines", "word_length", "length", "shouting", "digits")
SYMBOL = re.compile(r"[#$%&*^~<>|{}\[\]\\=@_+]")
CAPITAL = re.compile(r"[A-ZÀ-ÖØ-Þ]")
DIGIT = re.compile(r"\d")
LETTER = re.compile(r"[^\W\d_]")


def measures(text: str) -> tuple[dict[str, float], list[str]]:
    """What the labellers look at, over the whole text."""
    words = text.split()
    lines = [x for x in (y.strip() for y in text.split("\n")) if x]
    chars = max(len(text), 1)
    letters = max(len(text) - len(DIGIT.findall(text)) - text.count(" "), 1)
    counts = Counter(words)
    n = max(len(words), 1)
    return {
        "symbols": len(SYMBOL.findall(text)) / chars,
        "capitals": len(CAPITAL.findall(text)) / letters,
        "distinct": len(counts) / n,
        "commonest": max(counts.values(), default=0) / n,
        "lines": 1 - len(set(lines)) / max(len(lines), 1),
        "word_length": (chars - n) / n,
        "length": float(len(words)),
        "shouting": text.count("!") / n,
        "digits": len(DIGIT.findall(text)) / chars,
    }, words


def votes(m: dict[str, float]) -> list[int]:
    """1 good, 0 bad, 2 abstain, in the order of ``LABELLERS`` (thresholds are fixed values)."""
    n = m["length"]
    return [
        0 if m["symbols"] > 0.03 else 1 if m["symbols"] < 0.01 else 2,
        0 if m["capitals"] > 0.3 else 1 if m["capitals"] < 0.15 else 2,
        2 if n < 20 else 0 if m["distinct"] < 0.25 else 1 if m["distinct"] > 0.35 else 2,
        2 if n < 20 else 0 if m["commonest"] > 0.2 else 1 if m["commonest"] < 0.12 else 2,
        0 if m["lines"] > 0.3 else 2,
        0 if not 2 <= m["word_length"] <= 14 else 2,
        0 if n < 3 else 1 if n >= 40 else 2,
        0 if m["shouting"] > 0.15 else 1 if m["shouting"] < 0.02 else 2,
        0 if m["digits"] > 0.2 else 1 if m["digits"] < 0.05 else 2,
    ]


def fit_accuracies(patterns: np.ndarray, counts: np.ndarray, rounds: int = 60) -> tuple[float, np.ndarray]:
    """(share of good texts, P(vote | class) as classes x labellers x 3) from counts of vote patterns.

    The start is the majority vote, which also fixes which class is the good one.
    """
    good = (patterns == 1).sum(1) - 2 * (patterns == 0).sum(1)
    post = 1 / (1 + np.exp(-good.astype(float)))
    one_hot = np.eye(3)[patterns]
    for _ in range(rounds):
        share = float((post * counts).sum() / counts.sum())
        table = np.stack([np.einsum("p,plv->lv", w * counts, one_hot) + 0.5 for w in (1 - post, post)])
        table /= table.sum(2, keepdims=True)
        post = posterior(patterns, share, table)
    return share, table


def posterior(patterns: np.ndarray, share: float, table: np.ndarray) -> np.ndarray:
    logs = np.log(table)[:, np.arange(patterns.shape[1]), patterns].sum(2)
    share = min(max(share, 1e-6), 1 - 1e-6)
    return 1 / (1 + np.exp(-(logs[1] - logs[0] + np.log(share / (1 - share)))))


def hashed(m: dict[str, float], words: list[str]) -> tuple[np.ndarray, np.ndarray]:
    """Slots and values: banded measures, and shares of word endings and shapes."""
    slots, values = [], []

    def put(name: str, value: float):
        slots.append(zlib.crc32(name.encode("utf-8", "surrogatepass")) % SLOTS)
        values.append(value)

    for k, v in m.items():
        put(f"{k}:{int(np.log2(v + 1e-4) * 2)}", 1.0)
    n = max(len(words), 1)
    for e, c in Counter([w[-2:] for w in words]).items():
        put("e" + e, c / n)
    put("upper", sum(map(str.isupper, words)) / n)
    put("title", sum(map(str.istitle, words)) / n)
    put("bias", 1.0)
    return np.array(slots), np.array(values)


def train_linear(rows: list[tuple[np.ndarray, np.ndarray, float]], epochs: int = 6, rate: float = 0.3) -> np.ndarray:
    """Logistic regression on posterior labels by adaptive stochastic gradients."""
    w, seen = np.zeros(SLOTS), np.full(SLOTS, 1e-2)
    order = np.random.default_rng(11)
    for _ in range(epochs):
        for k in order.permutation(len(rows)):
            slots, values, y = rows[k]
            p = 1 / (1 + np.exp(-np.clip(w[slots] @ values, -30, 30)))
            g = (p - y) * values
            np.add.at(seen, slots, g**2)
            np.subtract.at(w, slots, rate * g / np.sqrt(seen[slots]))
    return w


def learn(docs: DataFrame, train_rows: int = 6000, id_col: str = "doc_id", text_col: str = "text"):
    """(share, accuracy table, weights). Vote patterns are counted over all texts (there are at most 3^9 of them); the
    linear scorer is fitted on at most ``train_rows`` texts, chosen by a hash. None on an empty table."""
    frame = doc_frame(docs, id_col, text_col)

    def vote(batches):
        seen: Counter = Counter()
        for batch in batches:
            for _, t in texts(batch):
                seen["".join(map(str, votes(measures(t or "")[0])))] += 1
        yield {"pattern": list(seen), "n": list(seen.values())}

    found = map_rows(frame.select("text"), vote, "pattern string, n long").groupBy("pattern").agg(F.sum("n")).collect()
    if not found:
        return None
    found = sorted(map(tuple, found))
    patterns = np.array([[int(c) for c in p] for p, _ in found])
    share, table = fit_accuracies(patterns, np.array([n for _, n in found], float))
    sample = bounded_sample(frame, train_rows)

    def features(batches):
        for batch in batches:
            out = {"slots": [], "values": [], "y": []}
            for _, t in texts(batch):
                m, words = measures(t or "")
                slots, values = hashed(m, words)
                out["slots"].append(slots.astype("<u2").tobytes())
                out["values"].append(values.astype("<f4").tobytes())
                out["y"].append(float(posterior(np.array([votes(m)]), share, table)[0]))
            yield out

    got = sorted(tuple(r) for r in map_rows(sample.select("text"), features, "slots binary, values binary, y double").collect())
    rows = [(np.frombuffer(bytes(s), "<u2").astype(int), np.frombuffer(bytes(v), "<f4").astype(float), y) for s, v, y in got]
    return share, table, train_linear(rows)


def quality(docs: DataFrame, model=None, id_col: str = "doc_id", text_col: str = "text", **options) -> DataFrame:
    """``doc_id, score, weak_label, predicted, kept`` of every row, over whole texts.

    ``score`` is the linear scorer's probability of good quality, ``weak_label`` the labellers' posterior; ``kept`` is
    true unless both find the text bad. Null and empty texts are scored as texts without a word.
    """
    model = model or learn(docs, id_col=id_col, text_col=text_col, **options)

    def step(batches):
        share, table, w = model
        for batch in batches:
            score, weak = [], []
            for _, t in texts(batch):
                m, words = measures(t or "")
                slots, values = hashed(m, words)
                score.append(float(1 / (1 + np.exp(-np.clip(w[slots] @ values, -30, 30)))))
                weak.append(float(posterior(np.array([votes(m)]), share, table)[0]))
            good = [int(s >= 0.5) for s in score]
            yield {"doc_id": batch.column("doc_id"), "score": score, "weak_label": weak, "predicted": good, "kept": [s >= 0.5 or v >= 0.5 for s, v in zip(score, weak, strict=True)]}

    schema = "doc_id long, score double, weak_label double, predicted int, kept boolean"
    if model is None:
        return docs.sparkSession.createDataFrame([], schema)
    return map_rows(doc_frame(docs, id_col, text_col), step, schema)
