"""Language identification by nearest centroid over normalised TF-IDF vectors of byte trigrams."""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from signedcluster.llm.common import doc_frame, has_letter, map_rows, text_mark, texts, without_rows

DIMS = 4096
CHUNK = 1 << 20
#: Lengths are told apart by powers of two of their trigrams; the shortest beginning of a text has so many letters.
LEVELS, SHORTEST = 24, 12
TO_SPACE = bytes(b if b >= 128 or 97 <= b <= 122 else 32 for b in range(256))


def trigram_counts(text: str) -> np.ndarray:
    """Counts of hashed byte trigrams of the whole lower-cased text; runs of other ASCII than letters are one space."""
    letters = b" ".join(text.lower().encode("utf-8", "surrogatepass").translate(TO_SPACE).split())
    raw = np.frombuffer(b" " + letters + b" ", np.uint8).astype(np.uint32)
    total = np.zeros(DIMS, np.int64)
    for at in range(0, max(len(raw) - 2, 0), CHUNK):
        part = raw[at : at + CHUNK + 2]
        mixed = part[:-2] * np.uint32(0x9E3779B1) ^ part[1:-1] * np.uint32(0x85EBCA77) ^ part[2:] * np.uint32(0xC2B2AE3D)
        total += np.bincount((mixed >> np.uint32(9)) & np.uint32(DIMS - 1), minlength=DIMS)
    return total


def unit_rows(counts: np.ndarray, idf: np.ndarray) -> np.ndarray:
    rows = np.log1p(counts).astype(np.float32) * idf
    return rows / np.maximum(np.linalg.norm(rows, axis=1, keepdims=True), 1e-12)


@dataclass
class Centroids:
    languages: list[str]
    owner: np.ndarray
    rows: np.ndarray
    idf: np.ndarray
    least: np.ndarray


def levels(counts: np.ndarray) -> np.ndarray:
    return np.clip(np.log2(np.maximum(counts.sum(1), 1)).astype(int), 0, LEVELS - 1)


def least_cosines(close: np.ndarray, level: np.ndarray, low: float, fewest: int = 20) -> np.ndarray:
    """(centroid x level) ``low`` quantile of the cosines of a centroid's own members of that length or half of it.

    A longer text is nearer to its centroid, so a level with fewer than ``fewest`` members takes what holds for shorter ones.
    """
    best, near = close.argmax(1), close.max(1)
    out = np.zeros((close.shape[1], LEVELS), np.float32)
    for j in range(len(out)):
        for k in range(LEVELS):
            mine = near[(best == j) & ((level == k) | (level == k - 1))]
            if len(mine) >= fewest:
                out[j, k] = np.quantile(mine, low)
    return np.maximum.accumulate(out, axis=1)


def spherical_kmeans(rows: np.ndarray, k: int, rounds: int = 12) -> np.ndarray:
    """Unit centroids; the start is spread by taking the row least similar to those taken."""
    taken = [rows.mean(0)]
    for _ in range(1, min(k, len(rows))):
        taken.append(rows[np.argmin((rows @ np.array(taken).T).max(1))])
    centre = np.array(taken)
    for _ in range(rounds):
        centre /= np.maximum(np.linalg.norm(centre, axis=1, keepdims=True), 1e-12)
        near = np.argmax(rows @ centre.T, axis=1)
        centre = np.array([rows[near == j].mean(0) if (near == j).any() else centre[j] for j in range(len(centre))])
    return centre / np.maximum(np.linalg.norm(centre, axis=1, keepdims=True), 1e-12)


def fit(train: DataFrame, per_language: int = 1000, clusters: int = 4, low: float = 0.005) -> Centroids | None:
    """``train(doc_id, text, lang)``. Document frequencies are of all its rows; centroids are fitted on about
    ``per_language`` rows of each language, chosen by a hash of the id, so what reaches the driver has a bound.
    The least cosine at which a text is kept is the ``low`` quantile of a centroid's members of its length, the members
    being the chosen texts and their beginnings. Null and empty texts are left out. Returns None when nothing can be learned."""
    train = train.where("lang is not null and text is not null and text <> ''")

    def frequencies(batches):
        total, n = np.zeros(DIMS, np.int64), 0
        for batch in batches:
            for _, t in texts(batch):
                total += trigram_counts(t) > 0
                n += 1
        yield {"dim": np.append(np.arange(DIMS), -1), "n": np.append(total, n)}

    held = dict(map_rows(train.select("text"), frequencies, "dim int, n long").groupBy("dim").agg(F.sum("n")).collect())
    if not held.get(-1):
        return None
    df = np.array([held.get(k, 0) for k in range(DIMS)])
    idf = np.log((1 + held[-1]) / (1 + df)).astype(np.float32) + 0.05
    counts = dict(train.groupBy("lang").count().collect())
    share = F.create_map(*[F.lit(x) for lang, n in counts.items() for x in (lang, min(1.0, per_language / n))])[F.col("lang")]
    chosen = train.where(F.pmod(F.xxhash64("doc_id", "text"), F.lit(1 << 20)) < share * (1 << 20))

    def features(batches):
        for batch in batches:
            out = {k: [] for k in ("lang", "whole", "dims", "counts")}
            languages = batch.column("lang").to_pylist()
            for row, t in texts(batch):
                for k in range(LEVELS):
                    part = t[: SHORTEST << k]
                    whole = len(part) == len(t)
                    if whole or has_letter(part):
                        c = trigram_counts(part)
                        dims = np.flatnonzero(c)
                        for name, v in zip(out, (languages[row], whole, dims.astype("<u2").tobytes(), np.minimum(c[dims], 65535).astype("<u2").tobytes()), strict=True):
                            out[name].append(v)
                    if whole:
                        break
            yield out

    def dense(mine):
        out = np.zeros((len(mine), DIMS), np.float32)
        for row, (dims, n) in zip(out, mine, strict=True):
            row[np.frombuffer(dims, "<u2")] = np.frombuffer(n, "<u2")
        return out

    by_language: dict[str, list] = {}
    parts = []
    for lang, whole, dims, n in map_rows(chosen, features, "lang string, whole boolean, dims binary, counts binary").toLocalIterator():
        parts.append((bytes(dims), bytes(n)))
        if whole:
            by_language.setdefault(lang, []).append(parts[-1])
    rows, owner = [], []
    languages = sorted(by_language)
    for k, lang in enumerate(languages):
        mine = sorted(by_language[lang])
        centre = spherical_kmeans(unit_rows(dense(mine), idf), clusters)
        rows.append(centre)
        owner += [k] * len(centre)
    centres = np.concatenate(rows).astype(np.float32)
    close, level = [], []
    for at in range(0, len(parts), 256):
        held_part = dense(parts[at : at + 256])
        # A text without a letter is rejected before any distance.
        held_part = held_part[held_part.sum(1) > 0]
        close.append(unit_rows(held_part, idf) @ centres.T)
        level.append(levels(held_part))
    least = least_cosines(np.concatenate(close), np.concatenate(level), low)
    return Centroids(languages, np.array(owner), centres, idf, least)


def predict(docs: DataFrame, model: Centroids | None, max_distance: float = 0.98, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``doc_id, lang_pred, score, rejected`` of every row, ``score`` the cosine with the nearest centroid (0 to 1).

    A text that is null or has no letter is ``und``, score 0 and rejected. Others get the language of the nearest
    centroid; they are rejected when its distance (1 - cosine) is above ``max_distance``, or above what is usual for
    the centroid's own members of that length (see :func:`fit`). Ties go to the first language
    by name. Without a model everything is ``und``.
    """
    return marked_predictions(docs, model, max_distance, id_col, text_col).drop("mark")


def marked_predictions(docs: DataFrame, model: Centroids | None, max_distance: float, id_col: str, text_col: str) -> DataFrame:
    """As :func:`predict`, with the ``mark`` of each row's text."""
    frame = doc_frame(docs, id_col, text_col, text_mark(text_col))

    def step(batches):
        for batch in batches:
            n = batch.num_rows
            lang, score, least = ["und"] * n, np.zeros(n), np.full(n, 1 - max_distance)
            held, at = [], []

            def flush():
                counts = np.array(held)
                close = unit_rows(counts, model.idf) @ model.rows.T
                best = close.argmax(1)
                least[at] = np.maximum(1 - max_distance, model.least[best, levels(counts)])
                for row, b, c in zip(at, best.tolist(), close.max(1).tolist(), strict=True):
                    lang[row], score[row] = model.languages[model.owner[b]], min(max(c, 0.0), 1.0)
                held.clear()
                at.clear()

            for row, t in texts(batch):
                if model is not None and t and has_letter(t):
                    held.append(trigram_counts(t))
                    at.append(row)
                    if len(held) == 256:
                        flush()
            if held:
                flush()
            yield {"doc_id": batch.column("doc_id"), "mark": batch.column("mark"), "lang_pred": lang, "score": score, "rejected": [x == "und" or s < m for x, s, m in zip(lang, score.tolist(), least.tolist(), strict=True)]}

    return map_rows(frame, step, "doc_id long, mark long, lang_pred string, score double, rejected boolean")


def drop_rejected(docs: DataFrame, model: Centroids | None, max_distance: float = 0.98, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``docs`` without the rows that :func:`predict` rejects, each row by its own text (ids may repeat or be null)."""
    return without_rows(docs, marked_predictions(docs, model, max_distance, id_col, text_col).where("rejected"), id_col, text_col)
