"""SimHash near-duplicates linked through pivot distance tables."""

from __future__ import annotations

from itertools import combinations
from math import log2

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from signedcluster.llm.common import doc_frame, map_rows, popcount, text_mark, texts, without_rows, words_of
from signedcluster.operators.components import components
from signedcluster.shared import materialize


def fingerprint(text: str | None, shingle: int = 4, seed: int = 42) -> int:
    """64 majority bits over XXH64 of all word shingles, repeats included; zero without a word."""
    words = words_of(text)
    if not words:
        return 0
    joined = b" ".join(words)
    ends = np.cumsum(np.fromiter(map(len, words), np.int64, len(words)) + 1) - 1
    starts = np.concatenate(([0], ends[:-1] + 1))
    width = min(shingle, len(words))
    digest = xxhash.xxh64_intdigest
    spans = zip(starts[: len(words) - width + 1].tolist(), ends[width - 1 :].tolist(), strict=True)
    hashes = np.array([digest(joined[a:b], seed) for a, b in spans], dtype="<u8")
    ones = np.zeros(64, np.int64)
    for at in range(0, len(hashes), 1 << 15):
        part = hashes[at : at + (1 << 15)]
        ones += np.unpackbits(part.view(np.uint8).reshape(-1, 8), axis=1, bitorder="little").sum(0, dtype=np.int64)
    return int(np.packbits(2 * ones > len(hashes), bitorder="little").view("<u8")[0])


def fingerprints(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", shingle: int = 4, seed: int = 42) -> DataFrame:
    """``(doc_id, mark, fp)`` of every row; ``mark`` is a hash of the text, ``fp`` holds the 64 bits as a signed long."""

    def step(batches):
        for batch in batches:
            found = np.fromiter((fingerprint(t, shingle, seed) for _, t in texts(batch)), np.uint64, batch.num_rows)
            yield {"doc_id": batch.column("doc_id"), "mark": batch.column("mark"), "fp": found.view(np.int64)}

    return map_rows(doc_frame(docs, id_col, text_col, text_mark(text_col)), step, "doc_id long, mark long, fp long")


def block_masks(distinct: int, max_distance: int, bucket_rows: int = 64) -> list[int]:
    """Bit masks such that fingerprints within ``max_distance`` agree on at least one of them.

    The 64 bits are cut into ``max_distance + k`` blocks; every choice of ``k`` of them is a mask. More blocks give
    longer keys, so that a bucket of unrelated fingerprints stays near ``bucket_rows`` rows at any input size. Every
    choice is exact; only the cost differs.
    """
    need = log2(max(2, distinct) / bucket_rows)
    for k in range(1, 65 - max_distance):
        blocks = max_distance + k
        if 64 * k // blocks >= need or k >= 8:
            break
    edges = np.linspace(0, 64, blocks + 1).round().astype(int)
    part = [((1 << int(b)) - 1) ^ ((1 << int(a)) - 1) for a, b in zip(edges[:-1], edges[1:], strict=True)]
    return [sum(pick) for pick in combinations(part, k)]


def pivot_fingerprints(count: int = 24, seed: int = 7) -> np.ndarray:
    """Reference fingerprints, drawn once from a fixed seed."""
    return np.random.default_rng(seed).integers(0, 2**64, count, dtype=np.uint64)


def link_bucket_rows(group: np.ndarray, fps: np.ndarray, pivots: np.ndarray, max_distance: int) -> tuple[np.ndarray, np.ndarray, tuple]:
    """Links within equal values of the sorted array ``group``.

    Returns (row, smallest row of its local component) for rows that are linked, and counts (pairs, left after the
    pivot table, links). Pairs are met by shifts over the sorted rows, never stored beyond one shift and its links.
    """
    table = np.stack([popcount(fps ^ p) for p in pivots]).astype(np.int8)
    label = np.arange(len(fps))
    pairs = survived = linked = 0
    links_a, links_b = [], []
    here = np.arange(len(fps))
    for shift in range(1, len(fps)):
        here = here[here + shift < len(fps)]
        here = here[group[here] == group[here + shift]]
        if not len(here):
            break
        a, b = here, here + shift
        pairs += len(a)
        for coordinate in table:
            near = np.abs(coordinate[a] - coordinate[b]) <= max_distance
            a, b = a[near], b[near]
        survived += len(a)
        near = popcount(fps[a] ^ fps[b]) <= max_distance
        a, b = a[near], b[near]
        # Those that are already of one local component add nothing.
        fresh = label[a] != label[b]
        linked += int(near.sum())
        if fresh.any():
            links_a.append(a[fresh])
            links_b.append(b[fresh])
            _settle(label, np.concatenate(links_a), np.concatenate(links_b))
    rows = np.flatnonzero(label != np.arange(len(fps)))
    return rows, label[rows], (pairs, survived, linked)


def _settle(label: np.ndarray, a: np.ndarray, b: np.ndarray) -> None:
    while True:
        low = np.minimum(label[a], label[b])
        if (label[a] == low).all() and (label[b] == low).all():
            return
        np.minimum.at(label, label[a], low)
        np.minimum.at(label, label[b], low)
        np.minimum.at(label, a, low)
        np.minimum.at(label, b, low)
        while (label[label] != label).any():
            label[:] = label[label]


def near_links(distinct: DataFrame, n_distinct: int, max_distance: int = 4, pivots: int = 24, bucket_cap: int = 2048) -> DataFrame:
    """Links ``(u, v)`` over ``distinct(fp, rep)`` that join all fingerprints within ``max_distance``.

    Candidates share a masked key; a bucket above ``bucket_cap`` rows is cut into chunks and every pair of chunks is a
    bucket of its own, so no task holds more than two chunks and no pair is lost. In a bucket, distances to the pivot
    fingerprints are tabulated; a pair whose coordinates differ by more than ``max_distance`` anywhere cannot be linked
    (triangle inequality) and is discarded; survivors are compared in full. Each bucket returns a spanning forest, not
    all its pairs.
    """
    signed = lambda m: m - (1 << 64) if m >> 63 else m
    masks = block_masks(n_distinct, max_distance)
    keyed = distinct.select(
        "fp", "rep", F.posexplode(F.array(*[F.col("fp").bitwiseAND(F.lit(signed(m)).cast("long")) for m in masks])).alias("mask", "key")
    )
    sizes = materialize(keyed.groupBy("mask", "key").agg(F.count("*").alias("n")).where("n > 1"), "buckets")
    chunk = F.pmod(F.xxhash64("fp", F.lit(11)), F.col("chunks")).cast("int")
    rows = (
        keyed.join(sizes, ["mask", "key"])
        .withColumn("chunks", F.ceil(F.col("n") / F.lit(bucket_cap)).cast("int"))
        .withColumn("mine", chunk)
        .withColumn("other", F.explode(F.expr("sequence(0, chunks - 1)")))
        .select("fp", "rep", F.xxhash64("mask", "key", F.least("mine", "other"), F.greatest("mine", "other")).alias("bucket"))
    )
    points = pivot_fingerprints(pivots)

    def step(batches):
        held: list[pa.RecordBatch] = []

        def work(batch):
            group = batch.column("bucket").to_numpy()
            fps = batch.column("fp").to_numpy().view(np.uint64)
            reps = batch.column("rep").to_numpy()
            r, low, _ = link_bucket_rows(group, fps, points, max_distance)
            return {"u": reps[low], "v": reps[r]}

        for batch in batches:
            held.append(batch)
            whole = pa.Table.from_batches(held).combine_chunks()
            group = whole.column("bucket").to_numpy()
            last = np.searchsorted(group, group[-1]) if len(group) else 0
            if last:
                yield work(whole.slice(0, last).to_batches()[0])
            held = whole.slice(last).combine_chunks().to_batches()
        if held:
            yield work(pa.Table.from_batches(held).combine_chunks().to_batches()[0])

    dealt = rows.repartition("bucket").sortWithinPartitions("bucket")
    return map_rows(dealt, step, "u long, v long").where("u <> v").distinct()


def marked_duplicates(
    docs: DataFrame,
    id_col: str = "doc_id",
    text_col: str = "text",
    shingle: int = 4,
    seed: int = 42,
    max_distance: int = 4,
    pivots: int = 24,
) -> DataFrame:
    """``doc_id, mark, fp, first`` of each row: ``first`` is the least (id is null, id, mark) of the row's class."""
    fps = materialize(fingerprints(docs, id_col, text_col, shingle, seed), "fps")
    row = F.struct(F.col("doc_id").isNull().alias("none"), "doc_id", "mark")
    reps = materialize(fps.groupBy("fp").agg(F.min(row).alias("first")), "reps")
    found = components(near_links(reps.select("fp", F.col("fp").alias("rep")), reps.count(), max_distance, pivots)).withColumnRenamed("v", "fp")
    placed = materialize(reps.join(found, "fp", "left").select("fp", F.coalesce("comp", "fp").alias("comp"), "first"), "placed")
    firsts = placed.groupBy("comp").agg(F.min("first").alias("first"))
    classes = materialize(placed.select("fp", "comp").join(firsts, "comp").select("fp", "first"), "classes")
    return fps.join(classes, "fp").select("doc_id", "mark", "fp", "first")


def near_duplicates(docs: DataFrame, **options) -> DataFrame:
    """One row per input row: ``doc_id, fp, component_id`` (the smallest id reachable by links of near fingerprints).

    Equal fingerprints collapse to one row first, so groups of copies cost one row each. Null and empty texts
    and texts without a word have fingerprint zero and are linked like any other. Rows with a null id are linked like others;
    a class of null ids only has a null ``component_id``. An empty table gives an empty result.
    """
    return marked_duplicates(docs, **options).select("doc_id", "fp", F.col("first.doc_id").alias("component_id"))


def keep_one_per_class(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", **options) -> DataFrame:
    """``docs`` with one row of each class: the smallest id (rows with an id before rows without), of one id the smallest
    text hash. Each row has its own verdict, so other rows of a repeated id stay; repeats of the kept row stay with it."""
    found = marked_duplicates(docs, id_col=id_col, text_col=text_col, **options)
    other = ~F.col("doc_id").eqNullSafe(F.col("first.doc_id")) | (F.col("mark") != F.col("first.mark"))
    return without_rows(docs, found.where(other), id_col, text_col)
