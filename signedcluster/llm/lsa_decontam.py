"""Benchmark decontamination by latent semantic retrieval and sequence checks."""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from signedcluster.llm.common import by_bytes, doc_frame, map_rows, numbered_words, offsets_of, text_mark, without_rows, words_of

SLOT_BITS = 18
SLOTS = 1 << SLOT_BITS
PART = 1 << 12
BLOCK = 16
NUMBERS = 1 << 21
PAIR = ("doc_id", "mark", "item_id", "cosine", "share", "answer_found")
STRIP = b".,;:!?\"'()[]{}"
SIGNS = np.isin(np.arange(256), list(STRIP))


def plain_words(text: str | None) -> list[bytes]:
    return [x for w in words_of(text) if (x := w.strip(STRIP))]


def slots_of(words: pa.StringArray) -> np.ndarray:
    """A slot for each word, by a polynomial hash of its bytes without the signs of ``STRIP`` around it."""
    ends = offsets_of(words).astype(np.int64)
    data = np.frombuffer(words.buffers()[2] or b"", np.uint8)[ends[0] : ends[-1]]
    a, b = ends[:-1] - ends[0], ends[1:] - ends[0]
    for _ in range(len(data)):
        drop = np.flatnonzero(a < b)
        drop = drop[SIGNS[data[a[drop]]]]
        if not len(drop):
            break
        a[drop] += 1
    for _ in range(len(data)):
        drop = np.flatnonzero(a < b)
        drop = drop[SIGNS[data[b[drop] - 1]]]
        if not len(drop):
            break
        b[drop] -= 1
    # The sum of byte * P^place over a word, divided by P^(place of its start); P is odd, so it has an inverse.
    sums = np.zeros(len(data) + 1, np.uint64)
    place = np.arange(len(data) + 1)
    power = POWERS[0][place & 4095] * POWERS[1][place >> 12 & 4095] * POWERS[2][place >> 24]
    np.cumsum((data.astype(np.uint64) + np.uint64(1)) * power[:-1], out=sums[1:])
    inverse = INVERSES[0][a & 4095] * INVERSES[1][a >> 12 & 4095] * INVERSES[2][a >> 24]
    h = (sums[b] - sums[a]) * inverse
    h = (h ^ h >> np.uint64(32)) * np.uint64(0x9E3779B97F4A7C15)
    return (h >> np.uint64(64 - SLOT_BITS)).astype(np.int64)


def powers(base: int) -> list[np.ndarray]:
    """Powers 0 to 4095 of base, of its 4096th and of its 2^24th power (the last fewer), modulo 2^64."""
    out = []
    for step, many in ((1, 4096), (1 << 12, 4096), (1 << 24, 128)):
        one = pow(base, step, 1 << 64)
        out.append(np.array([pow(one, k, 1 << 64) for k in range(many)], np.uint64))
    return out


BASE = 0xD6E8FEB86659FD93
POWERS, INVERSES = powers(BASE), powers(pow(BASE, -1, 1 << 64))


def document_frequencies(docs: DataFrame) -> tuple[np.ndarray, int]:
    """Documents that hold each word slot, over all of ``docs(text)``; the number of slots bounds what is gathered."""

    def step(batches):
        total, n = np.zeros(SLOTS, np.int64), 0
        for batch in batches:
            for part in by_bytes(batch, "text"):
                words, at, edges = numbered_words(part.column("text"))
                doc = np.repeat(np.arange(part.num_rows), np.diff(edges))
                held = np.sort(doc * SLOTS + slots_of(words)[at])
                total += np.bincount(held[np.flatnonzero(np.diff(held, prepend=-1))] & (SLOTS - 1), minlength=SLOTS)
                n += part.num_rows
        parts = total.astype(np.int32).reshape(-1, PART)
        yield {"part": [*range(len(parts)), -1], "df": [*(p.tobytes() for p in parts), b""], "n": [*[0] * len(parts), n]}

    def add(batches):
        sums: dict[int, np.ndarray] = {}
        docs: dict[int, int] = {}
        for batch in batches:
            for part, df, n in zip(*(batch.column(k).to_pylist() for k in ("part", "df", "n")), strict=True):
                docs[part] = docs.get(part, 0) + n
                sums[part] = sums.get(part, 0) + np.frombuffer(df, np.int32).astype(np.int64)
        yield {"part": list(sums), "df": [v.tobytes() for v in sums.values()], "n": [docs[k] for k in sums]}

    schema = "part int, df binary, n long"
    out, n = np.zeros((SLOTS // PART, PART), np.int64), 0
    for part, df, docs_n in map_rows(map_rows(docs.select("text"), step, schema).repartition("part"), add, schema).collect():
        if part >= 0:
            out[part] = np.frombuffer(bytes(df), np.int64)
        n += docs_n
    return out.ravel(), n


def passages(items: list[tuple[int, str | None]], words: int = 64) -> Iterator[tuple[int, list[bytes]]]:
    """Benchmark items in passages of at most ``words`` words; a short rest joins its predecessor."""
    for item, text in items:
        all_words = plain_words(text)
        cuts = list(range(0, max(len(all_words) - words // 2, 1), words))
        for a, b in zip(cuts, [*cuts[1:], len(all_words)], strict=True):
            if all_words[a:b]:
                yield item, all_words[a:b]


def randomised_svd(dims: list[np.ndarray], weights: list[np.ndarray], width: int, rank: int, rounds: int = 3, seed: int = 3) -> np.ndarray:
    """Right singular vectors (width x rank) of the sparse matrix with these rows."""
    basis = np.linalg.qr(np.random.default_rng(seed).standard_normal((width, rank)))[0]
    for _ in range(rounds):
        total = np.zeros(basis.shape)
        for d, w in zip(dims, weights, strict=True):
            total[d] += w[:, None] * (w @ basis[d])
        basis = np.linalg.qr(total + 1e-9 * basis)[0]
    return basis


def block_bases(spark, blocks: list[tuple[np.ndarray, list[np.ndarray], list[np.ndarray]]]) -> list[np.ndarray]:
    """A basis for each block ``(slots, dims of its passages, weights)``, one block to a row, so each is factored by a task.

    The rank is the number of passages, so that a passage keeps its whole norm however many blocks there are.
    """
    rows = [(k, len(used), [len(d) for d in dims], np.concatenate(dims).astype("<u4").tobytes(), np.concatenate(weights).astype("<f4").tobytes()) for k, (used, dims, weights) in enumerate(blocks)]
    frame = spark.createDataFrame(rows, "block int, width int, sizes array<int>, dims binary, weights binary").repartition(max(1, min(len(rows), 64)))

    def step(batches):
        for batch in batches:
            for block, width, sizes, dims, weights in zip(*(batch.column(k).to_pylist() for k in ("block", "width", "sizes", "dims", "weights")), strict=True):
                cuts = np.cumsum(sizes)[:-1]
                d, w = np.split(np.frombuffer(dims, "<u4"), cuts), np.split(np.frombuffer(weights, "<f4").astype(float), cuts)
                yield {"block": [block], "basis": [randomised_svd(d, w, width, min(len(sizes), width)).astype("<f4").tobytes()]}

    out = [np.zeros((0, 1), np.float32)] * len(blocks)
    for block, basis in map_rows(frame, step, "block int, basis binary").toLocalIterator():
        out[block] = np.frombuffer(bytes(basis), "<f4").reshape(len(blocks[block][0]), -1)
    return out


class Index:
    """Latent passages of the benchmark, and what is needed to bring documents into the same spaces.

    Passages are cut into blocks of at most ``rank``, each with a basis of its own. The rows of all bases lie in one matrix
    by word: those of dimension d are ``start[d]`` to ``start[d + 1]``, ``block`` names the space of each. ``latent`` has a
    block's passages, ``first`` the number of the first of them, ``kept`` each passage's share of norm in its space.
    """

    def __init__(self, spark, benchmark: list[tuple[int, str | None]], df: np.ndarray, docs: int, rank: int):
        found = sorted(passages(benchmark), key=lambda x: (x[0] is not None, x[0] or 0, x[1]))
        self.items = [k for k, _ in found]
        self.words = [w for _, w in found]
        self.idf = (np.log((docs + 1) / (df + 1)) + 0.1).astype(np.float32)
        every = slots_of(pa.array([x.decode("utf-8", "replace") for w in self.words for x in w], pa.string()))
        slots = [np.unique(s, return_counts=True) for s in np.split(every, np.cumsum([len(w) for w in self.words])[:-1])] if found else []
        slots = [(held, self.idf[held] * tf) for held, tf in slots]
        used = np.unique(np.concatenate([held for held, _ in slots])) if slots else np.zeros(0, int)
        self.dim = np.full(SLOTS, -1, np.int32)
        self.dim[used] = np.arange(len(used))
        self.first, self.latent, self.kept = [0], [], np.zeros(0)
        if not found:
            self.start, self.block, self.weighted = np.zeros(1, np.int64), np.zeros(0, np.int64), np.zeros((0, 1), np.float32)
            return
        blocks = []
        for part in np.array_split(np.arange(len(found)), -(-len(found) // rank)):
            own = np.unique(np.concatenate([slots[k][0] for k in part]))
            dims = [np.searchsorted(own, slots[k][0]) for k in part]
            weights = [(w / np.linalg.norm(w)).astype("<f4") for _, w in (slots[k] for k in part)]
            blocks.append((own, dims, weights))
            self.first.append(self.first[-1] + len(part))
        bases = block_bases(spark, blocks)
        for (_, dims, weights), basis in zip(blocks, bases, strict=True):
            latent = np.array([w @ basis[d] for d, w in zip(dims, weights, strict=True)], np.float32)
            norm = np.linalg.norm(latent, axis=1, keepdims=True)
            self.kept = np.append(self.kept, norm)
            self.latent.append(latent / np.maximum(norm, 1e-9))
        dim = np.concatenate([self.dim[own] for own, _, _ in blocks])
        order = np.argsort(dim, kind="stable")
        self.block = np.repeat(np.arange(len(blocks)), [len(own) for own, _, _ in blocks])[order]
        self.start = np.searchsorted(dim[order], np.arange(len(used) + 1))
        stacked = np.zeros((len(dim), max(x.shape[1] for x in bases)), np.float32)
        at = 0
        for (own, _, _), basis in zip(blocks, bases, strict=True):
            stacked[at : at + len(own), : basis.shape[1]] = basis * self.idf[own][:, None]
            at += len(own)
        self.weighted = stacked[order]


def longest_common_subsequence(a: list[bytes], b: list[bytes]) -> int:
    """Bit-parallel over the shorter sequence's positions."""
    if len(a) > len(b):
        a, b = b, a
    places: dict[bytes, int] = {}
    for k, w in enumerate(a):
        places[w] = places.get(w, 0) | 1 << k
    full = (1 << len(a)) - 1
    row = full
    for w in b:
        hit = row & places.get(w, 0)
        row = ((row + hit) | (row - hit)) & full
    return len(a) - row.bit_count()


@dataclass
class Blocks:
    """Blocks of ``BLOCK`` words of many texts. ``doc`` and ``last`` (the document's last block) by block, ``at`` the
    first word; ``slot`` and ``of`` (its block) are the distinct words of each block, ``norm`` a block's squared weight."""

    doc: np.ndarray
    at: np.ndarray
    last: np.ndarray
    of: np.ndarray
    slot: np.ndarray
    norm: np.ndarray


def blocks_of(slots: np.ndarray, edges: np.ndarray, idf: np.ndarray) -> Blocks:
    """Blocks of the texts that start at ``edges`` in ``slots``; no block goes over the end of a text."""
    size = np.diff(edges)
    many = -(-size // BLOCK)
    ends = np.cumsum(many)
    doc = np.repeat(np.arange(len(size)), many)
    at = (np.arange(len(doc)) - np.repeat(ends - many, many)) * BLOCK
    # A row for each block; the last of a text is filled up with -1.
    held = np.full(len(doc) * BLOCK, -1, np.int32)
    held[np.arange(len(slots)) + np.repeat((ends - many) * BLOCK - edges[:-1], size)] = slots
    held = np.sort(held.reshape(-1, BLOCK), axis=1)
    # A word counts once in a block, so that a text that repeats one word is no longer than its weight.
    of, place = np.nonzero(np.diff(held, axis=1, prepend=-1))
    slot = held[of, place]
    norm = np.bincount(of, idf[slot].astype(np.float64) ** 2, len(doc))
    return Blocks(doc, at, np.repeat(ends - 1, many), of, slot, norm)


def windows(values: np.ndarray, near: dict[int, np.ndarray], axis: int = -1) -> dict[int, np.ndarray]:
    """Sums of ``values`` over windows of two and four blocks from each block on, that end with the document."""
    ahead = lambda x, k: np.concatenate((x[..., k:], np.zeros((*x.shape[:-1], min(k, x.shape[-1])), x.dtype)), -1) * near[k]
    values = np.moveaxis(values, axis, -1)
    two = values + ahead(values, 1)
    four = two + ahead(two, 2)
    return {2: np.moveaxis(two, -1, axis), 4: np.moveaxis(four, -1, axis)}


def find_candidates(blocks: Blocks, index: Index, min_cosine: float) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """(first block, blocks, passage, cosine) of windows of two and four blocks near a benchmark passage.

    Blocks go in stretches that overlap by a window, so that memory grows neither with a text nor with the passages.
    """
    n, out = len(blocks.doc), []
    stretch = max(64, NUMBERS // max(len(index.latent) * index.weighted.shape[1], 1))
    for at in range(0, n, stretch):
        to = min(at + stretch + 3, n)
        found = candidates_within(blocks, at, to, index, min_cosine)
        mine = found[0] < at + stretch
        out.append(tuple(x[mine] for x in found))
    return tuple(np.concatenate(x) for x in zip(*out, strict=True)) if out else (np.zeros(0, int),) * 4


def candidates_within(blocks: Blocks, first: int, to: int, index: Index, min_cosine: float) -> tuple[np.ndarray, ...]:
    none, n, spaces = (np.zeros(0, int),) * 4, to - first, len(index.latent)
    a, b = np.searchsorted(blocks.of, (first, to))
    slots, block = blocks.slot[a:b], blocks.of[a:b] - first
    dims = index.dim[slots]
    own = np.flatnonzero(dims >= 0)
    if not len(own):
        return none
    doc, last = blocks.doc[first:to], blocks.last[first:to] - first
    # The first block of a document's last window, however short the document is.
    head = np.arange(n) - blocks.at[first:to] // BLOCK
    near = {k: np.concatenate((doc[k:] == doc[:-k], np.zeros(min(k, n), bool))).astype(np.float32) for k in (1, 2)}
    square = windows(blocks.norm[first:to], near)
    # Each word has a row in every space whose passages hold it.
    begin = index.start[dims[own]]
    times = index.start[dims[own] + 1] - begin
    rows = np.repeat(begin - np.cumsum(times) + times, times) + np.arange(times.sum())
    place = index.block[rows] * n + np.repeat(block[own], times)
    # A window's part in a space is no longer than the sum of its blocks' parts, and no cosine passes that share of the
    # window; so most blocks are not projected at all.
    part = np.sqrt(np.bincount(place, np.repeat(index.idf[slots[own]].astype(np.float64) ** 2, times), spaces * n)).reshape(spaces, n)
    reach, starts, used = windows(part, near), {}, np.zeros((spaces, n + 3), bool)
    for width in (2, 4):
        real = np.arange(n) <= np.maximum(head, last + 1 - width)
        starts[width] = (reach[width] ** 2 >= min_cosine**2 * square[width]) & real
        for k in range(width):
            used[:, k : n + k] |= starts[width]
    keep = used[:, :n].ravel()[place]
    place, rows = place[keep], rows[keep]
    if not len(place):
        return none
    if spaces > 1:
        order = np.argsort(place, kind="stable")
        place, rows = place[order], rows[order]
    # The k-th words of all blocks are added together, as no two of them are of one block.
    first_row = np.flatnonzero(np.r_[True, place[1:] != place[:-1]])
    turn = np.arange(len(place)) - np.repeat(first_row, np.diff(first_row, append=len(place)))
    order = np.argsort(turn, kind="stable")
    low = np.zeros((spaces, n, index.weighted.shape[1]), np.float32)
    flat = low.reshape(spaces * n, -1)
    for some in np.split(order, np.cumsum(np.bincount(turn))[:-1]):
        flat[place[some]] += index.weighted[rows[some]]
    out = []
    for s in range(spaces):
        latent = index.latent[s]
        for width, total in windows(low[s, :, : latent.shape[1]], near, 0).items():
            here = np.flatnonzero(starts[width][s])
            here = here[np.einsum("ij,ij->i", total[here], total[here]) >= min_cosine**2 * square[width][here]]
            cosine = (total[here] @ latent.T) / np.sqrt(np.maximum(square[width][here], 1e-9))[:, None]
            row, passage = np.nonzero(cosine >= min_cosine)
            out.append((here[row] + first, np.full(len(row), width), passage + index.first[s], cosine[row, passage]))
    return tuple(np.concatenate(x) for x in zip(*out, strict=True))


def judge(region: list[bytes], passage: list[bytes], close: float, loose: float) -> tuple[float, bool, bool]:
    """(share of the passage found in order, whether its answer is found, contaminated).

    The answer is the passage's last quarter, three words at least. A share of ``close`` decides alone; from ``loose`` on
    the answer must be there as well (a paraphrase keeps the answer).
    """
    share = longest_common_subsequence(passage, region) / len(passage)
    answer = passage[-max(3, len(passage) // 4) :]
    found = longest_common_subsequence(answer, region) >= 0.8 * len(answer)
    return share, found, share >= close or (share >= loose and found)


def marked_pairs(
    docs: DataFrame,
    benchmark: DataFrame,
    rank: int = 96,
    min_cosine: float = 0.25,
    close: float = 0.8,
    loose: float = 0.5,
    id_col: str = "doc_id",
    text_col: str = "text",
    item_col: str = "item_id",
    item_text_col: str = "text",
) -> DataFrame:
    """As :func:`contaminated_pairs`, with the ``mark`` of each document's text."""
    frame = doc_frame(docs, id_col, text_col, text_mark(text_col))
    items = [(r[0], r[1]) for r in benchmark.select(F.col(item_col).cast("long"), F.col(item_text_col).cast("string")).where(F.col(item_text_col).isNotNull()).collect()]
    df, n = document_frequencies(frame)
    index = Index(docs.sparkSession, items, df, n, rank)

    def step(batches):
        for batch in batches:
            for part in by_bytes(batch, "text"):
                out = {k: [] for k in PAIR}
                ids, marks = part.column("doc_id").to_pylist(), part.column("mark").to_pylist()
                words, at, edges = numbered_words(part.column("text"))
                if not len(at) or not index.items:
                    continue
                blocks = blocks_of(slots_of(words)[at], edges, index.idf)
                bare: dict[int, bytes] = {}
                best: dict[tuple, tuple] = {}
                for block, width, p, c in zip(*(x.tolist() for x in find_candidates(blocks, index, min_cosine)), strict=True):
                    doc, passage = int(blocks.doc[block]), index.words[p]
                    a = int(blocks.at[block])
                    b = min(a + width * BLOCK, int(edges[doc + 1] - edges[doc]))
                    region = at[edges[doc] + max(0, a - len(passage)) : min(edges[doc] + b + len(passage), edges[doc + 1])].tolist()
                    for k in region:
                        if k not in bare:
                            bare[k] = words[k].as_py().encode().strip(STRIP)
                    share, found, bad = judge([bare[k] for k in region], passage, close, loose)
                    key = (doc, index.items[p])
                    if bad and (share, c) > best.get(key, (0, 0))[:2]:
                        best[key] = (share, c, found)
                for (doc, item), (share, c, found) in best.items():
                    for k, v in zip(PAIR, (ids[doc], marks[doc], item, min(float(c), 1.0), float(share), found), strict=True):
                        out[k].append(v)
                yield out

    return map_rows(frame, step, "doc_id long, mark long, item_id long, cosine double, share double, answer_found boolean")


def contaminated_pairs(docs: DataFrame, benchmark: DataFrame, **options) -> DataFrame:
    """``(doc_id, item_id, cosine, share, answer_found)`` of documents that hold a benchmark passage or a paraphrase.

    The benchmark is the query side and is held by the driver and the tasks: its size (rows of item text) is the bound.
    Document frequencies are of all documents. Passages of the benchmark are cut into blocks of at
    most ``rank``, each factored by a randomised SVD of its TF-IDF matrix at full rank, so that more passages make more
    spaces and none loses norm; overlapping windows of 32 and 64 words of each whole document are projected on it and compared
    by cosine; candidates then pass the checks of :func:`judge` on the words themselves. One row for each row of
    documents and item, the best window. Null and empty texts and items match nothing; items of null id, and documents
    of null id, are searched like any other and reported with their null id.
    """
    return marked_pairs(docs, benchmark, **options).drop("mark")


def drop_contaminated(docs: DataFrame, benchmark: DataFrame, id_col: str = "doc_id", text_col: str = "text", **options) -> DataFrame:
    """``docs`` without the rows that hold a benchmark passage, each row judged by its own text (ids may repeat or be null)."""
    return without_rows(docs, marked_pairs(docs, benchmark, id_col=id_col, text_col=text_col, **options), id_col, text_col)
