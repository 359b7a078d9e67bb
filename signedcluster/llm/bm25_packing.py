"""Lexical retrieval packing: a sharded BM25 inverted index fills each seed's window with unused neighbours."""

from __future__ import annotations

import heapq
import zlib

import numpy as np
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from signedcluster.llm.common import map_rows
from signedcluster.llm.tokens import Distinct, id_arrays, id_counts, id_type, token_table, tokenizer_file, vocabulary_size
from signedcluster.shared import materialize

PIECE = "doc_id long, start long, length long, ids_crc32 long, doc_tokens long, sequence_id long, offset long"
K1, B = 1.2, 0.75


def crc_of(ids: np.ndarray) -> int:
    return zlib.crc32(ids.astype("<u4").tobytes())


class Postings:
    """BM25 weights of a shard's documents by term.

    Terms in more than a share ``dense`` of the shard have a column of a matrix, and their part of all scores is one
    product; the others have posting lists.
    """

    def __init__(self, terms: list[np.ndarray], counts: list[np.ndarray], lengths: np.ndarray, idf: np.ndarray, mean_length: float, dense: float = 0.05):
        n = len(terms)
        doc = np.repeat(np.arange(n, dtype=np.int32), [len(t) for t in terms])
        term = np.concatenate(terms) if n else np.zeros(0, np.int64)
        tf = np.concatenate(counts).astype(np.float32) if n else np.zeros(0, np.float32)
        norm = (K1 * (1 - B + B * lengths / max(mean_length, 1e-9))).astype(np.float32)
        weight = (idf[term] * tf * (K1 + 1) / (tf + norm[doc])).astype(np.float32)
        held, at, many = np.unique(term, return_inverse=True, return_counts=True)
        column = np.cumsum(many > dense * n) - 1
        wide = (many > dense * n)[at]
        matrix = np.zeros((n, int(column[-1]) + 1 if n and len(column) else 0), np.float32)
        matrix[doc[wide], column[at[wide]]] = weight[wide]
        self.common = (matrix > 0).astype(np.float32) @ matrix.T
        doc, at, weight = doc[~wide], at[~wide], weight[~wide]
        self.query = np.split(at, np.searchsorted(doc, np.arange(1, n)))
        order = np.argsort(at, kind="stable")
        self.doc, self.weight, self.n = doc[order], weight[order], n
        self.first = np.searchsorted(at[order], np.arange(len(held) + 1))

    def scores(self, seed: int) -> np.ndarray:
        """BM25 score of every document of the shard for the seed's distinct terms."""
        at = self.query[seed]
        a = self.first[at]
        size = self.first[at + 1] - a
        index = np.repeat(a - np.cumsum(size) + size, size) + np.arange(int(size.sum()))
        return self.common[seed] + np.bincount(self.doc[index], self.weight[index], self.n)


def route_of(terms: np.ndarray, df: np.ndarray) -> int:
    """The rarest term that another document has too, ties by id; -1 without any."""
    shared = terms[df[terms] > 1]
    return int(shared[np.lexsort((shared, df[shared]))[0]]) if len(shared) else -1


def plan_shards(routes: list[tuple[int, int]], df: np.ndarray, shard_docs: int) -> list[tuple[int, int, int]]:
    """(route, first shard, shards) from the documents of each route, in the order of how rare the route's term is.

    Routes of few documents share a shard, one of more than ``shard_docs`` is dealt over shards of its own.
    """
    out, shard, held = [], 0, 0
    for route, n in sorted(routes, key=lambda x: (int(df[x[0]]) if x[0] >= 0 else -1, x[0])):
        if n > shard_docs:
            many = -(-n // shard_docs)
            shard += held > 0
            out.append((route, shard, many))
            shard, held = shard + many, 0
            continue
        if held + n > shard_docs:
            shard, held = shard + 1, 0
        out.append((route, shard, 1))
        held += n
    return out


def fill_windows(lengths: list[int], postings: Postings, window: int):
    """Windows of exactly ``window`` ids (the last may be shorter) as lists of (document, start, length).

    The seed is the longest unused piece; its neighbours follow by falling score, ties by position. The piece that
    overflows is cut at the window's end and seeds a later window with what is left.
    """
    left = list(lengths)
    seeds = [(-n, k) for k, n in enumerate(left) if n]
    heapq.heapify(seeds)
    unused = np.array(left) > 0
    while seeds:
        n, seed = heapq.heappop(seeds)
        if left[seed] != -n or not n:
            continue
        room, filled = window, []

        def take(k):
            nonlocal room
            n = min(room, left[k])
            filled.append((k, lengths[k] - left[k], n))
            left[k] -= n
            room -= n
            if left[k]:
                heapq.heappush(seeds, (-left[k], k))
            else:
                unused[k] = False

        take(seed)
        if room and unused.any():
            score = postings.scores(seed)
            free = np.flatnonzero(unused)
            # A window needs few neighbours; more are ranked only if those don't fill it.
            some = min(len(free), 32)
            while room:
                near = free if some == len(free) else free[np.argpartition(-score[free], some - 1)[:some]]
                for k in near[np.lexsort((near, -score[near]))].tolist():
                    if room and left[k] and unused[k]:
                        take(k)
                free = free[unused[free]]
                if not len(free):
                    break
                some = min(len(free), some * 4)
        yield filled


def pack_documents(
    docs: DataFrame,
    tokenizer: str | None = None,
    window: int = 1024,
    end_id: int = 0,
    shard_docs: int = 1024,
    id_col: str = "doc_id",
    text_col: str = "text",
) -> DataFrame:
    """One row per piece: ``doc_id, start, length, ids_crc32, doc_tokens, sequence_id, offset``.

    Each document's ids are its text's and ``end_id``. Windows that a document fills alone are cut from its start on;
    what remains (less than a window) is packed with neighbours of its shard. Documents are dealt to shards by the rarest
    term that they share with another one, so copies and documents of like words meet; a term of more than ``shard_docs``
    documents has several shards, dealt by a hash, so no group of copies is one task's. A seed searches its own shard
    only, which makes the neighbours approximate (README has the measured recall). The index holds all terms
    with their whole counts; document frequencies and the mean length are those of all documents. Every id is in one
    piece; all windows are full except one a shard.

    Null texts are empty: the end id alone. Repeated rows are packed once each. An empty table gives no piece.
    """
    path = tokenizer or tokenizer_file("byte_bpe_50k.json")
    dtype, size = id_type(path), vocabulary_size(path)
    tokens = materialize(token_table(docs, path, keep_space=True, end_id=end_id, id_col=id_col, text_col=text_col), "tokens")
    n_docs, n_ids = tokens.agg(F.count("*"), F.coalesce(F.sum("n"), F.lit(0))).first()
    df = id_counts(tokens, dtype, size, per_document=True)
    idf = np.log1p((n_docs - df + 0.5) / (df + 0.5)).astype(np.float32)
    mean_length = n_ids / max(n_docs, 1)

    def alone(batches):
        """Windows that one document fills."""
        place = TaskContext.get().partitionId() << 32
        made = 0
        for batch in batches:
            out = {k.split()[0]: [] for k in PIECE.split(", ")}
            for d, n, ids in zip(batch.column("doc_id").to_pylist(), batch.column("n").to_pylist(), batch.column("ids"), strict=True):
                if n < window:
                    continue
                ids = np.frombuffer(ids.as_py(), dtype)
                for at in range(0, n - window + 1, window):
                    for k, v in zip(out, (d, at, window, crc_of(ids[at : at + window]), n, place + made, 0), strict=True):
                        out[k].append(v)
                    made += 1
            yield out

    def rest(batches):
        distinct = Distinct(size)
        for batch in batches:
            out = {"doc_id": [], "n": [], "tail": [], "terms": [], "counts": [], "route": []}
            all_ids, edges = id_arrays(batch.column("ids"), dtype)
            for d, n, a in zip(batch.column("doc_id").to_pylist(), batch.column("n").to_pylist(), edges[:-1].tolist(), strict=True):
                if n % window == 0:
                    continue
                ids = all_ids[a : a + n]
                terms, counts = distinct(ids)
                out["doc_id"].append(d)
                out["n"].append(n)
                out["tail"].append(ids[n - n % window :].tobytes())
                out["terms"].append(terms.tobytes())
                out["counts"].append(counts.astype("<u1" if counts.max() < 256 else "<u4").tobytes())
                out["route"].append(route_of(terms, df))
            yield out

    def pack(batches):
        for shard, rows in _groups(batches, "shard"):
            tails = [np.frombuffer(x, dtype) for x in rows["tail"]]
            lengths = np.array(rows["n"])
            terms = [np.frombuffer(x, dtype).astype(np.int64) for x in rows["terms"]]
            counts = [np.frombuffer(x, f"<u{len(x) // len(t)}") for x, t in zip(rows["counts"], terms, strict=True)]
            index = Postings(terms, counts, lengths, idf, mean_length)
            out = {k.split()[0]: [] for k in PIECE.split(", ")}
            for made, filled in enumerate(fill_windows([len(t) for t in tails], index, window)):
                offset = 0
                for k, a, n in filled:
                    whole = rows["n"][k]
                    start = whole - len(tails[k]) + a
                    row = (rows["doc_id"][k], start, n, crc_of(tails[k][a : a + n]), whole, (1 << 62) + (shard << 32) + made, offset)
                    for name, v in zip(out, row, strict=True):
                        out[name].append(v)
                    offset += n
            yield out

    tails = materialize(map_rows(tokens, rest, "doc_id long, n long, tail binary, terms binary, counts binary, route int"), "tails")
    # As many rows as the vocabulary has ids, at most.
    plan = plan_shards([tuple(r) for r in tails.groupBy("route").count().collect()], df, shard_docs)
    routes = docs.sparkSession.createDataFrame(plan, "route int, first long, many long")
    spread = F.col("first") + F.pmod(F.xxhash64("doc_id", "tail"), F.col("many"))
    dealt = tails.join(F.broadcast(routes), "route").withColumn("shard", spread).drop("route", "first", "many")
    shards = max((first + many for _, first, many in plan), default=1)
    dealt = dealt.repartition(max(shards // 2, 1), "shard").sortWithinPartitions("shard", "doc_id", "n", "tail")
    return map_rows(tokens, alone, PIECE).unionByName(map_rows(dealt, pack, PIECE))


def _groups(batches, key: str):
    """(key, columns as lists) of each run of equal keys in rows sorted by it."""
    now, held = None, None
    for batch in batches:
        cols = batch.to_pydict()
        keys = np.array(cols[key])
        edges = np.flatnonzero(np.diff(keys)) + 1
        for a, b in zip([0, *edges.tolist()], [*edges.tolist(), len(keys)], strict=True):
            if b <= a:
                continue
            if held is None or keys[a] != now:
                if held is not None:
                    yield now, held
                now, held = int(keys[a]), {k: [] for k in cols}
            for k in cols:
                held[k].extend(cols[k][a:b])
    if held is not None:
        yield now, held
