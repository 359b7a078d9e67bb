"""Graphs from tables, and generated graphs."""

from __future__ import annotations

from math import ceil

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from signedcluster.functions.groups import map_tables
from signedcluster.functions.sets import common, lists, pack, run_codes, run_hashes, unpack
from signedcluster.model import SignedGraph, normalise
from signedcluster.shared import materialize
from signedcluster.sources.tables import load, packed

REGION, NATION, CUSTOMER, ORDER, PART, SUPPLIER, DOCUMENT, ITEM = range(1, 9)


def fk_edges(child: DataFrame, child_kind: int, child_key: str, parent_kind: int, parent_key: str) -> DataFrame:
    """A positive edge from each row to the row it refers to."""
    return child.select(packed(parent_kind, parent_key).alias("u"), packed(child_kind, child_key).alias("v"))


def geo(spark: SparkSession, folder: str) -> SignedGraph:
    nation, customer, orders = (load(spark, folder, t) for t in ("nation", "customer", "orders"))
    edges = (
        fk_edges(nation, NATION, "n_nationkey", REGION, "n_regionkey")
        .unionByName(fk_edges(customer, CUSTOMER, "c_custkey", NATION, "c_nationkey"))
        .unionByName(fk_edges(orders, ORDER, "o_orderkey", CUSTOMER, "o_custkey"))
    )
    region = load(spark, folder, "region").select(packed(REGION, "r_regionkey").alias("v"))
    return normalise(edges, region.unionByName(customer.select(packed(CUSTOMER, "c_custkey").alias("v"))).unionByName(nation.select(packed(NATION, "n_nationkey").alias("v"))))


def chain_edges(rows: DataFrame, key: str, order: list, gap=None) -> DataFrame:
    """Each row to the next of its key; ``gap`` tells whether the pair (columns ``here``, ``next``) is near enough."""
    w = Window.partitionBy(key).orderBy(*order)
    near = gap(w) if gap else F.lit(True)
    found = rows.select(F.col("id").alias("u"), F.lead("id").over(w).alias("v"), near.alias("near"))
    return found.where("v is not null and near").select("u", "v")


def event_chain(spark: SparkSession, folder: str, hours: float = 6) -> SignedGraph:
    rows = load(spark, folder, "events").select(F.col("event_id").alias("id"), "user_id", F.unix_micros(F.col("ts").cast("timestamp")).alias("t"))
    gap = lambda w: F.lead("t").over(w) - F.col("t") <= int(hours * 3600e6)
    return normalise(chain_edges(rows, "user_id", ["t", "id"], gap), rows.select(F.col("id").alias("v")))


def conv_chain(spark: SparkSession, folder: str) -> SignedGraph:
    rows = load(spark, folder, "conversations").select((F.col("conv_id") * 100 + F.col("turn")).alias("id"))
    edges = rows.select(F.col("id").alias("u"), (F.col("id") + 1).alias("v")).join(rows.select(F.col("id").alias("v")), "v", "left_semi")
    return normalise(edges, rows.select(F.col("id").alias("v")))


def order_part(spark: SparkSession, folder: str) -> SignedGraph:
    line = load(spark, folder, "lineitem")
    return normalise(line.select(packed(ORDER, "l_orderkey").alias("u"), packed(PART, "l_partkey").alias("v")))


def part_supp(spark: SparkSession, folder: str) -> SignedGraph:
    line = load(spark, folder, "lineitem")
    return normalise(line.select(packed(PART, "l_partkey").alias("u"), packed(SUPPLIER, "l_suppkey").alias("v")))


def cooccur_edges(pairs: DataFrame, group: str, item: str, least: int) -> DataFrame:
    """Items that share at least ``least`` groups. ``pairs`` must be distinct; groups are small (an order's lines)."""
    a = pairs.select(group, F.col(item).alias("u"))
    both = a.join(pairs.select(group, F.col(item).alias("v")), group).where("u < v")
    return both.groupBy("u", "v").agg(F.count("*").alias("c")).where(F.col("c") >= least).select("u", "v")


def copart(spark: SparkSession, folder: str, least: int = 2) -> SignedGraph:
    pairs = load(spark, folder, "lineitem").select("l_orderkey", packed(PART, "l_partkey").alias("part")).distinct()
    parts = load(spark, folder, "part").select(packed(PART, "p_partkey").alias("v"))
    return normalise(cooccur_edges(pairs, "l_orderkey", "part", least), parts)


def keyed_products(keyed: DataFrame, threshold: float, block_rows: int) -> DataFrame:
    """``(u, v)`` of rows of one ``key`` with cosine at least ``threshold``, from ``keyed(key, id, x array<double>)``.

    A key's rows are cut into blocks of about ``block_rows``, and each pair of blocks is a bucket that one task multiplies
    as matrices; a block meets itself once. So no task holds more than two blocks, however many rows a key has.
    """
    keyed = materialize(keyed.where("x is not null"), "vectors")
    sizes = keyed.groupBy("key").agg(F.ceil(F.count("*") / block_rows).cast("int").alias("blocks"), F.count("*").alias("n")).where("n > 1").drop("n")
    mine = keyed.join(sizes, "key").withColumn("b", F.pmod(F.xxhash64("id"), F.col("blocks")).cast("int"))
    mine = mine.withColumn("o", F.explode(F.sequence(F.lit(0), F.col("blocks") - 1)))
    dealt = mine.select(F.xxhash64("key", F.least("b", "o"), F.greatest("b", "o")).alias("bucket"), (F.col("b") > F.col("o")).alias("second"), (F.col("b") == F.col("o")).alias("same"), "id", "x")

    def near(_, rows):
        ids = rows.column("id").to_numpy()
        x = rows.column("x").combine_chunks()
        x = x.flatten().to_numpy(zero_copy_only=False).reshape(len(ids), -1)
        x = x / np.sqrt((x * x).sum(1, keepdims=True))
        if rows.column("same")[0].as_py():
            i, j = np.nonzero(np.triu(x @ x.T >= threshold, 1))
            u, v = ids[i], ids[j]
        else:
            second = rows.column("second").to_numpy(zero_copy_only=False)
            i, j = np.nonzero(x[~second] @ x[second].T >= threshold)
            u, v = ids[~second][i], ids[second][j]
        return {"u": np.minimum(u, v), "v": np.maximum(u, v)}

    return map_tables(dealt, "bucket", near, "u long, v long")


def cosine_edges(rows: DataFrame, threshold: float, block_rows: int = 2048) -> DataFrame:
    """Pairs of ``rows(id, x array<double>)`` with cosine at least ``threshold``, exact: all pairs, each once, by products of
    blocks. The work is quadratic; for very large inputs see :func:`hyperplane_edges`. Null vectors and those of norm zero have no pair."""
    return keyed_products(rows.select(F.lit(0).cast("long").alias("key"), "id", "x"), threshold, block_rows)


def hyperplane_edges(rows: DataFrame, threshold: float, bits: int = 4, tables: int = 32, seed: int = 5, block_rows: int = 2048) -> DataFrame:
    """Approximate: only pairs that agree on the signs of ``bits`` random projections in one of ``tables`` tables are
    compared. A pair at angle t is met with chance 1 - (1 - (1 - t/pi)^bits)^tables."""

    def signs(batches):
        planes = None
        for batch in batches:
            if not batch.num_rows:
                continue
            x = batch.column("x").flatten().to_numpy(zero_copy_only=False).reshape(batch.num_rows, -1)
            if planes is None:
                planes = np.random.default_rng(seed).standard_normal((x.shape[1], bits * tables))
            side = (x @ planes >= 0).reshape(len(x), tables, bits)
            keys = side @ (1 << np.arange(bits)) + (np.arange(tables) << bits)
            offsets = pa.array(np.arange(len(x) + 1, dtype=np.int32) * tables)
            yield pa.RecordBatch.from_arrays([batch.column("id"), batch.column("x"), pa.ListArray.from_arrays(offsets, pa.array(keys.ravel(), pa.int64()))], ["id", "x", "keys"])

    keyed = rows.where("x is not null").select("id", "x").mapInArrow(signs, "id long, x array<double>, keys array<long>")
    return keyed_products(keyed.select(F.explode("keys").alias("key"), "id", "x"), threshold, block_rows).distinct()


def embedding_rows(spark: SparkSession, folder: str) -> DataFrame:
    return load(spark, folder, "embeddings").select(F.col("vec_id").cast("long").alias("id"), F.col("embedding").cast("array<double>").alias("x"))


def emb(spark: SparkSession, folder: str, threshold: float = 0.30) -> SignedGraph:
    rows = embedding_rows(spark, folder)
    return normalise(cosine_edges(rows, threshold), rows.select(F.col("id").alias("v")))


def words_of(text):
    """Runs of ``\\w`` of a text column, lower case."""
    return F.regexp_extract_all(F.lower(text), F.lit(r"(?U)\w+"), F.lit(0))


def shingle_sets(text, size: int = 5):
    """Distinct shingles of ``size`` words (runs of ``\\w``, lower case) of a text column; a shorter text is one shingle."""
    starts = lambda w: F.sequence(F.lit(0), F.greatest(F.size(w) - size, F.lit(0)))
    # The words are bound once to a lambda's variable, else each shingle would cut the whole text again.
    return F.transform(F.array(words_of(text)), lambda w: F.array_distinct(F.transform(starts(w), lambda i: F.array_join(F.slice(w, i + 1, size), " "))))[0]


#: The items that shingles are runs of, and the length of a run.
shingle_sets.cut = (words_of, 5)


def jaccard_edges(sh: DataFrame, threshold: float, most: int = 512) -> DataFrame:
    """As :func:`near_sets`, of sets given as rows ``sh(id, s)``."""
    return near_sets(sh.groupBy("id").agg(F.collect_set("s").alias("x")), threshold, most)


SKETCH = 1 << 20
#: Ids up to this number are broadcast; more are joined.
FEW_IDS = 1 << 19


def hashed(items):
    return F.transform(items, lambda s: F.xxhash64(s))


def digests(sets: DataFrame, items_of, size: int) -> tuple[DataFrame, np.ndarray, int]:
    """Of ``sets(id, x)`` in one pass: ``(id, k)`` with a digest of the items; of all hashes of runs, logarithms of how many
    fall into each of ``SKETCH`` bins, and their number. Tasks count, one sums up."""
    listed = sets.select("id", items_of(F.col("x")).alias("w"))
    whole = F.unhex(F.md5(F.array_join(F.array_sort("w") if size == 1 else F.col("w"), "\x1f").cast("binary")))

    def count(batches):
        total = np.zeros(SKETCH, np.int64)
        for batch in batches:
            values, edges = lists(batch.column("w"))
            for a in range(0, batch.num_rows, 1000):
                part = edges[a : a + 1001]
                h = run_hashes(values.to_numpy(zero_copy_only=False)[part[0] : part[-1]], part - part[0], size)[1]
                total += np.bincount((h & np.uint64(SKETCH - 1)).astype(np.int64), minlength=SKETCH)
            yield pa.RecordBatch.from_arrays([batch.column("id"), batch.column("k"), pa.nulls(batch.num_rows, pa.binary())], ["id", "k", "c"])
        few = np.minimum(total, 65535).astype("<u2").tobytes()
        yield pa.RecordBatch.from_arrays([pa.nulls(1, pa.int64()), pa.nulls(1, pa.binary()), pa.array([few], pa.binary())], ["id", "k", "c"])

    def add(batches):
        total = np.zeros(SKETCH, np.int64)
        for batch in batches:
            for c in batch.column("c"):
                total += np.frombuffer(c.as_py(), "<u2")
        yield pa.RecordBatch.from_arrays([pa.array([total.astype("<i8").tobytes()], pa.binary())], ["c"])

    made = materialize(listed.select("id", whole.alias("k"), hashed(F.col("w")).alias("w")).mapInArrow(count, "id long, k binary, c binary"), "digests")
    found = made.where("c is not null").select("c").repartition(1).mapInArrow(add, "c binary").first()
    total = np.frombuffer(bytes(found[0]), "<i8")
    return made.where("id is not null").select("id", "k"), np.log2(total + 1.0).astype(np.uint8), int(total.sum())


def rarest_runs(sets: DataFrame, items_of, size: int, threshold: float, heavy: np.ndarray, total: int, other: np.ndarray) -> DataFrame:
    """``(s, ids, n)``: of the rarest n - ceil(threshold n) + 1 runs of each set but ``other`` the leading bits of the hash,
    with the sets that have it and their numbers of runs, where there are two of sizes near enough. Hashes go in packed
    form, by ranges of them."""
    buckets = max(32, ceil(total * (1 - threshold) / 500_000))

    def rarest(batches):
        held, many = [], 0

        def packed_up():
            h, ids, n = (np.concatenate(x) for x in zip(*held, strict=True))
            order = np.argsort(h)
            h, ids, n = h[order], ids[order], n[order]
            cuts = np.searchsorted(((h >> np.uint64(32)) * np.uint64(buckets)) >> np.uint64(32), np.arange(buckets + 1).astype(np.uint64))
            full = np.flatnonzero(np.diff(cuts))
            for a in range(0, len(full), 64):
                some = full[a : a + 64]
                blobs = [pack(h[cuts[b] : cuts[b + 1]], ids[cuts[b] : cuts[b + 1]], n[cuts[b] : cuts[b + 1]]) for b in some]
                yield pa.RecordBatch.from_arrays([pa.array(some, pa.int64()), pa.array(blobs, pa.binary())], ["bucket", "blob"])

        for batch in batches:
            names = batch.column("id").to_numpy()
            values, edges = lists(batch.column("w"))
            values = values.to_numpy(zero_copy_only=False)
            for a in range(0, batch.num_rows, 1000):
                part, ids = edges[a : a + 1001], names[a : a + 1000]
                of, h = run_hashes(values[part[0] : part[-1]], part - part[0], size)
                here = ~np.isin(ids, other)[of]
                of, h = of[here].astype(np.uint16), h[here]
                order = np.lexsort((h, heavy[(h & np.uint64(SKETCH - 1)).astype(np.int64)], of))
                of, h = of[order], h[order]
                first = np.ones(len(h), bool)
                first[1:] = (h[1:] != h[:-1]) | (of[1:] != of[:-1])
                of, h = of[first].astype(np.int64), h[first]
                n = np.bincount(of, minlength=len(ids))
                front = np.arange(len(h)) - (np.cumsum(n) - n)[of] < (n - np.ceil(threshold * n - 1e-9) + 1)[of]
                held.append((h[front], ids[of[front]], n[of[front]]))
                many += int(front.sum())
                if many >= 1_000_000:
                    yield from packed_up()
                    held, many = [], 0
        if many:
            yield from packed_up()

    def meet(_, rows):
        h, ids, n = unpack(x.as_py() for x in rows.column("blob"))
        order = np.lexsort((n, h))
        h, ids, n = h[order], ids[order], n[order]
        # Of the sets with one hash in the order of size, a set has a partner exactly if one beside it is near enough.
        beside = (h[1:] == h[:-1]) & (n[:-1] >= threshold * n[1:] - 1e-9)
        keep = np.zeros(len(h), bool)
        keep[1:] |= beside
        keep[:-1] |= beside
        h, ids, n = h[keep], ids[keep], n[keep]
        cuts = np.flatnonzero(np.concatenate([[True], h[1:] != h[:-1]])) if len(h) else np.zeros(0, np.int64)
        edges = pa.array(np.append(cuts, len(h)).astype(np.int32))
        return {"s": h[cuts], "ids": pa.ListArray.from_arrays(edges, pa.array(ids)), "n": pa.ListArray.from_arrays(edges, pa.array(n))}

    listed = sets.select("id", hashed(items_of(F.col("x"))).alias("w")).mapInArrow(rarest, "bucket long, blob binary")
    return map_tables(listed, "bucket", meet, "s long, ids array<long>, n array<long>", buckets)


def candidate_pairs(front: DataFrame, threshold: float, most: int) -> DataFrame:
    """``(cell, u, v)``: pairs of ids that meet in hashes of ``front(s, ids, n)`` and can reach the threshold, each once.

    Ids are numbered in the order of the least hash they have, which copies mostly have in common, and cut into blocks of
    ``most``. The pairs of two blocks are a cell, which gets the hashes that both have, packed; one task counts them for
    each pair. Of two sets, all common runs that are not among these are behind the front of one of them.
    """
    each = front.select("s", F.explode("ids").alias("id"))
    place = numbered(each.groupBy("id").agg(F.min("s").alias("r")).select(F.struct("r", "id").alias("key")), "key")
    place = materialize(place.select(F.col("key.id").alias("name"), F.col("id").alias("at")), "places")
    names = at = None
    if place.count() <= FEW_IDS:
        known = np.array([tuple(r) for r in place.collect()], np.int64).reshape(-1, 2)
        names, at = known[np.argsort(known[:, 0])].T.copy()
    else:
        flat = front.select("s", F.explode(F.arrays_zip("ids", "n")).alias("x")).select("s", F.col("x.ids").alias("name"), F.col("x.n").alias("n"))
        front = flat.join(place, "name").groupBy("s").agg(F.collect_list(F.struct("at", "n")).alias("x")).select("s", F.col("x.at").alias("ids"), F.col("x.n").alias("n"))

    def deal(batches):
        """The entries of a hash go to each cell of their block and another that has the hash."""
        held, many = [], 0

        def packed_up():
            cell, s, ids, n = (np.concatenate(x) for x in zip(*held, strict=True))
            order = np.lexsort((s, cell))
            cell, s, ids, n = cell[order], s[order], ids[order], n[order]
            cuts = [*np.flatnonzero(np.concatenate([[True], cell[1:] != cell[:-1]])).tolist(), len(cell)]
            for k in range(0, len(cuts) - 1, 1000):
                some = list(zip(cuts[k : k + 1000], cuts[k + 1 : k + 1001], strict=False))
                blobs = [pack(s[x:y] << 16, ids[x:y], n[x:y]) for x, y in some]
                yield pa.RecordBatch.from_arrays([pa.array([int(cell[x]) for x, _ in some], pa.int64()), pa.array(blobs, pa.binary())], ["cell", "blob"])

        for batch in batches:
            if not batch.num_rows:
                continue
            ids, edges = lists(batch.column("ids"))
            ids, n = ids.to_numpy(), lists(batch.column("n"))[0].to_numpy()
            if names is not None:
                ids = at[np.searchsorted(names, ids)]
            of, b = np.repeat(np.arange(batch.num_rows), np.diff(edges)), ids // most
            s = batch.column("s").to_numpy()
            # The distinct blocks of each hash, and the entries beside each of them.
            own = np.unique(of * (int(b.max()) + 1) + b)
            whose, block = own // (int(b.max()) + 1), own % (int(b.max()) + 1)
            begin = np.searchsorted(whose, np.arange(batch.num_rows + 1))
            times = np.diff(begin)[of]
            e = 0
            while e < len(of):
                end = e + max(1, int(np.searchsorted(np.cumsum(times[e:]), 2_000_000)))
                t = times[e:end]
                x = np.repeat(np.arange(e, min(end, len(of))), t)
                o = block[np.arange(len(x)) - np.repeat(np.cumsum(t) - t, t) + begin[of[x]]]
                held.append((np.minimum(b[x], o) << 32 | np.maximum(b[x], o), s[of[x]], ids[x], n[x]))
                many += len(x)
                e = end
                if many >= 1_000_000:
                    yield from packed_up()
                    held, many = [], 0
        if many:
            yield from packed_up()

    def count(cell, rows):
        s, ids, n = unpack(x.as_py() for x in rows.column("blob"))
        known, who = np.unique(ids, return_inverse=True)
        size, same = np.zeros(len(known), np.int64), np.zeros(len(known), bool)
        size[who] = n
        order = np.lexsort((who, s))
        s, who = s[order], who[order]
        # A set that has one hash twice is not counted right, so its pairs all pass.
        same[who[1:][(s[1:] == s[:-1]) & (who[1:] == who[:-1])]] = True
        cut = int(np.searchsorted(known // most, (cell & 0xFFFFFFFF))) if cell >> 32 != cell & 0xFFFFFFFF else 0
        met = np.zeros((cut or len(known), len(known) - cut), np.int32)
        cuts = [0, *(np.flatnonzero(np.diff(s)) + 1).tolist(), len(s)]
        for x, y in zip(cuts[:-1], cuts[1:], strict=True):
            if y - x > 1:
                w = who[x:y]
                k = int(np.searchsorted(w, cut)) if cut else 0
                met[np.ix_(w[:k] if cut else w, w[k:] - cut)] += 1
        i, j = np.nonzero(met if cut else np.triu(met, 1))
        c, j = met[i, j], j + cut
        small, large = np.minimum(size[i], size[j]), np.maximum(size[i], size[j])
        behind = np.minimum(small, np.ceil(threshold * large - 1e-9) - 1)
        least = threshold / (1 + threshold) * (small + large) - 1e-6
        near = (small >= threshold * large - 1e-9) & ((c + behind >= least) | same[i] | same[j])
        return {"cell": np.full(int(near.sum()), cell), "pu": known[i[near]], "pv": known[j[near]]}

    found = map_tables(front.mapInArrow(deal, "cell long, blob binary"), "cell", count, "cell long, pu long, pv long")
    found = found.join(place.select(F.col("at").alias("pu"), F.col("name").alias("a")), "pu").join(place.select(F.col("at").alias("pv"), F.col("name").alias("b")), "pv")
    return found.select("cell", F.least("a", "b").alias("u"), F.greatest("a", "b").alias("v"))


def near_pairs(sets: DataFrame, pairs: DataFrame, threshold: float, items_of, size: int) -> DataFrame:
    """Of ``pairs(cell, u, v)`` those whose sets, compared by their runs themselves, reach the threshold. A set goes once to
    each cell it has pairs in."""
    need = materialize(pairs.select("cell", F.explode(F.array("u", "v")).alias("id")).distinct(), "needed")
    ids = need.select("id").distinct()
    if ids.count() <= FEW_IDS:
        sets = sets.join(F.broadcast(ids), "id", "left_semi")
    none = F.lit(None).cast("long")
    rows = sets.join(need, "id").select("cell", "id", "x", none.alias("u"), none.alias("v"))
    rows = rows.unionByName(pairs.select("cell", none.alias("id"), F.lit(None).cast(sets.schema["x"].dataType).alias("x"), "u", "v"))

    def compare(_, rows):
        held = rows.filter(pc.is_valid(rows.column("id")))
        asked = rows.filter(pc.is_valid(rows.column("u")))
        ids = held.column("id").to_numpy()
        order = np.argsort(ids)
        u, v = (order[np.searchsorted(ids[order], asked.column(x).to_numpy())] for x in ("u", "v"))
        by = np.argsort(u, kind="stable")
        u, v = u[by], v[by]
        values, edges = lists(held.column("w").combine_chunks())
        of, code = run_codes(values.dictionary_encode().indices.to_numpy(), edges, size)
        n, k = common(of, code, len(ids), u, v)
        near = k >= threshold * (n[u] + n[v] - k)
        return {"u": ids[u[near]], "v": ids[v[near]]}

    return map_tables(rows, "cell", compare, "u long, v long", last=lambda df: df.select("cell", "id", "u", "v", items_of(F.col("x")).alias("w")))


def near_sets(sets: DataFrame, threshold: float, most: int = 512, shingles_of=lambda x: x) -> DataFrame:
    """Pairs of ``sets(id, x)``, whose sets are ``shingles_of(x)``, with Jaccard at least ``threshold``: all of them,
    however common their shingles are. Shingles that are runs of items are made from these in numpy (``shingles_of.cut``).

    Ids of equal items are compared once, through the smallest of them. Two sets that reach the threshold share one of the
    first n - ceil(threshold n) + 1 of a set's n shingles in any order common to all; only hashes of these are sent, those
    in bins that hold few shingles first, and what a single set has is dropped where it arrives. Candidates are then
    compared by the shingles themselves, in blocks of ``most`` sets.
    """
    items_of, size = getattr(shingles_of, "cut", (shingles_of, 1))
    sets = sets.where("id is not null and x is not null")
    keys, heavy, total = digests(sets, items_of, size)
    first = keys.groupBy("k").agg(F.min("id").alias("rep"), F.count("*").alias("m")).where("m > 1").select("k", "rep")
    groups = materialize(keys.join(first, "k").select("id", "rep"), "same_sets")
    other = groups.where("id <> rep").select("id")
    ones, known = sets, np.zeros(0, np.int64)
    if other.count() <= FEW_IDS:
        known = np.array([r[0] for r in other.collect()], np.int64)
    else:
        ones = sets.join(other, "id", "left_anti")
    front = materialize(rarest_runs(ones, items_of, size, threshold, heavy, total, known), "rarest_shingles")
    pairs = materialize(candidate_pairs(front, threshold, most), "candidates")
    near = near_pairs(sets, pairs, threshold, items_of, size)
    # Members of a group are near each other, and near the members of the groups theirs is near to.
    found = near.select(F.col("u").alias("ru"), F.col("v").alias("rv")).unionByName(groups.where("id = rep").select(F.col("rep").alias("ru"), F.col("rep").alias("rv")))
    every = found.join(groups.select(F.col("id").alias("a"), F.col("rep").alias("ru")), "ru", "left").join(groups.select(F.col("id").alias("b"), F.col("rep").alias("rv")), "rv", "left")
    every = every.select("ru", "rv", F.coalesce("a", "ru").alias("a"), F.coalesce("b", "rv").alias("b"))
    return every.where("ru <> rv or a < b").select(F.least("a", "b").alias("u"), F.greatest("a", "b").alias("v"))


def doc_near(spark: SparkSession, folder: str, threshold: float = 0.5) -> SignedGraph:
    docs = load(spark, folder, "documents")
    sets = docs.select(packed(DOCUMENT, "doc_id").alias("id"), F.col("text").alias("x"))
    return normalise(near_sets(sets, threshold, shingles_of=shingle_sets), docs.select(packed(DOCUMENT, "doc_id").alias("v")))


def same_key_edges(rows: DataFrame) -> DataFrame:
    """All pairs of ``rows(id, k)`` with one key: the clique graph itself, so as large as its definition says."""
    return rows.select("k", F.col("id").alias("u")).join(rows.select("k", F.col("id").alias("v")), "k").where("u < v").select("u", "v")


def doc_exact(spark: SparkSession, folder: str) -> SignedGraph:
    text = F.trim(F.regexp_replace(F.lower("text"), r"[ \t\n\r\f]+", " "))
    rows = load(spark, folder, "documents").select(packed(DOCUMENT, "doc_id").alias("id"), F.md5(text).alias("k"))
    return normalise(same_key_edges(rows), rows.select(F.col("id").alias("v")))


def page_host(spark: SparkSession, folder: str) -> SignedGraph:
    rows = load(spark, folder, "pages").select(F.col("page_id").cast("long").alias("id"), F.regexp_extract("url", "^https?://([^/?#]+)", 1).alias("k"))
    return normalise(same_key_edges(rows), rows.select(F.col("id").alias("v")))


def run_rows(rows: DataFrame, size: int = 5, bits: np.ndarray | None = None) -> DataFrame:
    """``(id, h)`` of hashes of the shingles of ``rows(id, text)``; of those only whose bit is set, if ``bits`` are given."""

    def hashes(batches):
        for batch in batches:
            ids = batch.column("id").to_numpy()
            values, edges = lists(batch.column("w"))
            values = values.to_numpy(zero_copy_only=False)
            for a in range(0, batch.num_rows, 1000):
                part = edges[a : a + 1001]
                of, h = run_hashes(values[part[0] : part[-1]], part - part[0], size)
                if bits is not None:
                    at = h & np.uint64(8 * len(bits) - 1)
                    here = (bits[(at >> np.uint64(3)).astype(np.int64)] >> (at & np.uint64(7)).astype(np.uint8)) & 1 == 1
                    of, h = of[here], h[here]
                yield pa.RecordBatch.from_arrays([pa.array(ids[a + of]), pa.array(h.view(np.int64))], ["id", "h"])

    kept = rows.where("id is not null and text is not null")
    return kept.select("id", hashed(words_of(F.col("text"))).alias("w")).mapInArrow(hashes, "id long, h long")


def bits_of(hashes: DataFrame, n: int) -> np.ndarray:
    """A bit for each of ``n`` hashes among 32 times as many, from 8 KB to 32 MB in all."""
    many = 1 << min(max((32 * n).bit_length(), 16), 28)

    def put(batches):
        bits = np.zeros(many >> 3, np.uint8)
        for batch in batches:
            at = batch.column("h").to_numpy().view(np.uint64) & np.uint64(many - 1)
            np.bitwise_or.at(bits, (at >> np.uint64(3)).astype(np.int64), np.uint8(1) << (at & np.uint64(7)).astype(np.uint8))
        yield pa.RecordBatch.from_arrays([pa.array([bits.tobytes()], pa.binary())], ["c"])

    return np.frombuffer(bytes(hashes.repartition(1).mapInArrow(put, "c binary").first()[0]), np.uint8)


def doc_bench(spark: SparkSession, folder: str) -> SignedGraph:
    """Documents and benchmark items that share a shingle. Of the documents' shingles only hashes are sent whose bit an item
    has set; the shingles themselves are compared for documents that have a hash in common with an item."""
    docs = load(spark, folder, "documents").select(packed(DOCUMENT, "doc_id").alias("id"), "text")
    items = load(spark, folder, "benchmark").select(packed(ITEM, "item_id").alias("id"), "text")
    known = materialize(run_rows(items).select("h").distinct(), "item_hashes")
    met = run_rows(docs, bits=bits_of(known, known.count()))
    touched = materialize(met.join(known, "h", "left_semi").select("id").distinct(), "touched")
    some = docs.join(F.broadcast(touched) if touched.count() <= FEW_IDS else touched, "id", "left_semi")
    one, two = (rows.select("id", F.explode(shingle_sets(F.col("text"))).alias("s")) for rows in (some, items))
    return normalise(one.select("s", F.col("id").alias("u")).join(two.select("s", F.col("id").alias("v")), "s").select("u", "v"))


def numbered(rows: DataFrame, key: str) -> DataFrame:
    """``(id, key)``: the rows numbered from 0 without gaps in the order of ``key``: ranges of the key are sorted apart and
    begin where the rows of the ranges before them end."""
    parts = materialize(rows.select(key).repartitionByRange(key).withColumn("part", F.spark_partition_id()), "ranges")
    begins, at = [], 0
    for part, n in sorted((r[0], r[1]) for r in parts.groupBy("part").count().collect()):
        begins.append((part, at))
        at += n
    begins = rows.sparkSession.createDataFrame(begins, "part int, begin long")
    place = F.row_number().over(Window.partitionBy("part").orderBy(key)) - 1
    return parts.withColumn("place", place).join(F.broadcast(begins), "part").select((F.col("begin") + F.col("place")).cast("long").alias("id"), key)


def scalefree_of(cells: DataFrame, k: int = 2, p: int = 2) -> SignedGraph:
    """Vertex j >= k of ``cells(id)`` links to floor(j h^p) for k hashed draws h: a few early vertices become hubs,
    arboricity at most k."""
    j = cells.where(F.col("id") >= k).select(F.col("id").alias("j"), F.explode(F.sequence(F.lit(0), F.lit(k - 1))).alias("i"))
    h = F.conv(F.substring(F.md5(F.concat(F.lit("7:"), F.col("j"), F.lit(":"), F.col("i")).cast("binary")), 1, 8), 16, 10).cast("double") / F.lit(float(1 << 32))
    j = j.withColumn("h", h)
    power = F.col("h")
    for _ in range(p - 1):
        power = power * F.col("h")
    return normalise(j.select(F.floor(F.col("j") * power).cast("long").alias("u"), F.col("j").alias("v")), cells.select(F.col("id").alias("v")))


def scalefree(spark: SparkSession, n: int, k: int = 2, p: int = 2) -> SignedGraph:
    return scalefree_of(spark.range(n), k, p)


def grid(cells: DataFrame) -> SignedGraph:
    """The cells ``id`` from 0 row by row in a square; right and lower neighbours."""
    n = cells.count()
    side = ceil(n**0.5)
    right = cells.where((F.col("id") % side != side - 1) & (F.col("id") + 1 < n)).select(F.col("id").alias("u"), (F.col("id") + 1).alias("v"))
    below = cells.where(F.col("id") + side < n).select(F.col("id").alias("u"), (F.col("id") + side).alias("v"))
    return normalise(right.unionByName(below), cells.select(F.col("id").alias("v")))


def band(spark: SparkSession, n: int) -> SignedGraph:
    """Each vertex joined to the two before it (treewidth two)."""
    x = spark.range(n).select(F.col("id").alias("u"), F.explode(F.array(F.lit(1), F.lit(2))).alias("d"))
    return normalise(x.select("u", (F.col("u") + F.col("d")).alias("v")).where(F.col("v") < n), spark.range(n).select(F.col("id").alias("v")))


def path(spark: SparkSession, n: int) -> SignedGraph:
    x = spark.range(n)
    return normalise(x.where(F.col("id") + 1 < n).select(F.col("id").alias("u"), (F.col("id") + 1).alias("v")), x.select(F.col("id").alias("v")))


def star(spark: SparkSession, n: int) -> SignedGraph:
    x = spark.range(n)
    return normalise(x.where("id > 0").select(F.lit(0).alias("u"), F.col("id").alias("v")), x.select(F.col("id").alias("v")))


def cliques(spark: SparkSession, count: int, size: int) -> SignedGraph:
    x = spark.range(count * size)
    u, step = F.col("id"), F.explode(F.sequence(F.lit(1), F.lit(max(size - 1, 1))))
    e = x.select(u.alias("u"), step.alias("d")).where((F.col("u") % size + F.col("d")) < size)
    return normalise(e.select("u", (F.col("u") + F.col("d")).alias("v")), x.select(F.col("id").alias("v")))


def barbell(spark: SparkSession, k: int) -> SignedGraph:
    """Two cliques of k vertices and an edge between them."""
    two = cliques(spark, 2, k)
    bridge = spark.range(1).select(F.lit(k - 1).cast("long").alias("u"), F.lit(k).cast("long").alias("v"))
    return normalise(two.edges.unionByName(bridge), two.vertices)


def customer_barbells(spark: SparkSession, folder: str, size: int) -> tuple[SignedGraph, DataFrame]:
    """Barbells of orders, and ``(v, cid)`` by customer: the orders of a customer with exactly ``size`` of them are a clique,
    and of such customers in the order of their keys every two are bridged from the first one's last order to the second
    one's first. A last customer without another is left out."""
    orders = load(spark, folder, "orders").select("o_custkey", "o_orderkey")
    some = orders.groupBy("o_custkey").agg(F.count("*").alias("n"), F.min("o_orderkey").alias("first"), F.max("o_orderkey").alias("last")).where(F.col("n") == size)
    some = materialize(some, "customers")
    place = materialize(numbered(some, "o_custkey"), "places")
    pair = F.floor(F.col("id") / 2).alias("pair")
    whole = some.join(place.where(pair < F.floor(F.lit(place.count()) / 2)), "o_custkey")
    mine = materialize(orders.join(whole.select("o_custkey"), "o_custkey").select(packed(ORDER, "o_orderkey").alias("id"), F.col("o_custkey").alias("k")), "members")
    left = whole.where("id % 2 = 0").select(pair, packed(ORDER, "last").alias("u"))
    bridges = left.join(whole.where("id % 2 = 1").select(pair, packed(ORDER, "first").alias("v")), "pair").select("u", "v")
    return normalise(same_key_edges(mine).unionByName(bridges), mine.select(F.col("id").alias("v"))), mine.select(F.col("id").alias("v"), F.col("k").alias("cid"))


def pairs(spark: SparkSession, n: int) -> SignedGraph:
    return cliques(spark, n, 2)


def empty(spark: SparkSession, n: int = 0) -> SignedGraph:
    x = spark.range(n).select(F.col("id").alias("v"))
    return SignedGraph(x, spark.createDataFrame([], "u long, v long"))
