"""Gated recurrent language model in numpy with a class-factored output softmax, scoring complete documents.

Words fall into classes: the most frequent words and the document end have a class of their own, all other words (known
or not) the class of a hash of their last two bytes. A gated recurrent unit reads the classes. The output softmax has four
factors: the next span of ``SPAN`` neighbouring classes given the state; the class given span and state; inside a class of
many words, the next group (a hash of the first three bytes) given class and state; the word inside its group by
log(c + 0.1) of corpus counts over all training texts, with one entry of 0.1 for words never seen. So a token needs
``SPANS + SPAN`` exponentials for its class, not ``CLASSES``. The first three are learned by truncated backpropagation, the
state is carried across windows to the end of each document. A token is coded as its class plus ``CLASSES`` times its group.
"""

from __future__ import annotations

import heapq
import zlib
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from signedcluster.llm.common import by_bytes, doc_frame, fold, map_rows, numbered_words, offsets_of, strings
from signedcluster.shared import materialize

HEAD, TAIL, GROUPS, HIDDEN = 79, 48, 32, 32
CLASSES = HEAD + TAIL + 1
END = CLASSES - 1
SPANS, SPAN = 8, CLASSES // 8
LN10 = float(np.log(10))
#: Updates that a task should make in a round at least, and tokens it gets: fewer tasks learn more before each average.
UPDATES, TASK_TOKENS = 256, 1 << 21


def tail_class(word: bytes) -> int:
    return HEAD + zlib.crc32(word[-2:]) % TAIL


def tail_code(word: bytes) -> int:
    return tail_class(word) + CLASSES * (zlib.crc32(word[:3]) % GROUPS)


@dataclass
class Ready:
    """Weights as the products need them: rows and matrix of the gates times -1 and of the new values times -2, biases as a last
    row below the weights of each factor, which are (softmaxes x hidden and one x choices)."""

    gate_rows: np.ndarray
    new_rows: np.ndarray
    gates: np.ndarray
    new: np.ndarray
    span: np.ndarray
    out: np.ndarray
    group: np.ndarray


class GatedUnit:
    """Weights and windows of the recurrent unit; inputs are class ids, so the input product is a row lookup."""

    def __init__(self, seed: int = 5, weights: dict[str, np.ndarray] | None = None):
        self.spaces: dict[str, np.ndarray] = {}
        if weights is not None:
            self.w = {k: v.astype(np.float32) for k, v in weights.items()}
            return
        draw = np.random.default_rng(seed)
        small = lambda *shape: (draw.standard_normal(shape) * 0.1).astype(np.float32)
        self.w = {
            "in": small(CLASSES, 3 * HIDDEN),
            "gates": small(HIDDEN, 2 * HIDDEN),
            "new": small(HIDDEN, HIDDEN),
            "out": small(SPANS, HIDDEN, SPAN),
            "bias": np.zeros((SPANS, SPAN), np.float32),
            "span": np.zeros((1, HIDDEN, SPANS), np.float32),
            "span_bias": np.zeros((1, SPANS), np.float32),
            "group": np.zeros((TAIL, HIDDEN, GROUPS), np.float32),
            "group_bias": np.zeros((TAIL, GROUPS), np.float32),
        }

    def space(self, name: str, *shape: int, kind=None) -> np.ndarray:
        """An array that is used again by the next call of that name, so that its memory is not asked for each time."""
        kind, n = np.dtype(kind or self.w["new"].dtype), int(np.prod(shape))
        held = self.spaces.get(name)
        if held is None or held.size < n or held.dtype != kind:
            held = self.spaces[name] = np.empty(n, kind)
        return held[:n].reshape(shape)

    def ready(self) -> Ready:
        w = self.w
        joined = (np.concatenate((w[k], w[b][:, None]), 1) for k, b in (("span", "span_bias"), ("out", "bias"), ("group", "group_bias")))
        return Ready(-w["in"][:, : 2 * HIDDEN], -2 * w["in"][:, 2 * HIDDEN :], -w["gates"], -2 * w["new"], *joined)

    def run(self, xs: np.ndarray, fresh: np.ndarray, h: np.ndarray, ready: Ready, keep_parts: bool = False):
        """States of one window (steps x lanes x hidden) from state ``h``, and the parts that its gradients need: the states
        before, these after the reset, keep and reset gates, new values, and the states before less the new values.

        All of them hold until the next window.
        """
        x, kind = xs % CLASSES, self.w["new"].dtype
        steps, lanes = x.shape
        room = steps if keep_parts else 1
        states, now = self.space("states", steps, lanes, HIDDEN), self.space("now", lanes, 2 * HIDDEN)
        parts = tuple(self.space(k, room, lanes, HIDDEN) for k in ("before", "inner", "keep", "reset", "new", "less"))
        for_gates, for_new = self.space("for_gates", lanes, 2 * HIDDEN), self.space("for_new", lanes, HIDDEN)
        h = h.astype(kind)
        for t, starts in enumerate(fresh.any(1).tolist()):
            if starts:
                h = np.where(fresh[t][:, None], 0, h).astype(kind)
            before, inner, keep, reset, new, less = (part[t if keep_parts else 0] for part in parts)
            ready.gate_rows.take(x[t], 0, now, "clip")
            now += np.matmul(h, ready.gates, out=for_gates)
            np.exp(now, out=now)
            now += 1
            np.reciprocal(now[:, :HIDDEN], out=keep)
            np.reciprocal(now[:, HIDDEN:], out=reset)
            ready.new_rows.take(x[t], 0, new, "clip")
            new += np.matmul(np.multiply(reset, h, out=inner), ready.new, out=for_new)
            np.exp(new, out=new)  # tanh(z) = 2 / (1 + exp(-2 z)) - 1
            new += 1
            np.divide(2, new, out=new)
            new -= 1
            if keep_parts:
                before[:] = h
            h = np.multiply(np.subtract(h, new, out=less), keep, out=states[t])
            h += new
        return states, parts

    def by_class(self, states: np.ndarray, codes: np.ndarray):
        """(order of the codes by class, states in it with a last column of ones, codes in it, and the rows of the whole, of
        each span and of each class of many words as parts of it)."""
        kind = (codes % CLASSES).astype(np.int16)
        order = np.argsort(kind, kind="stable")
        cuts = np.concatenate(([0], np.cumsum(np.bincount(kind, minlength=CLASSES)))).tolist()
        at = self.space("at", len(order), HIDDEN + 1)
        at[:, :HIDDEN], at[:, HIDDEN] = np.take(states, order, axis=0, mode="clip"), 1
        part = lambda edges: [(k, slice(a, b)) for k, (a, b) in enumerate(zip(edges[:-1], edges[1:], strict=True)) if b > a]
        return order, at, codes[order], [(0, slice(0, len(order)))], part(cuts[::SPAN]), part(cuts[HEAD : END + 1])

    def factor(self, name: str, at: np.ndarray, parts: list, weights: np.ndarray, asked: np.ndarray):
        """(exponentials of the logits, their sums, log probabilities of what is asked for) of one factor; bounded logits need
        no shift. ``parts`` tells which rows each softmax has."""
        e = self.space(name, len(asked), weights.shape[2])
        for k, part in parts:
            np.matmul(at[part], weights[k], out=e[part])
        if len(e) and max(e.max(), -e.min()) > 60:
            e -= e.max(1, keepdims=True)
        picked = e[np.arange(len(e)), asked]
        np.exp(e, out=e)
        total = e @ np.ones(e.shape[1], e.dtype)
        return e, total, picked - np.log(total)

    def class_factors(self, at: np.ndarray, codes: np.ndarray, whole: list, spans: list, ready: Ready):
        span, inside = np.divmod(codes % CLASSES, SPAN)
        return (span, inside), self.factor("span", at, whole, ready.span, span), self.factor("class", at, spans, ready.out, inside)

    def group_factor(self, at: np.ndarray, codes: np.ndarray, tails: list, ready: Ready):
        """Of the rows of classes of many words: which they are, parts of these, groups asked for and the factor."""
        rows = slice(tails[0][1].start, tails[-1][1].stop) if tails else slice(0, 0)
        parts = [(k, slice(p.start - rows.start, p.stop - rows.start)) for k, p in tails]
        asked = codes[rows] // CLASSES
        return rows, parts, asked, self.factor("group", at[rows], parts, ready.group, asked)

    def log_probs(self, states: np.ndarray, codes: np.ndarray, ready: Ready, of_class: bool = True, of_group: bool = True) -> np.ndarray:
        """Of the class, and of the group where the class has many words."""
        order, at, codes, whole, spans, tails = self.by_class(states, codes)
        out, got = np.empty(len(codes)), np.zeros(len(codes))
        if of_class:
            _, (*_, of_span), (*_, inside) = self.class_factors(at, codes, whole, spans, ready)
            got += of_span
            got += inside
        if of_group:
            rows, _, _, (*_, p) = self.group_factor(at, codes, tails, ready)
            got[rows] += p
        out[order] = got
        return out

    def group_log_probs(self, states: np.ndarray, target: np.ndarray) -> np.ndarray:
        return self.log_probs(states, target, self.ready(), of_class=False)

    def class_log_probs(self, states: np.ndarray, target: np.ndarray) -> np.ndarray:
        return self.log_probs(states, target, self.ready(), of_group=False)

    def pull(self, at: np.ndarray, parts: list, weights: np.ndarray, asked: np.ndarray, n: int, e: np.ndarray, total: np.ndarray):
        """Gradients of a factor's weights (biases last) and of the states before it, from :meth:`factor`; ``n``: all tokens."""
        e[np.arange(len(e)), asked] -= total
        e *= (1 / (total * n))[:, None]
        g, back = np.zeros_like(weights), self.space("pulled", len(e), HIDDEN)
        for k, part in parts:
            np.matmul(at[part].T, e[part], out=g[k])
            np.matmul(e[part], weights[k, :HIDDEN].T, out=back[part])
        return g, back

    def window_gradients(self, xs: np.ndarray, ys: np.ndarray, fresh: np.ndarray, h: np.ndarray):
        """Truncated backpropagation over one window (steps x lanes); returns gradients, loss, state at its end."""
        w, ready, (steps, lanes) = self.w, self.ready(), xs.shape
        states, (before, inner, keep, reset, new, less) = self.run(xs, fresh, h, ready, True)
        n, g = ys.size, {k: np.zeros_like(v) for k, v in w.items()}
        order, at, codes, whole, spans, tails = self.by_class(states.reshape(-1, HIDDEN), ys.ravel().astype(np.int64))
        (span, inside), of_span, of_class = self.class_factors(at, codes, whole, spans, ready)
        rows, parts, asked, of_group = self.group_factor(at, codes, tails, ready)
        loss = -sum(f[2].sum() for f in (of_span, of_class, of_group)) / n
        sorted_down = self.space("sorted_down", n, HIDDEN)
        for k, b, held, own, of, want, f in (
            ("span", "span_bias", slice(0, n), whole, ready.span, span, of_span),
            ("out", "bias", slice(0, n), spans, ready.out, inside, of_class),
            ("group", "group_bias", rows, parts, ready.group, asked, of_group),
        ):
            both, back = self.pull(at[held], own, of, want, n, *f[:2])
            g[k], g[b] = both[:, :HIDDEN], both[:, HIDDEN]
            if k == "span":
                sorted_down[:] = back
            else:
                sorted_down[held] += back
        down = self.space("down", n, HIDDEN)
        down[order] = sorted_down
        down = down.reshape(states.shape)
        rest = np.subtract(1, keep, out=self.space("rest", *keep.shape))
        np.multiply(new, new, out=new)
        by_new = np.subtract(1, new, out=new)
        by_new *= rest
        by_keep = less
        by_keep *= keep
        by_keep *= rest
        by_reset = np.subtract(1, reset, out=rest)
        by_reset *= inner
        d_all = self.space("d_all", steps, lanes, 3 * HIDDEN)
        d_gates, d_new = d_all[..., : 2 * HIDDEN], d_all[..., 2 * HIDDEN :]
        carry, back = np.zeros_like(states[0]), self.space("back", lanes, HIDDEN)
        back_new, back_gates = np.ascontiguousarray(w["new"].T), np.ascontiguousarray(w["gates"].T)
        starts = fresh.any(1).tolist()
        for t in reversed(range(steps)):
            d = down[t]
            d += carry
            np.multiply(d, by_keep[t], out=d_gates[t, :, :HIDDEN])
            np.matmul(np.multiply(d, by_new[t], out=d_new[t]), back_new, out=back)
            np.multiply(back, by_reset[t], out=d_gates[t, :, HIDDEN:])
            np.matmul(d_gates[t], back_gates, out=carry)
            d *= keep[t]
            back *= reset[t]
            carry += d
            carry += back
            if starts[t]:
                carry[fresh[t]] = 0
        d_all = d_all.reshape(-1, 3 * HIDDEN)
        g["gates"] = before.reshape(-1, HIDDEN).T @ d_all[:, : 2 * HIDDEN]
        g["new"] = inner.reshape(-1, HIDDEN).T @ d_all[:, 2 * HIDDEN :]
        read = (xs.ravel() % CLASSES).astype(np.int16)
        order = np.argsort(read, kind="stable")
        cuts, one = np.searchsorted(read[order], np.arange(CLASSES + 1)).tolist(), np.ones(n, d_all.dtype)
        d_in = np.take(d_all, order, axis=0, mode="clip", out=self.space("d_in", *d_all.shape))
        for c, (a, b) in enumerate(zip(cuts[:-1], cuts[1:], strict=True)):
            if b > a:
                np.dot(one[a:b], d_in[a:b], out=g["in"][c])
        return g, loss, states[-1].copy()


def lanes_of(lengths: list[int], lanes: int) -> list[list[int]]:
    """Documents dealt to lanes, longest first to the shortest lane; lanes by falling length."""
    order = sorted(range(len(lengths)), key=lambda k: -lengths[k])
    lanes = max(1, min(lanes, -(-sum(lengths) // max(lengths, default=1)) + 8, len(lengths)))
    heap = [(0, k) for k in range(lanes)]
    out: list[list[int]] = [[] for _ in range(lanes)]
    for doc in order:
        n, k = heapq.heappop(heap)
        out[k].append(doc)
        heapq.heappush(heap, (n + lengths[doc], k))
    return sorted((x for x in out if x), key=lambda x: -sum(lengths[d] for d in x))


def lay_out(seqs: list[np.ndarray], lanes: list[list[int]]):
    """Arrays (steps x lanes) of previous class, class, whether a document starts, and the document (-1 beyond a lane)."""
    size = [sum(len(seqs[d]) for d in lane) for lane in lanes]
    shape = (max(size, default=0), len(lanes))
    x, y = np.full(shape, END, np.int16), np.zeros(shape, np.int16)
    fresh, doc = np.zeros(shape, bool), np.full(shape, -1, np.int32)
    for k, lane in enumerate(lanes):
        at = 0
        for d in lane:
            n = len(seqs[d])
            y[at : at + n, k], doc[at : at + n, k] = seqs[d], d
            x[at + 1 : at + n, k] = seqs[d][:-1]
            fresh[at, k] = True
            at += n
    return x, y, fresh, doc, np.array(size)


def segments(seqs: list[np.ndarray], lanes: int):
    """As :func:`lay_out`, all texts in one row cut into lanes of equal length (the last may be shorter), wherever texts end."""
    y = np.concatenate(seqs).astype(np.int16)
    fresh = np.zeros(len(y), bool)
    fresh[np.cumsum([0, *(len(s) for s in seqs[:-1])])] = True
    x = np.where(fresh, END, np.r_[END, y[:-1]]).astype(np.int16)
    steps = -(-len(y) // lanes)
    lanes = -(-len(y) // steps)
    size = np.full(lanes, steps)
    size[-1] = len(y) - steps * (lanes - 1)
    cut = lambda v: np.pad(v, (0, steps * lanes - len(v))).reshape(lanes, steps).T
    return cut(x), cut(y), cut(fresh), size


def epoch(unit: GatedUnit, seqs: list[np.ndarray], done: float, share: float, window: int = 16, rate: float = 6e-3, ends: np.ndarray | None = None) -> np.ndarray:
    """One pass over every token, from ``done`` to ``done + share`` of the training; returns the states at the lanes' ends.

    64 to 256 lanes, by the number of tokens, so that ``UPDATES`` windows are left if 64 allow it; the rate grows with the root of
    their number. A lane that starts inside a text begins in the state ``ends`` in which the lane before it ended an epoch ago.
    """
    lanes = min(256, max(64, sum(map(len, seqs)) // (window * UPDATES)))
    rate *= (lanes / 64) ** 0.5
    x, y, fresh, size = segments(seqs, lanes)
    # The weights as parts of one array, so that an update is a few passes over it.
    shapes = {k: v.shape for k, v in unit.w.items()}
    w = np.concatenate([v.ravel() for v in unit.w.values()])
    edges = np.cumsum([v.size for v in unit.w.values()])[:-1]
    unit.w = {k: v.reshape(shapes[k]) for k, v in zip(shapes, np.split(w, edges), strict=True)}
    a, m, v = np.empty_like(w), np.zeros_like(w), np.zeros_like(w)
    cuts = sorted({*range(0, len(x), window), int(size[-1]), len(x)})
    ends = np.zeros((x.shape[1], HIDDEN), np.float32) if ends is None else ends
    h = np.roll(ends, 1, axis=0)
    for n, (at, to) in enumerate(zip(cuts[:-1], cuts[1:], strict=True), 1):
        live = int((size > at).sum())
        g, _, h = unit.window_gradients(x[at:to, :live], y[at:to, :live], fresh[at:to, :live], h[:live])
        ends[:live] = h
        np.concatenate([x.ravel() for x in g.values()], out=a)
        a *= 0.1 / max(1.0, np.sqrt(float(a @ a)))
        m *= 0.9
        m += a
        a *= a
        v *= 0.99
        v += a
        lr = rate * (1 - 0.9 * (done + share * n / (len(cuts) - 1)))
        np.sqrt(v, out=a)
        a += 1e-8 * (1 - 0.99**n) ** 0.5
        np.divide(m, a, out=a)
        a *= lr * (1 - 0.99**n) ** 0.5 / (1 - 0.9**n)
        w -= a
    return ends


def train(seqs: list[np.ndarray], epochs: int = 3, unit: GatedUnit | None = None) -> GatedUnit:
    """Whole epochs over every token, in one place."""
    unit, ends = unit or GatedUnit(), None
    for k in range(epochs if seqs else 0):
        ends = epoch(unit, seqs, k / epochs, 1 / epochs, ends=ends)
    return unit


def code_arrays(column: pa.Array) -> list[np.ndarray]:
    """The codes of each row of a binary column of little-endian 16-bit integers."""
    edges = offsets_of(column) // 2
    flat = np.frombuffer(column.buffers()[2] or b"", "<i2", edges[-1])
    return [flat[a:b] for a, b in zip(edges[:-1].tolist(), edges[1:].tolist(), strict=True)]


def train_apart(rows: DataFrame, n_texts: int, n_tokens: int, unit: GatedUnit, rounds: int, least_docs: int) -> GatedUnit:
    """Rounds over all ``rows(row, doc_id, codes)``: each task passes once over its part from the same weights, which are
    then averaged by the number of tokens, by a few tasks and then by one, so the driver gets the weights once a round.

    A round reads a window of the hashes of id and codes, 1/``rounds`` of them or what gives ``least_docs`` texts. Windows
    leave no gap, so every text is read in one round at least, and in each of them if there are few.
    """
    shapes = {k: v.shape for k, v in unit.w.items()}
    ring = 1 << 30
    wide = max(-(-ring // rounds), min(ring, -(-ring * least_docs // max(n_texts, 1))))
    parts = max(1, -(-n_tokens * wide // ring // TASK_TOKENS))
    for k in range(rounds):
        start = unit.w
        at = F.pmod(F.pmod(F.xxhash64("doc_id", "codes"), F.lit(ring)) - F.lit(k * ring // rounds), F.lit(ring))
        table = rows.where(at < F.lit(wide)).repartition(parts, F.xxhash64("row", "doc_id")).select("codes")

        def part(batches, start=start, k=k):
            held = sorted(c for batch in batches for c in batch.column("codes").to_pylist())
            if held:
                own = GatedUnit(weights=start)
                seqs = [np.frombuffer(c, "<i2") for c in held]
                epoch(own, seqs, k / rounds, 1 / rounds)
                n = sum(map(len, seqs))
                yield {"n": [n], "w": [np.concatenate([v.ravel() for v in own.w.values()]).astype("<f4").tobytes()]}

        def mean(batches):
            n, total = 0, 0.0
            for batch in batches:
                for here, w in zip(batch.column("n").to_pylist(), batch.column("w").to_pylist(), strict=True):
                    n += here
                    total = total + np.frombuffer(w, "<f4").astype(float) * here
            if n:
                yield {"n": [n], "w": [(total / n).astype("<f4").tobytes()]}

        schema = "n long, w binary"
        found = map_rows(map_rows(table, part, schema).repartition(min(parts, 16)), mean, schema)
        found = map_rows(found.repartition(1), mean, schema).collect()
        if not found:
            continue
        whole = np.frombuffer(bytes(found[0]["w"]), "<f4")
        cuts = np.cumsum([int(np.prod(x)) for x in shapes.values()])[:-1]
        unit = GatedUnit(weights={k: v.reshape(x) for (k, x), v in zip(shapes.items(), np.split(whole, cuts), strict=True)})
    return unit


def document_log_probs(unit: GatedUnit, seqs: list[np.ndarray], lanes: int = 256, window: int = 64) -> np.ndarray:
    """Natural log probability of each whole class sequence, with its state carried from window to window."""
    if not seqs:
        return np.zeros(0)
    x, y, fresh, doc, size = lay_out(seqs, lanes_of([len(s) for s in seqs], lanes))
    total = np.zeros(len(seqs))
    h, ready = np.zeros((x.shape[1], HIDDEN), np.float32), unit.ready()
    for at in range(0, len(x), window):
        live = int((size > at).sum())
        states, _ = unit.run(x[at : at + window, :live], fresh[at : at + window, :live], h[:live], ready)
        h = states[-1].copy()
        where = doc[at : at + window, :live].ravel()
        states, target = states.reshape(-1, HIDDEN), y[at : at + window, :live].ravel().astype(np.int64)
        if (where < 0).any():
            real = where >= 0
            states, target, where = states[real], target[real], where[real]
        total += np.bincount(where, unit.log_probs(states, target, ready), len(seqs))
    return total


@dataclass
class WordCounts:
    """Corpus counts: the whole table (distributed) and its most frequent words (at most ``top_words``: whole bands of
    counts, so that no task has to send more words than are kept)."""

    table: DataFrame
    top: list[tuple[bytes, int]]
    docs: int
    tokens: int
    distinct: int
    group_tokens: np.ndarray
    group_words: np.ndarray

    def base_total(self) -> float:
        return self.tokens + 0.1 * (self.distinct + 1)

    def group_total(self) -> np.ndarray:
        """(class of many words x group)."""
        return self.group_tokens + 0.1 * (self.group_words + 1)


def tail_column():
    return (F.crc32(F.substring("w", -2, 2)) % TAIL).cast("int")


def group_column():
    return (F.crc32(F.substring("w", 1, 3)) % GROUPS).cast("int")


def count_words(texts_df: DataFrame, top_words: int) -> WordCounts:
    """Counts of all words of all ``texts_df(text)``: counts of each slice of text, then one shuffle of (word, count)."""

    def step(batches):
        n = 0
        for batch in batches:
            n += batch.num_rows
            for part in by_bytes(batch, "text"):
                words, at, _ = numbered_words(part.column("text"))
                yield {"w": words.cast(pa.binary()), "c": np.bincount(at, minlength=len(words)), "docs": np.zeros(len(words), np.int64)}
        yield {"w": [b""], "c": [0], "docs": [n]}

    parts = map_rows(texts_df, step, "w binary, c long, docs long")
    counts = materialize(parts.groupBy("w").agg(F.sum("c").alias("c"), F.sum("docs").alias("docs")), "word-counts")
    docs = counts.where("w = X''").agg(F.sum("docs")).first()[0] or 0
    table = counts.where("w <> X''").select("w", "c")
    band = F.floor(F.log2("c") * 64).cast("int")
    room, least = top_words, None
    for k, n in table.groupBy(band.alias("band")).count().orderBy(F.desc("band")).collect():
        if n > room:
            break
        room, least = room - n, k
    top = [] if least is None else [(bytes(r[0]), r[1]) for r in table.where(band >= least).collect()]
    top.sort(key=lambda x: (-x[1], x[0]))
    sums = table.groupBy(tail_column().alias("k"), group_column().alias("g")).agg(F.sum("c").alias("c"), F.count("*").alias("n")).collect()
    tokens, words = np.zeros((TAIL, GROUPS)), np.zeros((TAIL, GROUPS))
    for r in sums:
        tokens[r["k"], r["g"]], words[r["k"], r["g"]] = r["c"], r["n"]
    total, distinct = int(tokens.sum()) + docs, int(words.sum()) + (docs > 0)
    for w, c in top[:HEAD]:
        place = tail_code(w) % CLASSES - HEAD, tail_code(w) // CLASSES
        tokens[place] -= c
        words[place] -= 1
    return WordCounts(table, top, docs, total, distinct, tokens, words)


def score_documents(
    docs: DataFrame,
    held_out_of: int = 10,
    top_words: int = 1 << 17,
    least_docs: int = 1000,
    rounds: int = 3,
    id_col: str = "doc_id",
    text_col: str = "text",
) -> DataFrame:
    """``doc_id, held_out, n_tokens, n_known, train_tokens, base_score, score`` of every whole text.

    Learns from all texts outside fold 0 of ``held_out_of``: word counts, group totals and the recurrent weights. These are
    learned in ``rounds`` rounds by tasks of about ``TASK_TOKENS`` tokens, whose weights are averaged after each round; every
    token of every such text is read in one round, and in more if a round would have fewer than ``least_docs`` texts.
    ``score`` is the model's log10 probability of the text and its end; a word never seen has, as in ``base_score``, the
    mass of one unseen word (of its group). Counts of the ``top_words`` most frequent words go to all tasks; words beyond
    them are joined with the count table, a distinct word of a document once. Texts are coded once, for training and scores.

    Null and empty texts are the end token alone. Rows with repeated or null ids are scored one by one; null ids count as
    held out. With no training text, counts are zero and the class model is uniform. An empty table gives no row.
    """
    frame = doc_frame(docs, id_col, text_col)
    held = fold(F.col("doc_id"), held_out_of) == 0
    counts = count_words(frame.where(~held).select("text"), top_words)
    unit = GatedUnit()
    inside = counts.group_tokens.sum(1)
    of_class = np.array([c for _, c in counts.top[:HEAD]] + [0] * (HEAD - len(counts.top[:HEAD])) + inside.tolist() + [counts.docs]) + 0.1
    of_class = (of_class / of_class.sum()).reshape(SPANS, SPAN)
    unit.w["bias"], unit.w["span_bias"] = np.log(of_class).astype(np.float32), np.log(of_class.sum(1))[None].astype(np.float32)
    unit.w["group_bias"] = np.log(counts.group_total() / counts.group_total().sum(1, keepdims=True)).astype(np.float32)

    base_total, group_total = max(counts.base_total(), 0.1), counts.group_total()
    n = np.array([c for _, c in counts.top] + [counts.docs], float)
    top_base = np.log10((n + 0.1) / base_total)
    top_code = np.array([k if k < HEAD else tail_code(w) for k, (w, _) in enumerate(counts.top)] + [END], np.int64)
    kind = top_code % CLASSES
    tail = (kind >= HEAD) & (kind < END)
    top_inner = np.where(tail, np.log10((n + 0.1) / group_total[np.clip(kind - HEAD, 0, TAIL - 1), top_code // CLASSES]), 0.0)
    listed, end_at, end_known = b"\n".join(w for w, _ in counts.top), len(counts.top), counts.docs > 0
    any_top = bool(counts.top)

    def step(batches):
        place, made = TaskContext.get().partitionId() << 33, 0
        index = {w.decode(): k for k, w in enumerate(listed.split(b"\n"))} if any_top else {}
        look = index.get
        for batch in batches:
            for part in by_bytes(batch, "text"):
                rows = part.num_rows
                words, at, edges = numbered_words(part.column("text"))
                shown = strings(words)
                known = np.fromiter((look(w, -1) for w in shown), np.int64, len(shown))
                code = np.where(known >= 0, top_code[known], 0)
                for k in np.flatnonzero(known < 0).tolist():
                    code[k] = tail_code(shown[k].encode())
                doc = np.repeat(np.arange(rows), np.diff(edges))
                top = known[at]
                listed_at = np.flatnonzero(top >= 0)
                total = lambda values: np.bincount(doc[listed_at], values[top[listed_at]], rows)  # noqa: B023, E731
                codes = np.insert(code[at], edges[1:], END).astype("<i2")
                ends = ((edges + np.arange(rows + 1)) * codes.itemsize).astype(np.int32)
                # Each word that is not listed once a document, with how often it is there.
                pairs, times = np.unique((doc * max(len(shown), 1) + at)[top < 0], return_counts=True)
                of, which = np.divmod(pairs, max(len(shown), 1))
                offsets = pa.array(np.searchsorted(of, np.arange(rows + 1)).astype(np.int32))
                yield {
                    "row": place + made + np.arange(rows),
                    "doc_id": part.column("doc_id"),
                    "n": np.diff(edges) + 1,
                    "known": np.bincount(doc[listed_at], minlength=rows) + int(end_known),
                    "base": total(top_base) + top_base[end_at],
                    "inner": total(top_inner),
                    "codes": pa.Array.from_buffers(pa.binary(), rows, [None, pa.py_buffer(ends), pa.py_buffer(codes)]),
                    "words": pa.ListArray.from_arrays(offsets, words.take(pa.array(which)).cast(pa.binary())),
                    "times": pa.ListArray.from_arrays(offsets, pa.array(times.astype(np.int32))),
                }
                made += rows

    schema = "row long, doc_id long, n long, known long, base double, inner double, codes binary, words array<binary>, times array<int>"
    coded = materialize(map_rows(frame, step, schema), "lm-codes")
    unit = train_apart(coded.where(~held).select("row", "doc_id", "codes"), counts.docs, counts.tokens, unit, rounds, least_docs)

    def judge(batches):
        for batch in batches:
            for part in by_bytes(batch, "codes"):
                found = {name: part.column(name) for name in ("row", "doc_id", "n", "known", "base")}
                yield found | {"score": part.column("inner").to_numpy() + document_log_probs(unit, code_arrays(part.column("codes"))) / LN10}

    numbers = coded.select("row", "doc_id", "n", "known", "base", "inner", "codes")
    scored = materialize(map_rows(numbers, judge, "row long, doc_id long, n long, known long, base double, score double"), "lm-scores")
    rare = coded.where("size(words) > 0").select("row", F.explode(F.arrays_zip("words", "times")).alias("x"))
    rare = rare.select("row", F.col("x.words").alias("w"), F.col("x.times").alias("times")).join(counts.table, "w", "left")
    seen = F.coalesce("c", F.lit(0))
    totals = docs.sparkSession.createDataFrame([(k, g, float(group_total[k, g])) for k in range(TAIL) for g in range(GROUPS)], "k int, g int, total double")
    rare = rare.withColumn("k", tail_column()).withColumn("g", group_column()).join(F.broadcast(totals), ["k", "g"])
    rare = rare.groupBy("row").agg(
        F.sum(F.when(seen > 0, F.col("times")).otherwise(0)).alias("more_known"),
        F.sum(F.col("times") * F.log10((seen + 0.1) / F.lit(base_total))).alias("more_base"),
        F.sum(F.col("times") * F.log10((seen + 0.1) / F.col("total"))).alias("more_score"),
    )
    zero = lambda c: F.coalesce(c, F.lit(0))
    return scored.join(rare, "row", "left").select(
        "doc_id",
        (fold(F.col("doc_id"), held_out_of) == 0).alias("held_out"),
        F.col("n").alias("n_tokens"),
        (F.col("known") + zero("more_known")).cast("long").alias("n_known"),
        F.lit(counts.tokens).cast("long").alias("train_tokens"),
        (F.col("base") + zero("more_base")).alias("base_score"),
        (F.col("score") + zero("more_score")).alias("score"),
    )
