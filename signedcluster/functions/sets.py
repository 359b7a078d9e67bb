"""Lists of items in Arrow columns as sets of their runs: hashes, exact codes and comparisons in numpy."""

from __future__ import annotations

import numpy as np

MIX = np.uint64(0x9E3779B97F4A7C15)


def lists(column) -> tuple:
    """(items of all lists, where each list begins and the last ends) of an Arrow column without nulls."""
    edges = column.offsets.to_numpy().astype(np.int64)
    return column.flatten(), edges - edges[0]


def runs(edges: np.ndarray, size: int) -> tuple[np.ndarray, np.ndarray]:
    """(list, place of its first item) of each run of ``size`` items; a shorter list is one run, of single items none if empty."""
    n = np.diff(edges)
    many = n if size == 1 else np.maximum(n - size, 0) + 1
    of = np.repeat(np.arange(len(n)), many)
    return of, np.arange(len(of)) - np.repeat(np.cumsum(many) - many, many) + edges[:-1][of]


def places(values: np.ndarray, edges: np.ndarray, of: np.ndarray, at: np.ndarray, size: int):
    """The first, second, ... items of all runs; 0 where a shorter list has ended."""
    more = np.concatenate([values, np.zeros(size, values.dtype)])
    short, end = (np.diff(edges) < size).any(), edges[1:][of]
    for j in range(size):
        x = more[at + j]
        yield np.where(at + j < end, x, x.dtype.type(0)) if short else x


def run_hashes(values: np.ndarray, edges: np.ndarray, size: int) -> tuple[np.ndarray, np.ndarray]:
    """(list, 64-bit hash) of each run, from hashes of the items."""
    of, at = runs(edges, size)
    h = np.zeros(len(of), np.uint64)
    for x in places(values.view(np.uint64), edges, of, at, size):
        h = (h ^ x) * MIX
        h ^= h >> np.uint64(32)
    return of, h


def run_codes(values: np.ndarray, edges: np.ndarray, size: int) -> tuple[np.ndarray, np.ndarray]:
    """(list, code) of each run of items numbered from 0: runs have one code exactly if they are equal."""
    of, at = runs(edges, size)
    base = int(values.max()) + 2 if len(values) else 1
    code, most = np.zeros(len(of), np.int64), 1
    for x in places(values.astype(np.int64) + 1, edges, of, at, size):
        if most * base >= 1 << 62:
            names, code = np.unique(code, return_inverse=True)
            most = len(names) + 1
        code, most = code * base + x, most * base
    return of, np.unique(code, return_inverse=True)[1]


def common(of: np.ndarray, code: np.ndarray, n: int, u: np.ndarray, v: np.ndarray, held: int = 1 << 21) -> tuple[np.ndarray, np.ndarray]:
    """(sizes of the ``n`` sets, codes that sets ``u`` and ``v`` share), the pairs sorted by ``u``; sets of one pair's end
    are looked up in a table of the other's codes, about ``held`` at a time."""
    kinds = int(code.max()) + 1 if len(code) else 1
    own = np.unique(of.astype(np.int64) * kinds + code)
    edges = np.searchsorted(own, np.arange(n + 1, dtype=np.int64) * kinds)
    own %= kinds
    sizes, table, shared = np.diff(edges), np.zeros(kinds, bool), np.zeros(len(u), np.int64)
    cuts = [0, *(np.flatnonzero(np.diff(u)) + 1).tolist(), len(u)]
    for a, b in zip(cuts[:-1], cuts[1:], strict=True):
        if a == b:
            continue
        mine = own[edges[u[a]] : edges[u[a] + 1]]
        table[mine] = True
        while a < b:
            end = a + max(1, int(np.searchsorted(np.cumsum(sizes[v[a:b]]), held)))
            end = min(end, b)
            many = sizes[v[a:end]]
            begin = np.cumsum(many) - many
            at = np.arange(int(many.sum())) - np.repeat(begin, many) + np.repeat(edges[v[a:end]], many)
            hits = np.concatenate([[0], np.cumsum(table[own[at]])])
            shared[a:end] = hits[begin + many] - hits[begin]
            a = end
        table[mine] = False
    return sizes, shared


def pack(h: np.ndarray, ids: np.ndarray, n: np.ndarray) -> bytes:
    """Leading 48 bits of hashes, ids and sizes as planes of bytes: leading bytes of sorted hashes and of ids compress."""
    raw = [h.astype("<u8").view(np.uint8).reshape(-1, 8)[:, 2:], ids.astype("<i8").view(np.uint8).reshape(-1, 8), n.astype("<u4").view(np.uint8).reshape(-1, 4)]
    return np.concatenate(raw, axis=1).T.tobytes()


def unpack(blobs) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    raw = np.concatenate([np.frombuffer(x, np.uint8).reshape(18, -1) for x in blobs], axis=1).T
    h = np.zeros((len(raw), 8), np.uint8)
    h[:, :6] = raw[:, :6]
    return h.view("<i8").ravel(), np.ascontiguousarray(raw[:, 6:14]).view("<i8").ravel(), np.ascontiguousarray(raw[:, 14:]).view("<u4").ravel().astype(np.int64)
