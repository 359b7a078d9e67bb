"""Token ids of whole texts by a public tokenizer file, kept as little-endian binaries."""

from __future__ import annotations

from itertools import chain

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame

from signedcluster.llm.common import by_bytes, doc_frame, map_rows, offsets_of
from signedcluster.shared import worker_cache

#: Words that a task remembers, of those met once and of those met again each, before it starts anew; bounds its memory.
MEMO_WORDS = 200_000
#: Separators that are white space to Python and not to the tokenizers, or the other way round.
ODD = "\x1c\x1d\x1e\x1f\x85\u180e\u200b\u2028\u2029"

#: Stands before a word that has no space before it; texts that hold it are encoded whole.
BARE = "\x01"
#: Longest run of signs that is cut off a word's end. Bytes that are signs, and bytes that are letters, of ASCII; for a
#: second byte, which letters (U+00C0 to U+017F without U+0130) it ends behind each of three first bytes.
RUN = 6
SIGNS = np.array([b > 32 and b < 127 and not chr(b).isalnum() for b in range(256)])
LETTERS = np.array([chr(b).isalpha() and b < 128 for b in range(256)])
SECOND = np.array([0x80 <= b < 0xC0 for b in range(256)])
NO_LETTER = np.isin(np.arange(256), (0x97, 0xB7))
#: Letters of whose case and class no Unicode version differs (the dotted capital I, which two letters stand for, left out).
PLAIN = f"^{BARE}?[A-Za-z\u00c0-\u00d6\u00d8-\u00f6\u00f8-\u012f\u0131-\u024f]+$"


def byte_letters() -> dict[int, str]:
    """The visible characters that byte-level vocabularies write for bytes; spaces stay as they are."""
    shown = [*range(33, 127), *range(161, 173), *range(174, 256)]
    hidden = [b for b in range(256) if b not in shown]
    return {b: chr(b) for b in shown} | {b: chr(256 + k) for k, b in enumerate(hidden)} | {32: " "}


BYTES, SPACE = byte_letters(), "\u0120"


def tokenizer_file(name: str) -> str:
    import public_tokenizers

    return public_tokenizers.path(name)


def _load(path: str):
    from tokenizers import Tokenizer

    cache = worker_cache()
    if path not in cache:
        cache[path] = Tokenizer.from_file(path)
    return cache[path]


def ends_in_letter(data: np.ndarray, at: np.ndarray) -> np.ndarray:
    last, before = data[at], data[np.maximum(at - 1, 0)]
    return LETTERS[last] | (SECOND[last] & (((before == 0xC4) & (last != 0xB0)) | (before == 0xC5) | ((before == 0xC3) & ~NO_LETTER[last])))


def cut_tails(words: pa.StringArray, edges: np.ndarray) -> tuple[pa.StringArray, np.ndarray, np.ndarray, pa.StringArray]:
    """Words without the run of at most ``RUN`` signs behind a letter at their end; the run is a word of its own.

    Returns the longer array, where each text now starts in it, the places of the runs and the runs.
    """
    ends = offsets_of(words)
    data = np.frombuffer(words.buffers()[2] or b"", np.uint8)
    at, cut = np.zeros(0, np.int64), np.zeros(0, ends.dtype)
    left = np.flatnonzero(np.diff(ends) >= 2)
    for k in range(1, RUN + 1):
        left = left[ends[left + 1] - ends[left] > k]
        left = left[SIGNS[data[ends[left + 1] - k]]]
        here = ends_in_letter(data, ends[left + 1] - k - 1)
        at, cut = np.append(at, left[here]), np.append(cut, ends[left[here] + 1] - k)
        left = left[~here]
        if not len(left):
            break
    order = np.argsort(at)
    at, cut = at[order], cut[order].astype(ends.dtype)
    longer = np.insert(ends, at + 1, cut)
    made = pa.StringArray.from_buffers(len(longer) - 1, pa.py_buffer(longer), words.buffers()[2])
    places = at + 1 + np.arange(len(at))
    return made, edges + np.searchsorted(at, edges), places, made.take(pa.array(places))


class ChunkEncoder:
    """Encodes whole texts, remembering the ids of each word between spaces.

    Both files' pre-tokenizers never join across a space that follows a non-space, so a text's ids are those of its
    words in order: with ``keep_space`` a word starts with its space (byte-level), else white space carries nothing (word
    ends) and ASCII letters are lower-cased beforehand, as the file does. A run of signs behind a letter and, in
    byte-level files, a line break between two words are pieces of their own in both; cut off, they leave fewer distinct
    words. A word of plain letters is one piece, so it meets only the vocabulary and its merges; other new words of many
    texts are encoded as one text by the whole tokenizer and cut where the words' bytes end, which tokens never
    cross; if the bytes do not add up, words are encoded one by one. Texts with double spaces or other white space
    around line breaks (where that matters), special-token openers, or letters and separators on which Unicode versions
    differ are encoded whole.
    """

    def __init__(self, path: str, keep_space: bool, dtype: str):
        self.tokenizer, self.keep_space, self.dtype = _load(path), keep_space, np.dtype(dtype)
        self.known: dict[str, bytes] = {}
        self.met: dict[str, bytes] = {}
        sizes = np.zeros(self.tokenizer.get_vocab_size(with_added_tokens=True), np.int64)
        for token, k in self.tokenizer.get_vocab(with_added_tokens=True).items():
            sizes[k] = len(token.removesuffix("</w>")) if not keep_space else len(token)
        self.sizes = sizes
        self.strange = f"<\\||[{BARE}{ODD}]" + (r"|  |\n[\s\v\p{Z}]|[\s\v\p{Z}]\n|^\n|\n$" if keep_space else r"|[A-Z]\p{M}")

    def whole(self, text: str) -> bytes:
        return np.array(self.tokenizer.encode(text, add_special_tokens=False).ids, self.dtype).tobytes()

    def cut(self, ids: list[int], wanted: np.ndarray) -> list[bytes] | None:
        """Ids cut where the bytes of their tokens reach ``wanted``; None if some cut would go through a token."""
        ids, width = np.array(ids, np.int64), self.dtype.itemsize
        ends = np.cumsum(self.sizes[ids])
        at = np.searchsorted(ends, wanted)
        if not len(ids) or at[-1] != len(ids) - 1 or (ends[np.minimum(at, len(ids) - 1)] != wanted).any():
            return None
        packed = ids.astype(self.dtype).tobytes()
        at = ((at + 1) * width).tolist()
        return list(map(packed.__getitem__, map(slice, [0, *at[:-1]], at)))

    def plain(self, words: list[str], space: bool) -> list[bytes]:
        """Ids of words of plain letters, with a space before each if ``space``."""
        if not words:
            return []
        text = " ".join(words)
        if not self.keep_space:
            text = text.lower()
        raw = text.encode()
        shown = text if len(raw) == len(text) else raw.decode("latin-1").translate(BYTES)
        if space:
            shown = SPACE + shown.replace(" ", " " + SPACE)
        ids = [[t.id for t in pieces] for pieces in map(self.tokenizer.model.tokenize, shown.split(" "))]
        packed = np.fromiter(chain.from_iterable(ids), self.dtype).tobytes()
        ends = (np.cumsum(np.fromiter(map(len, ids), np.int64, len(ids))) * self.dtype.itemsize).tolist()
        return list(map(packed.__getitem__, map(slice, [0, *ends[:-1]], ends)))

    def spaced(self, words: list[str]) -> list[bytes]:
        """Ids of any words with a space before each (which counts in byte-level files only)."""
        out = []
        for at in range(0, len(words), 2000):
            some = words[at : at + 2000]
            text = " " + " ".join(some)
            shown = text if self.tokenizer.normalizer is None else " " + self.tokenizer.normalizer.normalize_str(text).strip(" ")
            ids = self.tokenizer.encode_batch_fast([text], add_special_tokens=False)[0].ids
            raw = np.frombuffer(shown.encode("utf-8", "surrogatepass"), np.uint8)
            wanted = np.append(np.flatnonzero(raw == 32)[1:], len(raw))
            if not self.keep_space:
                wanted = wanted - np.arange(1, len(wanted) + 1)
            out += (self.cut(ids, wanted) if len(wanted) == len(some) else None) or [self.whole(" " + w) for w in some]
        return out

    def learn(self, new: pa.StringArray) -> list[bytes]:
        """Ids of words, with the space before them unless marked ``BARE``; remembered."""
        words = new.to_numpy(zero_copy_only=False)
        bare = pc.starts_with(new, BARE).to_numpy(zero_copy_only=False)
        odd = ~pc.match_substring_regex(new, PLAIN).to_numpy(zero_copy_only=False)
        out = np.empty(len(words), object)
        for k in range(4):
            mine = (bare == (k > 1)) & (odd == k % 2)
            shown = words[mine].tolist()
            if k > 1:
                shown = [w[1:] for w in shown]
            if k == 3:
                found = [np.array(e.ids, self.dtype).tobytes() for e in self.tokenizer.encode_batch_fast(shown, add_special_tokens=False)]
            else:
                found = self.spaced(shown) if k == 1 else self.plain(shown, self.keep_space and k == 0)
            out[mine] = found
        out = out.tolist()
        if len(self.met) + len(out) > MEMO_WORDS:
            self.met.clear()
        self.met.update(zip(words.tolist(), out, strict=True))
        return out

    def remembered(self, words: list[str]) -> list[bytes | None]:
        """Ids of known words. A word met in a second slice of text is kept longer than one met once."""
        found = list(map(self.known.get, words))
        take = self.met.pop
        again = {words[k]: ids for k, v in enumerate(found) if v is None and (ids := take(words[k], None)) is not None}
        if again:
            if len(self.known) + len(again) > MEMO_WORDS:
                self.known.clear()
            self.known.update(again)
            found = [v if v is not None else again.get(w) for v, w in zip(found, words, strict=True)]
        return found

    def encode_all(self, texts: pa.Array, end: bytes = b"") -> pa.Array:
        """Binaries of the ids of each text, with ``end`` after them.

        Words are numbered by Arrow; only distinct ones meet Python. A text that is encoded whole is an entry of its own.
        """
        texts = pc.fill_null(texts, "")
        odd = pc.match_substring_regex(texts, self.strange).to_numpy(zero_copy_only=False)
        whole = [texts[int(k)].as_py() for k in np.flatnonzero(odd)]
        if whole:
            texts = pc.if_else(pa.array(odd), "", texts)
        if self.keep_space:
            split = pc.split_pattern(pc.binary_join_element_wise(BARE, pc.replace_substring(texts, "\n", f" {BARE}\n {BARE}"), ""), " ")
        else:
            split = pc.utf8_split_whitespace(pc.ascii_lower(texts))
        edges = split.offsets.to_numpy().astype(np.int64)
        words, edges, tails, signs = cut_tails(split.flatten(), edges)
        words, signs = words.dictionary_encode(), signs.dictionary_encode()
        seen = words.dictionary.to_numpy(zero_copy_only=False).tolist()
        at = words.indices.to_numpy().astype(np.int32)
        ids = self.remembered(seen)
        new = [k for k, v in enumerate(ids) if v is None]
        if new:
            for k, v in zip(new, self.learn(words.dictionary.take(pa.array(new))), strict=True):
                ids[k] = v
        at[tails] = len(ids) + signs.indices.to_numpy()
        ids += map(self.whole, signs.dictionary.to_pylist())
        at[edges[:-1][odd]] = len(ids) + np.arange(len(whole))
        ids += map(self.whole, whole)
        at = np.insert(at, edges[1:], len(ids))
        edges += np.arange(len(edges))
        ids = pa.array([*ids, end], pa.binary()).take(pa.array(at))
        offsets = offsets_of(ids)[edges]
        return pa.BinaryArray.from_buffers(pa.binary(), len(texts), [None, pa.py_buffer(offsets), ids.buffers()[2]])


def token_table(docs: DataFrame, path: str, keep_space: bool, end_id: int, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``(doc_id, n, ids)``: ids of the text and ``end_id`` after them, two bytes each if the vocabulary allows.

    Null and empty texts are the end id alone. Very long texts are encoded whole.
    """
    dtype = id_type(path)

    def step(batches):
        import os

        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        coder = ChunkEncoder(path, keep_space, dtype)
        end = np.array([end_id], dtype).tobytes()
        for batch in batches:
            for part in by_bytes(batch, "text"):
                ids = coder.encode_all(part.column("text"), end)
                yield {"doc_id": part.column("doc_id"), "n": np.diff(offsets_of(ids)) // coder.dtype.itemsize, "ids": ids}
            pa.default_memory_pool().release_unused()

    return map_rows(doc_frame(docs, id_col, text_col), step, "doc_id long, n long, ids binary")


def vocabulary_size(path: str) -> int:
    return _load(path).get_vocab_size(with_added_tokens=True)


def id_type(path: str) -> str:
    return "<u2" if vocabulary_size(path) <= 1 << 16 else "<u4"


def id_arrays(column: pa.Array, dtype: str) -> tuple[np.ndarray, np.ndarray]:
    """Ids of all rows of a binary column, and where each row starts (with the end after the last)."""
    edges = offsets_of(column).astype(np.int64)
    width = np.dtype(dtype).itemsize
    total = int(edges[-1] - edges[0])
    ids = np.frombuffer(column.buffers()[2], dtype, total // width, int(edges[0])) if total else np.zeros(0, dtype)
    return ids, (edges - edges[0]) // width


class Distinct:
    """Distinct ids of a document, each at its last place, without sorting."""

    def __init__(self, size: int):
        self.place = np.zeros(size, np.int64)

    def __call__(self, ids: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(distinct ids, occurrences of each)."""
        at = np.arange(len(ids))
        self.place[ids] = at
        last = self.place[ids]
        kept = np.flatnonzero(last == at)
        return ids[kept], np.bincount(last, minlength=len(ids))[kept]


def id_counts(tokens: DataFrame, dtype: str, size: int, per_document: bool) -> np.ndarray:
    """Occurrences of each id (or documents that hold it). ``size`` is the vocabulary's, which bounds what is gathered."""

    def step(batches):
        total = np.zeros(size, np.int64)
        distinct = Distinct(size)
        for batch in batches:
            ids, edges = id_arrays(batch.column("ids"), dtype)
            if per_document:
                for a, b in zip(edges[:-1].tolist(), edges[1:].tolist(), strict=True):
                    total[distinct(ids[a:b])[0]] += 1
            else:
                total += np.bincount(ids, minlength=size)
        held = np.flatnonzero(total)
        yield {"id": held, "n": total[held]}

    out = np.zeros(size, np.int64)
    for row in map_rows(tokens.select("ids"), step, "id int, n long").groupBy("id").agg({"n": "sum"}).collect():
        out[row[0]] = row[1]
    return out
