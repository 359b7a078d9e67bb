"""What several operators of this subpackage share."""

from __future__ import annotations

import ctypes
import re
from collections.abc import Iterable, Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from signedcluster.shared import materialize


#: Text whose words are numbered at once.
SLICE_BYTES = 4 << 20


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def fold(id_col: Column, parts: int) -> Column:
    """crc32 of the id as text, modulo ``parts``; a null id falls in fold 0."""
    return F.coalesce(F.crc32(id_col.cast("string").cast("binary")) % parts, F.lit(0))


def words_of(text: str | None) -> list[bytes]:
    """UTF-8 words between runs of ``[\\x20\\x09-\\x0D]`` with A-Z lower-cased (bytes methods touch ASCII only)."""
    return text.encode("utf-8", "surrogatepass").lower().split() if text else []


def doc_frame(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", *more: Column) -> DataFrame:
    """Only what an operator reads, under its own names, so that clashing extra columns cannot matter."""
    return docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("string").alias("text"), *more)


def text_mark(text_col: str | Column = "text") -> Column:
    """A hash that tells rows of one id apart by their text; null and empty texts have marks of their own."""
    text = (F.col(text_col) if isinstance(text_col, str) else text_col).cast("string")
    return F.xxhash64(text, F.octet_length(text)).alias("mark")


def few(frame: DataFrame, rows: int = 1 << 17) -> DataFrame:
    """``frame`` (written before, of some numbers a row) to be broadcast if it has at most ``rows`` rows, else as it is."""
    return F.broadcast(frame) if frame.count() <= rows else frame


#: Bits of a filter for each entry, and of the largest filter (32 MB).
FILTER_SHARE, FILTER_BITS = 16, 1 << 28


def bit_filter(hashes: DataFrame) -> tuple[DataFrame, int]:
    """(``bucket, bits``, number of bits): a bitmap of ``hashes(h)``, sized by their number, of at most 2^28 bits (32 MB).

    With more entries than a sixteenth of that, more of the others pass it too; none of its own is ever refused.
    """
    size = 1 << 15
    while size < min(hashes.count() * FILTER_SHARE, FILTER_BITS):
        size *= 2
    slot = F.pmod("h", F.lit(size)).alias("slot")
    bits = hashes.select(slot).groupBy(F.bitmap_bucket_number("slot").alias("bucket")).agg(F.bitmap_construct_agg(F.bitmap_bit_position("slot")).alias("bits"))
    return materialize(bits, "filter"), size


def flagged(rows: DataFrame, h: Column, kept: tuple[DataFrame, int], name: str) -> DataFrame:
    """``rows`` with a column ``name``: whether the bit of the hash ``h`` is set."""
    bits, size = kept
    slot = F.pmod(h, F.lit(size))
    with_slot = rows.withColumn(name, slot)
    joined = with_slot.join(F.broadcast(bits), F.bitmap_bucket_number(with_slot[name]) == bits["bucket"], "left")
    at = F.bitmap_bit_position(with_slot[name])
    byte = F.conv(F.hex(F.substring(bits["bits"], (F.floor(at / 8) + 1).cast("int"), F.lit(1))), 16, 10).cast("int")
    hit = F.coalesce(F.getbit(byte, F.pmod(at, F.lit(8)).cast("int")) == 1, F.lit(False))
    return joined.select(*[with_slot[c] for c in rows.columns], hit.alias(name))


def without_rows(docs: DataFrame, gone: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``docs`` without the rows whose id (null too) and text mark are in ``gone(doc_id, mark)``.

    A verdict holds for a row, not for its id: rows of one id with other texts stay. Only rows of the same id and text
    share one. If few go, they are broadcast; else a bit filter lets the rows pass that are surely not among them, and only
    the others are shuffled.
    """
    gone = materialize(gone.select(F.col("doc_id").alias("gone_id"), F.col("mark").alias("gone_mark")).distinct(), "gone")
    least = few(gone)
    same = lambda rows: rows[id_col].cast("long").eqNullSafe(gone["gone_id"]) & (text_mark(rows[text_col]) == gone["gone_mark"])
    if least is not gone:
        return docs.join(least, same(docs), "left_anti")
    name = "_among_gone"
    while name in docs.columns:
        name += "_"
    kept = bit_filter(gone.select(F.xxhash64("gone_id", "gone_mark").alias("h")))
    rows = flagged(docs, F.xxhash64(docs[id_col].cast("long"), text_mark(docs[text_col])), kept, name)
    sure, rest = rows.where(~F.col(name)).drop(name), rows.where(name).drop(name)
    return sure.unionByName(rest.join(gone, same(rest), "left_anti"))


def release() -> None:
    """Give freed memory back to the system, so that a worker that waits for its next task holds little."""
    pa.default_memory_pool().release_unused()
    trim = getattr(ctypes.CDLL(None), "malloc_trim", None)
    if trim is not None:
        trim(0)


def map_rows(df: DataFrame, step, schema: str) -> DataFrame:
    """``step(batches of column dicts) -> iterator of column dicts`` through Arrow, no pandas in between."""
    from pyspark.sql.pandas.types import to_arrow_schema
    from pyspark.sql.types import StructType

    kinds = StructType.fromDDL(schema)
    arrow = to_arrow_schema(kinds)

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for out in step(batches):
            held = (out[f.name] for f in arrow)
            columns = [c.cast(f.type) if isinstance(c, pa.Array) else pa.array(c, type=f.type) for c, f in zip(held, arrow, strict=True)]
            yield pa.RecordBatch.from_arrays(columns, schema=arrow)
        out = held = columns = None
        release()

    return df.mapInArrow(run, kinds)


def texts(batch: pa.RecordBatch, column: str = "text", step: int = 256) -> Iterator[tuple[int, str | None]]:
    """Row number and text, turned into Python strings a few hundred at a time."""
    col = batch.column(column)
    for at in range(0, len(col), step):
        yield from enumerate(col.slice(at, step).to_pylist(), at)


def bounded_sample(frame: DataFrame, rows: int) -> DataFrame:
    """About ``rows`` of ``frame(doc_id, text)``, never more, chosen by a hash of id and text.

    The share aims a little lower, so that the limit acts only on a table of like rows. It is set from the number of rows before any text moves, so each task sends on only its part of the sample.
    """
    n = frame.count()
    share = min(1.0, 0.95 * rows / max(n, 1)) if n > rows else 1.0
    return frame.where(F.pmod(F.xxhash64("doc_id", "text"), F.lit(1 << 30)) <= F.lit(int(share * (1 << 30)))).limit(rows)


def offsets_of(column: pa.Array) -> np.ndarray:
    """Where the values of a binary column start in its data, and the end of the last."""
    return np.frombuffer(column.buffers()[1], np.int32, len(column) + 1, column.offset * 4) if len(column) else np.zeros(1, np.int32)


def by_bytes(batch: pa.RecordBatch, column: str) -> Iterator[pa.RecordBatch]:
    """Slices of about ``SLICE_BYTES`` of ``column``; a longer value is a slice of its own."""
    sizes = pc.fill_null(pc.binary_length(batch.column(column)), 0).to_numpy().astype(np.int64)
    part = (np.cumsum(sizes) - sizes) // SLICE_BYTES
    cuts = [0, *(np.flatnonzero(np.diff(part)) + 1).tolist(), batch.num_rows]
    for a, b in zip(cuts[:-1], cuts[1:], strict=True):
        if b > a:
            yield batch.slice(a, b - a)


def numbered_words(texts: pa.Array) -> tuple[pa.StringArray, np.ndarray, np.ndarray]:
    """(distinct words, number of each word of all texts in order, where each text starts), words as in :func:`words_of`.

    Arrow cuts and numbers the words, so Python meets distinct ones only. Null texts have none.
    """
    split = pc.ascii_split_whitespace(pc.ascii_lower(pc.fill_null(texts, "")))
    words, edges = split.flatten(), split.offsets.to_numpy().astype(np.int64)
    there = np.diff(offsets_of(words)) > 0
    words = words.dictionary_encode()
    at = words.indices.to_numpy()
    if not there.all():
        at, edges = at[there], np.concatenate(([0], np.cumsum(there)))[edges]
    return words.dictionary, at, edges


def strings(column: pa.Array) -> list[str]:
    return column.to_numpy(zero_copy_only=False).tolist()


LETTER = re.compile(r"[^\W\d_]")


def has_letter(text: str) -> bool:
    """Whether a letter is among the signs; numbers that are no decimal digits (superscripts, fractions) are none."""
    return any(m.group().isalpha() for m in LETTER.finditer(text))


def popcount(x: np.ndarray) -> np.ndarray:
    return np.bitwise_count(x)
