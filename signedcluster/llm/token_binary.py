"""Token-id files: frequency ranks in byte-aligned variable-length codes with separate control bytes.

A folder holds ``ranks.bin`` (ids by falling frequency) and shard files in ascending id order. A shard is a sequence of
blocks: a header, document ids, document lengths, control bytes (four two-bit byte counts each), then the value bytes.
Frequent ids have small ranks, and ranks below 256 take one byte. Decoding looks byte counts up by control byte.
"""

from __future__ import annotations

import struct
import zlib

import numpy as np
from pyarrow import fs
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from signedcluster.llm.common import map_rows
from signedcluster.llm.tokens import id_counts, id_type, token_table, tokenizer_file, vocabulary_size
from signedcluster.shared import materialize, new_path

MAGIC = b"TIDB"
HEADER = "<4sIQQI"  # magic, documents, ids, value bytes, crc32 of all that follows
BLOCK_IDS = 1 << 20

#: Byte counts of the four values behind each control byte.
COUNTS = ((np.arange(256)[:, None] >> np.array([0, 2, 4, 6])) & 3).astype(np.int64) + 1


def pack_values(values: np.ndarray) -> tuple[bytes, bytes]:
    """Control bytes and value bytes of unsigned 32-bit values."""
    values = values.astype("<u4")
    size = (1 + (values > 0xFF) + (values > 0xFFFF) + (values > 0xFFFFFF)).astype(np.uint8)
    code = np.zeros(-(-len(values) // 4) * 4, np.uint8)
    code[: len(values)] = size - 1
    control = (code.reshape(-1, 4) << np.array([0, 2, 4, 6], np.uint8)).sum(1, dtype=np.uint8)
    kept = values.view(np.uint8).reshape(-1, 4)[np.arange(4) < size[:, None]]
    return control.tobytes(), kept.tobytes()


def unpack_values(control: bytes, data: bytes, n: int) -> np.ndarray:
    size = COUNTS[np.frombuffer(control, np.uint8)].ravel()[:n]
    start = np.cumsum(size) - size
    raw = np.frombuffer(data + b"\0\0\0", np.uint8)
    out = np.zeros(n, np.uint32)
    for k in range(4):
        wide = size > k
        if not wide.any():
            break
        out[wide] |= raw[start[wide] + k].astype(np.uint32) << np.uint32(8 * k)
    return out


def write_block(out, doc_ids: list[int | None], lengths: list[int], ranks: np.ndarray) -> None:
    """A null document id is written as the smallest 64-bit value."""
    ids = np.array([-(2**63) if d is None else d for d in doc_ids], "<i8").tobytes()
    control, data = pack_values(ranks)
    body = ids + np.array(lengths, "<u4").tobytes() + control + data
    out.write(struct.pack(HEADER, MAGIC, len(doc_ids), len(ranks), len(data), zlib.crc32(body)) + body)


def read_blocks(stream):
    """(document id or None, ranks) of each document, a block in memory at a time."""
    while head := stream.read(struct.calcsize(HEADER)):
        magic, docs, n, size, crc = struct.unpack(HEADER, head)
        body = stream.read(docs * 12 + -(-n // 4) + size)
        if magic != MAGIC or zlib.crc32(body) != crc:
            raise ValueError("damaged block")
        ids = np.frombuffer(body, "<i8", docs)
        lengths = np.frombuffer(body, "<u4", docs, docs * 8)
        at = docs * 12
        ranks = unpack_values(body[at : at + -(-n // 4)], body[at + -(-n // 4) :], n)
        ends = np.cumsum(lengths, dtype=np.int64)
        for d, a, b in zip(ids.tolist(), (ends - lengths).tolist(), ends.tolist(), strict=True):
            yield (None if d == -(2**63) else d), ranks[a:b]


def _open(uri: str):
    return fs.FileSystem.from_uri(uri)


def write_token_files(tokens: DataFrame, folder: str, dtype: str, size: int, shards: int) -> list[tuple[str, int, int]]:
    """Write the shards of a materialised ``(doc_id, n, ids)`` table; returns (file, documents, ids) in id order.

    What reaches the driver is a count for each id of the vocabulary and a row for each shard. A shard is written under
    a name of its attempt and renamed when whole, so a repeated task leaves one complete file.
    """
    counts = id_counts(tokens, dtype, size, per_document=False)
    order = np.lexsort((np.arange(size), -counts)).astype("<u4")
    rank_of = np.empty(size, np.uint32)
    rank_of[order] = np.arange(size, dtype=np.uint32)
    store, base = _open(folder)
    store.create_dir(base, recursive=True)
    with store.open_output_stream(f"{base}/ranks.bin") as out:
        out.write(order.tobytes())

    def step(batches):
        context = TaskContext.get()
        store, base = _open(folder)
        name = f"shard-{context.partitionId():06d}.tid"
        whole = f"{base}/.{name}-{context.taskAttemptId()}"
        docs = total = 0
        out, held, lengths, parts, waiting = None, [], [], [], 0
        for batch in batches:
            for d, ids in zip(batch.column("doc_id").to_pylist(), batch.column("ids"), strict=True):
                out = out or store.open_output_stream(whole)
                ranks = rank_of[np.frombuffer(ids.as_py(), dtype)]
                held.append(d)
                lengths.append(len(ranks))
                parts.append(ranks)
                waiting += len(ranks)
                docs, total = docs + 1, total + len(ranks)
                if waiting >= BLOCK_IDS:
                    write_block(out, held, lengths, np.concatenate(parts))
                    held, lengths, parts, waiting = [], [], [], 0
        if held:
            write_block(out, held, lengths, np.concatenate(parts))
        if out:
            out.close()
            store.move(whole, f"{base}/{name}")
            yield {"file": [name], "docs": [docs], "n": [total]}

    dealt = tokens.repartitionByRange(shards, "doc_id").sortWithinPartitions("doc_id", "ids")
    done = materialize(map_rows(dealt.select("doc_id", "ids"), step, "file string, docs long, n long"), "manifest")
    return [tuple(r) for r in done.orderBy("file").collect()]


def read_token_files(spark: SparkSession, folder: str, manifest: list[tuple[str, int, int]], column: str = "ids binary", made=bytes) -> DataFrame:
    """``(doc_id, start, n_tokens, ids)`` of each document, read from the files; ids as unsigned 32-bit binaries.

    ``column`` and ``made`` (of such a binary) name what else is wanted in place of the ids, so that only it leaves the task.
    """
    starts, at, name = [], 0, column.split()[0]
    for file, _, n in manifest:
        starts.append((file, at))
        at += n
    shards = spark.createDataFrame(starts, "file string, first long")
    if starts:
        shards = shards.repartitionByRange(len(starts), "file")

    def step(batches):
        store, base = _open(folder)
        with store.open_input_stream(f"{base}/ranks.bin") as f:
            order = np.frombuffer(f.read(), "<u4")
        for batch in batches:
            for file, at in zip(batch.column("file").to_pylist(), batch.column("first").to_pylist(), strict=True):
                rows = {"doc_id": [], "start": [], "n_tokens": [], name: []}
                with store.open_input_stream(f"{base}/{file}") as f:
                    for d, ranks in read_blocks(f):
                        rows["doc_id"].append(d)
                        rows["start"].append(at)
                        rows["n_tokens"].append(len(ranks))
                        rows[name].append(made(order[ranks].tobytes()))
                        at += len(ranks)
                        if len(rows["doc_id"]) >= 500:
                            yield rows
                            rows = {k: [] for k in rows}
                yield rows

    return map_rows(shards, step, f"doc_id long, start long, n_tokens long, {column}")


def encode_documents(
    docs: DataFrame,
    tokenizer: str | None = None,
    end_id: int = 2,
    folder: str | None = None,
    id_col: str = "doc_id",
    text_col: str = "text",
    shard_ids: int = 1 << 24,
) -> tuple[str, list[tuple[str, int, int]]]:
    """Encode whole texts and write the token files; returns the folder and its manifest.

    Null texts are empty: the end id alone. Repeated rows are written once each, in the order of their ids; null document
    ids come first. An empty table writes no shard. ``shard_ids`` is the aimed size of a shard.
    """
    spark = docs.sparkSession
    path = tokenizer or tokenizer_file("word_bpe_49k.json")
    folder = folder or new_path(spark, "token-files")
    tokens = materialize(token_table(docs, path, keep_space=False, end_id=end_id, id_col=id_col, text_col=text_col), "tokens")
    total = tokens.agg(F.sum("n")).first()[0] or 0
    shards = max(int(spark.conf.get("spark.sql.shuffle.partitions")), -(-total // shard_ids), 1)
    manifest = write_token_files(tokens, folder, id_type(path), vocabulary_size(path), shards)
    return folder, manifest
