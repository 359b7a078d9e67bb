"""Exact duplicates by progressive refinement: length, then prefix hash, then full hash. DataFrame functions only."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from signedcluster.llm.common import bit_filter, doc_frame, few, flagged, text_mark, without_rows
from signedcluster.shared import discard, materialize


def repeated(rows: DataFrame, *keys: str) -> DataFrame:
    """Values of ``keys`` that two or more rows have. Partial counts leave one row a task for a hot group of copies."""
    return rows.groupBy(*keys).agg(F.count("*").alias("n")).where("n > 1").drop("n")


def refined(rows: DataFrame, prefix_chars: int) -> DataFrame:
    """(length, prefix hash) of two or more rows: lengths are counted first, prefixes only of rows of a repeated length."""
    narrow = materialize(rows.select(F.octet_length("text").alias("bytes"), F.xxhash64(F.substring("text", 1, prefix_chars)).alias("prefix")), "prefixes")
    lengths = materialize(repeated(narrow, "bytes"), "lengths")
    found = materialize(repeated(narrow.join(few(lengths), "bytes", "left_semi"), "bytes", "prefix"), "survivors")
    discard(narrow)
    return found


def digests(docs: DataFrame, id_col: str, text_col: str, prefix_chars: int, digest_all: bool) -> DataFrame:
    """``(doc_id, mark, digest, candidate)``: rows whose length and prefix are not theirs alone are candidates."""
    rows = doc_frame(docs, id_col, text_col, text_mark(text_col)).withColumn("text", F.coalesce("text", F.lit("")))
    survivors = refined(rows, prefix_chars)
    key = F.xxhash64(F.octet_length("text"), F.xxhash64(F.substring("text", 1, prefix_chars)))
    kept = bit_filter(survivors.select(F.xxhash64("bytes", "prefix").alias("h")))
    full = F.unhex(F.sha2("text", 256))
    found = flagged(rows, key, kept, "candidate")
    return materialize(found.select("doc_id", "mark", (full if digest_all else F.when(F.col("candidate"), full)).alias("digest"), "candidate"), "digests")


def marked_groups(docs: DataFrame, id_col: str, text_col: str, prefix_chars: int, digest_all: bool) -> DataFrame:
    """As :func:`exact_groups`, with the ``mark`` of each row's text."""
    found = digests(docs, id_col, text_col, prefix_chars, digest_all)
    candidates = found.where("candidate")
    groups = candidates.groupBy("digest").agg(F.max("doc_id").alias("keep_id"), F.count("*").alias("group_size"))
    groups = few(materialize(groups.where("group_size > 1"), "groups"))
    one = found.where("not candidate").select("doc_id", "mark", "digest", F.lit(None).cast("long").alias("keep_id"), F.lit(1).cast("long").alias("group_size"))
    more = candidates.drop("candidate").join(groups, "digest", "left").select("doc_id", "mark", "digest", "keep_id", F.coalesce("group_size", F.lit(1)).cast("long").alias("group_size"))
    return one.unionByName(more).select(
        "doc_id",
        "mark",
        F.coalesce("keep_id", "doc_id").alias("keep_id"),
        "group_size",
        F.coalesce("keep_id", "doc_id").eqNullSafe(F.col("doc_id")).alias("kept"),
        F.lower(F.hex("digest")).alias("text_sha256"),
    )


def exact_groups(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", prefix_chars: int = 64, digest_all: bool = False) -> DataFrame:
    """One row per input row: ``doc_id, keep_id, group_size, kept, text_sha256``.

    Equal texts are those with the same bytes; null counts as empty. The row with the largest id of its group stays.
    Level 1 counts byte lengths. Level 2 counts hashes of the first ``prefix_chars`` characters among rows of a length that
    others have. Level 3 groups the full SHA-256 of the rows whose length and prefix others have: what level 2 leaves is a
    bit filter of proven size (see :func:`signedcluster.llm.common.bit_filter`); a row that passes it by chance forms a group
    of its own. Text is never shuffled. A row with a group of its own has a null ``text_sha256`` if it never came to
    level 3, unless ``digest_all`` asks for every digest as output; groups are made of level 3 in either case.

    Repeated rows with the same id and text are one group and all of them carry ``kept`` true. A null id never wins
    against another id; a group of null ids only keeps nothing apart and has ``keep_id`` null, ``kept`` true.
    An empty table gives an empty result.
    """
    return marked_groups(docs, id_col, text_col, prefix_chars, digest_all).drop("mark")


def drop_exact_copies(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", prefix_chars: int = 64) -> DataFrame:
    """``docs`` without the rows that :func:`exact_groups` drops, each row by its own verdict (ids may repeat or be null)."""
    return without_rows(docs, marked_groups(docs, id_col, text_col, prefix_chars, False).where("not kept"), id_col, text_col)
