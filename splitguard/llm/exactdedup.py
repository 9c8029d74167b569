"""Exact de-duplication by an exchange of Golomb-coded fingerprints.

1. One pass over the texts makes a narrow table: id, SHA-256 of the normalised
   text. Texts themselves do not move.
2. Each partition sends every owner of a fingerprint range one message: its
   distinct fingerprints, sorted, as Golomb-Rice coded gaps, and a bit for each
   that says whether the partition holds it more than once.
3. An owner answers each message with a bitmap: which of these fingerprints
   occur elsewhere or more than once.
4. Partitions decode the bitmaps against their messages; the fingerprints that
   are set are suspects, and a bitmap of them goes back to all partitions. Only
   texts whose bit is set are shuffled, grouped by their
   whole text with map-side combining, so a text with very many copies
   leaves each task once. The bytes decide; a fingerprint never does.

Fingerprints are short (48 bits) on purpose: chance matches cost a needless
verification, never a wrong result. Owners and senders are as many as the rows ask for, so
none holds more than about OWNER_ROWS fingerprints at any size of the table.

Defined results: a null text counts as empty; texts that differ only in runs of
ASCII white space are equal; the least (id, text hash) of a group stays, and of
rows equal in both exactly one; null ids sort first; an empty table gives an empty result.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from splitguard.functions.runtime import join_by_key, reliable, shuffle_width
from splitguard.llm.rows import NO_ID, bitmap_of, fresh, id_key, keep_rows, text_key

BITS = 48
#: Fingerprints that an owner or a sender holds, about.
OWNER_ROWS = 4_000_000
WHITE = r"[\x20\x09-\x0D]+"


def normal_text(text_col: str) -> Column:
    return F.regexp_replace(F.coalesce(F.col(text_col), F.lit("")), WHITE, " ")


# ---- Golomb-Rice code of a sorted set of integers --------------------------------


def rice_encode(values: np.ndarray) -> tuple[int, bytes]:
    """(k, code) of strictly rising non-negative integers.

    The code holds the quotients of all gaps in unary, padded to a byte, then all
    k-bit remainders, so that both parts decode without a loop over values.
    """
    if not len(values):
        return 0, b""
    gaps = np.diff(values, prepend=np.int64(-1)) - 1
    k = max(0, int(np.log2(max(1.0, gaps.mean()))))
    ends = np.cumsum((gaps >> k) + 1)
    unary = np.zeros(int(ends[-1]), np.uint8)
    unary[ends - 1] = 1
    remainders = ((gaps[:, None] >> np.arange(k)) & 1).astype(np.uint8)
    return k, np.packbits(unary).tobytes() + np.packbits(remainders.ravel()).tobytes()


def rice_decode(n: int, k: int, code: bytes) -> np.ndarray:
    if not n:
        return np.empty(0, np.int64)
    bits = np.unpackbits(np.frombuffer(code, np.uint8))
    ends = np.flatnonzero(bits)[:n]
    quotients = np.diff(ends, prepend=-1) - 1
    start = -(-(int(ends[-1]) + 1) // 8) * 8
    remainders = bits[start : start + n * k].reshape(n, k).astype(np.int64)
    gaps = (quotients.astype(np.int64) << k) + (remainders << np.arange(k)).sum(axis=1)
    return np.cumsum(gaps + 1) - 1


# ---- the three sides of the exchange ---------------------------------------------


def _send(owners: int, bits: int):
    span = -(-(1 << bits) // owners)

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held = [(b.column("part").to_numpy(), b.column("fp").to_numpy()) for b in batches if b.num_rows]
        if not held:
            return
        parts, prints = (np.concatenate(x) for x in zip(*held))
        out = []
        for part in np.unique(parts):
            values, copies = np.unique(prints[parts == part], return_counts=True)
            owner = values // span
            for o in np.unique(owner):
                own = owner == o
                k, code = rice_encode(values[own] - o * span)
                again = np.packbits(copies[own] > 1).tobytes()
                out.append((int(o), int(part), int(own.sum()), k, code, again))
        yield pa.RecordBatch.from_pylist(
            [dict(zip(("owner", "part", "n", "k", "code", "again"), x)) for x in out],
            schema=_MESSAGE,
        )

    return kernel


_MESSAGE = pa.schema(
    [
        ("owner", pa.int64()), ("part", pa.int64()), ("n", pa.int64()),
        ("k", pa.int64()), ("code", pa.binary()), ("again", pa.binary()),
    ]
)
_MESSAGE_DDL = "owner long, part long, n long, k long, code binary, again binary"


def _answer(key, table):
    """Bitmaps of one owner, which holds about OWNER_ROWS fingerprints."""
    sent = table.to_pylist()
    sets = [rice_decode(m["n"], m["k"], m["code"]) for m in sent]
    values, holders = np.unique(np.concatenate(sets), return_counts=True)
    shared = values[holders > 1]
    rows = []
    for m, own in zip(sent, sets):
        again = np.unpackbits(np.frombuffer(m["again"], np.uint8))[: m["n"]].astype(bool)
        bitmap = again | np.isin(own, shared, assume_unique=True)
        rows.append({"owner": m["owner"], "part": m["part"], "bitmap": np.packbits(bitmap).tobytes()})
    return pa.Table.from_pylist(
        rows, schema=pa.schema([("owner", pa.int64()), ("part", pa.int64()), ("bitmap", pa.binary())])
    )


def _receive(owners: int, bits: int):
    span = -(-(1 << bits) // owners)

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            found = []
            for m in batch.to_pylist():
                values = rice_decode(m["n"], m["k"], m["code"])
                hit = np.unpackbits(np.frombuffer(m["bitmap"], np.uint8))[: m["n"]].astype(bool)
                found.append(values[hit] + m["owner"] * span)
            prints = np.concatenate(found) if found else np.empty(0, np.int64)
            yield pa.RecordBatch.from_arrays([pa.array(prints, pa.int64())], names=["fp"])

    return kernel


def suspect_prints(rows: DataFrame, bits: int = BITS, owner_rows: int = OWNER_ROWS) -> DataFrame:
    """Distinct fingerprints that occur more than once in the checkpointed rows (fp, ...).

    There is an owner for every owner_rows rows, and at least one a shuffle partition. There
    are no more senders than owners, so that a message holds many fingerprints: the code gets
    shorter as they get denser. A sender holds one partition of rows, or a few small ones.
    """
    width = max(shuffle_width(rows.sparkSession), -(-rows.count() // owner_rows))
    slim = rows.select("fp").coalesce(width)
    senders = slim.select(F.spark_partition_id().cast("long").alias("part"), "fp")
    sent = reliable(senders.mapInArrow(_send(width, bits), _MESSAGE_DDL))
    bitmaps = sent.groupBy("owner").applyInArrow(_answer, "owner long, part long, bitmap binary")
    back = sent.join(bitmaps, ["owner", "part"])
    return reliable(back.mapInArrow(_receive(width, bits), "fp long").distinct())


def short_print(digest: Column, bits: int) -> Column:
    """The first bits of a hex digest as a non-negative integer."""
    return F.conv(F.substring(digest, 1, bits // 4), 16, 10).cast("long")


def exact_groups(
    docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", bits: int = BITS
) -> DataFrame:
    """(doc_id, row_text, keep_id, keep_text, group_size, text_sha256) for every row."""
    digest = F.sha2(normal_text(text_col), 256)
    rows = docs.select(
        F.col(id_col).cast("long").alias("doc_id"),
        id_key(id_col).alias("row_id"),
        text_key(text_col).alias("row_text"),
        digest.alias("text_sha256"),
    )
    rows = reliable(rows.withColumn("fp", short_print(F.col("text_sha256"), bits)))
    suspects = bitmap_of(suspect_prints(rows, bits), "fp")

    # Only suspects' texts are shuffled; equal texts are combined before that.
    bodies = docs.select(normal_text(text_col).alias("body"))
    texts, _ = suspects.split(bodies, short_print(F.sha2("body", 256), bits))
    same = (
        texts.groupBy("body")
        .agg(F.count(F.lit(1)).alias("copies"))
        .where("copies > 1")
        .select(F.sha2("body", 256).alias("text_sha256"))
    )
    verified = reliable(same)  # one row a text: bytes, not digests, made the groups
    if verified.count() != verified.distinct().count():
        raise RuntimeError("two different texts have one SHA-256 digest")

    key = F.struct("row_id", "row_text")
    # Copies are counted from the narrow table, combined before the shuffle.
    sizes = rows.groupBy("text_sha256").agg(
        F.min(key).alias("keep"), F.count(F.lit(1)).alias("group_size")
    )
    sizes = reliable(
        sizes.where("group_size > 1").join(verified, "text_sha256", "left_semi")
    )
    sizes = sizes.withColumn("n", F.col("group_size"))
    return join_by_key(rows, sizes, ["text_sha256"], how="left").select(
        "doc_id",
        "row_id",
        "row_text",
        F.coalesce(F.col("keep.row_id"), F.col("row_id")).alias("keep_id"),
        F.coalesce(F.col("keep.row_text"), F.col("row_text")).alias("keep_text"),
        F.coalesce("group_size", F.lit(1)).alias("group_size"),
        "text_sha256",
    )


def plain_id(column: str) -> Column:
    """A key made by id_key as an id again."""
    return F.when(F.col(column) != NO_ID, F.col(column))


def first_of_repeats(groups: DataFrame) -> DataFrame:
    """groups with a boolean column kept: exactly one row of each group.

    Rows equal in id and text are told apart only where there are any.
    """
    best = (F.col("row_id") == F.col("keep_id")) & (F.col("row_text") == F.col("keep_text"))
    groups = reliable(groups.withColumn("kept", best))
    twice = groups.where("kept").groupBy("text_sha256").agg(F.count(F.lit(1)).alias("n")).where("n > 1")
    twice = reliable(twice.select("text_sha256"))
    if not twice.limit(1).count():
        return groups
    at, first = fresh("at", groups), fresh("first", groups)
    numbered = reliable(groups.withColumn(at, F.monotonically_increasing_id()))
    firsts = numbered.groupBy("text_sha256").agg(
        F.min(F.when(F.col("kept"), F.col(at))).alias(first), F.count(F.lit(1)).alias("n")
    )
    marked = join_by_key(numbered, reliable(firsts), ["text_sha256"])
    return marked.withColumn("kept", F.col("kept") & (F.col(at) == F.col(first))).drop(at, first)


def drop_copies(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """docs with the first row of each group of equal texts."""
    best = (F.col("row_id") == F.col("keep_id")) & (F.col("row_text") == F.col("keep_text"))
    judged = exact_groups(docs, id_col, text_col).select("row_id", "row_text", best.alias("stays"))
    return keep_rows(docs, judged, id_col, text_col)
