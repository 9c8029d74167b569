"""Row keys, key bitmaps and row-level filters shared by the filtering stages.

A row is known by its id and a 64-bit hash of its text, so repeated ids with
different texts stay apart. Rows equal in both are repeats of one another.

Few keys are broadcast. Many keys become a bitmap over their hashes, of 64 MB at most at any
number of keys: rows whose bit is not set can't have one of the keys and stay where they are,
and only the others are shuffled for the exact join.
"""

from __future__ import annotations

import ctypes
from collections.abc import Callable, Iterator
from dataclasses import dataclass

import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from splitguard.functions.runtime import reliable

#: A table of row keys is broadcast up to this many rows (16 bytes each); beyond, its bitmap is.
BROADCAST_KEYS = 1_000_000
#: A bitmap has 64 bits a key as long as that many are no more than 2 ** MOST_BITS.
MOST_BITS = 29
LEAST_BITS = 16
_WORDS = 1024  # longs in one row of a bitmap
NO_ID = -(2**63) + 1


def id_key(id_col: str) -> Column:
    return F.coalesce(F.col(id_col).cast("long"), F.lit(NO_ID))


def text_key(text_col: str) -> Column:
    return F.xxhash64(F.col(text_col).isNull(), F.col(text_col))


def fresh(name: str, *taken: DataFrame) -> str:
    """name, lengthened until no column of the frames has it."""
    held = {c.lower() for df in taken for c in df.columns}
    while name.lower() in held:
        name += "_"
    return name


def stretches(texts: pa.Array, most: int) -> Iterator[tuple[int, int]]:
    """(start, end) of stretches of at most so many bytes of text, or of one text."""
    sizes = pc.fill_null(pc.binary_length(texts), 0).to_pylist()
    start, held = 0, 0
    for i, size in enumerate(sizes):
        if held and held + size > most:
            yield start, i
            start, held = i, 0
        held += size
    if sizes:
        yield start, len(sizes)


Batches = Iterator[pa.RecordBatch]


def lean(kernel: Callable[[Batches], Batches]) -> Callable[[Batches], Batches]:
    """kernel, with buffers of the system's allocator and freed memory given back after each batch.

    Workers outlive their tasks; what they hold on to counts against their executor.
    """

    def run(batches: Batches) -> Batches:
        pa.set_memory_pool(pa.system_memory_pool())
        give_back = getattr(ctypes.CDLL(None), "malloc_trim", None)  # only some C libraries have it

        def inputs() -> Batches:
            for batch in batches:
                yield batch
                del batch
                if give_back:
                    give_back(0)

        yield from kernel(inputs())
        if give_back:
            give_back(0)

    return run


# ---- bitmaps of keys ---------------------------------------------------------------


@dataclass(frozen=True)
class Bitmap:
    """Rows (chunk, words array<long>) of the bits set by a set of 64-bit keys."""

    table: DataFrame
    bits: int

    def split(self, df: DataFrame, key: Column) -> tuple[DataFrame, DataFrame]:
        """(rows of df whose bit is set, the others); every key of the set has its bit set."""
        spot = key.bitwiseAND(F.lit((1 << self.bits) - 1))
        chunk = F.shiftright(spot, 16)
        marked = df.join(F.broadcast(self.table), chunk == self.table["chunk"], "left")
        word = F.element_at(self.table["words"], (F.shiftright(spot, 6) % _WORDS + 1).cast("int"))
        hit = F.coalesce(F.getbit(word, (spot % 64).cast("int")) == 1, F.lit(False))
        own = [df[c] for c in df.columns]
        return marked.where(hit).select(*own), marked.where(~hit).select(*own)


def bitmap_of(keys: DataFrame, column: str) -> Bitmap:
    """Bitmap of a checkpointed table's column of well-mixed integers."""
    bits = max(LEAST_BITS, min(MOST_BITS, (keys.count() - 1).bit_length() + 6))
    spot = F.col(column).bitwiseAND(F.lit((1 << bits) - 1))
    words = (
        keys.select(
            F.shiftright(spot, 16).alias("chunk"),
            (F.shiftright(spot, 6) % _WORDS).cast("int").alias("word"),
            F.expr(f"shiftleft(1L, cast(pmod({column}, 64L) as int))").alias("bit"),
        )
        .groupBy("chunk", "word")
        .agg(F.bit_or("bit").alias("bits"))
        .groupBy("chunk")
        .agg(F.map_from_entries(F.collect_list(F.struct("word", "bits"))).alias("m"))  # _WORDS at most
    )
    filled = F.transform(
        F.sequence(F.lit(0), F.lit(_WORDS - 1)),
        lambda i: F.coalesce(F.try_element_at("m", i), F.lit(0).cast("long")),
    )
    return Bitmap(reliable(words.select("chunk", filled.alias("words"))), bits)


def rows_of_keys(df: DataFrame, keys: DataFrame, column: str) -> DataFrame:
    """Rows of df whose column is in the checkpointed table of distinct keys of that name."""
    keys = keys.select(column)
    if keys.limit(BROADCAST_KEYS + 1).count() <= BROADCAST_KEYS:
        return df.join(F.broadcast(keys), column, "left_semi")
    hits, _ = bitmap_of(keys, column).split(df, F.col(column))
    return hits.join(keys.hint("shuffle_merge"), column, "left_semi")


# ---- the filter of the stages -------------------------------------------------------


def keep_rows(docs: DataFrame, judged: DataFrame, id_col: str, text_col: str) -> DataFrame:
    """docs without the rows judged gone, and one row of each repeated kept key.

    judged: (row_id, row_text, stays), one row for each row of docs, by id_key and
    text_key. Only the narrow table of gone and repeated keys is joined; where it is too
    large to broadcast, its bitmap lets all other rows pass where they are.
    """
    keys = judged.groupBy("row_id", "row_text").agg(
        F.max("stays").alias("stays"), F.count(F.lit(1)).alias("copies")
    )
    keys = reliable(keys.where(~F.col("stays") | (F.col("copies") > 1)))
    return apply_keys(docs, keys, id_col, text_col)


def apply_keys(docs: DataFrame, keys: DataFrame, id_col: str, text_col: str) -> DataFrame:
    """docs without the rows of keys (row_id, row_text, stays) that don't stay, and one row of each
    key that does; rows of other keys are left alone. keys is checkpointed and has no key twice."""
    names = docs.columns
    own_id, own_text = fresh("row_key", docs), fresh("text_key", docs)
    marked = docs.select("*", id_key(id_col).alias(own_id), text_key(text_col).alias(own_text))
    few = keys.limit(BROADCAST_KEYS + 1).count() <= BROADCAST_KEYS
    passed = None
    if not few:
        marked, passed = bitmap_of(keys, "row_text").split(marked, F.col(own_text))

    def side(rows: DataFrame) -> DataFrame:
        rows = rows.select(F.col("row_id").alias(own_id), F.col("row_text").alias(own_text))
        return F.broadcast(rows) if few else rows.hint("shuffle_merge")

    on = [own_id, own_text]
    if keys.where("stays").limit(1).count():
        single = marked.join(side(keys), on, "left_anti").select(*names)
        twice = marked.join(side(keys.where("stays")), on, "left_semi")
        kept = single.unionByName(twice.dropDuplicates(on).select(*names))
    else:
        kept = marked.join(side(keys), on, "left_anti").select(*names)
    return kept if passed is None else kept.unionByName(passed.select(*names))
