"""SimHash near-duplicates: pigeonhole blocks, verified Hamming links, components.

Fingerprints are made once per row in an Arrow kernel and de-duplicated before
any search, so a group of exact copies is one node however many rows it has.
With at most d differing bits and d + r blocks, at least r blocks agree; every
choice of r blocks is a key. Rows are dealt by key and sorted, and each run of
equal keys yields a spanning set of verified links, never all its pairs.

Defined results: null and blank texts have fingerprint zero and are linked like
any other; a text under four words is one shingle; repeated rows each return a
row with the same component; an empty table gives an empty result; extra
columns are ignored by `fingerprints` and kept by `keep_one`.
"""

from __future__ import annotations

from collections.abc import Iterator
from itertools import combinations

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from splitguard.functions.runtime import join_by_key, reliable
from splitguard.llm.rows import NO_ID, keep_rows, lean, text_key
from splitguard.operators.components import connected_components

WORDS = 4
SEED = 42
MAX_BITS = 4
#: Mean number of unrelated fingerprints that a run of equal keys may hold.
RUN_PRINTS = 64
SMALL_RUN = 48

_LOWER = bytes(c + 32 if 65 <= c <= 90 else c for c in range(256))
_LANES = np.uint64(0x0101010101010101)


def bit_counts(hashes: np.ndarray) -> np.ndarray:
    """How often each of the 64 bits is set; index 0 is the least significant."""
    n = len(hashes)
    padded = np.zeros(-(-n // 255) * 255, np.uint64)
    padded[:n] = hashes
    out = np.zeros((8, 8), np.int64)  # [bit in byte][byte]
    for bit in range(8):
        lanes = (padded >> np.uint64(bit)) & _LANES
        sums = lanes.reshape(-1, 255).sum(axis=1, dtype=np.uint64)  # 255 ones fit a byte lane
        out[bit] = sums.view(np.uint8).reshape(-1, 8).sum(axis=0, dtype=np.int64)
    return out.T.reshape(64)


def fingerprint(text: str | None, words: int = WORDS) -> int:
    """Unsigned 64-bit SimHash of one text."""
    if not text:
        return 0
    parts = text.encode("utf-8", "surrogatepass").translate(_LOWER).split()
    if not parts:
        return 0
    line = b" ".join(parts)
    if len(parts) <= words:
        return xxhash.xxh64_intdigest(line, SEED)
    lengths = np.fromiter(map(len, parts), np.int64, len(parts))
    starts = np.concatenate(([0], np.cumsum(lengths + 1)[:-1]))
    n = len(parts) - words + 1
    begins, ends = starts[:n].tolist(), (starts + lengths)[words - 1 :].tolist()
    digest = xxhash.xxh64_intdigest
    hashes = np.fromiter(
        (digest(line[i:j], SEED) for i, j in zip(begins, ends)), np.uint64, n
    )
    set_bits = np.flatnonzero(2 * bit_counts(hashes) > n)
    return int(sum(1 << int(b) for b in set_bits))


def _fingerprint_batches(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        prints = np.fromiter(
            (fingerprint(t.as_py()) for t in batch.column("text")), np.uint64, batch.num_rows
        )
        columns = [batch.column("doc_id"), batch.column("row_text"), pa.array(prints.view(np.int64))]
        yield pa.RecordBatch.from_arrays(columns, names=["doc_id", "row_text", "fp"])


def fingerprints(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc_id, row_text, fp): fp is the fingerprint as a signed 64-bit integer."""
    slim = docs.select(
        F.col(id_col).cast("long").alias("doc_id"),
        text_key(text_col).alias("row_text"),
        F.col(text_col).alias("text"),
    )
    return slim.mapInArrow(lean(_fingerprint_batches), "doc_id long, row_text long, fp long")


def block_layout(max_bits: int, blocks: int) -> tuple[list[tuple[int, int]], int]:
    """(shift, width) of each block, and how many blocks two linked prints must share."""
    if blocks <= max_bits:
        raise ValueError("there must be more blocks than differing bits")
    width, extra = divmod(64, blocks)
    sizes = [width + (i < extra) for i in range(blocks)]
    shifts = [sum(sizes[:i]) for i in range(blocks)]
    return list(zip(shifts, sizes)), blocks - max_bits


def blocks_for(prints: int, max_bits: int = MAX_BITS) -> int:
    """Fewest blocks whose keys leave about RUN_PRINTS unrelated fingerprints a run.

    More blocks make longer keys and more of them; links are the same with any number.
    """
    blocks = max_bits + 2
    while blocks < 2 * max_bits and prints >> (64 * (blocks - max_bits) // blocks) > RUN_PRINTS:
        blocks += 1
    return blocks


def _block_keys(max_bits: int, blocks: int):
    layout, agree = block_layout(max_bits, blocks)
    keys = []
    for no, chosen in enumerate(combinations(layout, agree)):
        key = F.lit(no).cast("long")
        for shift, width in chosen:
            part = F.shiftrightunsigned(F.col("fp"), shift).bitwiseAND(F.lit((1 << width) - 1))
            key = F.shiftleft(key, width).bitwiseOR(part)
        keys.append(key)
    return F.explode(F.array(*keys))


def _far(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    return np.bitwise_count(a ^ b)


def dense_links(prints: np.ndarray, max_bits: int) -> list[tuple[int, int]]:
    """Links that connect whatever pairs within max_bits connect, for one large run.

    Pivots cover the run at half the radius, so a pivot's members are linked by
    a star. Two pivots' members can be linked only if the pivots differ in at
    most twice the radius; such clusters are compared once and only while
    they are not already joined.
    """
    half = max_bits // 2
    rest, pivots, members, links = prints, [], [], []
    while len(rest):
        pivot = rest[0]
        close = _far(rest, pivot) <= half
        own = rest[close]
        pivots.append(pivot)
        members.append(own)
        links += [(int(pivot), int(x)) for x in own[1:]]
        rest = rest[~close]
    centre = np.array(pivots, np.uint64)
    parent = np.arange(len(pivots))

    def root(i: int) -> int:
        while parent[i] != i:
            parent[i] = parent[parent[i]]
            i = parent[i]
        return int(i)

    for i in range(len(pivots)):
        for j in i + 1 + np.flatnonzero(_far(centre[i + 1 :], centre[i]) <= max_bits + 2 * half):
            a, b = root(i), root(int(j))
            if a == b:
                continue
            small, large = sorted((members[i], members[j]), key=len)
            for x in small:
                hit = np.flatnonzero(_far(large, x) <= max_bits)
                if len(hit):
                    links.append((int(x), int(large[hit[0]])))
                    parent[b] = a
                    break
    return links


def run_links(keys: np.ndarray, prints: np.ndarray, max_bits: int) -> tuple[np.ndarray, np.ndarray]:
    """Verified links inside the runs of equal keys; keys are sorted."""
    if len(keys) < 2:
        return np.empty(0, np.uint64), np.empty(0, np.uint64)
    edges = np.flatnonzero(np.diff(keys)) + 1
    starts, ends = np.concatenate(([0], edges)), np.concatenate((edges, [len(keys)]))
    sizes = ends - starts
    big = sizes > SMALL_RUN
    left, right = [], []
    for s, e in zip(starts[big], ends[big]):
        for x, y in dense_links(np.unique(prints[s:e]), max_bits):
            left.append(np.uint64(x))
            right.append(np.uint64(y))
    left, right = [np.array(left, np.uint64)], [np.array(right, np.uint64)]
    small = np.repeat(~big & (sizes > 1), sizes)
    keys, prints = keys[small], prints[small]
    for step in range(1, int(sizes[~big].max(initial=1))):
        if step >= len(keys):
            break
        a, b = prints[:-step], prints[step:]
        hit = (keys[:-step] == keys[step:]) & (_far(a, b) <= max_bits)
        left.append(a[hit])
        right.append(b[hit])
    return np.concatenate(left), np.concatenate(right)


def _link_kernel(max_bits: int):
    def links(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held_keys, held_prints = [], []

        def flush(keys, prints):
            a, b = run_links(keys, prints, max_bits)
            return pa.RecordBatch.from_arrays(
                [pa.array(a.view(np.int64)), pa.array(b.view(np.int64))], names=["a", "b"]
            )

        for batch in batches:
            if not batch.num_rows:
                continue
            keys = batch.column(0).to_numpy()
            prints = batch.column(1).to_numpy().view(np.uint64)
            cut = int(np.searchsorted(keys, keys[-1]))  # the last run may go on
            if cut:
                yield flush(
                    np.concatenate([*held_keys, keys[:cut]]),
                    np.concatenate([*held_prints, prints[:cut]]),
                )
                held_keys, held_prints = [], []
            held_keys.append(keys[cut:])
            held_prints.append(prints[cut:])
        if held_keys:
            yield flush(np.concatenate(held_keys), np.concatenate(held_prints))

    return links


def print_links(prints: DataFrame, max_bits: int = MAX_BITS, blocks: int | None = None) -> DataFrame:
    """Verified links (a, b) between distinct fingerprints, enough to connect every near pair.

    A run's fingerprints are different and lie in few small Hamming balls besides the
    unrelated ones, so its size doesn't grow with the number of copies.
    """
    blocks = blocks or blocks_for(prints.count(), max_bits)
    dealt = (
        prints.select("fp", _block_keys(max_bits, blocks).alias("key"))
        .repartition("key")
        .sortWithinPartitions("key", "fp")
        .select("key", "fp")
    )
    return dealt.mapInArrow(lean(_link_kernel(max_bits)), "a long, b long")


def near_duplicates(
    docs: DataFrame,
    id_col: str = "doc_id",
    text_col: str = "text",
    max_bits: int = MAX_BITS,
    blocks: int | None = None,
) -> DataFrame:
    """(doc_id, row_text, fp, class, component_id) per row.

    component_id is the least doc_id reachable; class names the component by a fingerprint.
    """
    rows = reliable(fingerprints(docs, id_col, text_col))
    prints = reliable(rows.groupBy("fp").agg(F.min("doc_id").alias("least"), F.count(F.lit(1)).alias("n")))
    nodes = connected_components(print_links(prints, max_bits, blocks), "a", "b")
    # A fingerprint without links is a class of its own.
    classed = reliable(
        prints.join(nodes.withColumnRenamed("node", "fp"), "fp", "left").select(
            "fp", "least", "n", F.coalesce("component", "fp").alias("class")
        )
    )
    # `prints` counts a class's fingerprints, n a fingerprint's rows; either may be a hot key.
    least = classed.groupBy("class").agg(F.min("least").alias("component_id"), F.count(F.lit(1)).alias("prints"))
    owner = join_by_key(classed.drop("least"), reliable(least), ["class"], "prints")
    found = join_by_key(rows, reliable(owner), ["fp"])
    return found.select("doc_id", "row_text", "fp", "class", "component_id")


def keep_least(docs: DataFrame, found: DataFrame, id_col: str, text_col: str) -> DataFrame:
    """docs with the row of the least id of each class; found: (doc_id, row_text, class) per row."""
    found = reliable(found)
    key = F.struct(F.coalesce("doc_id", F.lit(NO_ID)).alias("row_id"), "row_text")
    best = reliable(found.groupBy("class").agg(F.min(key).alias("best"), F.count(F.lit(1)).alias("n")))
    judged = join_by_key(found, best, ["class"]).select(
        key["row_id"].alias("row_id"), "row_text", (key == F.col("best")).alias("stays")
    )
    return keep_rows(docs, judged, id_col, text_col)


def keep_one(
    docs: DataFrame,
    id_col: str = "doc_id",
    text_col: str = "text",
    max_bits: int = MAX_BITS,
    blocks: int | None = None,
) -> DataFrame:
    """docs with one row of each near-duplicate group: the one with the least id."""
    found = near_duplicates(docs, id_col, text_col, max_bits, blocks)
    return keep_least(docs, found, id_col, text_col)
