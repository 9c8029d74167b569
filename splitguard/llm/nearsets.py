"""Near copies by SimHash and the Jaccard similarity of word shingles, with exact verification.

A text is the set of its five-word shingles; texts with equal sets are one node. Two nodes
are linked if their sets have a similarity of at least LEAST. Candidates come first from
SimHash: every set has a 64-bit fingerprint of its shingles, and pigeonhole blocks find those
within simhash.MAX_BITS bits of one another. Texts at that similarity may differ in up to a
fifth of the bits, too many for pigeonhole blocks alone, so further candidates share a key made
of several least hash values; with similarity s and the default
numbers they share one with chance 1 - (1 - s ** 4) ** 16, which is 0.9998 at 0.8. Every
link is verified on the whole sets, but for pairs whose 64 least values agree so seldom that
their sets can't be that alike (six standard deviations); only the sets of the others move.

Nodes of a run of equal keys are first compared with the least of them. Where a run's nodes
are not in one component after that, the run is searched whole: an index from shingles to
sets tells how many shingles a set shares with all others of a block at once, and only links
that join two components come out, so there are fewer of them than nodes. Nodes that are in
the run's largest component already are not looked up. Runs of the same nodes are searched
once; a run of more shingles than a task should hold is cut into blocks, and every two blocks
meet in a task of their own.

Defined results: null and blank texts have the empty set and are copies of one another; a
text under five words is one shingle; very long texts are read whole; repeated rows are one
node; an empty table gives an empty result; extra columns are kept by `keep_one`.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from splitguard.functions.runtime import join_by_key, reliable
from splitguard.llm.rows import bitmap_of, lean, rows_of_keys, text_key
from splitguard.llm.simhash import _LOWER, MAX_BITS, SEED, bit_counts, keep_least, print_links
from splitguard.operators.components import connected_components

WORDS = 5
LEAST = 0.8
KEYS = 16
#: Least hash values in a key.
VALUES = 4
#: Shingles of a run in one block.
BLOCK_SHINGLES = 1_000_000
#: Shingles hashed anew at once.
SLICE = 2048
#: Words of a text that are objects at once.
STRETCH = 4096

_FACTORS = np.random.default_rng(SEED).integers(1 << 62, 1 << 63, KEYS * VALUES, np.uint64) * 2 + 1


def shingle_set(text: str | None, words: int = WORDS) -> np.ndarray:
    """The different 64-bit hashes of a text's word shingles, sorted."""
    parts = (text or "").encode("utf-8", "surrogatepass").translate(_LOWER).split()
    if not parts:
        return np.empty(0, np.uint64)
    line = b" ".join(parts)
    ends = np.cumsum(np.fromiter(map(len, parts), np.int64, len(parts)) + 1) - 1
    del parts
    begins = np.concatenate(([0], ends[:-1] + 1))
    n = max(1, len(ends) - words + 1)
    last = ends[words - 1 :] if len(ends) >= words else ends[-1:]
    digest = xxhash.xxh64_intdigest
    out = np.empty(n, np.uint64)
    for at in range(0, n, STRETCH):
        spans = zip(begins[at : min(n, at + STRETCH)].tolist(), last[at : at + STRETCH].tolist())
        out[at : at + STRETCH] = [digest(line[i:j], SEED) for i, j in spans]
    return np.unique(out)


def least_values(shingles: np.ndarray) -> np.ndarray:
    """(KEYS, VALUES) least values of a set that isn't empty, under as many hash functions."""
    least = np.full(len(_FACTORS), np.iinfo(np.uint64).max, np.uint64)
    for at in range(0, len(shingles), SLICE):
        part = _FACTORS[:, None] * shingles[None, at : at + SLICE]
        np.minimum(least, part.min(axis=1), out=least)
    return least.reshape(KEYS, VALUES)


def search_keys(shingles: np.ndarray) -> list[int]:
    """KEYS signed 64-bit keys, each of VALUES least hash values; none for the empty set."""
    return _keys_of(least_values(shingles)) if len(shingles) else []


def _keys_of(values: np.ndarray) -> list[int]:
    prints = [xxhash.xxh64_intdigest(row.tobytes(), no) for no, row in enumerate(values)]
    return np.array(prints, np.uint64).view(np.int64).tolist()


def _node(shingles: np.ndarray) -> int:
    return xxhash.xxh64_intdigest(shingles.tobytes(), SEED)


def set_print(shingles: np.ndarray) -> int:
    """Unsigned 64-bit SimHash of a set: the bits set in over half of its shingles; zero if it is empty."""
    return int(sum(1 << int(b) for b in np.flatnonzero(2 * bit_counts(shingles) > len(shingles))))


def _key_batches(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Fingerprints and keys of whole texts, and as `sketch` one byte of each least value."""
    for batch in batches:
        nodes, prints = (np.empty(batch.num_rows, np.uint64) for _ in range(2))
        keys, sketches = [], []
        for i, text in enumerate(batch.column("text")):
            shingles = shingle_set(text.as_py())
            nodes[i], prints[i] = _node(shingles), set_print(shingles)
            values = least_values(shingles) if len(shingles) else np.empty((0, VALUES), np.uint64)
            keys.append(_keys_of(values))
            sketches.append((values >> np.uint64(20)).astype(np.uint8).tobytes())
        yield pa.RecordBatch.from_arrays(
            [
                batch.column("doc_id"),
                batch.column("row_text"),
                pa.array(nodes.view(np.int64)),
                pa.array(prints.view(np.int64)),
                pa.array(keys, pa.list_(pa.int64())),
                pa.array(sketches, pa.binary()),
            ],
            names=["doc_id", "row_text", "node", "fp", "keys", "sketch"],
        )


def _set_batches(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        for text in batch.column("text"):
            shingles = shingle_set(text.as_py())
            yield pa.RecordBatch.from_arrays(
                [
                    pa.array(np.array([_node(shingles)], np.uint64).view(np.int64)),
                    pa.array([shingles.view(np.int64)], pa.list_(pa.int64())),
                ],
                names=["node", "shingles"],
            )


def _print_pairs(rows: DataFrame) -> DataFrame:
    """Candidates (a, b), a < b, of rows (node, fp, keys, ...) by SimHash: each node beside the least of
    its fingerprint, and those of fingerprints that pigeonhole blocks link within MAX_BITS bits."""
    named = reliable(rows.where(F.size("keys") > 0).select("node", "fp").distinct())
    hubs = reliable(named.groupBy("fp").agg(F.min("node").alias("hub"), F.count(F.lit(1)).alias("n")))
    same = join_by_key(named, hubs.where("n > 1"), ["fp"]).select("node", "hub")
    # A fingerprint has few links here: those of a run span small Hamming balls.
    links = print_links(hubs.select("fp"), MAX_BITS).distinct()
    ends = [hubs.select(F.col("fp").alias(x), F.col("hub").alias(f"hub_{x}")) for x in "ab"]
    near = links.join(ends[0], "a").join(ends[1], "b").select("hub_a", "hub_b")
    pairs = same.union(near).toDF("x", "y").where("x != y")
    return reliable(pairs.select(F.least("x", "y").alias("a"), F.greatest("x", "y").alias("b")).distinct())


def _plausible(pairs: DataFrame, sketches: DataFrame, least: float) -> DataFrame:
    """The pairs (a, b) whose sketches (node, sketch) agree in as many bytes as alike sets' do."""
    count = KEYS * VALUES
    bound = count * least - 6 * (count * least * (1 - least)) ** 0.5
    left = sketches.select(F.col("node").alias("a"), F.col("sketch").alias("x"))
    right = sketches.select(F.col("node").alias("b"), F.col("sketch").alias("y"))

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            x, y = (np.frombuffer(b"".join(batch.column(c).to_pylist()), np.uint8) for c in ("x", "y"))
            same = (x == y).reshape(batch.num_rows, count).sum(axis=1)
            yield batch.select(["a", "b"]).filter(pa.array(same >= bound))

    both = pairs.join(left, "a").join(right, "b").select("a", "b", "x", "y")
    return reliable(both.mapInArrow(lean(kernel), "a long, b long"))


def _verified(pairs: DataFrame, sets: DataFrame, least: float) -> DataFrame:
    """The pairs (a, b) of nodes whose shingle sets are alike enough."""
    ends = reliable(pairs.select(F.explode(F.array("a", "b")).alias("node")).distinct())
    sets = rows_of_keys(sets, ends, "node")
    left = sets.select(F.col("node").alias("a"), F.col("shingles").alias("x"))
    right = sets.select(F.col("node").alias("b"), F.col("shingles").alias("y"))
    n, m = F.size("x"), F.size("y")
    joined = pairs.join(left, "a").join(right, "b").where(F.least(n, m) >= least * F.greatest(n, m))
    both = F.size(F.array_intersect("x", "y"))
    return reliable(joined.where(both >= least * (n + m - both)).select("a", "b"))


def joining_links(c: np.ndarray, sets: list[np.ndarray], least: float) -> list[tuple[int, int]]:
    """Links (i, j) of alike sets, enough to join whatever components c they join."""
    lengths = np.fromiter(map(len, sets), np.int64, len(sets))
    begins = np.cumsum(lengths) - lengths
    _, token = np.unique(np.concatenate(sets), return_inverse=True)
    holders = np.repeat(np.arange(len(sets)), lengths)[np.argsort(token, kind="stable")]
    counts = np.bincount(token)
    first = np.cumsum(counts) - counts
    _, label = np.unique(c, return_inverse=True)
    links = []
    for i in np.flatnonzero(label != np.bincount(label).argmax()).tolist():
        own = token[begins[i] : begins[i] + lengths[i]]
        n = counts[own]
        ends = np.cumsum(n)
        at = np.repeat(first[own] - ends + n, n) + np.arange(n.sum())
        both = np.bincount(holders[at], minlength=len(sets))
        alike = both >= least * (lengths[i] + lengths - both)
        for j in np.flatnonzero(alike & (label != label[i])).tolist():
            if label[j] != label[i]:
                links.append((i, j))
                label[label == label[j]] = label[i]
    return links


def _searched(runs: DataFrame, sets: DataFrame, least: float) -> DataFrame:
    """Links (a, b) between the components of runs (key, node, c)."""
    held = runs.join(sets.select("node", F.size("shingles").alias("size")), "node")
    held = reliable(held)
    blocks = held.groupBy("key").agg(
        F.count(F.lit(1)).alias("n"),
        F.bit_xor(F.xxhash64("node")).alias("all"),
        F.ceil(F.sum("size") / BLOCK_SHINGLES).cast("int").alias("blocks"),
    )
    blocks = reliable(blocks.dropDuplicates(["n", "all"]).select("key", "blocks", "n"))
    dealt = join_by_key(held, blocks, ["key"])
    own = F.pmod(F.xxhash64("node"), F.col("blocks")).cast("int")
    pairs = F.transform(
        F.sequence(F.lit(0), F.col("blocks") - 1),
        lambda other: F.struct(F.least(own, other).alias("p"), F.greatest(own, other).alias("q")),
    )
    met = dealt.select("key", "node", "c", F.explode(pairs).alias("t")).select("key", "t.p", "t.q", "node", "c")

    def kernel(table: pa.Table) -> pa.Table:
        nodes = table.column("node").to_numpy()
        found = joining_links(table.column("c").to_numpy(), [x.values.to_numpy() for x in table.column("shingles")], least)
        a, b = (np.array([nodes[x[k]] for x in found], np.int64) for k in (0, 1))
        return pa.table({"a": a, "b": b})

    return reliable(met.join(sets, "node").groupBy("key", "p", "q").applyInArrow(kernel, "a long, b long"))


def near_duplicates(
    docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", least: float = LEAST
) -> DataFrame:
    """(doc_id, row_text, node, class) per row; class names the component by a node."""
    slim = docs.select(
        F.col(id_col).cast("long").alias("doc_id"),
        text_key(text_col).alias("row_text"),
        F.col(text_col).alias("text"),
    )
    schema = "doc_id long, row_text long, node long, fp long, keys array<long>, sketch binary"
    rows = reliable(slim.mapInArrow(lean(_key_batches), schema))
    by_print = _print_pairs(rows)
    dealt = rows.select("node", F.explode("keys").alias("key"))
    runs = dealt.groupBy("key").agg(F.min("node").alias("low"), F.max("node").alias("high"))
    runs = reliable(runs.where("low != high").select("key", "low"))
    # Most keys are one node's; the bitmap keeps those out of the join.
    shared, _ = bitmap_of(runs, "key").split(dealt, F.col("key"))
    shared = reliable(shared.distinct().join(runs, "key"))
    members = shared.select("node").union(by_print.select(F.explode(F.array("a", "b"))))
    members = reliable(members.distinct())
    # One row of each node that shares a key or has a near fingerprint.
    firsts = rows_of_keys(rows.select("node", "row_text", "sketch"), members, "node")
    firsts = reliable(firsts.groupBy("node").agg(F.min("row_text").alias("row_text"), F.first("sketch").alias("sketch")))
    texts = reliable(firsts.select("row_text").distinct())
    wanted = rows_of_keys(slim.select("row_text", "text"), texts, "row_text").select("text")
    sets = reliable(wanted.mapInArrow(lean(_set_batches), "node long, shingles array<long>"))
    if sets.count() > texts.count():  # rows with equal texts
        sets = reliable(sets.dropDuplicates(["node"]))

    ends = shared.select("node", F.col("low").alias("end")).where("node != end")
    by_key = ends.select(F.least("node", "end").alias("a"), F.greatest("node", "end").alias("b"))
    tried = reliable(by_print.union(by_key).distinct())
    links = _verified(_plausible(tried, firsts, least), sets, least)
    # Two steps along the links name most components; what has two names is only searched once more.
    up = reliable(links.groupBy(F.col("b").alias("node")).agg(F.min("a").alias("c")))
    second = up.select(F.col("node").alias("c"), F.col("c").alias("cc"))
    up = up.join(second, "c", "left").select("node", F.coalesce("cc", "c").alias("c"))
    classed = reliable(
        shared.join(up, "node", "left").select("key", "node", F.coalesce("c", "node").alias("c"))
    )
    split = classed.groupBy("key").agg(F.min("c").alias("c0"), F.max("c").alias("c1"), F.count(F.lit(1)).alias("n"))
    # Both nodes of a run of two have been compared.
    split = reliable(split.where("c0 != c1 and n > 2").select("key"))
    if split.limit(1).count():
        rest = reliable(classed.join(split, "key", "left_semi"))
        ends = reliable(rest.select("node").distinct())
        links = links.union(_searched(rest, reliable(rows_of_keys(sets, ends, "node")), least))
    nodes = connected_components(links, "a", "b")
    held = rows.groupBy("node").agg(F.count(F.lit(1)).alias("n"))
    nodes = reliable(nodes.join(held, "node"))
    return join_by_key(rows.drop("fp", "keys", "sketch"), nodes, ["node"], how="left").select(
        "doc_id", "row_text", "node", F.coalesce("component", "node").alias("class")
    )


def keep_one(
    docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", least: float = LEAST
) -> DataFrame:
    """docs with one row of each group of near copies: the one with the least id."""
    return keep_least(docs, near_duplicates(docs, id_col, text_col, least), id_col, text_col)
