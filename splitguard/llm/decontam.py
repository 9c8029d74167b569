"""Benchmark decontamination by Wu-Manber search for many strings at once.

Windows of ten benchmark words are the patterns. Texts become bytes with one space
around every word, so a window occurs as words exactly where it occurs as bytes.
A table of shifts, indexed by a hash of an eight-byte block, tells how far no
pattern can end; where the shift is zero, the block itself finds the patterns
that have it at their end, and these are compared byte by byte. Many lanes of
text advance together in numpy; a lane is a stretch of a text, never a prefix.

Patterns are compiled in sets of about PATTERN_BYTES. A benchmark of more than one set is
searched set after set: each is broadcast, searched for, and let go before the next, and what
it finds is kept by row key, so no process holds more than one set. Results are the same.

Defined results: a null or wordless text has no words and no hits; an item of
fewer words than a window is one window; a wordless item is none; items with one
id count once; items without an id count as one and are not among the ids; very long texts
are searched whole, in lanes; repeated rows give equal results; with no benchmark nothing is
hit; an empty table gives an empty result; columns of any other name pass through `clean`.
"""

from __future__ import annotations

import hashlib
import pickle
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark import cloudpickle
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from splitguard.functions.runtime import reliable
from splitguard.llm.rows import apply_keys, id_key, lean, stretches, text_key

WORDS = 10
#: Bytes of patterns in one compiled set.
PATTERN_BYTES = 32 * 1024 * 1024
LANE = 4096
SLICE_BYTES = 2 * 1024 * 1024
_CLASSES = (3, 8, 24)  # least pattern lengths of the classes searched apart
_TABLE_BITS = 22

# Letters A-Z fall to lower case; digits, a-z and all bytes from 0x80 are word bytes.
_WORD_BYTES = bytes(
    c + 32
    if 0x41 <= c <= 0x5A
    else c
    if 0x30 <= c <= 0x39 or 0x61 <= c <= 0x7A or c >= 0x80
    else 0x20
    for c in range(256)
)


def words_of(text: str | None) -> list[bytes]:
    return text.encode("utf-8", "surrogatepass").translate(_WORD_BYTES).split() if text else []


def windows_of(text: str | None, size: int = WORDS) -> list[tuple[bytes, int]]:
    """(padded window, words in it) of one item."""
    words = words_of(text)
    n = min(size, len(words))
    return [
        (b" " + b" ".join(words[i : i + n]) + b" ", n) for i in range(len(words) - n + 1) if n
    ]


class _Class:
    """Shift table and suffix buckets of patterns whose length is at least some least."""

    def __init__(self, patterns: list[bytes], numbers: list[int]):
        self.m = min(map(len, patterns))
        self.block = min(8, self.m)
        self.mask = np.uint64((1 << (8 * self.block)) - 1)
        heads = np.zeros((len(patterns), self.m + 8), np.uint8)
        for i, p in enumerate(patterns):
            heads[i, : self.m] = np.frombuffer(p[: self.m], np.uint8)
        self.shift = np.full(1 << _TABLE_BITS, min(255, self.m - self.block + 1), np.uint8)
        for end in range(self.block, self.m + 1):
            at = self._hash(self._blocks(heads, end))
            self.shift[at] = np.minimum(self.shift[at], min(255, self.m - end))
        last = self._blocks(heads, self.m)
        order = np.argsort(last, kind="stable")
        self.last = last[order]
        self.first = self._blocks(heads, self.block)[order]
        self.number = np.array(numbers)[order]

    def _blocks(self, rows: np.ndarray, end: int) -> np.ndarray:
        start = end - self.block
        return rows[:, start : start + 8].copy().view("<u8")[:, 0] & self.mask

    @staticmethod
    def _hash(blocks: np.ndarray) -> np.ndarray:
        return (blocks * np.uint64(0x9E3779B97F4A7C15)) >> np.uint64(64 - _TABLE_BITS)

    def search(self, text: np.ndarray, size: int) -> tuple[np.ndarray, np.ndarray]:
        """(start, pattern) whose first and last blocks agree; text has 8 spare bytes."""
        view = np.ndarray((size,), "<u8", text.data, 0, (1,))
        pos = np.arange(0, max(0, size - self.m + 1), LANE, dtype=np.int64)
        stop = np.minimum(pos + LANE, size - self.m + 1)
        starts: list[np.ndarray] = []
        reach = self.m - self.block
        while len(pos):
            step = self.shift[self._hash(view[pos + reach] & self.mask)]
            zero = step == 0
            if zero.any():
                starts.append(pos[zero])
            pos = pos + np.maximum(step, 1)
            going = pos < stop
            if not going.all():
                pos, stop = pos[going], stop[going]
        if not starts:
            return np.empty(0, np.int64), np.empty(0, np.int64)
        at = np.concatenate(starts)
        block = view[at + reach] & self.mask
        low = np.searchsorted(self.last, block, "left")
        count = np.searchsorted(self.last, block, "right") - low
        at, low, count = at[count > 0], low[count > 0], count[count > 0]
        where = np.repeat(at, count)
        entry = np.repeat(low - np.cumsum(count) + count, count) + np.arange(count.sum())
        same = (view[where] & self.mask) == self.first[entry]
        return where[same], self.number[entry[same]]


class Patterns:
    """All windows of some benchmark items, compiled."""

    def __init__(self, items: list[tuple[str | None, str | None]], size: int = WORDS):
        found: dict[bytes, tuple[int, set]] = {}
        for item, text in items:
            for window, n in windows_of(text, size):
                found.setdefault(window, (n, set()))[1].add(item)
        self.windows = sorted(found)
        self.lengths = [found[w][0] for w in self.windows]
        self.items = [found[w][1] for w in self.windows]
        self.classes = []
        for least, beyond in zip(_CLASSES, (*_CLASSES[1:], 1 << 62)):
            numbers = [i for i, w in enumerate(self.windows) if least <= len(w) < beyond]
            if numbers:
                self.classes.append(_Class([self.windows[i] for i in numbers], numbers))

    def occurrences(self, text: bytes) -> tuple[np.ndarray, np.ndarray]:
        """(start, window number) of every occurrence in text, confirmed byte by byte."""
        padded = np.frombuffer(text + bytes(8), np.uint8)
        starts, numbers = [np.empty(0, np.int64)], [np.empty(0, np.int64)]
        for c in self.classes:
            at, number = c.search(padded, len(text))
            good = np.fromiter(
                (text.startswith(self.windows[k], s) for s, k in zip(at.tolist(), number.tolist())),
                bool,
                len(at),
            )
            starts.append(at[good])
            numbers.append(number[good])
        return np.concatenate(starts), np.concatenate(numbers)


class _Bodies:
    """Some texts as one padded string of words."""

    def __init__(self, texts: list[str | None]):
        split = [words_of(t) for t in texts]
        self.counts = [len(w) for w in split]
        bodies = [b" " + b" ".join(w) + b" \n" for w in split]
        del split
        self.text = b"".join(bodies)
        self.begins = np.concatenate(([0], np.cumsum(np.fromiter(map(len, bodies), np.int64, len(bodies)))))
        self.spaces = np.flatnonzero(np.frombuffer(self.text, np.uint8) == 32)

    def occurrences(self, patterns: Patterns) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """(number of the first word, text, window) of each occurrence; words are counted over all texts."""
        at, number = patterns.occurrences(self.text)
        return np.searchsorted(self.spaces, at), np.searchsorted(self.begins, at, "right") - 1, number


def _items(docs: np.ndarray, number: np.ndarray, patterns: Patterns, found: dict[int, set]) -> None:
    for key in np.unique(docs * len(patterns.windows) + number).tolist():
        doc, k = divmod(key, len(patterns.windows))
        found.setdefault(doc, set()).update(patterns.items[k])


def judge_texts(texts: list[str | None], sets: list[Patterns]) -> list[tuple[int, int, int, list[str]]]:
    """(words, hit words, items with an occurring window, their ids) of each text."""
    bodies = _Bodies(texts)
    cover = np.zeros(len(bodies.spaces) + 1, np.int64)
    items: dict[int, set] = {}
    for patterns in sets:
        word, docs, number = bodies.occurrences(patterns)
        if len(word):
            np.add.at(cover, word, 1)
            np.add.at(cover, word + np.array(patterns.lengths)[number], -1)
            _items(docs, number, patterns, items)
    hit = np.concatenate(([0], np.cumsum(np.cumsum(cover)[:-1] > 0)))
    bounds = np.searchsorted(bodies.spaces, bodies.begins)
    hits = hit[bounds[1:]] - hit[bounds[:-1]]
    return [
        (n, int(h), len(items.get(i, ())), _ids(items.get(i, ())))
        for i, (n, h) in enumerate(zip(bodies.counts, hits))
    ]


def _ids(items) -> list[str]:
    return sorted(x for x in items if x is not None)


def hit_spans(texts: list[str | None], patterns: Patterns) -> dict[int, tuple[list[tuple[int, int]], set]]:
    """text's number -> (runs of hit words, items) of the texts that have any."""
    bodies = _Bodies(texts)
    word, docs, number = bodies.occurrences(patterns)
    items: dict[int, set] = {}
    if not len(word):
        return {}
    _items(docs, number, patterns, items)
    first = np.searchsorted(bodies.spaces, bodies.begins)[docs]
    spans: dict[int, list[tuple[int, int]]] = {}
    ends = word + np.array(patterns.lengths)[number] - first
    for doc, s, e in sorted(zip(docs.tolist(), (word - first).tolist(), ends.tolist())):
        own = spans.setdefault(doc, [])
        if own and s <= own[-1][1]:
            own[-1] = (own[-1][0], max(e, own[-1][1]))
        else:
            own.append((s, e))
    return {doc: (own, items[doc]) for doc, own in spans.items()}


def _by_slice(texts: pa.Array, judge) -> Iterator[tuple[int, object]]:
    """(start, judge(texts)) of stretches of a column."""
    for start, end in stretches(texts, SLICE_BYTES):
        yield start, judge(texts.slice(start, end - start).to_pylist())


def pattern_sets(benchmark: DataFrame, item_col: str, text_col: str, size: int = WORDS):
    """(number of sets, maker of the k-th one): Patterns of the benchmark, in sets of a checked size."""
    items = benchmark.select(
        F.col(item_col).cast("string").alias("item"), F.col(text_col).alias("text")
    ).where(F.col("text").isNotNull())
    # A window repeats a text's bytes once for each of its words.
    weight = items.agg(F.coalesce(F.sum(F.octet_length("text")), F.lit(0))).first()[0] * size
    parts = max(1, -(-int(weight) // PATTERN_BYTES))
    part = F.pmod(F.xxhash64("item", "text"), F.lit(parts))

    def make(k: int):
        rows = (items if parts == 1 else items.where(part == k)).collect()
        compiled = Patterns([(r["item"], r["text"]) for r in rows], size)
        return benchmark.sparkSession.sparkContext.broadcast(cloudpickle.dumps(compiled))

    return parts, make


def _found_by_set(keyed: DataFrame, parts: int, make) -> DataFrame:
    """(row_id, row_text, spans, items) of rows (row_id, row_text, text) with hits, a row a set."""
    found = None
    for k in range(parts):
        shared = make(k)

        def kernel(batches: Iterator[pa.RecordBatch], shared=shared) -> Iterator[pa.RecordBatch]:
            patterns = pickle.loads(shared.value)
            schema = pa.schema(
                [("row_id", pa.int64()), ("row_text", pa.int64()),
                 ("spans", pa.list_(pa.struct([("s", pa.int64()), ("e", pa.int64())]))), ("items", pa.list_(pa.string()))]
            )
            for batch in batches:
                ids, texts = batch.column("row_id"), batch.column("row_text")
                rows = [
                    {"row_id": ids[start + i].as_py(), "row_text": texts[start + i].as_py(),
                     "spans": [{"s": s, "e": e} for s, e in spans], "items": list(items)}
                    for start, hits in _by_slice(batch.column("text"), lambda t: hit_spans(t, patterns))
                    for i, (spans, items) in hits.items()
                ]
                yield pa.RecordBatch.from_pylist(rows, schema=schema)

        schema = "row_id long, row_text long, spans array<struct<s: long, e: long>>, items array<string>"
        own = reliable(keyed.mapInArrow(lean(kernel), schema).dropDuplicates(["row_id", "row_text"]))
        shared.unpersist()
        found = own if found is None else found.unionByName(own)
    return found


def _keyed(docs: DataFrame, id_col: str, text_col: str) -> DataFrame:
    return docs.select(
        id_key(id_col).alias("row_id"), text_key(text_col).alias("row_text"), F.col(text_col).alias("text")
    )


def _joined_sets(docs, id_col, text_col, keep, parts, make) -> DataFrame:
    """contamination() set after set."""
    found = _found_by_set(_keyed(docs, id_col, text_col), parts, make)
    found = found.groupBy("row_id", "row_text").agg(  # bounded by one document and its items
        F.array_sort(F.flatten(F.collect_list("spans"))).alias("spans"),
        F.array_distinct(F.flatten(F.collect_list("items"))).alias("items"),
    )
    union = F.aggregate(
        "spans",
        F.struct(F.lit(0).cast("long").alias("upto"), F.lit(0).cast("long").alias("n")),
        lambda a, x: F.struct(
            F.greatest(a["upto"], x["e"]).alias("upto"),
            (a["n"] + F.greatest(F.lit(0), x["e"] - F.greatest(a["upto"], x["s"]))).alias("n"),
        ),
    )
    found = found.select("row_id", "row_text", union["n"].alias("n_hit"), "items")
    names = [F.col(id_col).cast("long").alias("doc_id"), *keep]
    # ASCII capitals are letters too: they make no other words than their small ones.
    words = F.regexp_count(F.coalesce(F.col(text_col), F.lit("")), F.lit(r"[^\x00-\x2F\x3A-\x40\x5B-\x60\x7B-\x7F]+"))
    rows = docs.select(*names, id_key(id_col).alias("row_id"), text_key(text_col).alias("row_text"),
                       words.cast("long").alias("n_words"))
    ids = F.coalesce(F.array_sort(F.filter("items", lambda x: x.isNotNull())), F.expr("cast(array() as array<string>)"))
    hits = F.coalesce("n_hit", F.lit(0).cast("long"))
    return rows.join(reliable(found), ["row_id", "row_text"], "left").select(
        "doc_id", *keep, "n_words", hits.alias("n_hit"),
        F.when(F.col("items").isNull(), 0).otherwise(F.size("items")).cast("long").alias("n_items"),
        ids.alias("items"), F.sha2(F.array_join(ids, ","), 256).alias("items_sha256"), (hits > 0).alias("contaminated"),
    )


def contamination(
    docs: DataFrame,
    benchmark: DataFrame,
    id_col: str = "doc_id",
    text_col: str = "text",
    item_col: str = "item_id",
    item_text_col: str = "text",
    size: int = WORDS,
    keep: tuple[str, ...] = (),
) -> DataFrame:
    """(doc_id, keep..., n_words, n_hit, n_items, items, items_sha256, contaminated) per row."""
    parts, make = pattern_sets(benchmark, item_col, item_text_col, size)
    if parts > 1:
        return _joined_sets(docs, id_col, text_col, keep, parts, make)
    shared = make(0)
    slim = docs.select(
        F.col(id_col).cast("long").alias("doc_id"), *keep, F.col(text_col).alias("text")
    )
    names = ["doc_id", *keep]
    types = dict(slim.dtypes)

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        sets = [pickle.loads(shared.value)]
        for batch in batches:
            judged = [x for _, part in _by_slice(batch.column("text"), lambda t: judge_texts(t, sets)) for x in part]
            digests = [hashlib.sha256(",".join(x[3]).encode()).hexdigest() for x in judged]
            columns = [batch.column(c) for c in names]
            columns += [
                pa.array([x[0] for x in judged], pa.int64()),
                pa.array([x[1] for x in judged], pa.int64()),
                pa.array([x[2] for x in judged], pa.int64()),
                pa.array([x[3] for x in judged], pa.list_(pa.string())),
                pa.array(digests, pa.string()),
                pa.array([x[1] > 0 for x in judged], pa.bool_()),
            ]
            yield pa.RecordBatch.from_arrays(columns, names=[*names, *_RESULT])

    kept = "".join(f"`{c}` {types[c]}, " for c in names)
    return slim.mapInArrow(
        lean(kernel),
        kept + "n_words long, n_hit long, n_items long, items array<string>, items_sha256 string, "
        "contaminated boolean",
    )


def clean(
    docs: DataFrame,
    benchmark: DataFrame,
    id_col: str = "doc_id",
    text_col: str = "text",
    item_col: str = "item_id",
    item_text_col: str = "text",
    size: int = WORDS,
) -> DataFrame:
    """docs without the rows that hold a window of an item; columns stay as they are.

    With one set nothing is shuffled: texts go through the search once and come back with a
    mark. With more, only the keys of hit rows are gathered and their rows dropped.
    """
    parts, make = pattern_sets(benchmark, item_col, item_text_col, size)
    if parts > 1:
        keyed = _keyed(docs, id_col, text_col)
        gone = _found_by_set(keyed, parts, make).select("row_id", "row_text").distinct()
        return apply_keys(docs, reliable(gone.withColumn("stays", F.lit(False))), id_col, text_col)
    shared = make(0)
    names = docs.columns

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        sets = [pickle.loads(shared.value)]
        for batch in batches:
            judged = [x for _, part in _by_slice(batch.column(text_col), lambda t: judge_texts(t, sets)) for x in part]
            yield batch.filter(pa.array([not x[1] for x in judged], pa.bool_()))

    schema = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in docs.schema.fields)
    return docs.select(*names).mapInArrow(lean(kernel), schema)


_RESULT = ("n_words", "n_hit", "n_items", "items", "items_sha256", "contaminated")
