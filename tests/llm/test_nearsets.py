"""The pipeline's near-copy stage against brute force over shingle sets."""

import re

import numpy as np
import pytest

import corpus_pipeline
from splitguard.llm import nearsets, simhash

SCHEMA = "doc_id long, text string, extra int"


def plain_set(text):
    lowered = "".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in text or "")
    parts = re.findall(r"[^\x20\x09-\x0D]+", lowered)
    return frozenset(" ".join(parts[i : i + 5]) for i in range(max(1, len(parts) - 4))) if parts else frozenset()


def similarity(a, b):
    return len(a & b) / len(a | b) if a | b else 1.0


def plain_kept(rows):
    sets = [plain_set(t) for _, t in rows]
    parent = list(range(len(rows)))

    def root(i):
        while parent[i] != i:
            i = parent[i]
        return i

    for i in range(len(rows)):
        for j in range(i):
            if similarity(sets[i], sets[j]) >= 0.8:
                parent[max(root(i), root(j))] = min(root(i), root(j))
    return sorted(min(rows[i][0] for i in range(len(rows)) if root(i) == r) for r in {root(i) for i in range(len(rows))})


def edited(words, rng, edits):
    words = list(words)
    for at in rng.choice(len(words) // 5, edits, replace=False):
        words[5 * at] = f"new{rng.integers(1 << 30)}"
    return " ".join(words)


def test_shingle_sets_are_the_plain_ones():
    for text in (None, "", " \n", "One", "a b c d", "A b C d e", "é x Y z w v é x Y z w v", "w " * 3000):
        assert len(nearsets.shingle_set(text)) == len(plain_set(text))
    assert nearsets.search_keys(nearsets.shingle_set(" ")) == []
    assert nearsets.search_keys(nearsets.shingle_set("A b")) == nearsets.search_keys(nearsets.shingle_set("a  B"))


@pytest.fixture(scope="module")
def rows():
    rng = np.random.default_rng(3)
    out = []
    for _ in range(12):  # bases, copies over and under the bound, and a chain
        words = [f"w{x}" for x in rng.integers(0, 5000, 300)]
        out.append(" ".join(words))
        out += [edited(words, rng, k) for k in (1, 3, 5, 6, 9, 14)]
        near = edited(words, rng, 5)
        out += [near, edited(near.split(), rng, 5)]
    return [*enumerate(out), (900, None), (901, ""), (902, " "), (903, "a b"), (904, "A  b"), (905, "a c")]


def test_stage_drops_what_brute_force_drops(spark, rows):
    docs = spark.createDataFrame([(i, t, 1) for i, t in rows], SCHEMA).repartition(3)
    want = plain_kept(rows)
    assert want != sorted(r["doc_id"] for r in simhash.keep_one(docs).collect())
    kept = corpus_pipeline.drop_near_copies(spark, docs, "")
    assert kept.columns == docs.columns
    assert sorted(r["doc_id"] for r in kept.collect()) == want
    assert nearsets.keep_one(docs.limit(0)).count() == 0


def test_stage_on_the_given_documents(spark):
    docs = spark.read.parquet("/root/testdata/sf0.001/documents.parquet").select("doc_id", "text")
    rows = sorted((r["doc_id"], r["text"]) for r in docs.collect())
    assert sorted(r["doc_id"] for r in nearsets.keep_one(docs).collect()) == plain_kept(rows)


def test_simhash_alone_finds_near_fingerprints(spark, monkeypatch):
    """With keys that only equal sets share, pairs come from pigeonhole blocks of fingerprints."""
    rng = np.random.default_rng(11)
    words = [[f"w{x}" for x in rng.integers(0, 50000, 3000)] for _ in range(6)]
    rows = [(2 * i + k, " ".join(w) if not k else edited(w, rng, 2)) for i, w in enumerate(words) for k in (0, 1)]
    prints = [nearsets.set_print(nearsets.shingle_set(t)) for _, t in rows]
    apart = [(prints[i] ^ prints[i + 1]).bit_count() for i in range(0, len(rows), 2)]
    assert nearsets.set_print(nearsets.shingle_set(" ")) == 0 and min(apart) <= 4
    monkeypatch.setattr(nearsets, "_keys_of", lambda values: [int(values.view(np.int64).sum())])
    docs = spark.createDataFrame([*rows, (90, ""), (91, None)], "doc_id long, text string")
    kept = {r["doc_id"] for r in nearsets.keep_one(docs).collect()}
    gone = {2 * i + 1 for i, bits in enumerate(apart) if bits <= 4}
    assert kept == set(range(12)) - gone | {90}
