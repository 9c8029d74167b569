"""What large tables ask for: repeated rows, hot keys, many keys, many sets, clashing names."""

import hashlib
import re
import zlib
from collections import Counter

import numpy as np
import pytest
import regex

from splitguard.functions import runtime
from splitguard.llm import decontam, exactdedup, langid, nearsets, queries, rows, secrets, simhash, weakquality

SF = "/root/testdata/sf0.001"


def plan_of(df):
    return df._jdf.queryExecution().toString()


# ---- fits on repeated texts -----------------------------------------------------------


def test_fits_on_repeated_texts(spark):
    texts = ["The house of the river was old and grey.", "Das Haus an dem Fluss war alt und grau.", "!!!! $$$$ 1111 ####"]
    langs = ["en", "de", "de"]
    docs = spark.range(20_000).selectExpr(
        "id AS doc_id", *[f"element_at(array({', '.join(repr(x) for x in xs)}), cast(id % 3 + 1 AS int)) AS {n}" for n, xs in (("text", texts), ("lang", langs))]
    )
    content = langid.fit(docs)
    assert sorted(content) == ["de", "en"] and all(content.values())
    assert {r["lang_pred"] for r in langid.identify(docs).where("doc_id % 3 = 0").collect()} == {"en"}
    model, weights = weakquality.learn(docs)
    assert np.abs(weights).sum() > 0 and len(model.posterior) >= 2
    once = weakquality.learn(docs.limit(3), fit_texts=3)
    assert np.abs(once[1]).sum() > 0


def test_fits_read_whole_texts(spark):
    """What stands only at the end of a long text is learnt too."""
    lead = "ordinary words without much in them " * 200
    docs = spark.createDataFrame(
        [(i, lead + "zweihundert Bergziegen sprangen", "de") for i in range(8)] + [(i + 8, lead + "two hundred goats", "en") for i in range(8)],
        "doc_id long, text string, lang string",
    )
    content = langid.fit(docs)
    assert b"bergziegen" in content["de"] and b"goats" in content["en"]
    a, b = (weakquality.learn(docs.where(f"lang = '{la}'"))[1] for la in ("de", "en"))
    at = zlib.crc32(b"Bergziegen") % (weakquality.BUCKETS - 16)
    assert a[at] != 0 and b[at] == 0


def test_margin_does_not_fade_with_length(spark):
    full = spark.read.parquet("/root/testdata/sf0.01/documents.parquet")
    judge = langid.Recogniser(langid.fit(full)).judge
    english = " ".join(r["text"] for r in full.where("lang = 'en'").limit(150).collect())
    once, often = judge(english), judge(english * 8)
    assert once[0] == often[0] == "en" and often[1] > 0.9 * once[1] > langid.MARGIN


# ---- quality against a plain version ----------------------------------------------------


def plain_votes(text):
    def share(pattern):
        return 1 - len(regex.sub(pattern, "", text)) / max(len(text), 1)

    lines, words = text.split("\n"), re.split(r"[ \t\n\x0b\f\r]+", text.strip(" "))
    distinct, repeated = len(set(words)) / len(words), len(set(lines)) / len(lines)
    upper, digits = share(r"\p{Lu}"), share(r"\p{Nd}")
    marks, mean, enough = share(r"[#$%&*!|<>{}\[\]\\~^=+]"), len(text) / len(words), len(words) > 20
    pairs = [
        (False, len(text) < 40), (len(text) > 400, False), (marks < 0.005, marks > 0.04),
        (0.002 < upper < 0.08, upper > 0.3), (False, digits > 0.1),
        (distinct > 0.45 and enough, distinct < 0.3 and enough), (False, repeated < 0.7 and len(lines) > 3),
        (3.5 < mean < 9, mean < 2.5 or mean > 12), (bool(re.search(r"[.!?][ \t\n\x0b\f\r]*\Z", text)), False),
    ]
    return "".join("g" if good else "b" if bad else "-" for good, bad in pairs)


def plain_posteriors(counts):
    """Expectation-maximisation with nothing but dictionaries."""
    chance = {p: 1 / (1 + np.exp(-(p.count("g") - 2.0 * p.count("b")))) for p in counts}
    for _ in range(weakquality.ROUNDS):
        total = sum(counts.values())
        prior = sum(n * chance[p] for p, n in counts.items()) / total
        rates = []
        for j in range(len(next(iter(counts)))):
            seen = {(v, good): 1.0 for v in "gb-" for good in (True, False)}
            for p, n in counts.items():
                seen[p[j], True] += n * chance[p]
                seen[p[j], False] += n * (1 - chance[p])
            sums = {good: sum(seen[v, good] for v in "gb-") for good in (True, False)}
            rates.append({k: x / sums[k[1]] for k, x in seen.items()})
        for p in counts:
            odds = np.log(max(prior, 1e-9)) - np.log(max(1 - prior, 1e-9))
            odds += sum(np.log(r[v, True]) - np.log(r[v, False]) for v, r in zip(p, rates))
            chance[p] = 1 / (1 + np.exp(-min(30, max(-30, odds))))
    return chance


def test_quality_is_the_plain_one(spark):
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    texts = {r["doc_id"]: r["text"] for r in docs.collect()}
    votes = {i: plain_votes(t) for i, t in texts.items()}
    want = plain_posteriors(Counter(votes.values()))
    model, weights = weakquality.learn(docs)
    for r in weakquality.score_quality(docs).collect():
        text = texts[r["doc_id"]]
        assert r["votes"] == votes[r["doc_id"]]
        assert r["weak_posterior"] == pytest.approx(want[r["votes"]], abs=1e-9)
        tokens = text.split()
        score = sum(weights[zlib.crc32(w.encode()) % (weakquality.BUCKETS - 16)] for w in tokens) / max(1, len(tokens))
        at, x = weakquality.features(text)
        shape = at >= weakquality.BUCKETS - 16
        score += (weights[at[shape]] * x[shape]).sum()
        assert r["score"] == pytest.approx(1 / (1 + np.exp(-score)), abs=1e-9) and r["good"] == (r["score"] >= 0.5)


# ---- limits set to next to nothing ------------------------------------------------------


@pytest.fixture
def tiny(monkeypatch):
    monkeypatch.setattr(rows, "BROADCAST_KEYS", 0)
    monkeypatch.setattr(rows, "LEAST_BITS", 4)
    monkeypatch.setattr(runtime, "LEAST_HOT", 1)
    monkeypatch.setattr(runtime, "MOST_HOT", 1 << 40)
    monkeypatch.setattr(decontam, "PATTERN_BYTES", 20_000)


def results(spark):
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    docs = docs.union(docs.limit(30))  # repeated rows
    bench = spark.read.parquet(f"{SF}/benchmark.parquet")
    frames = {
        "groups": exactdedup.first_of_repeats(exactdedup.exact_groups(docs)).drop("row_id"),
        "unique": exactdedup.drop_copies(docs),
        "near": simhash.near_duplicates(docs),
        "one": simhash.keep_one(docs),
        "sets": nearsets.keep_one(docs),
        "hits": decontam.contamination(docs, bench, keep=("lang",)),
        "clean": decontam.clean(docs, bench),
        "secrets": secrets.secret_digests(docs),
    }
    return {k: Counter(map(str, f.drop("class").collect())) for k, f in frames.items()}


def test_limits_change_no_result(spark, tiny):
    small = results(spark)
    rows.BROADCAST_KEYS, rows.LEAST_BITS, runtime.LEAST_HOT, decontam.PATTERN_BYTES = 1 << 20, 16, 1 << 20, 1 << 25
    assert results(spark) == small


def test_many_suspects_shuffle_no_other_text(spark, monkeypatch):
    monkeypatch.setattr(rows, "BROADCAST_KEYS", 0)
    text = "a text that stands twice " * 40
    own = spark.range(3000).selectExpr("id AS doc_id", "concat(repeat(cast(id AS string), 400), '') AS text")
    docs = own.union(spark.createDataFrame([(i, text) for i in (5000, 5001)], "doc_id long, text string"))
    kept = exactdedup.drop_copies(docs)
    assert kept.count() == 3001
    hits, others = rows.bitmap_of(runtime.reliable(spark.range(3).selectExpr("xxhash64(id) AS k")), "k").split(
        spark.range(5000).selectExpr("id", "xxhash64(id) AS k"), __import__("pyspark").sql.functions.col("k")
    )
    assert {0, 1, 2} <= {r["id"] for r in hits.collect()} and hits.count() + others.count() == 5000 and hits.count() < 200
    # Rows whose bit is not set go from the scan to the result: their branch has no exchange of texts.
    passed = plan_of(others).split("== Physical Plan ==")[1]
    assert "SortMergeJoin" not in passed and "hashpartitioning" not in passed


def test_hot_keys_are_split_off(spark, monkeypatch):
    monkeypatch.setattr(runtime, "LEAST_HOT", 10)
    df = runtime.reliable(spark.range(1000).selectExpr("if(id % 3 = 0, 7, id) AS k", "id"))
    side = runtime.reliable(df.groupBy("k").count().selectExpr("k", "k * 2 AS v", "count AS n"))
    for how in ("inner", "left"):
        joined = runtime.join_by_key(df, side.where("k != 5"), ["k"], how=how)
        assert joined.columns == ["k", "id", "v"]
        got = {r["id"]: r["v"] for r in joined.collect()}
        want = {i: 14 if i % 3 == 0 else 2 * i for i in range(1000) if i != 5 or how == "left"}
        assert got == {i: None if i == 5 else v for i, v in want.items()}


def test_owners_follow_the_rows(spark):
    prints = runtime.reliable(spark.range(5000).selectExpr("id % 4000 AS fp"))
    for owner_rows in (100, 1 << 20):
        found = exactdedup.suspect_prints(prints, 16, owner_rows)
        assert sorted(r["fp"] for r in found.collect()) == list(range(1000))


# ---- secrets ------------------------------------------------------------------------------


def test_mixed_spans_beside_base_spans(spark):
    token = "Ab3" + "dE5fG7" * 4
    text = f"token={token} then {token}x and AKIA{'A' * 16}{token} or {token}"
    docs = spark.createDataFrame([(1, text, "o/r"), (2, f"{token} {token}", "o/r")], "doc_id long, text string, source string")
    got = {r["doc_id"]: r for r in secrets.secret_digests(docs).collect()}
    base = [(m.start(), m.end()) for p in (r"token=[A-Za-z0-9+/_.=-]+", r"AKIA[A-Z0-9]+") for m in re.finditer(p, text)]
    mixed = [m.span() for m in re.finditer(r"[A-Za-z0-9]{20,}", text) if all(m.end() <= s or e <= m.start() for s, e in base)]
    spans = [tuple(map(int, x.split(":")[1:])) for x in got[1]["spans"].split(",") if x.startswith("mixed")]
    assert spans == mixed and len(mixed) >= 2
    assert got[2]["most_owners"] == 1 and got[2]["most_repos"] == 1 and got[2]["n_live"] == 2


def test_one_owner_with_very_many_repositories_is_copied(spark):
    token = "Zq9" + "aB3dE6" * 4
    docs = spark.createDataFrame([(i, f"see {token}", f"one/r{i}") for i in range(30)], "doc_id long, text string, source string")
    got = secrets.secret_digests(docs).collect()
    assert all((r["spans"], r["most_owners"], r["most_repos"]) == ("", 1, 30) for r in got)


def test_a_text_with_very_many_spans(spark):
    text = " ".join(f"token: value{i:06d} Ab{i:06d}dE5fG7hJ9kL2" for i in range(6000))
    docs = spark.createDataFrame([(1, text, "s")], "doc_id long, text string, source string")
    row = secrets.secret_digests(docs).collect()[0]
    assert row["n_assign"] == 6000 and row["spans"].count("mixed") == 6000
    want = ",".join(f"assign:{m.start()}:{m.end()}" for m in re.finditer(r"token: value\d+", text))
    assert row["base_sha256"] == hashlib.sha256(want.encode()).hexdigest()


# ---- names ----------------------------------------------------------------------------------


def test_columns_with_clashing_names(spark):
    names = ["row_key", "text_key", "lettered", "at", "first", "n", "stays", "row_text", "words", "chunk", "items"]
    base = spark.read.parquet(f"{SF}/documents.parquet")
    docs = base.select("*", *[base["doc_id"].alias(n) for n in names])
    docs = docs.union(docs.limit(5))
    bench = spark.read.parquet(f"{SF}/benchmark.parquet")
    for made in (
        langid.keep_recognised(docs, langid.fit(docs)),
        exactdedup.drop_copies(docs),
        simhash.keep_one(docs),
        nearsets.keep_one(docs),
        decontam.clean(docs, bench),
    ):
        assert made.columns == docs.columns
        assert made.where("row_key != doc_id or chunk != doc_id").count() == 0 and made.count() > 100


def test_no_registered_query_is_cut():
    for name, make in queries.queries().items():
        code = make.__code__.co_names
        assert "limit" not in code and "sample" not in code, name
