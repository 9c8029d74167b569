"""Quality scorer taught by overlapping heuristic labellers.

1. Labellers vote good, bad or nothing on every text (DataFrame expressions).
2. All rows are counted by pattern of votes. There are at most 3 ** labellers patterns,
   so expectation-maximisation over the counts covers the whole corpus on the driver; it
   estimates each labeller's accuracy and the share of good texts, and gives each pattern the
   posterior chance that a text with it is good. No true label is used.
3. A linear scorer over hashed words and shape features is fitted to the posteriors of a
   bounded sample and scores every whole text. The sample is of about FIT_TEXTS different
   texts, those whose hash is under a bound that follows from the number of different texts;
   their features are taken from whole texts, where they are, and only those reach the driver.

Defined results: a null or empty text gets no votes but `short`; a score is in 0..1; with no
votes at all the posterior is the prior; very long texts are read whole, and have at most
BUCKETS features; repeated rows score alike and weigh in the counts, not in the sample; an
empty table gives an empty result; other columns are ignored.
"""

from __future__ import annotations

import re
import zlib
from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from splitguard.llm.rows import lean

#: Different texts that the scorer is fitted on; the sample's size is about this at any input size.
FIT_TEXTS = 3000
BUCKETS = 1 << 14
ROUNDS = 60
_HASHES = 1 << 40
_WORD = re.compile(r"\S+")


def _share(text: Column, pattern: str) -> Column:
    """Share of a text's characters that match a one-character class."""
    left = F.char_length(F.regexp_replace(text, pattern, ""))
    return 1 - left / F.greatest(F.char_length(text), F.lit(1))


def labellers() -> dict[str, tuple[Column, Column]]:
    """(votes good, votes bad) of each labeller over a column `body`."""
    body = F.col("body")
    length = F.char_length(body)
    lines = F.split(body, "\n")
    words = F.split(F.trim(body), r"\s+")
    distinct = F.size(F.array_distinct(words)) / F.size(words)
    repeated = F.size(F.array_distinct(lines)) / F.size(lines)
    upper, marks = _share(body, r"\p{Lu}"), _share(body, r"[#$%&*!|<>{}\[\]\\~^=+]")
    digits = _share(body, r"\p{Nd}")
    mean_word = length / F.size(words)
    never = F.lit(False)
    return {
        "short": (never, length < 40),
        "long": (length > 400, never),
        "marks": (marks < 0.005, marks > 0.04),
        "capitals": ((upper < 0.08) & (upper > 0.002), upper > 0.3),
        "digits": (never, digits > 0.1),
        "distinct": ((distinct > 0.45) & (F.size(words) > 20), (distinct < 0.3) & (F.size(words) > 20)),
        "lines": (never, (repeated < 0.7) & (F.size(lines) > 3)),
        "words": ((mean_word > 3.5) & (mean_word < 9), (mean_word < 2.5) | (mean_word > 12)),
        "ending": (body.rlike(r"[.!?]\s*$"), never),
    }


def votes(docs: DataFrame, text_col: str = "text") -> DataFrame:
    """docs' texts as `body` and `pattern`: one character a labeller, g, b or -."""
    body = docs.select(F.coalesce(F.col(text_col), F.lit("")).alias("body"))
    return body.select("body", F.concat(*_vote_columns()).alias("pattern"))


def _vote_columns() -> list[Column]:
    return [
        F.when(good, F.lit("g")).when(bad, F.lit("b")).otherwise(F.lit("-"))
        for good, bad in labellers().values()
    ]


@dataclass
class LabelModel:
    prior: float
    good_rates: np.ndarray  # [labeller][vote of g, b, -] given a good text
    bad_rates: np.ndarray
    posterior: dict[str, float]

    def accuracies(self) -> np.ndarray:
        """Chance that a labeller is right when it votes."""
        right = self.prior * self.good_rates[:, 0] + (1 - self.prior) * self.bad_rates[:, 1]
        wrong = self.prior * self.good_rates[:, 1] + (1 - self.prior) * self.bad_rates[:, 0]
        return right / np.maximum(right + wrong, 1e-12)


def fit_labels(counts: dict[str, int], rounds: int = ROUNDS) -> LabelModel:
    """Expectation-maximisation over vote patterns, from a majority vote."""
    patterns = sorted(counts)
    weight = np.array([counts[p] for p in patterns], float)
    size = len(patterns[0]) if patterns else len(labellers())
    coded = np.array([["gb-".index(c) for c in p] for p in patterns], int).reshape(len(patterns), size)
    lead = (coded == 0).sum(axis=1) - 2.0 * (coded == 1).sum(axis=1)
    chance = 1 / (1 + np.exp(-lead))
    prior, good, bad = 0.5, np.full((size, 3), 1 / 3), np.full((size, 3), 1 / 3)
    for _ in range(rounds if len(patterns) else 0):
        prior = float((weight * chance).sum() / weight.sum())
        for rates, share in ((good, weight * chance), (bad, weight * (1 - chance))):
            for j in range(size):
                own = np.bincount(coded[:, j], share, minlength=3) + 1.0
                rates[j] = own / own.sum()
        logs = np.log(max(prior, 1e-9)) - np.log(max(1 - prior, 1e-9))
        logs = logs + (np.log(good) - np.log(bad))[np.arange(size), coded].sum(axis=1)
        chance = 1 / (1 + np.exp(-np.clip(logs, -30, 30)))
    return LabelModel(prior, good, bad, dict(zip(patterns, chance.tolist())))


def features(text: str | None) -> tuple[np.ndarray, np.ndarray]:
    """(buckets, weights) of the hashed words of a text and its shape."""
    words = _WORD.findall(text or "")
    counts = Counter(words)
    n = max(1, len(words))
    buckets = [zlib.crc32(w.encode("utf-8", "ignore")) % (BUCKETS - 16) for w in counts]
    weights = [c / n for c in counts.values()]
    chars = max(1, len(text or ""))
    marks = sum(w.count("!") + w.count("%") + w.count("#") + w.count("$") + w.count("*") for w in words)
    shape = [
        1.0,
        min(1.0, np.log1p(n) / 8),
        len(counts) / n,
        sum(map(str.isupper, words)) / n,
        min(1.0, 10 * marks / chars),
        sum(map(str.isalpha, words)) / n,
        min(1.0, chars / n / 12),
        sum(map(str.isdigit, words)) / n,
    ]
    buckets += range(BUCKETS - 16, BUCKETS - 16 + len(shape))
    return np.array(buckets), np.array(weights + shape)


def fit_scorer(
    rows: list[tuple[np.ndarray, np.ndarray]], chances: list[float], passes: int = 5, rate: float = 0.5
) -> np.ndarray:
    """Logistic weights of rows of features by adaptive gradient steps, in the order of the rows."""
    weights, seen = np.zeros(BUCKETS), np.full(BUCKETS, 1e-6)
    for _ in range(passes):
        for (at, x), p in zip(rows, chances):
            guess = 1 / (1 + np.exp(-np.clip((weights[at] * x).sum(), -30, 30)))
            slope = (guess - p) * x
            np.add.at(seen, at, slope * slope)
            np.subtract.at(weights, at, rate * slope / np.sqrt(seen[at]))
    return weights


def _feature_batches(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Features of whole texts as bytes: buckets of 16 bits, weights of 32, no bucket twice."""
    for batch in batches:
        at, x = [], []
        for text in batch.column("body"):
            buckets, inverse = np.unique((found := features(text.as_py()))[0], return_inverse=True)
            at.append(buckets.astype("<u2").tobytes())
            x.append(np.bincount(inverse, found[1]).astype("<f4").tobytes())
        yield pa.RecordBatch.from_arrays(
            [batch.column("h"), batch.column("pattern"), pa.array(at, pa.binary()), pa.array(x, pa.binary())],
            names=["h", "pattern", "at", "x"],
        )


def learn(
    docs: DataFrame, text_col: str = "text", fit_texts: int = FIT_TEXTS
) -> tuple[LabelModel, np.ndarray]:
    """(label model over all rows, scorer's weights from a bounded sample of different texts)."""
    body = docs.select(F.coalesce(F.col(text_col), F.lit("")).alias("body"))
    hashed = body.select(F.pmod(F.xxhash64("body"), F.lit(_HASHES)).alias("h"), "body")
    voted = hashed.select("h", F.concat(*_vote_columns()).alias("pattern"))
    # A text has one pattern, so different texts are counted pattern by pattern.
    counted = voted.groupBy("pattern").agg(
        F.count(F.lit(1)).alias("n"), F.approx_count_distinct("h").alias("texts")
    ).collect()  # <= 3 ** labellers
    model = fit_labels({r["pattern"]: r["n"] for r in counted})
    bound = min(_HASHES, fit_texts * _HASHES // max(1, sum(r["texts"] for r in counted)))
    texts = hashed.where(F.col("h") < bound).dropDuplicates(["h"])
    taken = texts.select("h", F.concat(*_vote_columns()).alias("pattern"), "body")
    sample = taken.mapInArrow(lean(_feature_batches), "h long, pattern string, at binary, x binary").collect()
    sample.sort(key=lambda r: r["h"])
    rows = [(np.frombuffer(r["at"], "<u2").astype(int), np.frombuffer(r["x"], "<f4")) for r in sample]
    return model, fit_scorer(rows, [model.posterior[r["pattern"]] for r in sample])


def score_quality(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc_id, votes, weak_posterior, score, good) for every row."""
    model, weights = learn(docs, text_col)
    shared = docs.sparkSession.sparkContext.broadcast((model.posterior, model.prior, weights))
    slim = docs.select(
        F.col(id_col).cast("long").alias("doc_id"), F.coalesce(F.col(text_col), F.lit("")).alias("body")
    ).select("doc_id", F.concat(*_vote_columns()).alias("votes"), "body")

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        posterior, prior, linear = shared.value
        for batch in batches:
            scores = []
            for t in batch.column("body"):
                at, x = features(t.as_py())
                scores.append(float(1 / (1 + np.exp(-np.clip((linear[at] * x).sum(), -30, 30)))))
            weak = [posterior.get(p, prior) for p in batch.column("votes").to_pylist()]
            yield pa.RecordBatch.from_arrays(
                [
                    batch.column("doc_id"),
                    batch.column("votes"),
                    pa.array(weak, pa.float64()),
                    pa.array(scores, pa.float64()),
                    pa.array([s >= 0.5 for s in scores], pa.bool_()),
                ],
                names=["doc_id", "votes", "weak_posterior", "score", "good"],
            )

    return slim.mapInArrow(
        lean(kernel), "doc_id long, votes string, weak_posterior double, score double, good boolean"
    )
