"""Language identification by compression with per-language dictionaries.

Every language has a raw-content zstandard dictionary made of labelled texts. A
text is encoded with each and belongs to the language whose dictionary gives
the smallest size; where the margin to the runner-up is narrow, it is rejected.
Texts are reduced to lower-case words of letters first: digits, marks and capitals
cost bytes that say little about the language. The whole of a text is encoded, as stretches
of at most STRETCH bytes, each on its own, and the sizes are added: a dictionary helps the
start of a stretch most, so the margin doesn't fade with the length of the text. The encoder
stores a block as it is unless that saves some bytes, which would make all sizes of a short
one equal; so every stretch follows a primer that the dictionary already holds.

The dictionaries are fitted on a bounded sample. Labelled texts are cut, whole, into pieces
of PIECE_CHARS characters; the different pieces of a language whose hash is under a bound are
taken, about SAMPLE_PIECES of them (the bound follows from the number of different pieces, so
repeated texts neither crowd out others nor leave a language without any), and fill the
dictionary in the order of the hash up to `dictionary_bytes` (parameter, 128 KiB by default).

Defined results: a null text, or one without a letter, is `und` with score 0 and is
rejected; equal sizes are settled by the order of the language names and give
score 0; very long texts are judged whole, a stretch at a time; repeated rows are predicted
alike; with no labelled rows all are `und`; an empty table gives an empty result; columns of
any other name pass through `keep_recognised`.
"""

from __future__ import annotations

import re
from collections.abc import Iterator

import pyarrow as pa
import zstandard
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from splitguard.llm.rows import fresh, lean

DICTIONARY_BYTES = 128 * 1024
#: Different pieces of a language's texts that reach the driver, about.
SAMPLE_PIECES = 600
PIECE_CHARS = 2048
LEVEL = 9
#: Least margin, as a share of the runner-up's size, that is not rejected.
MARGIN = 0.002
UNKNOWN = "und"
PRIMER_BYTES = 512
STRETCH = 8192
_HASHES = 1 << 40
_WORD = re.compile(r"[^\W\d_]+")


def letters_only(text: str) -> bytes:
    return f" {' '.join(_WORD.findall(text.lower()))} ".encode("utf-8", "ignore")


def held_out(id_col: str) -> Column:
    return F.coalesce(
        F.crc32(F.encode(F.col(id_col).cast("string"), "UTF-8")) % 4 == 2, F.lit(False)
    )


def has_letter(text: Column) -> Column:
    return F.coalesce(text.rlike(r"\p{L}"), F.lit(False))


def _pieces(labelled: DataFrame, chars: int) -> DataFrame:
    """(lang, piece, h): all texts cut into pieces; h is a hash in 0.._HASHES - 1."""
    cut = F.regexp_extract_all("text", F.lit(rf"(?s).{{1,{chars}}}"), F.lit(0))
    pieces = labelled.where(F.col("lang").isNotNull()).select("lang", F.explode(cut).alias("piece"))
    return pieces.select("lang", "piece", F.pmod(F.xxhash64("piece"), F.lit(_HASHES)).alias("h"))


def learn_dictionaries(
    labelled: DataFrame,
    dictionary_bytes: int = DICTIONARY_BYTES,
    sample_pieces: int = SAMPLE_PIECES,
    piece_chars: int = PIECE_CHARS,
) -> dict[str, bytes]:
    """Raw content per language from rows (text, lang).

    Equal pieces are combined before they are shuffled, so a text that fills a third of the
    table leaves each task once.
    """
    pieces = _pieces(labelled, piece_chars).where(has_letter(F.col("piece")))
    counts = pieces.groupBy("lang").agg(F.approx_count_distinct("h").alias("n")).collect()  # a row a language
    if not counts:
        return {}
    bounds = [
        x
        for r in counts
        for x in (F.lit(r["lang"]), F.lit(min(_HASHES, sample_pieces * _HASHES // max(1, r["n"]))))
    ]
    rows = (
        pieces.where(F.col("h") < F.create_map(*bounds)[F.col("lang")])
        .dropDuplicates(["lang", "h"])
        .collect()
    )
    rows.sort(key=lambda r: (r["lang"], r["h"]))
    texts: dict[str, list[bytes]] = {}
    for r in rows:
        texts.setdefault(r["lang"], []).append(letters_only(r["piece"]))
    out = {}
    for lang, parts in sorted(texts.items()):
        content, size = [], 0
        for p in parts:
            if size >= dictionary_bytes:
                break
            content.append(p[: dictionary_bytes - size])
            size += len(content[-1])
        out[lang] = b"".join(content)
    return out


class Recogniser:
    """Compressors of all languages, made once per worker."""

    def __init__(self, dictionaries: dict[str, bytes], level: int = LEVEL):
        self.languages = sorted(dictionaries)
        self.encoders = []
        for lang in self.languages:
            content = zstandard.ZstdCompressionDict(
                dictionaries[lang], dict_type=zstandard.DICT_TYPE_RAWCONTENT
            )
            parameters = zstandard.ZstdCompressionParameters.from_level(
                level, write_content_size=False, write_checksum=False, write_dict_id=False
            )
            encoder = zstandard.ZstdCompressor(dict_data=content, compression_params=parameters)
            self.encoders.append((encoder.compress, dictionaries[lang][-PRIMER_BYTES:]))

    def sizes(self, text: str) -> list[int]:
        data = letters_only(text)
        parts = [data[i : i + STRETCH] for i in range(0, len(data), STRETCH)]
        return [
            sum(len(compress(primer + part)) for part in parts) for compress, primer in self.encoders
        ]

    def judge(self, text: str) -> tuple[str, float]:
        """(language, margin): how much smaller the best is than the runner-up, as a share."""
        if not self.languages:
            return UNKNOWN, 0.0
        sizes = self.sizes(text)
        best = min(range(len(sizes)), key=sizes.__getitem__)
        others = [s for i, s in enumerate(sizes) if i != best]
        if not others:
            return self.languages[best], 1.0
        second = min(others)
        return self.languages[best], (second - sizes[best]) / second


def _judged(texts: pa.ChunkedArray | pa.Array, lettered: list[bool], judge) -> list[tuple[str, float]]:
    return [judge(t.as_py()) if ok else (UNKNOWN, 0.0) for ok, t in zip(lettered, texts)]


def predict(
    docs: DataFrame,
    dictionaries: dict[str, bytes],
    id_col: str = "doc_id",
    text_col: str = "text",
    margin: float = MARGIN,
) -> DataFrame:
    """(doc_id, held_out, lang_pred, score, rejected) for every row."""
    slim = docs.select(
        F.col(id_col).cast("long").alias("doc_id"),
        held_out(id_col).alias("held_out"),
        has_letter(F.col(text_col)).alias("lettered"),
        F.col(text_col).alias("text"),
    )
    shared = docs.sparkSession.sparkContext.broadcast(dictionaries)  # at most DICTIONARY_BYTES a language

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        judge = Recogniser(shared.value).judge
        for batch in batches:
            found = _judged(batch.column("text"), batch.column("lettered").to_pylist(), judge)
            columns = [
                batch.column("doc_id"),
                batch.column("held_out"),
                pa.array([p for p, _ in found], pa.string()),
                pa.array([s for _, s in found], pa.float64()),
                pa.array([p == UNKNOWN or s < margin for p, s in found], pa.bool_()),
            ]
            yield pa.RecordBatch.from_arrays(
                columns, names=["doc_id", "held_out", "lang_pred", "score", "rejected"]
            )

    return slim.mapInArrow(
        lean(kernel), "doc_id long, held_out boolean, lang_pred string, score double, rejected boolean"
    )


def keep_recognised(
    docs: DataFrame, dictionaries: dict[str, bytes], text_col: str = "text", margin: float = MARGIN
) -> DataFrame:
    """docs without the rows whose language is rejected; all columns stay as they are."""
    shared = docs.sparkSession.sparkContext.broadcast(dictionaries)
    names = docs.columns
    schema = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in docs.schema.fields)
    mark = fresh("lettered", docs)

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        judge = Recogniser(shared.value).judge
        for batch in batches:
            found = _judged(batch.column(text_col), batch.column(mark).to_pylist(), judge)
            clear = pa.array([p != UNKNOWN and s >= margin for p, s in found], pa.bool_())
            yield batch.select(names).filter(clear)

    marked = docs.select("*", has_letter(F.col(text_col)).alias(mark))
    return marked.mapInArrow(lean(kernel), schema)


def fit(docs: DataFrame, id_col="doc_id", text_col="text", lang_col="lang") -> dict[str, bytes]:
    """Dictionaries learnt from the labelled rows that are not held out."""
    labelled = docs.where(~held_out(id_col)).select(
        F.col(text_col).alias("text"), F.col(lang_col).alias("lang")
    )
    return learn_dictionaries(labelled)


def identify(docs: DataFrame, id_col="doc_id", text_col="text", lang_col="lang") -> DataFrame:
    """Fit on the rows that are not held out, predict every row."""
    return predict(docs, fit(docs, id_col, text_col, lang_col), id_col, text_col)
