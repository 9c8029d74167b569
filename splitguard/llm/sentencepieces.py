"""SentencePiece encoding by batched Viterbi in numpy, and decoding.

A text becomes units that no piece crosses: a run of space marks with the letters
after it, or a line break. Units of equal length form a matrix and advance together,
one end position at a time: for every piece length, hashes of the substrings that
end there probe the sorted hashes of the pieces, and a vectorised maximum keeps the best
score and a backpointer for every unit. Characters without a piece fall back to bytes.
Units seen before come from a bounded cache.

The segmentation is the one with the largest total score, that of a unigram model. A file
made for merges has merge numbers where a unigram model has log chances; `scores`
says whether to take the file's scores or chances from the order of its pieces.

Vocabulary files stay where they are; their path is a parameter. The arrays made from one
(about 1 MB for 32,000 pieces) are broadcast.

Defined results: a null text has null ids; an empty text has none; a space mark that
stands in the text itself is encoded as bytes, so decoding returns every text exactly;
repeated rows give equal results; an empty table gives an empty result.
"""

from __future__ import annotations

import pickle
import re
from collections.abc import Iterator
from dataclasses import dataclass, field
from itertools import chain, islice, repeat

import numpy as np
import pyarrow as pa
from pyspark import cloudpickle
from pyspark.sql import DataFrame

from splitguard.llm.rows import lean, stretches

MODEL = "/opt/tokenizers/piece_bpe_32k.model"
SPACE = "▁"
UNKNOWN_PENALTY = 10.0
#: Units that the store holds; over that, all but the first KEPT_UNITS go. Common units come early.
CACHE_UNITS = 200_000
KEPT_UNITS = 100_000
BATCH_BYTES = 1024 * 1024
_BASE = np.uint64(0x9E3779B97F4A7C15)
_SLOT_BITS = 16
_SLOT_SHIFT = np.uint64(64 - _SLOT_BITS)
_UNIT = re.compile(f"{SPACE}+[^{SPACE}\n]*|\n?[^{SPACE}\n]+|\n")
# No piece has one of these marks after a letter (checked when a vocabulary is read).
_AFTER_LETTER = re.compile("(?<=[a-zà-ÿ])[.,]")


@dataclass
class Vocabulary:
    pieces: list[str]  # text of each id; of control and byte ids, empty
    scores: np.ndarray
    bytes_of: dict[int, int]  # id of a byte piece -> byte
    byte_ids: list[int]  # byte -> id
    spelling: list[bytes] = field(init=False)  # what each id stands for in a text

    def __post_init__(self):
        self.spelling = [
            bytes([self.bytes_of[i]]) if i in self.bytes_of else p.replace(SPACE, " ").encode()
            for i, p in enumerate(self.pieces)
        ]

    @classmethod
    def load(cls, path: str = MODEL, scores: str = "rank") -> Vocabulary:
        """The vocabulary in a model file, with the file's scores or scores by rank."""
        import sentencepiece

        model = sentencepiece.SentencePieceProcessor(model_file=path)
        ids = range(model.get_piece_size())
        plain = [
            not (model.is_byte(i) or model.is_control(i) or model.is_unknown(i) or model.is_unused(i))
            for i in ids
        ]
        names = [model.id_to_piece(i) for i in ids]
        bytes_of = {i: int(names[i][3:5], 16) for i in ids if model.is_byte(i)}
        if len(bytes_of) != 256:
            raise ValueError(f"{path} has no byte pieces")
        pieces = [p if ok else "" for p, ok in zip(names, plain)]
        if any(re.search(f"[^{SPACE}]{SPACE}|\n|{_AFTER_LETTER.pattern}", p) for p in pieces):
            raise ValueError("a piece crosses units")
        by_byte = sorted((b, i) for i, b in bytes_of.items())
        if scores == "model":
            chance = np.array([model.get_score(i) for i in ids])
        else:
            chance = rank_scores(plain)
        return cls(pieces, chance, bytes_of, [i for _, i in by_byte])


def rank_scores(plain: list[bool], offset: int = 10) -> np.ndarray:
    """Log chances of pieces that a file lists by falling frequency: as one over the rank.

    A file of merges holds merge numbers as scores. Their sum would favour many early pieces
    over one late piece, so chances are taken from the order of the pieces instead.
    """
    rank = np.cumsum(plain) + offset
    return np.float32(-np.log(rank)).astype(float)


def _code_points(texts: list[str], length: int) -> np.ndarray:
    flat = "".join(texts).encode("utf-32-le", "surrogatepass")
    return np.frombuffer(flat, "<u4").reshape(len(texts), length).astype(np.uint64)


def _hash_columns(codes: np.ndarray) -> np.ndarray:
    """Polynomial hashes of all prefixes, modulo 2**64; column j is of the first j characters."""
    out = np.zeros((codes.shape[0], codes.shape[1] + 1), np.uint64)
    for j in range(codes.shape[1]):
        out[:, j + 1] = out[:, j] * _BASE + codes[:, j] + np.uint64(1)
    return out


class Encoder:
    def __init__(self, vocabulary: Vocabulary):
        self.vocabulary = vocabulary
        keys, ids, self.lengths = [], [], []
        by_length: dict[int, list[int]] = {}
        for i, p in enumerate(vocabulary.pieces):
            if p:
                by_length.setdefault(len(p), []).append(i)
        self.power = [np.uint64(1)]
        for _ in range(max(by_length)):
            self.power.append(np.uint64(int(self.power[-1]) * int(_BASE) % (1 << 64)))
        self.tables: dict[int, tuple[np.ndarray, np.ndarray, np.ndarray]] = {}
        for n, members in by_length.items():
            hashes = _hash_columns(_code_points([vocabulary.pieces[i] for i in members], n))[:, n]
            order = np.argsort(hashes)
            keys, ids = hashes[order], np.array(members)[order]
            if len(keys) > 1 and (keys[1:] == keys[:-1]).any():
                raise ValueError("two pieces share a hash")
            # One bit a slot: most substrings are no piece, and few of them get past this.
            slots = np.zeros(1 << _SLOT_BITS, bool)
            slots[(keys >> _SLOT_SHIFT).astype(np.int64)] = True
            self.tables[n] = keys, ids, slots
        known = [i for i, p in enumerate(vocabulary.pieces) if p]
        self.unknown = float(vocabulary.scores[known].min()) - UNKNOWN_PENALTY
        self.clear()

    def _spelled(self, character: str) -> tuple[int, ...]:
        return tuple(
            self.vocabulary.byte_ids[b] for b in character.encode("utf-8", "surrogatepass")
        )

    def viterbi(self, units: list[str], length: int) -> list[tuple[int, ...]]:
        """Ids of units that all have this length."""
        n = len(units)
        hashes = np.ascontiguousarray(_hash_columns(_code_points(units, length)).T)
        tables = sorted(self.tables.items())
        best = np.full((length + 1, n), -np.inf)
        best[0] = 0.0
        piece = np.full((length + 1, n), -1, np.int64)
        back = np.zeros((length + 1, n), np.int64)
        scores = self.vocabulary.scores
        for end in range(1, length + 1):
            # A single character that is no piece is always possible, as bytes.
            best[end] = best[end - 1] + self.unknown
            back[end] = end - 1
            for size, (keys, ids, slots) in tables:
                if size > end:
                    break
                start = end - size
                wanted = hashes[end] - hashes[start] * self.power[size]
                row = np.flatnonzero(slots[(wanted >> _SLOT_SHIFT).astype(np.int64)])
                if not len(row):
                    continue
                wanted = wanted[row]
                at = np.minimum(np.searchsorted(keys, wanted), len(keys) - 1)
                found = keys[at] == wanted
                row, which = row[found], ids[at[found]]
                total = best[start, row] + scores[which]
                better = total > best[end, row]
                row, which = row[better], which[better]
                best[end, row] = total[better]
                piece[end, row] = which
                back[end, row] = start
        ends = np.full(n, length)
        rows = np.arange(n)
        taken = np.full((length, n), -2, np.int64)  # from the last piece to the first
        for step in range(length):
            taken[step] = np.where(ends > 0, piece[ends, rows], -2)
            ends = back[ends, rows]
            if not ends.any():
                break
        forward = taken[::-1].T
        used = forward >= 0
        cuts = np.cumsum(used.sum(axis=1)).tolist()
        flat = forward[used].tolist()
        out = [tuple(flat[i:j]) for i, j in zip([0, *cuts], cuts)]
        for i in np.flatnonzero((forward == -1).any(axis=1)).tolist():
            ids, at = [], 0
            for p in forward[i].tolist():
                if p >= 0:
                    ids.append(p)
                    at += len(self.vocabulary.pieces[p])
                elif p == -1:  # no piece: the character's bytes
                    ids += self._spelled(units[i][at])
                    at += 1
            out[i] = tuple(ids)
        return out

    def learn(self, units: set[str]) -> None:
        """Put the ids of units in the store."""
        by_length: dict[int, list[str]] = {}
        for u in units:
            by_length.setdefault(len(u), []).append(u)
        for length, members in sorted(by_length.items()):
            for i in range(0, len(members), 16_384):
                part = members[i : i + 16_384]
                self._store(part, self.viterbi(part, length))

    def _store(self, units: list[str], ids: list[tuple[int, ...]]) -> None:
        self.index.update(zip(units, range(len(self.index), len(self.index) + len(units))))
        self.sizes.append(np.fromiter(map(len, ids), np.int64, len(ids)))
        self.flats.append(np.fromiter(chain.from_iterable(ids), np.int32))

    def _numbers(self, units: list[str]) -> np.ndarray:
        """Numbers of units in the store, which learns those that it lacks."""
        if len(self.index) > CACHE_UNITS:
            self.trim()
        get = self.index.get
        numbers = np.fromiter(map(get, units, repeat(-1)), np.int64, len(units))
        lacking = np.flatnonzero(numbers < 0)
        if len(lacking):
            missing = [units[i] for i in lacking.tolist()]
            self.learn(set(missing))
            numbers[lacking] = np.fromiter(map(self.index.__getitem__, missing), np.int64, len(missing))
        return numbers

    def clear(self) -> None:
        self.index: dict[str, int] = {}
        self.sizes: list[np.ndarray] = []
        self.flats: list[np.ndarray] = []
        self._store([""], [self._spelled(SPACE)])

    def trim(self) -> None:
        size = np.concatenate(self.sizes)[:KEPT_UNITS]
        self.index = dict(islice(self.index.items(), len(size)))
        self.sizes, self.flats = [size], [np.concatenate(self.flats)[: size.sum()].copy()]

    def encode_batch(self, texts: list[str]) -> tuple[np.ndarray, np.ndarray]:
        """(ids of all texts end to end, number of ids of each text)."""
        split = [units_of(t) for t in texts]
        numbers = self._numbers(list(chain.from_iterable(split)))
        size, flat = np.concatenate(self.sizes), np.concatenate(self.flats)
        self.sizes, self.flats = [size], [flat]
        begin = np.cumsum(size) - size
        length = size[numbers]
        ends = np.cumsum(length)
        ids = flat[np.repeat(begin[numbers] - ends + length, length) + np.arange(length.sum())]
        bounds = np.cumsum([len(u) for u in split], dtype=np.int64)
        upto = np.concatenate(([0], ends))[bounds]
        return ids, np.diff(upto, prepend=0)


def units_of(text: str) -> list[str]:
    """Units that no piece crosses; an empty unit is a space mark of the text itself.

    A line break goes with the letters after it, which carry no space mark.
    """
    if not text:
        return []
    if SPACE in text:
        first, *others = text.split(SPACE)
        units = _UNIT.findall((SPACE + first).replace(" ", SPACE))
        for other in others:
            units += ["", *_UNIT.findall(other.replace(" ", SPACE))]
        return units
    if "  " in text or text[0] in " \n" or text[-1] == " " or " \n" in text:
        return _UNIT.findall(SPACE + text.replace(" ", SPACE))
    marked = SPACE + text.replace(" ", f" {SPACE}").replace("\n", " \n")
    return _AFTER_LETTER.sub(r" \g<0>", marked).split(" ")


def decode(ids, vocabulary: Vocabulary) -> str:
    """Text of ids, exactly the one that was encoded."""
    text = b"".join(map(vocabulary.spelling.__getitem__, ids)).decode("utf-8", "surrogatepass")
    return text[1:] if text.startswith(" ") else text


def encode_texts(
    docs: DataFrame,
    text_col: str = "text",
    model: str = MODEL,
    check: bool = False,
    text_kept: bool = True,
    scores: str = "rank",
) -> DataFrame:
    """docs with ids array<int> and n_pieces; with check, also round_trip boolean.

    scores: "rank" for chances by the order of the pieces, "model" for the file's own numbers.
    """
    shared = docs.sparkSession.sparkContext.broadcast(cloudpickle.dumps(Vocabulary.load(model, scores)))
    clash = {"ids", "n_pieces", *(["round_trip"] if check else [])}
    names = [c for c in docs.columns if c not in clash]
    slim = docs.select(*names)
    types = {f.name: f.dataType.simpleString() for f in slim.schema.fields}
    kept = [c for c in names if text_kept or c != text_col]

    def spell(texts: list[str | None], encoder: Encoder) -> tuple[pa.Array, list[bool | None]]:
        ids, lengths = encoder.encode_batch([t or "" for t in texts])
        offsets = np.concatenate(([0], np.cumsum(lengths)))
        good = []
        if check:
            pairs = zip(texts, offsets[:-1].tolist(), offsets[1:].tolist())
            good = [
                None if t is None else decode(ids[i:j].tolist(), encoder.vocabulary) == t
                for t, i, j in pairs
            ]
        missing = np.fromiter((t is None for t in texts), bool, len(texts))
        lists = pa.ListArray.from_arrays(
            pa.array(offsets, pa.int32()), pa.array(ids, pa.int32()), mask=pa.array(missing)
        )
        return lists, good

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encoder = Encoder(pickle.loads(shared.value))
        for batch in batches:
            for start, end in stretches(batch.column(text_col), BATCH_BYTES):
                part = batch.column(text_col).slice(start, end - start).to_pylist()
                lists, good = spell(part, encoder)
                columns = [batch.column(c).slice(start, end - start) for c in kept]
                counts = [None if x is None else n for x, n in zip(part, lists.value_lengths().to_pylist())]
                columns += [lists, pa.array(counts, pa.int64())]
                if check:
                    columns.append(pa.array(good, pa.bool_()))
                yield pa.RecordBatch.from_arrays(
                    columns, names=[*kept, "ids", "n_pieces", *(["round_trip"] if check else [])]
                )

    schema = "".join(f"`{c}` {types[c]}, " for c in kept) + "ids array<int>, n_pieces long"
    return slim.mapInArrow(lean(kernel), schema + (", round_trip boolean" if check else ""))
