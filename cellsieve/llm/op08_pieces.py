"""SentencePiece encoding and decoding for merge-type vocabularies, by backtracking.

Merging by rank is not run at all.  An Aho-Corasick automaton of the pieces finds, for each position of a unit, the longest piece that starts
there; pieces are laid side by side, longest first.  Two neighbours are compatible when undoing their last merges step by step never shows
a pair across their border that would have been merged earlier.  Where nothing fits, the position is marked in a bitfield and the last
piece is shortened to its longest proper prefix piece.  The outcome equals that of merging.

Texts are cut into units at borders that no piece crosses (before a space mark that follows another character, and around line ends), and
units that repeat are encoded once per worker, so the work per word is one look-up.

Definitions for odd input.  A null text gives null ids; an empty one gives no ids.  Characters outside the vocabulary become byte pieces.  The text
is never cut: a unit of any length is encoded whole.  Decoding gives the text back exactly, but for texts that hold the space mark
U+2581 itself, which decodes as a space; `exact` says whether it did.  Repeated rows repeat in the result.
"""

from __future__ import annotations

import heapq
import re
from array import array
from collections.abc import Iterable, Iterator
from functools import lru_cache

import ahocorasick
import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import chunks

MODEL = "/opt/tokenizers/piece_bpe_32k.model"
MARK = "▁"
#: Setting that names another model file.
SETTING = "spark.cellsieve.pieceModel"
#: Units, ids of units, and pairs of pieces that a worker remembers.  Beyond, it forgets the pairs, and those units that it met in neither of the last two rounds; a round
#: takes in half of CACHE.
CACHE = 500_000
CACHE_IDS = 10_000_000
CACHE_PAIRS = 500_000
#: Rows and bytes of texts encoded at a time; lists of their ids as Python numbers take some 60 times the bytes.
SLICE_ROWS = 128
SLICE_BYTES = 500_000


class Vocabulary:
    """Plain lists, so that it ships to workers; automata are built where they are used."""

    def __init__(self, pieces: list[tuple[str, float, int]]) -> None:
        self.pieces = pieces
        self.ids = {p: i for i, (p, _, kind) in enumerate(pieces) if kind == 1}
        self.bytes = {int(p[3:5], 16): i for i, (p, _, kind) in enumerate(pieces) if kind == 6}
        self.unknown = next((i for i, (_, _, kind) in enumerate(pieces) if kind == 2), 0)
        multi = sorted((i for p, i in self.ids.items() if len(p) > 1), key=lambda i: -pieces[i][1])
        self.rank = [0] * len(pieces)
        at, last = 0, None
        for i in multi:  # equal scores share a rank: among them the leftmost merge goes first
            if pieces[i][1] != last:
                at, last = at + 1, pieces[i][1]
            self.rank[i] = at
        self.parts: dict[int, tuple[int, int]] = {}
        for i in multi:
            left, whole = self.merged(pieces[i][0])
            if whole == [i]:
                self.parts[i] = left
        self.tied = {i for i in multi if set(pieces[i][0]) == {MARK}}
        self.line_ends_alone = not any("\n" in p for p in self.ids)
        if any(MARK in p[1:] and p.strip(MARK) for p in self.ids):
            raise ValueError("a piece holds a space mark after another character; units can't be cut before it")

    def merged(self, unit: str) -> tuple[tuple[int, int] | None, list[int]]:
        """The definition: merge the adjacent pair of the best rank, leftmost first, until none is left.  A heap of pairs over linked parts, so a unit
        of n characters costs n log n.  Used for set-up, runs of marks and where a stretch doesn't begin with a usable piece."""
        parts: list[str | None] = list(unit)
        after, before = list(range(1, len(parts) + 1)), list(range(-1, len(parts) - 1))
        heap: list[tuple[int, int, str]] = []

        def offer(j: int) -> None:
            if j >= 0 and after[j] < len(parts):
                whole = parts[j] + parts[after[j]]
                i = self.ids.get(whole)
                if i is not None:
                    heapq.heappush(heap, (self.rank[i], j, whole))

        for j in range(len(parts)):
            offer(j)
        last = None
        while heap:
            _, j, whole = heapq.heappop(heap)
            k = after[j]
            if parts[j] is None or k >= len(parts) or parts[j] + parts[k] != whole:
                continue
            last = (self.ids[parts[j]], self.ids[parts[k]]) if parts[j] in self.ids and parts[k] in self.ids else None
            parts[j], parts[k], after[j] = whole, None, after[k]
            if after[k] < len(parts):
                before[after[k]] = j
            offer(j)
            offer(before[j])
        return last, [self.ids.get(p, -1) for p in parts if p is not None]


@lru_cache(4)
def vocabulary(model: str = MODEL) -> Vocabulary:
    from sentencepiece import sentencepiece_model_pb2

    proto = sentencepiece_model_pb2.ModelProto()
    with open(model, "rb") as f:
        proto.ParseFromString(f.read())
    if proto.trainer_spec.model_type != 2:
        raise ValueError("only merge-type models can be encoded by backtracking")
    if proto.normalizer_spec.name != "identity" or not proto.normalizer_spec.add_dummy_prefix or proto.normalizer_spec.remove_extra_whitespaces:
        raise ValueError("only models without normalisation and with a leading space mark are supported")
    return Vocabulary([(p.piece, p.score, p.type) for p in proto.pieces])


class Encoder:
    def __init__(self, v: Vocabulary) -> None:
        self.v = v
        usable = {p: i for p, i in v.ids.items() if (len(p) == 1 or i in v.parts) and i not in v.tied}
        self.automaton = ahocorasick.Automaton()
        for p, i in usable.items():
            self.automaton.add_word(p, (len(p), i))
        self.automaton.make_automaton()
        self.size = {i: len(p) for p, i in usable.items()}
        self.shorter: dict[int, int] = {}
        for p, i in usable.items():
            for n in range(len(p) - 1, 0, -1):
                if p[:n] in usable:
                    self.shorter[i] = usable[p[:n]]
                    break
        self.chars = frozenset(p for p in usable if len(p) == 1)
        inside = {p[j : j + 2] for p in usable for j in range(len(p) - 1)}
        # an ending that no piece joins with what stands before it is a unit of its own
        self.endings = {c: frozenset(x for x in self.chars if x + c not in inside) for c in ".,;:!?)" if c in self.chars}
        self.fits: dict[int, bool] = {}
        self.index: dict[str, int] = {}
        self.flat, self.starts = array("i"), array("q", [0])
        self.turn()
        self.unit = re.compile(rf"[ {MARK}]+[^ {MARK}\n]*|[^ {MARK}\n]+|\n" if v.line_ends_alone else rf"[ {MARK}]+[^ {MARK}]*|[^ {MARK}]+")
        self.text_of = [b"" if kind in (2, 3) else bytes([int(p[3:5], 16)]) if kind == 6 else p.replace(MARK, " ").encode() for p, _, kind in v.pieces]

    def turn(self) -> None:
        """Begins a round: what the last one met can still be recalled, what only the one before it met is forgotten."""
        self.old = self.index, self.flat, self.starts
        self.index, self.flat, self.starts = {}, array("i"), array("q", [0])

    def compatible(self, a: int, b: int) -> bool:
        """Whether merging would leave the border between the pieces a and b alone."""
        v, pieces = self.v, self.v.pieces
        # a pair across the border, present until the side merged at `limit` was made, wins if its rank is better (or equal, when it lies further left)
        limit = 1 << 60
        while True:
            joint = v.ids.get(pieces[a][0] + pieces[b][0])
            if joint is not None and v.rank[joint] < limit:
                return False
            ra, rb = (v.rank[a] if a in v.parts else 0), (v.rank[b] if b in v.parts else 0)
            if not ra and not rb:
                return True
            if ra > rb or (ra == rb and ra):  # of equal ranks the right one was merged later
                if ra > rb:
                    limit, a = ra, v.parts[a][1]
                else:
                    limit, b = rb + 1, v.parts[b][0]
            else:
                limit, b = rb + 1, v.parts[b][0]

    def known(self, s: str) -> list[int]:
        """A stretch of characters that are all in the vocabulary, without runs of marks."""
        n, sizes, shorter, fits = len(s), self.size, self.shorter, self.fits
        longest = [0] * n
        for end, (size, i) in self.automaton.iter(s):  # of pieces with one start the longest comes last
            longest[end - size + 1] = i
        failed = bytearray(n + 1)
        out: list[int] = []
        at, piece, last = 0, longest[0], -1
        while True:
            end = at + sizes[piece]
            if not failed[end]:
                if last >= 0:
                    pair = last << 32 | piece
                    ok = fits.get(pair)
                    if ok is None:
                        ok = fits[pair] = self.compatible(last, piece)
                if last < 0 or ok:
                    out.append(piece)
                    if end == n:
                        return out
                    at, last = end, piece
                    piece = longest[at]
                    continue
            if piece in shorter:
                piece = shorter[piece]
                continue
            if last < 0:
                return self.v.merged(s)[1]
            failed[at] = 1
            piece = out.pop()
            at -= sizes[piece]
            last = out[-1] if out else -1

    def encode_unit(self, unit: str) -> list[int]:
        """unit: space marks, then characters without any."""
        unit = unit.replace(" ", MARK)
        body = unit.lstrip(MARK)
        marks = len(unit) - len(body)
        ids = self.v.ids
        out: list[int] = []
        if marks > 1 or (marks and not body):
            # a run of marks: all its merges rank last and are equal, so they run after the word has taken its mark, if it takes it
            if body and body[0] in ids and self.stretch(MARK + body, [])[0] != ids.get(MARK, -1):
                out, unit = self.run(marks - 1), MARK + body
            else:
                out, unit = self.run(marks), body
        return self.stretch(unit, out)

    def run(self, marks: int) -> list[int]:
        return [i for i in self.v.merged(MARK * marks)[1]] if marks else []

    def stretch(self, s: str, out: list[int]) -> list[int]:
        if self.chars.issuperset(s):
            return out + self.known(s) if s else out
        ids, start = self.v.ids, 0
        for j, c in enumerate(s):
            if c not in ids:
                if j > start:
                    out += self.known(s[start:j])
                out += [self.v.bytes.get(x, self.v.unknown) for x in c.encode("utf-8", "replace")] if self.v.bytes else [self.v.unknown]
                start = j + 1
        if start < len(s):
            out += self.known(s[start:])
        return out

    def codes(self, units: list[str]) -> list[int]:
        try:
            index = self.index
            return [index[u] for u in units]
        except KeyError:
            for u in set(units):
                if u not in self.index and not self.recalled(u):
                    if len(u) > 2 and u[-2] in self.endings.get(u[-1], ""):
                        stem, ending = self.remembered(u[:-1]), self.remembered(u[-1])
                        self.remember(u, self.flat[self.starts[stem] : self.starts[stem + 1]] + self.flat[self.starts[ending] : self.starts[ending + 1]])
                    else:
                        self.remembered(u)
            return [self.index[u] for u in units]

    def remember(self, unit: str, ids: Iterable[int]) -> int:
        self.index[unit] = len(self.starts) - 1
        self.flat.extend(ids)
        self.starts.append(len(self.flat))
        return self.index[unit]

    def recalled(self, unit: str) -> bool:
        """Whether the last round met the unit, which is taken into this one then."""
        index, flat, starts = self.old
        at = index.get(unit)
        if at is not None:
            self.remember(unit, flat[starts[at] : starts[at + 1]])
        return at is not None

    def remembered(self, unit: str) -> int:
        if unit not in self.index and not self.recalled(unit):
            self.remember(unit, self.encode_unit(unit))
        return self.index[unit]

    def encode(self, texts: list[str | None]) -> tuple[np.ndarray, np.ndarray]:
        """Ids of all texts, one after the other, and how many each has."""
        if 2 * len(self.index) > CACHE or 2 * len(self.flat) > CACHE_IDS:
            self.turn()
        if len(self.fits) > CACHE_PAIRS:
            self.fits.clear()
        codes, n_units = [], np.zeros(len(texts), np.int64)
        for k, t in enumerate(texts):
            if t:
                c = self.codes(self.unit.findall(" " + t))
                codes += c
                n_units[k] = len(c)
        # views, which end with this call: while there is one the arrays can't grow
        flat, starts = np.frombuffer(self.flat, np.int32), np.frombuffer(self.starts, np.int64)
        code = np.array(codes, np.int64)
        size = starts[code + 1] - starts[code] if len(code) else code
        ends = np.cumsum(size)
        at = np.repeat(starts[code] - (ends - size), size) + np.arange(ends[-1]) if len(code) else code
        unit_ends = np.concatenate([[0], ends])[np.concatenate([[0], np.cumsum(n_units)])]
        return flat[at] if len(code) else np.zeros(0, np.int32), np.diff(unit_ends)

    def decode(self, ids: list[int]) -> str:
        text = b"".join([self.text_of[i] for i in ids]).decode("utf-8", "replace")
        return text[1:] if text[:1] == " " else text


_encoders: dict[str, Encoder] = {}


def encoder(v: Vocabulary, model: str) -> Encoder:
    """One for each model and worker process, so that tasks of one worker share what it remembers."""
    if model not in _encoders:
        _encoders[model] = Encoder(v)
    return _encoders[model]


def encoded(e: Encoder, batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """What encode() gives, for batches of doc_id and text, a slice at a time."""
    for whole in batches:
        for b in chunks(whole, "text", SLICE_ROWS, SLICE_BYTES):
            texts = b.column("text").to_pylist()
            flat, n = e.encode(texts)
            ends = np.concatenate([[0], np.cumsum(n)])
            every = flat.tolist()
            exact = [None if t is None else e.decode(every[i:j]) == t for t, i, j in zip(texts, ends[:-1].tolist(), ends[1:].tolist())]
            null = np.array([t is None for t in texts])
            offsets = pa.array(ends.astype(np.int32), mask=np.append(null, False)) if null.any() else pa.array(ends.astype(np.int32))
            lists = pa.ListArray.from_arrays(offsets, pa.array(flat, pa.int32()))
            yield pa.RecordBatch.from_arrays([b.column("doc_id"), lists, pa.array(n.astype(np.int32), mask=null), pa.array(exact, pa.bool_())], ["doc_id", "ids", "n_ids", "exact"])


def encode(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", model: str | None = None) -> DataFrame:
    """(doc_id, ids, n_ids, exact): the piece ids, their number, and whether decoding them gives the text again.  The model is a path, or that of
    the session's SETTING, or MODEL; only the driver reads it."""
    model = model or docs.sparkSession.conf.get(SETTING, MODEL)
    v = docs.sparkSession.sparkContext.broadcast(vocabulary(model))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        return encoded(encoder(v.value, model), batches)

    src = docs.select(F.col(id_col).cast("bigint").alias("doc_id"), F.col(text_col).cast("string").alias("text"))
    return src.mapInArrow(run, "doc_id bigint, ids array<int>, n_ids int, exact boolean")


def decode(encoded: DataFrame, id_col: str = "doc_id", ids_col: str = "ids", model: str | None = None) -> DataFrame:
    """(doc_id, text) from ids; null ids give null; ids outside the vocabulary raise an error."""
    model = model or encoded.sparkSession.conf.get(SETTING, MODEL)
    v = encoded.sparkSession.sparkContext.broadcast(vocabulary(model))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        e = encoder(v.value, model)
        for b in batches:
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array([None if x is None else e.decode(x) for x in b.column(1).to_pylist()], pa.string())], ["doc_id", "text"])

    return encoded.select(F.col(id_col).cast("bigint").alias("doc_id"), F.col(ids_col).cast("array<int>").alias("ids")).mapInArrow(run, "doc_id bigint, text string")
