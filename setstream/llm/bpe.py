"""Byte-level BPE by longest-match backtracking.

A piece of text has one merge encoding. A token sequence is that encoding exactly if every adjacent pair of it is
compatible, so the encoder walks the piece taking the longest token that is compatible with the one before, tries
shorter prefixes when it isn't and steps back when none is left; end positions that led nowhere are marked and never
tried again, which keeps the walk linear. All matches come from one automaton over bytes read as Latin-1 characters.

Edge cases: null and empty texts have no tokens (and decode to the empty text); very long texts and pieces are walked in
linear time; special tokens are ordinary text; repeated rows each get a row; a null doc_id is only carried along; extra columns pass
through unless named like an output; an empty table gives an empty result.
"""

from __future__ import annotations

import base64
from collections.abc import Iterator
from itertools import chain

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import types as T

from .text import chunks

#: Pieces in each of the two generations that a worker remembers.
CACHE = 100_000


def read_ranks(path: str) -> list[bytes]:
    """Tokens by rank from a rank file (base64 token, blank, rank on each line)."""
    with open(path, "rb") as f:
        pairs = [line.split() for line in f if line.strip()]
    ranks = {int(rank): base64.b64decode(token) for token, rank in pairs}
    return [ranks[i] for i in range(len(ranks))]


def merge_slow(piece: bytes, rank: dict[bytes, int], below: int | None = None) -> list[bytes]:
    """The merges themselves: join the adjacent pair of lowest rank (leftmost first) until none is left."""
    parts = [piece[i : i + 1] for i in range(len(piece))]
    while len(parts) > 1:
        best = min(
            ((r, i) for i in range(len(parts) - 1) if (r := rank.get(parts[i] + parts[i + 1])) is not None and (below is None or r < below)),
            default=None,
        )
        if best is None:
            break
        i = best[1]
        parts[i : i + 2] = [parts[i] + parts[i + 1]]
    return parts


class Vocabulary:
    """What encoding needs of a rank list: the halves each token is merged from and its next shorter prefix token."""

    def __init__(self, tokens: list[bytes]):
        self.tokens = tokens
        self.rank = {t: i for i, t in enumerate(tokens)}
        self.prefix = [next((self.rank[t[:n]] for n in range(len(t) - 1, 0, -1) if t[:n] in self.rank), -1) for t in tokens]
        self.left, self.right = list(range(len(tokens))), list(range(len(tokens)))
        for i, t in enumerate(tokens):
            if len(t) > 1:
                halves = merge_slow(t, self.rank, below=i)
                if len(halves) == 2:
                    self.left[i], self.right[i] = self.rank[halves[0]], self.rank[halves[1]]
        self.merged = {(self.left[i], self.right[i]): i for i in range(len(tokens)) if self.left[i] != i}


class Pairs(dict):
    """Whether token b may follow token a, by ``a << 32 | b``; worked out once for each pair.

    The pair stands if the merges of a's bytes followed by b's end in exactly a, b. Undo merges next to the seam, the later
    one first; a merge across the seam that would have come before the one undone last would have been made, so the pair
    can't stand.
    """

    def __init__(self, vocabulary: Vocabulary):
        super().__init__()
        self.vocabulary = vocabulary

    def __missing__(self, key: int) -> bool:
        v, x, y, undone, stands = self.vocabulary, key >> 32, key & 0xFFFFFFFF, 1 << 60, True
        while True:
            across = v.merged.get((x, y))
            if across is not None and across < undone:
                stands = False
                break
            whole_x, whole_y = v.right[x] == x, v.left[y] == y
            if whole_x and whole_y:
                break
            if whole_y or (not whole_x and x > y):
                undone, x = x, v.right[x]
            else:  # at equal ranks the left merge is made first, so y's own merge still precedes
                undone, y = y + 1, v.left[y]
        if len(self) >= 2 * CACHE:
            self.clear()
        self[key] = stands
        return stands


class Encoder(dict):
    """Encodes texts; as a dict, the pieces it remembers. One is kept by each worker process."""

    def __init__(self, vocabulary: Vocabulary, pattern: str):
        import ahocorasick
        import regex

        super().__init__()
        v = self.vocabulary = vocabulary
        self.length = [len(t) for t in v.tokens]
        self.reach = max(self.length)
        self.split = regex.compile(pattern).findall
        self.automaton = ahocorasick.Automaton()
        for i, t in enumerate(v.tokens):
            self.automaton.add_word(t.decode("latin-1"), i)
        self.automaton.make_automaton()
        self.pairs = Pairs(v)
        self.before: dict[str, tuple[int, ...]] = {}  # the generation before, emptied as it is used

    def __missing__(self, piece: str) -> tuple[int, ...]:
        got = self.before.pop(piece, None)
        if got is None:
            got = self.encode_piece(piece.encode())
        if len(self) >= CACHE:
            self.before = dict(self)
            self.clear()
        self[piece] = got
        return got

    def encode_piece(self, piece: bytes) -> tuple[int, ...]:
        whole = self.vocabulary.rank.get(piece)
        if whole is not None:
            return (whole,)
        latin, pairs, longest = piece.decode("latin-1"), self.pairs, self.automaton.iter_long
        greedy = [token for _, token in longest(latin)]
        last = greedy[0]
        for i in range(1, len(greedy)):
            token = greedy[i]
            if not pairs[last << 32 | token]:
                break
            last = token
        else:
            return tuple(greedy)
        # From the first pair that can't stand: shorter tokens, steps back, and longest matches where they are needed.
        length, prefix, reach, n = self.length, self.vocabulary.prefix, self.reach, len(latin)
        out, token, dead = greedy[:i], greedy[i], set()
        at = sum([length[x] for x in out])
        while True:
            end = at + length[token]
            if end not in dead and (not out or pairs[out[-1] << 32 | token]):
                out.append(token)
                if end == n:
                    return tuple(out)
                at = end
                token = next(longest(latin[at : at + reach]))[1]
                continue
            token = prefix[token]
            while token < 0:  # nothing fits here: this position can't be a boundary
                dead.add(at)
                token = out.pop()
                at -= length[token]
                token = prefix[token]

    def encode(self, text: str) -> list[int]:
        return list(chain.from_iterable(map(self.__getitem__, self.split(text))))


_ENCODERS: dict[str, Encoder] = {}


def _encoder(key: str, shared, pattern: str) -> Encoder:
    if key not in _ENCODERS:
        _ENCODERS[key] = Encoder(shared.value, pattern)
    return _ENCODERS[key]


OUTPUT = [T.StructField("token_ids", T.ArrayType(T.IntegerType(), False), False), T.StructField("decoded", T.BinaryType(), False)]


def encode_decode(docs: DataFrame, path: str, pattern: str, text_col: str = "text") -> DataFrame:
    """``docs`` without the text, with ``token_ids`` and ``decoded`` (the bytes those ids stand for).

    ``path`` names the rank file on the driver, ``pattern`` splits texts before the merges. The vocabulary, of fixed
    size, is broadcast.
    """
    spark = docs.sparkSession
    shared = spark.sparkContext.broadcast(Vocabulary(read_ranks(path)))
    key = f"{path}:{pattern}"
    rest = [c for c in docs.columns if c not in (text_col, "token_ids", "decoded")]
    schema = T.StructType([docs.schema[c] for c in rest] + OUTPUT)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encoder = _encoder(key, shared, pattern)
        tokens = encoder.vocabulary.tokens
        for batch in batches:
            column = batch.column(text_col)
            for a, b in chunks(column):
                ids, counts, decoded = [], [0], []
                for text in column.slice(a, b - a).to_pylist():
                    own = encoder.encode(text) if text else []
                    ids.append(np.array(own, np.int32))
                    counts.append(len(own))
                    decoded.append(b"".join(map(tokens.__getitem__, own)))
                lists = pa.ListArray.from_arrays(pa.array(np.cumsum(counts), pa.int32()), pa.array(np.concatenate(ids), pa.int32()))
                kept = [batch.column(c).slice(a, b - a) for c in rest]
                yield pa.RecordBatch.from_arrays([*kept, lists, pa.array(decoded, pa.binary())], names=[*rest, "token_ids", "decoded"])

    return docs.select(*rest, text_col).mapInArrow(run, schema)
