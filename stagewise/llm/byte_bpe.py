"""Byte-level BPE as a lazily determinised transducer, and streaming decoding.

Which token sequences are BPE encodings can be told from neighbours alone: a sequence is the encoding of its bytes exactly when
each adjacent pair is the encoding of its own bytes. A nondeterministic transducer therefore guesses token after token along a
byte trie, and lets a token end only where it may follow the one before. Its subset states are made deterministic as they are
met: a state holds the guesses still alive, each as tokens not yet emitted and a place in the trie. What all guesses agree on is
emitted, so output lags by less than the longest token.
"""

from __future__ import annotations

import base64
import bisect
import collections
import hashlib
import itertools
import marshal
import re
import struct
from array import array
from collections.abc import Iterable, Iterator, Sequence

import numpy as np
import public_tokenizers
import pyarrow as pa
import regex
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import KEPT, small_batches, table, text_blocks, tidied

#: Bounds of a worker's tables; each is emptied and filled anew when full.
MAX_TRANSITIONS, MAX_PAIRS, MAX_PIECES, PIECE_BYTES = 400_000, 300_000, 400_000, 48
#: The states that moves lead to are as long as what their guesses hold back, so their bytes are bounded, too.
STATE_BYTES = 32 << 20
#: Deals moves and pairs out over the places of their tables.
SPREAD = 0x9E3779B1
DECODE_STEP = 1 << 16


def read_ranks(path: str) -> dict[bytes, int]:
    with open(path, "rb") as lines:
        return {base64.b64decode(token): int(rank) for token, rank in map(bytes.split, lines)}


def merge_by_rank(data: bytes, ranks: dict[bytes, int], below: int = 1 << 62) -> list[int]:
    """The definition: merge the adjacent pair of least rank, the leftmost of equals, until none of a rank under ``below`` is left."""
    parts = [data[i : i + 1] for i in range(len(data))]
    while len(parts) > 1:
        rank, i = min((ranks.get(parts[i] + parts[i + 1], 1 << 62), i) for i in range(len(parts) - 1))
        if rank >= below:
            break
        parts[i : i + 2] = [parts[i] + parts[i + 1]]
    return [ranks[p] for p in parts]


def pack_ids(ids: Sequence[int]) -> bytes:
    return struct.pack(f"<{len(ids)}I", *ids)


class Transducer:
    """``run(piece)`` gives the token ids of one piece of text, read byte by byte, as little-endian 32-bit integers.

    Two workers keep their tables beside an executor's heap, so nothing in them is an object of its own: the trie, the moves and the pairs
    are arrays of integers, and the states, each the bytes of its guesses, lie one after the other in one buffer.
    """

    def __init__(self, ranks: dict[bytes, int]):
        self.ranks = ranks
        self.bytes_of = {i: t for t, i in ranks.items()}
        # the trie, numbered level by level: the children of a node stand side by side, from ``first[node]`` to ``first[node + 1]``
        self.first, self.token, label = array("i"), array("i"), bytearray(1)
        tokens = sorted(ranks)
        todo = collections.deque([(0, len(tokens), 0)])
        while todo:
            lo, hi, depth = todo.popleft()
            ends = lo < hi and len(tokens[lo]) == depth
            self.token.append(ranks[tokens[lo]] if ends else -1)
            self.first.append(len(label))
            lo += ends
            while lo < hi:
                byte = tokens[lo][depth]
                cut = bisect.bisect_right(tokens, byte, lo, hi, key=lambda t, at=depth: t[at])
                todo.append((lo, cut, depth + 1))
                label.append(byte)
                lo = cut
        self.first.append(len(label))
        self.label = bytes(label)
        self._reset()
        #: pair << 1 | whether it follows, at its place; a pair takes the place of the one there before
        self.pairs = array("Q", bytes(8 * MAX_PAIRS))
        self.parts: dict[int, tuple[int, int] | None] = {}

    def _reset(self) -> None:
        self.limit = MAX_TRANSITIONS
        self.mask = (1 << (2 * self.limit).bit_length()) - 1
        self.numbers = self.keys = self.values = None  # the old ones go before there are new ones
        #: places by hash of the states' numbers plus one, and of moves: (state << 8 | byte) + 1 -> next state << 32 | output
        self.numbers = array("I", bytes(4 * self.mask + 4))
        self.keys, self.values, self.moves = array("I", bytes(4 * self.mask + 4)), array("Q", bytes(8 * self.mask + 8)), 0
        self.kept, self.ends = bytearray(), array("I", [0])
        #: an output is a token << 1 | 1, or twice the place here of none or of several
        self.outputs: list[tuple[int, ...]] = [()]
        self.output_number: dict[tuple[int, ...], int] = {(): 0}
        self.start = self._state((-1, (((), 0),)))

    def _state(self, state: tuple) -> int:
        data = marshal.dumps(state, 2)  # this version writes equal states alike
        at = hash(data) & self.mask
        while n := self.numbers[at]:
            if self.kept[self.ends[n - 1] : self.ends[n]] == data:
                return n - 1
            at = at + 1 & self.mask
        self.kept += data
        self.ends.append(len(self.kept))
        self.numbers[at] = n = len(self.ends) - 1
        return n - 1

    def _guesses(self, n: int) -> tuple[int, tuple[tuple[tuple[int, ...], int], ...]]:
        """The state of this number: the last token emitted, and (tokens not yet emitted, place in the trie) of each guess."""
        return marshal.loads(self.kept[self.ends[n] : self.ends[n + 1]])

    def _output(self, ids: tuple[int, ...]) -> int:
        if len(ids) == 1:
            return ids[0] << 1 | 1
        n = self.output_number.get(ids)
        if n is None:
            n = self.output_number[ids] = len(self.outputs)
            self.outputs.append(ids)
        return n << 1

    def parts_of(self, token: int) -> tuple[int, int] | None:
        """The two tokens whose merge makes this one; None for a single byte."""
        found = self.parts.get(token, 0)
        if found == 0:
            ids = merge_by_rank(self.bytes_of[token], self.ranks, below=token)
            found = self.parts[token] = (ids[0], ids[1]) if len(ids) == 2 else None
        return found

    def follows(self, left: int, right: int) -> bool:
        """Whether the encoding of the two tokens' bytes is the two tokens.

        It is, unless at some moment of merging the two tokens that then met at the border had merged with each other. These
        moments are gone through backwards: the later of the two merges beside the border is undone, again and again. A merge
        across the border comes before one inside the left token of equal or higher rank, and before one inside the right
        token of strictly higher rank only, as the leftmost of equals goes first.
        """
        if left < 0:
            return True
        key, limit, known = left << 31 | right, 1 << 62, True
        place = (key * SPREAD >> 24) % len(self.pairs)
        kept = self.pairs[place]
        if kept >> 1 == key + 1:
            return kept & 1 == 1
        while True:
            joint = self.ranks.get(self.bytes_of[left] + self.bytes_of[right], 1 << 62)
            if joint < limit:
                known = False
                break
            a, b = self.parts_of(left), self.parts_of(right)
            if a and (not b or left > right):
                left, limit = a[1], left
            elif b:
                right, limit = b[0], right + 1
            else:
                break
        self.pairs[place] = key + 1 << 1 | known
        return known

    def _move(self, n: int, byte: int) -> int:
        last, guesses = self._guesses(n)
        alive: list[tuple[tuple[int, ...], int]] = []
        first = self.first
        for chain, node in guesses:
            child = self.label.find(byte, first[node], first[node + 1])
            if child < 0:
                continue
            if first[child] < first[child + 1]:
                alive.append((chain, child))
            t = self.token[child]
            if t >= 0 and self.follows(chain[-1] if chain else last, t):
                alive.append(((*chain, t), 0))
        if not alive:
            raise ValueError(f"the vocabulary has no token for byte {byte}")
        agreed = 0
        shortest = min(len(chain) for chain, _ in alive)
        while agreed < shortest and len({chain[agreed] for chain, _ in alive}) == 1:
            agreed += 1
        out = alive[0][0][:agreed]
        rest = tuple((chain[agreed:], node) for chain, node in alive)
        # the last token emitted matters to guesses that hold none of their own
        state = ((out[-1] if out else last) if agreed == shortest else -1, rest)
        return self._state(state) << 32 | self._output(out)

    def run(self, piece: bytes) -> bytes:
        at, ids, mask, keys, values = self.start, [], self.mask, self.keys, self.values
        for byte in piece:
            key = (at << 8 | byte) + 1
            place = key * SPREAD >> 24 & mask
            while (there := keys[place]) != key and there:
                place = place + 1 & mask
            if there:
                move = values[place]
            elif self.moves < self.limit and self.moves < MAX_TRANSITIONS and len(self.kept) < STATE_BYTES:
                keys[place], values[place], self.moves = key, (move := self._move(at, byte)), self.moves + 1
            else:
                here = self._guesses(at)
                keys = values = None
                self._reset()
                mask, keys, values = self.mask, self.keys, self.values
                move = self._move(self._state(here), byte)
            at = move >> 32
            out = move & 0xFFFFFFFF
            if out & 1:
                ids.append(out >> 1)
            elif out:
                ids += self.outputs[out >> 1]
        ids += next((chain for chain, node in self._guesses(at)[1] if node == 0), ())
        return pack_ids(ids)


class Pieces(dict):
    """Ids of pieces of text as little-endian 32-bit integers; those of short pieces are remembered.

    There are two generations, each of half the bound: when the young one is full it becomes the old one, whose pieces come back as they are met.
    """

    def __init__(self, transducer: Transducer):
        super().__init__()
        self.transducer = transducer
        self.old: dict[str, bytes] = {}

    def __missing__(self, piece: str) -> bytes:
        ids = self.old.get(piece)
        if ids is None:
            data = piece.encode()
            i = self.transducer.ranks.get(data)
            ids = self.transducer.run(data) if i is None else pack_ids((i,))
            if len(data) > PIECE_BYTES:
                return ids
        if len(self) >= MAX_PIECES // 2:
            self.old = dict(self)
            self.clear()
        self[piece] = ids
        return ids


class Utf8Stream:
    """Cuts a byte stream where characters end. The state is the start of a character that is not yet complete."""

    def __init__(self) -> None:
        self.pending = b""

    def feed(self, data: bytes) -> bytes:
        data = self.pending + data
        keep = 0
        for back in range(1, min(3, len(data)) + 1):
            lead = data[-back]
            if lead >= 0xC0:
                need = 2 if lead < 0xE0 else 3 if lead < 0xF0 else 4
                keep = back if need > back else 0
                break
            if lead < 0x80:
                break
        cut = len(data) - keep
        self.pending = data[cut:]
        return data[:cut]

    def finish(self) -> bytes:
        rest, self.pending = self.pending, b""
        return rest


def ascii_pattern(pattern: str) -> re.Pattern | None:
    """The same splitting for ASCII text in the standard library's faster engine; None if the pattern has classes unknown here."""
    out, inside, i = [], False, 0
    while i < len(pattern):
        if pattern.startswith((r"\p{L}", r"\p{N}"), i):
            chars = "A-Za-z" if pattern[i + 3] == "L" else "0-9"
            out.append(chars if inside else f"[{chars}]")
            i += 5
            continue
        if pattern.startswith((r"\p", r"\P"), i):
            return None
        step = 2 if pattern[i] == "\\" else 1
        if step == 1:
            inside = pattern[i] == "[" or inside and pattern[i] != "]"
        out.append(pattern[i : i + step])
        i += step
    return re.compile("".join(out), re.ASCII)


class Codec:
    """Encoding and decoding of whole texts with one vocabulary and one pattern."""

    def __init__(self, ranks: dict[bytes, int], pattern: str):
        self.pieces = Pieces(Transducer(ranks))
        self.split = regex.compile(pattern).findall
        quick = ascii_pattern(pattern)
        self.split_ascii = quick.findall if quick else self.split
        self.bytes_of = self.pieces.transducer.bytes_of

    def encode(self, text: str) -> bytes:
        """Ids as little-endian unsigned 32-bit integers."""
        return b"".join(map(self.pieces.__getitem__, (self.split_ascii if text.isascii() else self.split)(text)))

    def decode(self, ids: Iterable[int]) -> Iterator[bytes]:
        """Whole characters as they become complete; bytes that end no character come last."""
        stream, ids = Utf8Stream(), iter(ids)
        while step := list(itertools.islice(ids, DECODE_STEP)):
            yield stream.feed(b"".join(map(self.bytes_of.__getitem__, step)))
        yield stream.finish()

    def decode_text(self, ids: Iterable[int]) -> str:
        return "".join(part.decode("utf-8", "replace") for part in self.decode(ids))


_CODECS: dict[tuple[int, str], Codec] = KEPT.setdefault(__name__, {})


def _codec(ranks: dict[bytes, int], pattern: str) -> Codec:
    """One codec a worker process, so that its tables outlive a task."""
    key = (len(ranks), hashlib.sha256(repr(sorted(ranks.items())[:64]).encode()).hexdigest() + pattern)
    if key not in _CODECS:
        _CODECS.clear()
        _CODECS[key] = Codec(ranks, pattern)
    return _CODECS[key]


def encoded(docs: DataFrame, ranks_path: str, pattern: str, key: str = "doc_id", text: str = "text") -> DataFrame:
    """(key, ids binary): the ids of every whole text as little-endian unsigned 32-bit integers.

    Null and empty texts have no ids; repeated rows give repeated results, an empty table an empty one; other columns play no part.
    A text is held whole in one task, whatever its length, and is encoded in time linear in it.
    """
    kind = docs.schema[key].dataType.simpleString()
    vocabulary = docs.sparkSession.sparkContext.broadcast(read_ranks(ranks_path))  # one fixed vocabulary, whatever the input

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        codec = _codec(vocabulary.value, pattern)
        for batch in batches:
            for a, b, texts in text_blocks(batch, "t"):
                ids = [codec.encode(t.decode()) for t in texts]
                yield pa.record_batch([batch.column(0).slice(a, b - a), pa.array(ids, pa.binary())], names=["k", "ids"])

    return docs.select(F.col(key).alias("k"), F.col(text).alias("t")).transform(small_batches).mapInArrow(tidied(run), f"k {kind}, ids binary").withColumnRenamed("k", key)


def round_trip(docs: DataFrame, ranks_path: str, pattern: str, key: str = "doc_id", text: str = "text") -> DataFrame:
    """One row per input row: key, n_tokens, ids_sha256, decoded_sha256.

    Each match of ``pattern`` is encoded by itself, special tokens are ordinary text, and the ids are decoded again. Null and
    empty texts have no tokens. Repeated rows give repeated results; an empty table gives an empty one; other columns play no
    part. A text is held whole in one task, whatever its length, and is encoded in time linear in it, unbroken pieces too.
    """
    kind = docs.schema[key].dataType.simpleString()
    vocabulary = docs.sparkSession.sparkContext.broadcast(read_ranks(ranks_path))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        codec = _codec(vocabulary.value, pattern)
        for batch in batches:
            for a, b, texts in text_blocks(batch, "t"):
                counts, shas, back = [], [], []
                for t in texts:
                    ids = codec.encode(t.decode())
                    counts.append(len(ids) // 4)
                    shas.append(hashlib.sha256(ids).hexdigest())
                    sha = hashlib.sha256()
                    for part in codec.decode(np.frombuffer(ids, "<u4").tolist()):
                        sha.update(part)
                    back.append(sha.hexdigest())
                yield pa.record_batch(
                    [batch.column(0).slice(a, b - a), pa.array(counts, pa.int64()), pa.array(shas), pa.array(back)], names=["k", "n_tokens", "ids_sha256", "decoded_sha256"]
                )

    return (
        docs.select(F.col(key).alias("k"), F.col(text).alias("t"))
        .transform(small_batches).mapInArrow(tidied(run), f"k {kind}, n_tokens long, ids_sha256 string, decoded_sha256 string")
        .withColumnRenamed("k", key)
    )


def op2_byte_bpe(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents", "doc_id", "text")
    return round_trip(docs, public_tokenizers.path("byte_bpe_50k.tiktoken"), public_tokenizers.PATTERN)
