"""Elementary filters of one segment: how a task builds them and how an expression probes them.

A built filter is a struct (seed, m, width, words): m cells of ``width`` bits. ``build`` gets the accepted and the rejected keys;
``test`` answers in numpy inside a task, ``probe`` as a Spark expression outside of one. All have no false negatives; the exact
kinds answer rightly on both sets.
"""

from __future__ import annotations

import functools
import math
from collections import deque
from collections.abc import Callable
from dataclasses import dataclass

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F

from ..functions.hashing import below_col, below_np, hash_col, hash_np
from ..functions.theory import BLOOM_FACTOR, C_COUPLED, C_UNIFORM, COUPLED_WINDOW
from .cells import bit_col, pack, read_at, read_col, read_np

STAGE_TYPE = "struct<seed:long,m:int,width:int,words:array<long>>"
NONE = np.zeros(0, np.int64)
BLOCK_BITS, BUCKET_SLOTS, MAX_TRIES = 512, 4, 64


@dataclass
class Built:
    seed: int
    m: int
    width: int
    words: np.ndarray

    def row(self) -> dict:
        return {"seed": self.seed, "m": self.m, "width": self.width, "words": self.words}


# --- Bloom filters -----------------------------------------------------------------------------------------------------------


def bloom_shape(n: int, eps: float) -> tuple[int, int]:
    """(bits, hashes) for n keys at a rate."""
    k = max(1, round(-math.log2(min(0.999, eps)))) if eps < 1 else 1
    return max(64, math.ceil(n * BLOOM_FACTOR * -math.log2(min(0.999, eps)))), k


def bloom_bits(keys: np.ndarray, seed: int, m: int, k: int) -> np.ndarray:
    """(k, n) bits of each key."""
    return np.stack([below_np(hash_np(seed + i // 2, keys), m, i % 2) for i in range(k)])


def build_bloom(pos: np.ndarray, neg: np.ndarray, eps: float, seed: int, bits: int | None = None) -> Built:
    m, k = bloom_shape(len(pos), eps)
    if bits is not None:
        m, k = max(64, bits), max(1, round(bits / max(1, len(pos)) * math.log(2)))
    cells = np.zeros(m, np.uint8)
    cells[bloom_bits(pos, seed, m, k).ravel()] = 1
    return Built(seed, m, k, pack(cells, 1))


def test_bloom(f: Built, keys: np.ndarray) -> np.ndarray:
    return (read_np(f.words, bloom_bits(keys, f.seed, f.m, f.width).ravel(), 1).reshape(f.width, -1) == 1).all(0)


def _all_bits(f: Column, hashes: int | None, set_: Callable[[Column, int | Column], Column]) -> Column:
    """Whether ``set_(seed offset, half)`` holds for every hash: written out for few hashes, a loop over the struct's own number if None."""
    if hashes is None:
        return F.forall(F.sequence(F.lit(0), f["width"] - 1), lambda i: set_(F.shiftright(i, 1), i % 2))
    hit = F.lit(True)
    for i in range(hashes):
        bit = set_(F.lit(i // 2), i % 2)
        hit = hit & ((F.lit(i) >= f["width"]) | bit) if i else bit
    return hit


def _half(h: Column, n: Column, part: int | Column) -> Column:
    return below_col(h, n, part) if isinstance(part, int) else F.when(part == 0, below_col(h, n, 0)).otherwise(below_col(h, n, 1))


def bloom_places(f: Column, key: Column, hashes: int) -> list[Column]:
    return [below_col(hash_col(f["seed"] + i // 2, key), f["m"], i % 2) for i in range(hashes)]


def bloom_answer(f: Column, key: Column, places: list[Column], cell: int = 1) -> Column:
    """Whether the cells at the places that the struct's own number of hashes has are all set."""
    hit = F.lit(True)
    for i, p in enumerate(places):
        own = (bit_col(f["words"], p) == 1) if cell == 1 else (read_col(f["words"], p, cell) > 0)
        hit = hit & ((F.lit(i) >= f["width"]) | own) if i else own
    return hit


def probe_bloom(f: Column, key: Column, hashes: int | None) -> Column:
    return _all_bits(f, hashes, lambda s, half: bit_col(f["words"], _half(hash_col(f["seed"] + s, key), f["m"], half)) == 1)


def build_blocked(pos: np.ndarray, neg: np.ndarray, eps: float, seed: int) -> Built:
    m, k = bloom_shape(len(pos), eps)
    m = -(-m // BLOCK_BITS) * BLOCK_BITS
    cells = np.zeros(m, np.uint8)
    cells[_blocked_bits_np(pos, seed, m, k).ravel()] = 1
    return Built(seed, m, k, pack(cells, 1))


def _blocked_bits_np(keys: np.ndarray, seed: int, m: int, k: int) -> np.ndarray:
    block = below_np(hash_np(seed, keys), m // BLOCK_BITS) * BLOCK_BITS
    return np.stack([block + below_np(hash_np(seed + 1 + i // 2, keys), BLOCK_BITS, i % 2) for i in range(k)])


def test_blocked(f: Built, keys: np.ndarray) -> np.ndarray:
    return (read_np(f.words, _blocked_bits_np(keys, f.seed, f.m, f.width).ravel(), 1).reshape(f.width, -1) == 1).all(0)


def blocked_places(f: Column, key: Column, hashes: int) -> list[Column]:
    block = below_col(hash_col(f["seed"], key), F.shiftright(f["m"], 9)) * BLOCK_BITS
    return [block + below_col(hash_col(f["seed"] + 1 + i // 2, key), F.lit(BLOCK_BITS), i % 2) for i in range(hashes)]


def probe_blocked(f: Column, key: Column, hashes: int | None) -> Column:
    block = below_col(hash_col(f["seed"], key), F.shiftright(f["m"], 9)) * BLOCK_BITS
    return _all_bits(f, hashes, lambda s, half: bit_col(f["words"], block + _half(hash_col(f["seed"] + 1 + s, key), F.lit(BLOCK_BITS), half)) == 1)


def build_counting(pos: np.ndarray, neg: np.ndarray, eps: float, seed: int, counts: np.ndarray | None = None) -> Built:
    """Four-bit counters, which saturate at 15; ``counts`` are the occurrences of each key."""
    m, k = bloom_shape(len(pos), eps)
    at = bloom_bits(pos, seed, m, k)
    weight = np.broadcast_to(np.ones(len(pos)) if counts is None else counts, at.shape)
    return Built(seed, m, k, pack(np.minimum(15, np.bincount(at.ravel(), weight.ravel(), minlength=m)).astype(np.uint64), 4))


def test_counting(f: Built, keys: np.ndarray) -> np.ndarray:
    return (read_np(f.words, bloom_bits(keys, f.seed, f.m, f.width).ravel(), 4).reshape(f.width, -1) > 0).all(0)


def probe_counting(f: Column, key: Column, hashes: int | None) -> Column:
    return _all_bits(f, hashes, lambda s, half: read_col(f["words"], _half(hash_col(f["seed"] + s, key), f["m"], half), 4) > 0)


# --- XOR tables --------------------------------------------------------------------------------------------------------------


#: Cells a key of coupled tables by j: (from how many keys on, cells). Small tables need more than their asymptotic share.
COUPLED_CELLS = {3: ((1 << 20, C_COUPLED), (1 << 16, 1.17), (0, 1.20)), 4: ((1 << 20, 1.08), (1 << 17, 1.10), (1 << 15, 1.14), (0, 1.20))}


def table_size(n: int, layout: str, C: float | None = None, j: int = 3) -> int:
    """Cells for n keys."""
    if C is None:
        C = C_UNIFORM if layout == "uniform" else next(c for least, c in COUPLED_CELLS[j] if n >= least)
    return max(6, math.ceil(n * C) + min(24 if layout == "uniform" else 8, 6 + n // 4))


def slots_np(keys: np.ndarray, seed: int, m: int, layout: str, j: int = 3) -> np.ndarray:
    """(j, n) cells of each key. Uniform: one in each of j equal blocks; coupled: one in each of j consecutive chunks."""
    if layout == "uniform":
        b = m // j
        return np.stack([i * b + below_np(hash_np(seed + i, keys), b) for i in range(j)])
    z = window_of(m, j)
    c = m // (z + j - 1)
    first = below_np(hash_np(seed, keys), z)
    return np.stack([(first + i) * c + below_np(hash_np(seed + 1 + i, keys), c) for i in range(j)])


def window_of(m: int, j: int = 3) -> int:
    """Positions that a coupled window can take: 120, fewer in tables too small for that."""
    return max(1, min(COUPLED_WINDOW, m // 128))


def slots_col(f: Column, key: Column, layout: str, j: int = 3) -> list[Column]:
    if layout == "uniform":
        b = F.floor(f["m"] / j)
        return [b * i + below_col(hash_col(f["seed"] + i, key), b) for i in range(j)]
    z = F.greatest(F.lit(1), F.least(F.lit(COUPLED_WINDOW), F.floor(f["m"] / 128))).cast("long")
    c = F.floor(f["m"] / (z + (j - 1)))
    first = below_col(hash_col(f["seed"], key), z)
    return [(first + i) * c + below_col(hash_col(f["seed"] + 1 + i, key), c) for i in range(j)]


def peel(slots: np.ndarray, m: int) -> list[tuple[np.ndarray, np.ndarray]] | None:
    """Rounds of (keys, own cell): in each round every cell that a single remaining key uses takes that key. None if keys are left."""
    j, n = slots.shape
    flat = slots.ravel()
    names = np.tile(np.arange(n), j)
    count = np.bincount(flat, minlength=m)
    mixed = np.zeros(m, np.int64)
    np.bitwise_xor.at(mixed, flat, names)
    left, rounds = n, []
    single = np.flatnonzero(count == 1)
    while len(single):
        keys, first = np.unique(mixed[single], return_index=True)
        rounds.append((keys, single[first]))
        left -= len(keys)
        gone = slots[:, keys].ravel()
        np.subtract.at(count, gone, 1)
        np.bitwise_xor.at(mixed, gone, np.tile(keys, j))
        touched = np.unique(gone)
        single = touched[count[touched] == 1]
    return rounds if left == 0 else None


def fill(slots: np.ndarray, m: int, rounds: list, values: np.ndarray) -> np.ndarray:
    """Cells such that each key's cells give its value by xor: the last peeled first."""
    cells = np.zeros(m, np.uint64)
    for keys, own in reversed(rounds):
        cells[own] = 0
        cells[own] = values[keys] ^ np.bitwise_xor.reduce(cells[slots[:, keys]], 0)
    return cells


def solve(keys: np.ndarray, value_of: Callable[[int], np.ndarray], width: int, seed: int, layout: str, j: int = 3, C: float | None = None) -> Built:
    """Peel with one seed after another; after every eight failures the table grows by 3%."""
    m = table_size(len(keys), layout, C, j)
    for t in range(MAX_TRIES):
        s = seed + 16 * t
        if t and t % 8 == 0:
            m = math.ceil(m * 1.03)
        slots = slots_np(keys, s, m, layout, j)
        rounds = peel(slots, m)
        if rounds is not None:
            return Built(s, m, width, pack(fill(slots, m, rounds, value_of(s)), width))
    raise RuntimeError(f"no table of {m} cells found for {len(keys)} keys")


def _print_np(keys: np.ndarray, seed: int, width: int) -> np.ndarray:
    return hash_np(seed + 9, keys) & np.uint64((1 << width) - 1)


def _xor_np(f: Built, keys: np.ndarray, layout: str, j: int) -> np.ndarray:
    slots = slots_np(keys, f.seed, f.m, layout, j)
    return np.bitwise_xor.reduce(read_np(f.words, slots.ravel(), f.width).reshape(slots.shape), 0)


def _xor_col(f: Column, key: Column, layout: str, j: int) -> Column:
    return functools.reduce(Column.bitwiseXOR, (read_col(f["words"], s, f["width"]) for s in slots_col(f, key, layout, j)))


def xor_places(f: Column, key: Column, layout: str = "uniform", j: int = 3, strategy: str = "a") -> list[Column]:
    """Where a key's cells begin, in bits."""
    return [s.cast("long") * f["width"] for s in slots_col(f, key, layout, j)]


def _xor_at(f: Column, places: list[Column]) -> Column:
    return functools.reduce(Column.bitwiseXOR, (read_at(f["words"], p, f["width"]) for p in places))


def xor_answer(f: Column, key: Column, places: list[Column], **shape) -> Column:
    mask = F.call_function("shiftleft", F.lit(1).cast("long"), f["width"]) - 1
    return _xor_at(f, places) == hash_col(f["seed"] + 9, key).bitwiseAND(mask)


def retrieval_answer(f: Column, key: Column, places: list[Column], layout: str = "uniform", j: int = 3, strategy: str = "a") -> Column:
    coin = hash_col(f["seed"] + 9, key).bitwiseAND(F.lit(1)) if strategy == "a" else F.lit(1)
    return functools.reduce(Column.bitwiseXOR, (bit_col(f["words"], p) for p in places)) == coin


def build_xor(pos: np.ndarray, neg: np.ndarray, eps: float, seed: int, layout: str = "uniform", C: float | None = None, j: int = 3, mixed: bool = False) -> Built:
    """Approximate: accepted keys carry a fingerprint of about log2(1/eps) bits.

    ``mixed``: of a rate between two whole numbers of bits, a segment takes the upper one with the probability of the fraction.
    """
    bits = -math.log2(eps)
    whole = math.floor(bits) + (float(np.random.default_rng(seed).random()) < bits % 1) if mixed else round(bits)
    width = max(1, min(32, whole))
    return solve(pos, lambda s: _print_np(pos, s, width), width, seed, layout, j, C)


def test_xor(f: Built, keys: np.ndarray, layout: str = "uniform", j: int = 3) -> np.ndarray:
    return _xor_np(f, keys, layout, j) == _print_np(keys, f.seed, f.width)


def probe_xor(f: Column, key: Column, layout: str = "uniform", j: int = 3) -> Column:
    mask = F.call_function("shiftleft", F.lit(1).cast("long"), f["width"]) - 1
    return _xor_col(f, key, layout, j) == hash_col(f["seed"] + 9, key).bitwiseAND(mask)


def build_retrieval(pos: np.ndarray, neg: np.ndarray, eps: float, seed: int, layout: str = "uniform", strategy: str = "a", C: float | None = None, j: int = 3) -> Built:
    """Exact, one bit a cell. At a rate above zero only the negatives that must be told apart are encoded.

    Strategy a answers "equal to the key's coin", so a negative that was left out passes half the time; strategy b answers "one".
    """
    if eps > 0:
        share = max(0.0, 1 - 2 * eps)
        neg = neg[hash_np(seed + 77, neg) < np.uint64(int(share * (2**64 - 1)))]
    keys = np.concatenate([pos, neg])
    truth = np.concatenate([np.ones(len(pos), np.uint64), np.zeros(len(neg), np.uint64)])
    coin = lambda s: _print_np(keys, s, 1) if strategy == "a" else np.ones(len(keys), np.uint64)
    return solve(keys, lambda s: coin(s) ^ np.uint64(1) ^ truth, 1, seed, layout, j, C)


def test_retrieval(f: Built, keys: np.ndarray, layout: str = "uniform", strategy: str = "a", j: int = 3) -> np.ndarray:
    coin = _print_np(keys, f.seed, 1) if strategy == "a" else np.uint64(1)
    return _xor_np(f, keys, layout, j) == coin


def probe_retrieval(f: Column, key: Column, layout: str = "uniform", strategy: str = "a", j: int = 3) -> Column:
    coin = hash_col(f["seed"] + 9, key).bitwiseAND(F.lit(1)) if strategy == "a" else F.lit(1)
    return _xor_col(f, key, layout, j) == coin


# --- both stages in shared blocks ------------------------------------------------------------------------------------------------
#
# A block is a fingerprint cell and two one-bit cells. A key has three blocks for both stages: the fingerprint is the xor of the
# upper parts, the answer the xor of one lower bit of each, so a lookup touches three places in all. The fingerprints alone let
# fewer negatives through than there are positives, so at most 2n keys are stored in the 2m one-bit cells.


def _block_bits_np(keys: np.ndarray, seed: int) -> np.ndarray:
    """Which of a block's two one-bit cells a key uses, in each of its three blocks."""
    h = hash_np(seed + 5, keys)
    return np.stack([((h >> np.uint64(i)) & np.uint64(1)).astype(np.int64) for i in range(3)])


def build_shared(pos: np.ndarray, neg: np.ndarray, eps: float, seed: int, C: float | None = None) -> Built:
    """Exact, for positives that are not the majority."""
    width = max(0, math.ceil(math.log2(max(1.0, len(neg) / max(1, len(pos))))))
    m = table_size(len(pos), "uniform", C)
    for t in range(MAX_TRIES):
        s = seed + 16 * t
        if t and t % 8 == 0:
            m = math.ceil(m * 1.03)
        slots = slots_np(pos, s, m, "uniform")
        rounds = peel(slots, m)
        if rounds is None:
            continue
        upper = fill(slots, m, rounds, _print_np(pos, s, width))
        own = lambda keys: np.bitwise_xor.reduce(upper[slots_np(keys, s, m, "uniform")], 0) == _print_np(keys, s, width)  # noqa: B023, E731
        keys = np.concatenate([pos, neg[own(neg)]])
        cells = 2 * slots_np(keys, s, m, "uniform") + _block_bits_np(keys, s)
        rounds = peel(cells, 2 * m)
        if rounds is None:
            continue
        lower = fill(cells, 2 * m, rounds, (np.arange(len(keys)) < len(pos)).astype(np.uint64))
        return Built(s, m, width + 2, pack(upper << np.uint64(2) | lower[1::2] << np.uint64(1) | lower[0::2], width + 2))
    raise RuntimeError(f"no shared table of {m} blocks found for {len(pos)} of {len(pos) + len(neg)} keys")


def test_shared(f: Built, keys: np.ndarray) -> np.ndarray:
    slots, bits = slots_np(keys, f.seed, f.m, "uniform"), _block_bits_np(keys, f.seed)
    blocks = read_np(f.words, slots.ravel(), f.width).reshape(slots.shape)
    same = np.bitwise_xor.reduce(blocks >> np.uint64(2), 0) == _print_np(keys, f.seed, f.width - 2)
    return same & (np.bitwise_xor.reduce(blocks >> bits.astype(np.uint64) & np.uint64(1), 0) == 1)


def probe_shared(f: Column, key: Column) -> Column:
    return shared_answer(f, key, xor_places(f, key))


def shared_answer(f: Column, key: Column, places: list[Column]) -> Column:
    blocks = [read_at(f["words"], p, f["width"]) for p in places]
    mask = F.call_function("shiftleft", F.lit(1).cast("long"), f["width"] - 2) - 1
    upper = F.shiftrightunsigned(functools.reduce(Column.bitwiseXOR, blocks), 2)
    h = hash_col(f["seed"] + 5, key)
    bit = lambda i: F.call_function("shiftrightunsigned", blocks[i], F.shiftrightunsigned(h, i).bitwiseAND(F.lit(1)).cast("int")).bitwiseAND(F.lit(1))
    return (upper == hash_col(f["seed"] + 9, key).bitwiseAND(mask)) & (bit(0).bitwiseXOR(bit(1)).bitwiseXOR(bit(2)) == 1)


# --- cuckoo filter -----------------------------------------------------------------------------------------------------------


def _cuckoo_np(keys: np.ndarray, seed: int, buckets: int, width: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    print_ = _print_np(keys, seed, width)
    print_ = np.where(print_ == 0, np.uint64(1), print_)
    first = (hash_np(seed, keys) & np.uint64(buckets - 1)).astype(np.int64)
    other = first ^ (hash_np(seed + 1, print_.view(np.int64)) & np.uint64(buckets - 1)).astype(np.int64)
    return print_, first, other


def build_cuckoo(pos: np.ndarray, neg: np.ndarray, eps: float, seed: int) -> Built:
    width = max(2, min(32, math.ceil(math.log2(2 * BUCKET_SLOTS / eps))))
    buckets = 1 << max(1, math.ceil(math.log2(max(1, len(pos)) / (BUCKET_SLOTS * 0.95))))
    for t in range(MAX_TRIES):
        s = seed + 16 * t
        print_, first, other = _cuckoo_np(pos, s, buckets, width)
        cells = _place(print_, first, other, buckets, np.random.default_rng(s))
        if cells is not None:
            return Built(s, buckets * BUCKET_SLOTS, width, pack(cells, width))
        if t % 4 == 3:
            buckets *= 2
    raise RuntimeError("no cuckoo placement found")


def _place(print_: np.ndarray, first: np.ndarray, other: np.ndarray, buckets: int, dice: np.random.Generator, rounds: int = 2000) -> np.ndarray | None:
    """Cells of the table, all keys at once: in a round each homeless key asks its bucket, free places go round, and the rest each turn one key out."""
    slot = np.full((buckets, BUCKET_SLOTS), -1, np.int64)
    asking, at = np.arange(len(print_)), first.copy()
    for r in range(rounds):
        if not len(asking):
            return np.where(slot.ravel() < 0, np.uint64(0), print_[slot.ravel()])
        order = np.argsort(at[asking], kind="stable")
        asking = asking[order]
        bucket = at[asking]
        nth = np.arange(len(bucket)) - np.searchsorted(bucket, bucket)  # place in the queue of the bucket
        free = (slot < 0).sum(1)[bucket]
        fits = nth < free
        # free places are kept at the end of a bucket
        slot[bucket[fits], BUCKET_SLOTS - free[fits] + nth[fits]] = asking[fits]
        bucket, nth, asking = bucket[~fits], (nth - free)[~fits], asking[~fits]
        turn = (nth == 0) & (r % 2 == 1)  # every other round they try their other bucket first
        victim_at = dice.integers(BUCKET_SLOTS, size=int(turn.sum()))
        victims = slot[bucket[turn], victim_at]
        slot[bucket[turn], victim_at] = asking[turn]
        asking = np.concatenate([asking[~turn], victims])
        at[asking] = first[asking] + other[asking] - at[asking]
    return None


def test_cuckoo(f: Built, keys: np.ndarray) -> np.ndarray:
    print_, first, other = _cuckoo_np(keys, f.seed, f.m // BUCKET_SLOTS, f.width)
    hit = np.zeros(len(keys), bool)
    for bucket in (first, other):
        for i in range(BUCKET_SLOTS):
            hit |= read_np(f.words, bucket * BUCKET_SLOTS + i, f.width) == print_
    return hit


def cuckoo_places(f: Column, key: Column) -> list[Column]:
    """The fingerprint and the first bit of either bucket."""
    last = (F.floor(f["m"] / BUCKET_SLOTS) - 1).cast("long")
    mask = F.call_function("shiftleft", F.lit(1).cast("long"), f["width"]) - 1
    print_ = F.greatest(F.lit(1).cast("long"), hash_col(f["seed"] + 9, key).bitwiseAND(mask))
    first = hash_col(f["seed"], key).bitwiseAND(last)
    other = first.bitwiseXOR(hash_col(f["seed"] + 1, print_).bitwiseAND(last))
    return [print_, first * BUCKET_SLOTS * f["width"], other * BUCKET_SLOTS * f["width"]]


def cuckoo_answer(f: Column, key: Column, places: list[Column]) -> Column:
    print_, *buckets = places
    return functools.reduce(Column.__or__, (read_at(f["words"], b + i * f["width"], f["width"]) == print_ for b in buckets for i in range(BUCKET_SLOTS)))


def probe_cuckoo(f: Column, key: Column) -> Column:
    last = (F.floor(f["m"] / BUCKET_SLOTS) - 1).cast("long")
    mask = F.call_function("shiftleft", F.lit(1).cast("long"), f["width"]) - 1
    print_ = F.greatest(F.lit(1).cast("long"), hash_col(f["seed"] + 9, key).bitwiseAND(mask))
    first = hash_col(f["seed"], key).bitwiseAND(last)
    other = first.bitwiseXOR(hash_col(f["seed"] + 1, print_).bitwiseAND(last))
    hit = F.lit(False)
    for bucket in (first, other):
        for i in range(BUCKET_SLOTS):
            hit = hit | (read_col(f["words"], bucket * BUCKET_SLOTS + i, f["width"]) == print_)
    return hit


# --- edge maps: exact, cheap to change -----------------------------------------------------------------------------------------


def nodes_np(keys: np.ndarray, seed: int, m: int) -> tuple[np.ndarray, np.ndarray]:
    """A key's node in either half of the cells."""
    left = (m * 4) // 7
    return below_np(hash_np(seed, keys), left), left + below_np(hash_np(seed + 1, keys), m - left)


def nodes_col(f: Column, key: Column) -> tuple[Column, Column]:
    """The same as expressions."""
    left = F.floor(f["m"] * 4 / 7)
    return below_col(hash_col(f["seed"], key), left), left + below_col(hash_col(f["seed"] + 1, key), f["m"] - left)


def build_edge_map(pos: np.ndarray, neg: np.ndarray, eps: float, seed: int) -> Built:
    """Keys are edges between two arrays of bits; a forest of edges lets the bits at an edge's ends differ exactly for positives."""
    keys = np.concatenate([pos, neg])
    want = np.concatenate([np.ones(len(pos), np.int8), np.zeros(len(neg), np.int8)])
    m = max(14, math.ceil(2.33 * len(keys)) + 8)
    for t in range(MAX_TRIES):
        s = seed + 16 * t
        a, b = nodes_np(keys, s, m)
        cells = two_colour(a, b, want, m)
        if cells is not None:
            return Built(s, m, 1, pack(cells, 1))
        if t % 8 == 7:
            m = math.ceil(m * 1.03)
    raise RuntimeError("no acyclic edge map found")


def two_colour(a: np.ndarray, b: np.ndarray, want: np.ndarray, m: int) -> np.ndarray | None:
    """Bits with ``bit[a] ^ bit[b] = want`` for every edge; None if edges contradict each other.

    Edges with an end that no other edge has are peeled round by round, which empties a forest; edges on cycles, few if any, are
    settled by union-find with parities, and the peeled ones follow from them, the last first.
    """
    rounds, left = _leaves(a, b, m)
    bits = _parities(a[left], b[left], want[left], m)
    if bits is None:
        return None
    for edges, leaf in reversed(rounds):
        other = np.where(a[edges] == leaf, b[edges], a[edges])
        bits[leaf] = bits[other] ^ want[edges].astype(np.uint64)
    return bits


def _leaves(a: np.ndarray, b: np.ndarray, m: int) -> tuple[list[tuple[np.ndarray, np.ndarray]], np.ndarray]:
    """Rounds of (edges, the end that is theirs alone), and the edges that are left."""
    count = np.bincount(np.concatenate([a, b]), minlength=m)
    mixed = np.zeros(m, np.int64)
    names = np.arange(len(a))
    np.bitwise_xor.at(mixed, a, names)
    np.bitwise_xor.at(mixed, b, names)
    alive, rounds = np.ones(len(a), bool), []
    single = np.flatnonzero(count == 1)
    while len(single):
        edges, first = np.unique(mixed[single], return_index=True)
        rounds.append((edges, single[first]))
        alive[edges] = False
        ends = np.concatenate([a[edges], b[edges]])
        np.subtract.at(count, ends, 1)
        np.bitwise_xor.at(mixed, ends, np.tile(edges, 2))
        touched = np.unique(ends)
        single = touched[count[touched] == 1]
    return rounds, np.flatnonzero(alive)


def _parities(a: np.ndarray, b: np.ndarray, want: np.ndarray, m: int) -> np.ndarray | None:
    parent: dict[int, int] = {}
    parity: dict[int, int] = {}

    def find(x: int) -> tuple[int, int]:
        p, path = 0, []
        while parent.setdefault(x, x) != x:
            path.append(x)
            x = parent[x]
        for y in reversed(path):  # nearest the root first: its parity is already to the root
            p ^= parity[y]
            parent[y], parity[y] = x, p
        return x, p

    for x, y, w in zip(a.tolist(), b.tolist(), want.tolist(), strict=True):
        (rx, px), (ry, py) = find(x), find(y)
        if rx == ry:
            if px ^ py != w:
                return None
        else:
            parent[rx], parity[rx] = ry, px ^ py ^ w
    bits = np.zeros(m, np.uint64)
    for x in list(parent):
        bits[x] = find(x)[1]
    return bits


def test_edge_map(f: Built, keys: np.ndarray) -> np.ndarray:
    a, b = nodes_np(keys, f.seed, f.m)
    return read_np(f.words, a, 1) != read_np(f.words, b, 1)


def probe_edge_map(f: Column, key: Column) -> Column:
    return edge_map_answer(f, key, nodes_col(f, key))


def edge_map_answer(f: Column, key: Column, places: tuple[Column, Column]) -> Column:
    a, b = places
    return bit_col(f["words"], a) != bit_col(f["words"], b)


def build_colour_map(pos: np.ndarray, neg: np.ndarray, eps: float, seed: int) -> Built:
    """Nodes have one of four colours, two bits each; the ends of a positive edge share a colour, those of a negative one do not."""
    n = len(pos) + len(neg)
    m = max(14, math.ceil(1.1 * n) + 8)
    for t in range(MAX_TRIES):
        s = seed + 16 * t
        colours = _four_colour(pos, neg, s, m)
        if colours is not None:
            return Built(s, m, 2, pack(colours, 2))
        if t % 4 == 3:
            m = math.ceil(m * 1.05)
    raise RuntimeError("no colouring found")


def _four_colour(pos: np.ndarray, neg: np.ndarray, seed: int, m: int) -> np.ndarray | None:
    parent = list(range(m))

    def find(x: int) -> int:
        while parent[x] != x:
            parent[x] = parent[parent[x]]
            x = parent[x]
        return x

    for x, y in zip(*(v.tolist() for v in nodes_np(pos, seed, m)), strict=True):
        parent[find(x)] = find(y)
    near: dict[int, set[int]] = {}
    for x, y in zip(*(v.tolist() for v in nodes_np(neg, seed, m)), strict=True):
        x, y = find(x), find(y)
        if x == y:
            return None
        near.setdefault(x, set()).add(y)
        near.setdefault(y, set()).add(x)
    degree = {x: len(ys) for x, ys in near.items()}
    easy, gone, order = [x for x, d in degree.items() if d < 4], set(), []
    waiting = deque(sorted(degree, key=degree.__getitem__))
    while len(order) < len(near):
        if not easy:  # none has a colour to spare for certain: try the least entangled
            while waiting and waiting[0] in gone:
                waiting.popleft()
            easy.append(waiting.popleft())
        x = easy.pop()
        if x in gone:
            continue
        gone.add(x)
        order.append(x)
        for y in near[x]:
            degree[y] -= 1
            if degree[y] == 3 and y not in gone:
                easy.append(y)
    colour: dict[int, int] = {}
    for x in reversed(order):
        free = {0, 1, 2, 3} - {colour[y] for y in near[x] if y in colour}
        if not free:
            return None
        colour[x] = min(free)
    return np.array([colour.get(find(x), 0) for x in range(m)], np.uint64)


def test_colour_map(f: Built, keys: np.ndarray) -> np.ndarray:
    a, b = nodes_np(keys, f.seed, f.m)
    return read_np(f.words, a, 2) == read_np(f.words, b, 2)


def probe_colour_map(f: Column, key: Column) -> Column:
    return colour_map_answer(f, key, nodes_col(f, key))


def colour_map_answer(f: Column, key: Column, places: tuple[Column, Column]) -> Column:
    a, b = places
    return read_col(f["words"], a, 2) == read_col(f["words"], b, 2)


# --- the kinds by name ---------------------------------------------------------------------------------------------------------


@dataclass(frozen=True)
class Kind:
    """``build(pos, neg, eps, seed, **options)``, ``test(built, keys, **shape)``, ``probe(struct, key, **shape)``; ``exact`` kinds use the negatives.

    ``places`` and ``answer`` are a probe in two steps: the places in the table first, which are then read.
    """

    build: Callable
    test: Callable
    probe: Callable
    exact: bool = False
    hashes: bool = False
    cell_bits: int = 0  # 0: the struct's width
    shape: tuple[str, ...] = ()
    places: Callable | None = None
    answer: Callable | None = None


KINDS = {
    "bloom": Kind(build_bloom, test_bloom, probe_bloom, hashes=True, cell_bits=1, places=bloom_places, answer=bloom_answer),
    "blocked": Kind(build_blocked, test_blocked, probe_blocked, hashes=True, cell_bits=1, places=blocked_places, answer=bloom_answer),
    "counting": Kind(build_counting, test_counting, probe_counting, hashes=True, cell_bits=4, places=bloom_places, answer=functools.partial(bloom_answer, cell=4)),
    "xor": Kind(build_xor, test_xor, probe_xor, shape=("layout", "j"), places=xor_places, answer=xor_answer),
    "retrieval": Kind(build_retrieval, test_retrieval, probe_retrieval, exact=True, shape=("layout", "strategy", "j"), places=xor_places, answer=retrieval_answer),
    "shared": Kind(build_shared, test_shared, probe_shared, exact=True, places=xor_places, answer=shared_answer),
    "cuckoo": Kind(build_cuckoo, test_cuckoo, probe_cuckoo, places=cuckoo_places, answer=cuckoo_answer),
    "edge_map": Kind(build_edge_map, test_edge_map, probe_edge_map, exact=True, places=nodes_col, answer=edge_map_answer),
    "colour_map": Kind(build_colour_map, test_colour_map, probe_colour_map, exact=True, places=nodes_col, answer=colour_map_answer),
}
