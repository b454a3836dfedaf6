"""One block of a transformed collection: local alphabet, move-to-front, zero runs, sealing and bit packing."""

from __future__ import annotations

import heapq
from dataclasses import dataclass

import numpy as np

from seqvault.cipher import KeyStream, add_many, block_nonce, seal_add, seal_xor, unseal_add

#: Blocks of a superblock.
PER_SUPER = 16
#: Blocks coded at once, at most, and their symbols.
BATCH, SYMBOLS = 512, 1 << 21
#: Elements that are counted at once: their arrays stay in a core's cache.
CACHED = 1 << 16


def remap_local(syms: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Ascending symbols of a block and each position's index among them."""
    alpha, codes = np.unique(syms, return_inverse=True)
    return alpha, codes.astype(np.int64)


def mtf(codes: np.ndarray, size: int) -> np.ndarray:
    """Move-to-front ranks, from an ascending list. Only positions where the symbol changes are worked on."""
    out = np.zeros(len(codes), np.int64)
    if not len(codes):
        return out
    table = list(range(size))
    moves = np.flatnonzero(np.append(True, codes[1:] != codes[:-1]))
    for i, c in zip(moves.tolist(), codes[moves].tolist(), strict=True):
        if table[0] != c:
            out[i] = r = table.index(c)
            del table[r]
            table.insert(0, c)
    return out


def _fronts(ranks: np.ndarray, size: int) -> list[int]:
    """What each of the ``ranks`` brings to the front of an ascending list. The list is held back to front: a symbol is taken
    out near its end and put at its end."""
    table = list(range(size - 1, -1, -1))
    pop, push, out = table.pop, table.append, []
    for r in (-1 - ranks).tolist():
        c = pop(r)
        push(c)
        out.append(c)
    return out


def unmtf(ranks: np.ndarray, size: int) -> np.ndarray:
    moves = np.flatnonzero(ranks)
    fronts = np.array([0, *_fronts(ranks[moves], size)], np.int64)
    return np.repeat(fronts, np.diff(np.concatenate([[0], moves, [len(ranks)]])))


def rle0(ranks: np.ndarray) -> np.ndarray:
    """Runs of zeros as bijective base-2 digits 0 and 1 (low digit first); a value v > 0 becomes v + 1."""
    zero = ranks == 0
    edge = np.flatnonzero(np.diff(np.concatenate([[0], zero.astype(np.int8), [0]])))
    out: list[np.ndarray] = []
    at = 0
    for low, high in zip(edge[::2].tolist(), edge[1::2].tolist(), strict=True):
        out.append(ranks[at:low] + 1)
        digits, n = [], high - low
        while n:
            n, digit = (n - 1) // 2, (n - 1) % 2
            digits.append(digit)
        out.append(np.array(digits, np.int64))
        at = high
    out.append(ranks[at:] + 1)
    return np.concatenate(out)


def unrle0(codes: np.ndarray) -> np.ndarray:
    digit = codes < 2
    edge = np.flatnonzero(np.diff(np.concatenate([[0], digit.astype(np.int8), [0]])))
    out: list[np.ndarray] = []
    at = 0
    for low, high in zip(edge[::2].tolist(), edge[1::2].tolist(), strict=True):
        out.append(codes[at:low] - 1)
        length = sum((d + 1) << i for i, d in enumerate(codes[low:high].tolist()))
        out.append(np.zeros(length, np.int64))
        at = high
    out.append(codes[at:] - 1)
    return np.concatenate(out)


def bits_for(m: int) -> int:
    """Bits that hold 0..m-1."""
    return max(0, int(m - 1).bit_length())


def pack_bits(codes: np.ndarray, bits: int) -> bytes:
    if not bits:
        return b""
    each = (codes[:, None] >> np.arange(bits - 1, -1, -1)) & 1
    return np.packbits(each.astype(np.uint8).reshape(-1)).tobytes()


def unpack_bits(data: bytes, bits: int, n: int) -> np.ndarray:
    if not bits:
        return np.zeros(n, np.int64)
    flat = np.unpackbits(np.frombuffer(data, np.uint8), count=n * bits).reshape(n, bits).astype(np.int64)
    return flat @ (1 << np.arange(bits - 1, -1, -1, dtype=np.int64))


@dataclass(frozen=True)
class Coding:
    """How blocks are sealed. ``mode``: add (modulo the alphabet) or xor (over packed bytes)."""

    encrypt: bool = True
    mode: str = "add"
    rounds: int = 20


@dataclass
class SealedBlock:
    n: int
    comp_len: int
    bits: int
    alpha: np.ndarray
    counts: np.ndarray
    payload: bytes


def encode_block(syms: np.ndarray, block_no: int, key: bytes, coding: Coding) -> SealedBlock:
    """All steps of a block at once. The modulus is one more than the local alphabet: zero runs add a symbol."""
    alpha, codes = remap_local(syms)
    runs = rle0(mtf(codes, len(alpha)))
    m = len(alpha) + 1
    stream = KeyStream(key, block_nonce(block_no), coding.rounds)
    if coding.encrypt and coding.mode == "add":
        runs = seal_add(runs, stream, m)
    payload = pack_bits(runs, bits_for(m))
    if coding.encrypt and coding.mode == "xor":
        payload = seal_xor(payload, stream)
    return SealedBlock(len(syms), len(runs), bits_for(m), alpha, np.bincount(codes, minlength=len(alpha)), payload)


def decode_block(block: SealedBlock, block_no: int, key: bytes, coding: Coding) -> np.ndarray:
    """The symbols of a block. With a wrong key the result has the right length and other symbols."""
    m = len(block.alpha) + 1
    stream = KeyStream(key, block_nonce(block_no), coding.rounds)
    payload = seal_xor(block.payload, stream) if coding.encrypt and coding.mode == "xor" else block.payload
    runs = unpack_bits(payload, block.bits, block.comp_len)
    if coding.encrypt and coding.mode == "add":
        runs = unseal_add(runs, stream, m)
    try:
        values, length, _ = unrle0_many(runs, np.array([len(runs)]))
        codes = unmtf(np.repeat(values, np.minimum(length, block.n)), len(block.alpha))
    except (IndexError, MemoryError, OverflowError):
        codes = np.zeros(0, np.int64)
    if len(codes) != block.n:  # only a wrong key leads here
        codes = np.resize(codes, block.n) if len(codes) else np.zeros(block.n, np.int64)
    return block.alpha[np.minimum(codes, len(block.alpha) - 1)]


def _smaller_before(value: np.ndarray, counts: np.ndarray) -> np.ndarray:
    """For each element, how many before it in its block are smaller. Blocks of ``counts`` elements hold 0, 1, .. once each.

    Blocks are split by the bits of their elements, the highest first: an element with a bit set counts those before it in
    its part that lack it. Parts of a width of a power of two have halves of equal size, so all blocks take a step at once.
    """
    out = np.empty(len(value), np.int64)
    starts = np.cumsum(counts) - counts
    widths = np.where(counts > 0, 1 << np.frexp(np.maximum(counts - 1, 0).astype(np.float64))[1].astype(np.int64), 0)
    for width in np.unique(widths[widths > 0]).tolist():
        # an element, and in the high half of the number how many were counted for it
        kind, shift = (np.uint32, 16) if width <= 1 << 16 else (np.uint64, 32)
        those = np.flatnonzero(widths == width)
        lot = max(1, CACHED // width)
        for i in range(0, len(those), lot):
            mine = those[i : i + lot]
            n = counts[mine]
            inside = np.arange(int(n.sum())) - np.repeat(np.cumsum(n) - n, n)
            row, source = np.repeat(np.arange(len(mine)) * width, n), np.repeat(starts[mine], n) + inside
            v = np.tile(np.arange(width, dtype=kind), len(mine))
            v[row + inside] = value[source]
            half = width
            while half > 1:
                half //= 2
                high = (v & kind(half)) > 0
                low = ~high
                before = np.cumsum(low, dtype=kind).reshape(-1, 2 * half)
                before -= np.arange(0, len(v) // 2, half, dtype=kind)[:, None]
                before <<= kind(shift)
                v += before.reshape(-1) * high
                v = np.concatenate([v[np.flatnonzero(x)].reshape(-1, half) for x in (low, high)], axis=1).reshape(-1)
            out[source] = v[row + value[source]] >> kind(shift)
    return out


def _ranks(codes: np.ndarray, counts: np.ndarray, size: int) -> np.ndarray:
    """Move-to-front ranks of the codes below ``size`` of blocks with ``counts`` codes, whatever the size of their alphabets.

    Before a code that stood at p last stand those seen since: the codes from p on whose own last place is before p. For a
    code not seen yet, those seen so far and the smaller ones.
    """
    n, block, starts = len(codes), np.repeat(np.arange(len(counts)), counts), np.cumsum(counts) - counts
    bits = max(1, (n - 1).bit_length())
    packed = ((block * size + codes) << bits) | np.arange(n)
    packed.sort()
    at, key = packed & ((1 << bits) - 1), packed >> bits
    head = np.append(True, key[1:] != key[:-1])[:n]
    before, follows = np.full(n, -1), np.zeros(n, bool)
    before[at[1:][~head[1:]]] = at[:-1][~head[1:]]
    follows[at[:-1][~head[1:]]] = True
    first = before < 0
    n_first = np.bincount(block[first], minlength=len(counts))
    value = np.empty(n, np.int64)
    heads = at[head]  # by block, then by code
    value[heads] = (np.cumsum(n_first)[block[heads]] - 1) - np.arange(len(heads))
    held = np.append(0, np.cumsum(follows))
    again = np.flatnonzero(~first)
    value[again] = n_first[block[again]] + held[before[again]] - held[starts[block[again]]]
    smaller = _smaller_before(value, counts)
    return np.where(first, codes + smaller, smaller - (before - starts[block]) - 1)


def mtf_many(codes: np.ndarray, first: np.ndarray, size: int) -> np.ndarray:
    """:func:`mtf` of blocks that begin at ``first``, one after another in ``codes``."""
    out = np.zeros(len(codes), np.int64)
    new = np.append(True, codes[1:] != codes[:-1])
    new[first] = True
    moves = np.flatnonzero(new)
    counts = np.diff(np.append(np.searchsorted(moves, first), len(moves)))
    out[moves] = _ranks(codes[moves], counts, size)
    return out


def unmtf_many(ranks: np.ndarray, first: np.ndarray, sizes: np.ndarray) -> np.ndarray:
    """:func:`unmtf` of blocks that begin at ``first``, with alphabets of ``sizes``."""
    moves = np.flatnonzero(ranks)
    counts = np.diff(np.append(np.searchsorted(moves, first), len(moves)))
    fronts = np.zeros(len(ranks), np.int64)
    taken, at = ranks[moves], 0
    for size, n in zip(sizes.tolist(), counts.tolist(), strict=True):
        fronts[moves[at : at + n]] = _fronts(taken[at : at + n], size)
        at += n
    keeps = np.zeros(len(ranks), np.int64)
    keeps[moves], keeps[first] = moves, first
    return fronts[np.maximum.accumulate(keeps)]


def rle0_many(ranks: np.ndarray, first: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """:func:`rle0` of blocks that begin at ``first``, and how many codes each has. The digits of a run are the binary ones
    of its length and one, without the highest."""
    zero = ranks == 0
    head = zero & np.append(True, ~zero[:-1])
    head[first] = zero[first]
    token = np.flatnonzero(~zero | head)
    runs = zero[token]
    longer = np.diff(np.append(token, len(ranks))) + 1
    n = np.where(runs, np.frexp(longer.astype(np.float64))[1] - 1, 1).astype(np.int64)
    ends = np.cumsum(n)
    digit = np.arange(ends[-1] if len(ends) else 0) - np.repeat(ends - n, n)
    out = np.where(np.repeat(runs, n), np.repeat(longer, n) >> digit & 1, np.repeat(ranks[token] + 1, n))
    before = np.append(0, ends)[np.searchsorted(token, np.append(first, len(ranks)))]
    return out, np.diff(before)


def unrle0_many(codes: np.ndarray, sizes: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Of blocks with ``sizes`` codes: the value and the length of each run, and each block's length in all."""
    ends = np.cumsum(sizes)
    digit = codes < 2
    head = digit & np.append(True, ~digit[:-1])
    first = (ends - sizes)[sizes > 0]
    head[first] = digit[first]
    token = np.flatnonzero(~digit | head)
    place = np.arange(len(codes)) - np.repeat(token, np.diff(np.append(token, len(codes))))
    worth = np.where(digit, (codes + 1) << np.minimum(place, 40), 1)  # only a wrong key has longer ones
    length = np.add.reduceat(worth, token) if len(token) else worth
    total = np.append(0, np.cumsum(length))[np.searchsorted(token, np.append(ends - sizes, len(codes)))]
    return np.where(digit[token], 0, codes[token] - 1), length, np.diff(total)


def encode_blocks(syms: np.ndarray, bs: int, key: bytes, coding: Coding) -> list[SealedBlock]:
    """:func:`encode_block` of all blocks of a transform, of which many take each step at once."""
    if coding.encrypt and coding.mode != "add":
        return [encode_block(syms[i : i + bs], i // bs, key, coding) for i in range(0, len(syms), bs)]
    out: list[SealedBlock] = []
    lot = bs * max(1, min(BATCH, SYMBOLS // bs))
    for low in range(0, len(syms), lot):
        some = syms[low : low + lot]
        first = np.arange(0, len(some), bs)
        local = [remap_local(some[i : i + bs]) for i in first.tolist()]
        m = np.array([len(a) + 1 for a, _ in local], np.int64)
        runs, sizes = rle0_many(mtf_many(np.concatenate([c for _, c in local]), first, int(m.max()) - 1), first)
        if coding.encrypt:
            runs = add_many(runs, sizes, key, len(out) + np.arange(len(first)), m, coding.rounds, 1)
        ends = np.cumsum(sizes)
        for (alpha, codes), end, size in zip(local, ends.tolist(), sizes.tolist(), strict=True):
            bits = bits_for(len(alpha) + 1)
            out.append(SealedBlock(len(codes), size, bits, alpha, np.bincount(codes, minlength=len(alpha)), pack_bits(runs[end - size : end], bits)))
    return out


def decode_blocks(blocks: list[SealedBlock], start: int | np.ndarray, key: bytes, coding: Coding) -> list[np.ndarray]:
    """:func:`decode_block` of consecutive blocks from number ``start`` on, or of those with the numbers ``start``."""
    number = np.zeros(len(blocks), np.int64) + start + (np.arange(len(blocks)) if np.ndim(start) == 0 else 0)
    if coding.encrypt and coding.mode != "add":
        return [decode_block(b, int(i), key, coding) for i, b in zip(number, blocks, strict=True)]
    out: list[np.ndarray] = []
    for low in range(0, len(blocks), BATCH):
        some = blocks[low : low + BATCH]
        sizes = np.array([b.comp_len for b in some], np.int64)
        m = np.array([len(b.alpha) + 1 for b in some], np.int64)
        n = np.array([b.n for b in some], np.int64)
        runs = np.concatenate([unpack_bits(b.payload, b.bits, b.comp_len) for b in some])
        if coding.encrypt:
            runs = add_many(runs, sizes, key, number[low : low + BATCH], m, coding.rounds, -1)
        values, length, total = unrle0_many(runs, sizes)
        flat = np.repeat(values, length) if (total == n).all() else None
        if flat is None or (flat >= np.repeat(m - 1, n)).any():
            out += [decode_block(b, int(i), key, coding) for i, b in zip(number[low : low + BATCH], some, strict=True)]  # only a wrong key leads here
            continue
        first = np.cumsum(n) - n
        codes = unmtf_many(flat, first, m - 1)
        out += [b.alpha[np.minimum(codes[f : f + b.n], len(b.alpha) - 1)] for f, b in zip(first.tolist(), some, strict=True)]
    return out


def huffman_bits(codes: np.ndarray) -> int:
    """Bits that one Huffman table would take for ``codes``: the coder that the sealed form does without."""
    heap = np.unique(codes, return_counts=True)[1].tolist()
    if len(heap) < 2:
        return len(codes)
    heapq.heapify(heap)
    total = 0
    while len(heap) > 1:
        pair = heapq.heappop(heap) + heapq.heappop(heap)
        total += pair
        heapq.heappush(heap, pair)
    return total
