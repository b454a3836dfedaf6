"""Search inside one shard of a sealed index: counts by block, blocks opened only where a query needs them.

Patterns are searched together: all displaced block patterns take their backward steps side by side as arrays, and a block
that several of them need in a step is looked at once for all.
"""

from __future__ import annotations

import itertools
import zlib
from collections import OrderedDict
from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
import pyarrow.dataset as ds

from seqvault import planner
from seqvault.alphabet import Alphabet
from seqvault.blocks import BATCH, Coding, SealedBlock, decode_block, decode_blocks
from seqvault.cipher import block_key
from seqvault.operators.shared_fs import resolve
from seqvault.pieces import whole_hits

#: Bytes of opened blocks, and of sealed payloads, that an open shard remembers.
OPEN_BYTES, SEALED_BYTES = 96 << 20, 32 << 20
#: Blocks from which on it pays to open them side by side.
TOGETHER = 8
#: Patterns planned together, at least and at most, their letters, and rows expanded together.
LOT, MOST, LOT_LETTERS, ROWS = 256, 4096, 1 << 18, 1 << 20
#: Places in the tables of symbols that fit the masks of patterns planned together.
FITS = 1 << 26


class WrongKey(ValueError):
    """A block's checksum does not fit the key."""


@dataclass
class Work:
    """What a search did: marked rows walked to, steps taken, rows checked at the last block."""

    lf_steps: int = 0
    checked: int = 0
    loaded: set[int] = field(default_factory=set)


@dataclass(frozen=True)
class Plans:
    """Displaced block patterns as places among a shard's used symbols: the fixed blocks are ``spots`` from ``begin`` to
    ``end``; ``first`` and ``last`` number, in ``fits``, the symbols that fit a masked first and last block (-1: it is fixed).
    A pattern of one block has ``first`` only."""

    pattern: np.ndarray
    d: np.ndarray
    m: np.ndarray
    first: np.ndarray
    last: np.ndarray
    begin: np.ndarray
    end: np.ndarray
    spots: np.ndarray
    fits: list[np.ndarray]

    def fitting(self, which: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """How many symbols fit each of ``which``, and all of them one after another."""
        n = np.array([len(f) for f in self.fits], np.int64)[which]
        return n, np.concatenate([np.zeros(0, np.int64), *(self.fits[i] for i in which.tolist())])


class ShardFM:
    """The index of one shard. Counts and marks are in memory; payloads are read by row group and opened by block."""

    def __init__(self, path: str, shard: int, meta: dict, key: bytes, commit: str, order: np.ndarray | None):
        self.meta, self.shard = meta, shard
        self.alphabet = Alphabet(tuple(meta["letters"]), meta["k"])
        self.k, self.bs, self.step = meta["k"], meta["bs"], meta["mark_step"]
        self.coding = Coding(meta["encrypt"], meta["cipher_mode"], meta["rounds"])
        self.key = block_key(key, bytes.fromhex(meta["commits"][commit]), shard, meta["nonce_mode"])
        self.order = order
        self.pad = meta["pad_wildcards"]
        self.piece = meta.get("piece", 0)
        self.folder = lambda kind: f"{path}/tables/commit={commit}/kind={kind}/shard={shard}"
        c = self._read("c_table", ["no", "a"]).sort_by("no")
        self.syms, self.c_before = c["no"].to_numpy(), c["a"].to_numpy()
        self.digits = planner.used_symbols(self.alphabet, self.order, self.syms)
        items = self._read("items", ["no", "b", "c", "a"])
        by_start = np.argsort(items["b"].to_numpy(), kind="stable")
        self.item_no, self.item_start, self.item_blocks, self.item_length = (items[x].to_numpy()[by_start] for x in ("no", "b", "c", "a"))
        marks = self._read("marks", ["no", "a"])
        by_row = np.argsort(marks["no"].to_numpy())
        self.mark_rows, self.mark_pos = marks["no"].to_numpy()[by_row], marks["a"].to_numpy()[by_row]
        self.row_of_mark = marks["no"].to_numpy()[np.argsort(marks["a"].to_numpy())]
        head = self._read("blocks", ["no", "a", "b", "c", "ints", "longs", "text"]).sort_by("no").combine_chunks()
        self.block_n, self.comp_len, self.bits = (head[x].to_numpy() for x in ("a", "b", "c"))
        self.checks = head["text"]
        self.n = int(self.block_n.sum())
        self.n_blocks = len(self.block_n)
        sizes = pc.list_value_length(head["ints"]).to_numpy()
        self.ends = np.cumsum(sizes)
        self.alpha = pc.list_flatten(head["ints"]).to_numpy().astype(np.int64)
        self.counts = pc.list_flatten(head["longs"]).to_numpy()
        owner = np.repeat(np.arange(self.n_blocks), sizes)
        spot = np.searchsorted(self.syms, self.alpha)
        turn = np.lexsort((owner, spot))
        self.pair = (spot * self.n_blocks + owner)[turn]
        self.pair_count = self.counts[turn]
        total = np.cumsum(self.pair_count) - self.pair_count
        first = np.searchsorted(self.pair, np.arange(len(self.syms)) * self.n_blocks)
        self.pair_before = total - np.repeat(total[first], np.diff(np.append(first, len(total)))) if len(total) else total
        self.groups: list[tuple[object, int, int]] | None = None
        self.payloads: OrderedDict[int, dict[int, bytes]] = OrderedDict()
        self.payload_bytes = 0
        self.open: OrderedDict[int, tuple[np.ndarray, np.ndarray, np.ndarray]] = OrderedDict()
        self.work = Work()

    def _read(self, kind: str, columns: list[str]) -> pa.Table:
        store, root = resolve(self.folder(kind))
        return ds.dataset(root, filesystem=store, format="parquet").to_table(columns=columns)

    # blocks

    def _payload(self, b: int) -> bytes:
        """A block's sealed bytes: the row group that holds it is read; the last read ones are kept, up to SEALED_BYTES."""
        if self.groups is None:
            store, root = resolve(self.folder("blocks"))
            self.groups = []
            for fragment in ds.dataset(root, filesystem=store, format="parquet").get_fragments():
                for piece in fragment.split_by_row_group():
                    span = piece.row_groups[0].statistics["no"]
                    self.groups.append((piece, span["min"], span["max"]))
        for g, (piece, low, high) in enumerate(self.groups):
            if not low <= b <= high:
                continue
            if g not in self.payloads:
                table = piece.to_table(columns=["no", "payload"])
                self.payloads[g] = dict(zip(table["no"].to_pylist(), table["payload"].to_pylist(), strict=True))
                self.payload_bytes += sum(map(len, self.payloads[g].values()))
                while self.payload_bytes > SEALED_BYTES and len(self.payloads) > 1:
                    _, gone = self.payloads.popitem(last=False)
                    self.payload_bytes -= sum(map(len, gone.values()))
            self.payloads.move_to_end(g)
            if b in self.payloads[g]:
                return self.payloads[g][b]
        raise KeyError(f"shard {self.shard} has no block {b}")

    def _sealed(self, b: int) -> SealedBlock:
        low = self.ends[b - 1] if b else 0
        alpha, counts = self.alpha[low : self.ends[b]], self.counts[low : self.ends[b]]
        return SealedBlock(int(self.block_n[b]), int(self.comp_len[b]), int(self.bits[b]), alpha, counts, self._payload(b))

    def _checked(self, b: int, syms: np.ndarray) -> np.ndarray:
        check = self.checks[b].as_py()
        if check and f"{zlib.crc32(syms.astype('<i8').tobytes()):08x}" != check:
            raise WrongKey(f"block {b} of shard {self.shard} does not open with this key")
        return syms

    def _opened(self, b: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Of a block: the place of each symbol among the used ones, how many equal ones stand before it in the block, and
        place * block size + position of all in ascending order."""
        self.work.loaded.add(b)
        if b in self.open:
            self.open.move_to_end(b)
            return self.open[b]
        return self._keep(b, self._checked(b, decode_block(self._sealed(b), b, self.key, self.coding)))

    def _keep(self, b: int, syms: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        spots = np.minimum(np.searchsorted(self.syms, syms), len(self.syms) - 1)
        keys = np.sort(spots * self.bs + np.arange(len(spots)))
        ordered = keys // self.bs
        heads = np.flatnonzero(np.append(True, ordered[1:] != ordered[:-1]))
        rank = np.empty(len(syms), np.int64)
        rank[keys % self.bs] = np.arange(len(syms)) - np.repeat(heads, np.diff(np.append(heads, len(syms))))
        self.open[b] = (spots, rank, keys)
        if len(self.open) > self._stay():
            self.open.popitem(last=False)
        return self.open[b]

    def _stay(self) -> int:
        """Blocks that stay open."""
        return max(16, OPEN_BYTES // (24 * self.bs))

    def keeps_all(self) -> bool:
        """Whether all blocks can stay open at once."""
        return self.n_blocks <= self._stay()

    def _open_many(self, numbers: np.ndarray) -> None:
        """Open blocks that a step needs side by side, as many as stay open."""
        missing = [b for b in numbers.tolist() if b not in self.open][: self._stay() // 2]
        if len(missing) < TOGETHER:
            return
        for low in range(0, len(missing), BATCH):
            some = missing[low : low + BATCH]
            for b, syms in zip(some, decode_blocks([self._sealed(b) for b in some], np.array(some), self.key, self.coding), strict=True):
                self._keep(b, self._checked(b, syms))

    def block(self, b: int) -> tuple[np.ndarray, np.ndarray]:
        """Symbols of a block and, for every position, how many equal ones stand before it in the block."""
        spots, rank, _ = self._opened(b)
        return self.syms[spots], rank

    # counting and stepping

    def occ_many(self, spots: np.ndarray, rows: np.ndarray) -> np.ndarray:
        """How often the ``spots``-th used symbols stand in the rows before ``rows``."""
        b = np.clip(rows // self.bs, 0, self.n_blocks - 1)
        at = np.maximum(np.searchsorted(self.pair, spots * self.n_blocks + b, "right") - 1, 0)
        found = (self.pair[at] // self.n_blocks == spots) & (self.pair[at] <= spots * self.n_blocks + b) & (rows > 0)
        inside = found & (self.pair[at] % self.n_blocks == b)
        out = np.where(found, self.pair_before[at] + np.where(inside, 0, self.pair_count[at]), 0)
        # a row at the start of a block needs nothing of it
        mine = np.flatnonzero(inside & (rows > b * self.bs))
        mine = mine[np.argsort(b[mine], kind="stable")]
        if not len(mine):
            return out
        cuts = np.flatnonzero(np.diff(b[mine], prepend=-1))
        self._open_many(b[mine[cuts]])
        for low, high in zip(cuts, np.append(cuts[1:], len(mine)), strict=True):
            m = mine[low:high]
            number = int(b[m[0]])
            keys = self._opened(number)[2]
            base = spots[m] * self.bs
            # a whole last block may be as long as the block size: its end is the start of the next symbol
            out[m] += np.searchsorted(keys, base + (rows[m] - number * self.bs)) - np.searchsorted(keys, base)
        return out

    def symbol_ranges(self, spots: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        ends = np.append(self.c_before[1:], self.n)
        return self.c_before[spots].astype(np.int64), ends[spots].astype(np.int64)

    def backward_many(self, low: np.ndarray, high: np.ndarray, flat: np.ndarray, at: np.ndarray, sizes: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Ranges of rows after each chain of symbols is put before what [low, high) stands for; empty ones are (0, 0).

        A chain is ``sizes`` symbols of ``flat``, from ``at`` on backwards.
        """
        low, high = low.copy(), high.copy()
        active, step = np.flatnonzero((low < high) & (sizes > 0)), 0
        while len(active):
            s = flat[at[active] - step]
            got = self.occ_many(np.concatenate([s, s]), np.concatenate([low[active], high[active]]))
            base = self.c_before[s]
            low[active], high[active] = base + got[: len(s)], base + got[len(s) :]
            step += 1
            active = active[(low[active] < high[active]) & (sizes[active] > step)]
        empty = low >= high
        low[empty] = high[empty] = 0
        return low, high

    def symbols_and_lf(self, rows: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Symbol before each row's suffix (as its place among the used ones) and the row of the suffix one longer."""
        spots, lf = np.empty(len(rows), np.int64), np.empty(len(rows), np.int64)
        number = rows // self.bs
        turn = np.argsort(number, kind="stable")
        cuts = np.flatnonzero(np.diff(number[turn], prepend=-1))
        self._open_many(number[turn[cuts]])
        for low, high in zip(cuts, np.append(cuts[1:], len(turn)), strict=True):
            mine = turn[low:high]
            b = int(number[mine[0]])
            held, rank, _ = self._opened(b)
            local = rows[mine] - b * self.bs
            spot = held[local]
            at = np.minimum(np.searchsorted(self.pair, spot * self.n_blocks + b), len(self.pair) - 1)
            spots[mine] = spot
            lf[mine] = self.c_before[spot] + self.pair_before[at] + rank[local]
        self.work.lf_steps += len(rows)
        return spots, np.minimum(lf, self.n - 1)

    def positions(self, rows: np.ndarray) -> np.ndarray:
        """Text position of each row: walk back to a marked one."""
        out = np.full(len(rows), -1, np.int64)
        walk, at, steps = np.arange(len(rows)), np.asarray(rows, np.int64).copy(), 0
        while len(walk) and steps <= self.step + 1:
            spot = np.minimum(np.searchsorted(self.mark_rows, at), len(self.mark_rows) - 1)
            marked = self.mark_rows[spot] == at
            out[walk[marked]] = self.mark_pos[spot[marked]] + steps
            walk, at = walk[~marked], at[~marked]
            if len(walk):
                _, at = self.symbols_and_lf(at)
            steps += 1
        return out

    def symbols_at(self, positions: np.ndarray) -> np.ndarray:
        """Place among the used symbols of the symbol at each text position: walk back from the next mark."""
        mark = positions // self.step + 1
        start = np.minimum(mark * self.step, self.n)
        rows = self.row_of_mark[np.where(mark * self.step < self.n, mark, 0)]
        out = np.empty(len(positions), np.int64)
        walk, left = np.arange(len(positions)), start - 1 - positions
        while len(walk):
            spots, rows = self.symbols_and_lf(rows)
            done = left == 0
            out[walk[done]] = spots[done]
            walk, rows, left = walk[~done], rows[~done], left[~done] - 1
        return out

    # patterns

    def spots_of(self, ids: np.ndarray) -> np.ndarray:
        """Places among the used symbols of blocks, -1 for those that the shard lacks."""
        syms = self.order[ids] if self.order is not None else ids
        spot = np.minimum(np.searchsorted(self.syms, syms), len(self.syms) - 1)
        return np.where(self.syms[spot] == syms, spot, -1)

    def fitting(self, mask: np.ndarray) -> np.ndarray:
        return np.flatnonzero(planner.mask_matches(self.digits, mask, self.pad))

    def lots(self, patterns: list[str]) -> Iterator[tuple[int, list[str]]]:
        """Patterns that are planned together, and how many come before: so many that their tables stay small."""
        most = max(LOT, min(MOST, FITS // (self.k * max(1, len(self.syms)))))
        low = letters = 0
        for i, pattern in enumerate(patterns):
            if i > low and (i - low >= most or letters + len(pattern) > LOT_LETTERS):
                yield low, patterns[low:i]
                low, letters = i, 0
            letters += len(pattern)
        if patterns:
            yield low, patterns[low:]

    def planned(self, patterns: list[str]) -> Plans:
        """The displaced block patterns of each pattern that this shard's symbols allow."""
        lot = planner.planned_lot(tuple(patterns), self.alphabet)
        spots = self.spots_of(lot.ids)
        lacks = np.append(0, np.cumsum(spots < 0))
        held = np.flatnonzero(lacks[lot.end] == lacks[lot.begin])
        asked = np.zeros(len(lot.masks) + 1, bool)  # the last place stands for none
        asked[lot.first[held]] = asked[lot.last[held]] = True
        none = np.zeros(0, np.int64)
        fits = [self.fitting(mask) if on else none for mask, on in zip(lot.masks, asked.tolist(), strict=False)]
        some = np.array([len(f) > 0 for f in fits] + [True])
        held = held[some[lot.first[held]] & some[lot.last[held]]]
        return Plans(*(x[held] for x in (lot.pattern, lot.d, lot.m, lot.first, lot.last, lot.begin, lot.end)), spots, fits)

    def states(self, plans: Plans, last: str) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray, np.ndarray]]:
        """Ranges of rows that answer ``plans``: number of the plan, low, high, whether the first block is still to be
        matched against its mask, and whether the last is to be verified.

        A masked last block is verified row by row or enumerated symbol by symbol; ``auto`` decides when it knows how many
        rows the fixed blocks leave.
        """
        n_fixed, ends_masked = plans.end - plans.begin, plans.last >= 0

        def of_first(j: np.ndarray, verify: bool):
            n, fits = plans.fitting(plans.first[j])
            number = np.repeat(j, n)
            return number, *self.symbol_ranges(fits), np.zeros(len(number), bool), np.full(len(number), verify)

        short = np.flatnonzero(plans.m == 1)
        if len(short):
            yield of_first(short, False)
        # fixed blocks alone: answers where nothing follows them, else candidates
        j = np.flatnonzero((plans.m > 1) & (n_fixed > 0) & (~ends_masked | (last != "enumerate")))
        enumerated = np.flatnonzero((plans.m > 1) & ends_masked & ((n_fixed == 0) | (last == "enumerate")))
        if len(j):
            low, high = self.symbol_ranges(plans.spots[plans.end[j] - 1])
            low, high = self.backward_many(low, high, plans.spots, plans.end[j] - 2, n_fixed[j] - 1)
            found = low < high
            if last == "auto":
                n = np.array([len(f) for f in plans.fits] + [0], np.int64)[plans.last[j]]
                turned = found & ends_masked[j] & planner.enumerates(high - low, self.step, n, plans.m[j])
                enumerated, found = np.concatenate([enumerated, j[turned]]), found & ~turned
            j = j[found]
            yield j, low[found], high[found], plans.first[j] >= 0, ends_masked[j]
        if last == "verify":  # both blocks masked: every row of a fitting first block
            open_, enumerated = enumerated[n_fixed[enumerated] == 0], enumerated[n_fixed[enumerated] > 0]
            if len(open_):
                yield of_first(open_, True)
        if len(enumerated):
            n, fits = plans.fitting(plans.last[enumerated])
            number = np.repeat(enumerated, n)
            low, high = self.backward_many(*self.symbol_ranges(fits), plans.spots, plans.end[number] - 1, n_fixed[number])
            found = low < high
            number = number[found]
            yield number, low[found], high[found], plans.first[number] >= 0, np.zeros(len(number), bool)

    def expanded(self, table: np.ndarray, first: np.ndarray, number: np.ndarray, low: np.ndarray, high: np.ndarray, masked: np.ndarray) -> Iterator[tuple[np.ndarray, np.ndarray]]:
        """Lots of (number of the plan, row of its first block) of ranges; ``table``: which symbols fit
        each mask, ``first``: the mask of each plan."""
        lots = np.cumsum(high - low) // ROWS
        for lot in np.unique(lots):
            m = np.flatnonzero(lots == lot)
            for begin in range(0, int((high[m] - low[m]).max(initial=0)), ROWS):  # one range may be larger than a lot
                a = np.minimum(low[m] + begin, high[m])
                n = np.minimum(high[m] - a, ROWS)
                ends = np.cumsum(n)
                rows = np.arange(ends[-1]) + np.repeat(a - (ends - n), n)
                owner, check = np.repeat(number[m], n), np.repeat(masked[m], n)
                if check.any():
                    spots, lf = self.symbols_and_lf(rows[check])
                    good = table[first[owner[check]], spots]
                    owner = np.concatenate([owner[~check], owner[check][good]])
                    rows = np.concatenate([rows[~check], lf[good]])
                yield owner, rows

    def _table(self, fits: list[np.ndarray]) -> np.ndarray:
        """Which used symbols fit each mask."""
        table = np.zeros((len(fits), len(self.syms)), bool)
        for row, wanted in zip(table, fits, strict=True):
            row[wanted] = True
        return table

    def find_many(self, plans: Plans, last: str) -> tuple[np.ndarray, np.ndarray]:
        """(number of the plan, text position in blocks) of every occurrence."""
        numbers, places = [np.zeros(0, np.int64)], [np.zeros(0, np.int64)]
        table = self._table(plans.fits)
        for number, low, high, masked, verify in self.states(plans, last):
            for flag in (False, True):
                mine = verify == flag
                for owner, rows in self.expanded(table, plans.first, number[mine], low[mine], high[mine], masked[mine]):
                    at = self.positions(rows)
                    if flag:
                        ahead = at + plans.m[owner] - 1
                        inside = ahead < self.n
                        owner, at, ahead = owner[inside], at[inside], ahead[inside]
                        self.work.checked += len(at)
                        if len(at):
                            good = table[plans.last[owner], self.symbols_at(ahead)]
                            owner, at = owner[good], at[good]
                    numbers.append(owner)
                    places.append(at)
        return np.concatenate(numbers), np.concatenate(places)

    def find_naive(self, p: planner.SuperPattern) -> np.ndarray:
        """One search for every concrete block pattern among the used symbols."""
        choices = [self.fitting(part) for part in p.parts]
        found = []
        for some in itertools.batched(itertools.product(*choices), 4096):
            chains = np.array(some, np.int64)
            low, high = self.symbol_ranges(chains[:, -1])
            m = chains.shape[1]
            low, high = self.backward_many(low, high, chains.reshape(-1), np.arange(len(chains)) * m + m - 2, np.full(len(chains), m - 1))
            found += [np.arange(a, b) for a, b in zip(low[low < high], high[low < high], strict=True)]
        return self.positions(np.concatenate(found)) if found else np.zeros(0, np.int64)

    def locate_many(self, patterns: list[str], last: str = "auto") -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray]]:
        """Lots of (number of the pattern, item_no, offset) of occurrences, 0-based characters. An empty pattern occurs
        nowhere."""
        for low, some in self.lots(patterns):
            if last == "naive":
                owners, shifts, numbers, at = [], [], [], []
                for i, pattern in enumerate(some):
                    digits = self.alphabet.digits(pattern)
                    if len(digits) and (digits >= 0).all():
                        for p in planner.displaced(digits, self.k):
                            at.append(self.find_naive(p))
                            numbers.append(np.full(len(at[-1]), len(owners)))
                            owners.append(i)
                            shifts.append(p.d)
                number, at = (np.concatenate([np.zeros(0, np.int64), *x]) for x in (numbers, at))
                owners, shifts = np.array(owners, np.int64), np.array(shifts, np.int64)
            else:
                plans = self.planned(some)
                owners, shifts = plans.pattern, plans.d
                number, at = self.find_many(plans, last)
            if not len(number):
                continue
            owner = np.searchsorted(self.item_start, at, "right") - 1
            pattern, item, offset = owners[number] + low, self.item_no[owner], (at - self.item_start[owner]) * self.k + shifts[number]
            if self.piece:
                mine, item, offset = whole_hits(item, offset, self.piece)
                pattern = pattern[mine]
            yield pattern, item, offset

    def locate(self, pattern: str, last: str = "auto") -> tuple[np.ndarray, np.ndarray]:
        """(item_no, offset) of every occurrence of one pattern."""
        found = list(self.locate_many([pattern], last))
        empty = np.zeros(0, np.int64)
        return tuple(np.concatenate([f[c] for f in found]) if found else empty for c in (1, 2))

    def count_many(self, patterns: list[str]) -> np.ndarray:
        """Number of occurrences of each pattern; masked last blocks are enumerated, so no row is walked."""
        out = np.zeros(len(patterns), np.int64)
        if self.piece:  # where a hit begins says whether it counts
            for number, _, _ in self.locate_many(patterns):
                np.add.at(out, number, 1)
            return out
        for low, some in self.lots(patterns):
            plans = self.planned(some)
            owner_of, table = plans.pattern + low, self._table(plans.fits)
            for number, a, b, masked, _ in self.states(plans, "enumerate"):
                np.add.at(out, owner_of[number[~masked]], (b - a)[~masked])
                for owner, _ in self.expanded(table, plans.first, number[masked], a[masked], b[masked], masked[masked]):
                    np.add.at(out, owner_of[owner], 1)
        return out

    def count(self, pattern: str) -> int:
        return int(self.count_many([pattern])[0])

    def exists(self, pattern: str) -> bool:
        return bool(self.count_many([pattern])[0])

    def extract(self, item_no: int, start: int, length: int) -> str | None:
        """Characters of an item from ``start``, clipped at its ends; None for an unknown item."""
        spot = np.flatnonzero(self.item_no == item_no)
        if not len(spot):
            return None
        low, high = max(0, start), min(start + length, int(self.item_length[spot[0]]))
        if low >= high:
            return ""
        first, last = low // self.k, (high - 1) // self.k
        base = int(self.item_start[spot[0]])
        mark = (base + last) // self.step + 1
        at = min(mark * self.step, self.n)
        row = np.array([self.row_of_mark[mark if mark * self.step < self.n else 0]])
        got = []
        while at > base + first:
            spots, row = self.symbols_and_lf(row)
            at -= 1
            got.append(int(spots[0]))
        digits = self.digits[got[::-1]][: last - first + 1].reshape(-1)
        text = self.alphabet.text(digits)
        return text[low - first * self.k : high - first * self.k]

    def transform(self) -> np.ndarray:
        """All symbols of the transform: opens every block, many at once, and keeps none."""
        out = [np.zeros(0, np.int64)]
        for low in range(0, self.n_blocks, BATCH):
            numbers = range(low, min(low + BATCH, self.n_blocks))
            opened = decode_blocks([self._sealed(b) for b in numbers], low, self.key, self.coding)
            out += [self._checked(b, syms) for b, syms in zip(numbers, opened, strict=True)]
        return np.concatenate(out)
