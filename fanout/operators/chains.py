"""Chains of hot cells grown on dense bit sets: the recorders that the cells of a chain share are counted while it grows.

A cell is m bits. The share of a chain only shrinks with every row, so a chain below the cut-off can end at once and nothing is
lost. Blocks of chains grow row by row in NumPy; a block that gets large is cut, so that memory does not depend on the chains.

Where nearly all cells are hot, chains multiply with every row. With the root check, or where the hash finds the lowest bits, an address has one chain, which its
hash names; then the addresses of a pair of rows 0 and 1 are listed by the hash and tested, 2^32 at most for all pairs, instead of growing chains.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator
from typing import Any

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.hashing import PRIME, ROOT
from ..functions.params import ADDRESS_BITS, GridParams
from ..sources.storage import stored
from .grid import CELL, words_of

#: Bytes of hot cells that are sent to all tasks at most; beyond, they are dealt to groups by a shuffle.
BITS_SEND = 64 << 20
#: Chains of a block.
BLOCK = 1_024
#: Addresses that are listed at once, and how many of them take as long as one comparison of two cells.
LISTED, LISTED_COST = 1 << 18, 4
#: Cells of chains and what they share; or nothing, what is shared and the addresses, where these were listed.
Found = Iterator[tuple[list[np.ndarray], np.ndarray] | tuple[None, np.ndarray, np.ndarray]]


def cell_bits(state: DataFrame, hot: DataFrame, m: int, by: tuple[str, ...] = ()) -> DataFrame:
    """(by, row_id, col_id, bits): the touched recorders of each hot cell as 64-bit words."""
    word = words_of(state.join(hot.select(*by, *CELL), [*by, *CELL]), by)
    held = word.groupBy(*by, *CELL).agg(F.map_from_entries(F.collect_list(F.struct("at", "word"))).alias("m"))
    return stored(held.select(*by, *CELL, F.transform(F.sequence(F.lit(0), F.lit((m - 1) // 64)), lambda i: F.coalesce(F.try_element_at("m", i), F.lit(0).cast("long"))).alias("bits")))


def _mod(x: np.ndarray) -> np.ndarray:
    """x modulo 2^31 - 1, by sums of its parts."""
    for _ in range(2):
        x = (x & PRIME) + (x >> 31)
    return np.where(x >= PRIME, x - PRIME, x)


def root(core: np.ndarray, w: int) -> np.ndarray:
    """`hashing.root_hash` of an array."""
    a1, b1, a2, b2 = ROOT
    h = _mod(core * a1 + b1)
    return _mod((h ^ (h >> 15)) * a2 + b2) & ((1 << w) - 1)


def of_root(c0: int, w: int) -> np.ndarray:
    """All addresses of ADDRESS_BITS bits whose `root` is c0: the hash run backwards."""
    a1, b1, a2, b2 = ROOT
    x = (np.arange(c0, PRIME, 1 << w) + (PRIME - b2)) % PRIME * pow(a2, -1, PRIME) % PRIME
    x = np.append(x, PRIME) if (x == 0).any() else x
    h = x ^ (x >> 15) ^ (x >> 30)
    core = (h[h < PRIME] + (PRIME - b1)) % PRIME * pow(a1, -1, PRIME) % PRIME
    return np.concatenate([core[core < (1 << ADDRESS_BITS) - k] + k for k in range(0, 1 << ADDRESS_BITS, PRIME)])


class Cells:
    """Hot cells of one grid: columns and bits of each row, joined ones in the order of their low bits."""

    def __init__(self, rows: np.ndarray, cols: np.ndarray, bits: np.ndarray, p: GridParams, n: int, low_from: int):
        self.p, self.n, self.cols, self.bits, self.starts = p, n, [], [], []
        self.rooted = p.root_check and not p.literal_shift and n == p.r
        searched = p.literal_shift and n == p.r  # the lowest d bits are found by the hash
        self.one_chain = searched or self.rooted and (p.pad_check or p.shift(n - 1) + p.w == ADDRESS_BITS)
        self.at, self.rests = [], {}
        for i in range(n):
            at = np.flatnonzero(rows == i)
            low = cols[at] & p.overlap_mask
            at = at[np.argsort(low if i >= low_from else cols[at], kind="stable")]
            self.cols.append(cols[at])
            self.bits.append(bits[at])
            self.starts.append(np.searchsorted(np.sort(low), np.arange(p.overlap_mask + 2)))
            if self.one_chain:
                self.at.append(np.full(1 << p.w, -1, np.int32))
                self.at[i][self.cols[i]] = np.arange(len(at), dtype=np.int32)

    @classmethod
    def of(cls, b: pd.DataFrame, p: GridParams, first: int = 0) -> Cells:
        """Rows from `first` on; with first = 1 (no row of roots) those after it are joined by their low bits, else those from row 2 on."""
        words = (p.m + 63) // 64
        bits = np.concatenate([np.asarray(x, np.int64) for x in b["bits"]]).view(np.uint64).reshape(-1, words) if len(b) else np.zeros((0, words), np.uint64)
        return cls(b["row_id"].to_numpy(np.int64) - first, b["col_id"].to_numpy(np.int64), bits, p, p.r - first, 2 - first)

    def grown(self, chain: list[np.ndarray], key: np.ndarray) -> Iterator[tuple[np.ndarray, np.ndarray]]:
        """(chain, cell) numbers of a block and the next row whose overlap fits, in blocks."""
        starts = self.starts[len(chain)]
        begin, n = starts[key], starts[key + 1] - starts[key]
        ends = np.cumsum(n)
        low = 0
        while low < len(n):
            done = ends[low - 1] if low else 0
            high = max(low + 1, int(np.searchsorted(ends, done + 2 * BLOCK, "right")))
            own = np.repeat(np.arange(low, high), n[low:high])
            yield own, begin[own] + np.arange(len(own)) - (ends[own] - n[own] - done)
            low = high

    def shared(self, bits: np.ndarray, own: np.ndarray | None, other: np.ndarray, at: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Numbers of the pairs (bits[own], other[at]) whose common recorders reach the cut-off, their bits and counts. Without own, bits are taken in order and lost."""
        both = bits if own is None else bits.take(own, axis=0)
        both &= other.take(at, axis=0)
        n = np.einsum("ij->i", np.bitwise_count(both).astype(np.float32)).astype(np.int64)  # exact below 2^24
        keep = np.flatnonzero(n >= self.p.cutoff)
        return keep, both.take(keep, axis=0), n[keep]

    def finish(self, chain: list[np.ndarray], bits: np.ndarray, touched: np.ndarray, key: Callable) -> Found:
        """A block of chains -> all full chains that grow from it, depth first by blocks."""
        if not len(touched):
            return
        i = len(chain)
        if i == self.n:
            yield chain, touched
            return
        last = self.rooted and i == self.n - 1
        if last:
            part = address(chain, self.p)
        for own, at in self.grown(chain, key(chain)):
            if last:  # the address is known, and its hash leaves few chains to compare
                core = part[own] | (self.cols[i][at] ^ chain[0][own]) << self.p.shift(i)
                fits = np.flatnonzero(root(core, self.p.w) == chain[0][own])
                own, at = own[fits], at[fits]
            keep, both, n = self.shared(bits, own, self.bits[i], at)
            own, at = own[keep], at[keep]
            yield from self.finish([*(c[own] for c in chain), self.cols[i][at]], both, n, key)

    def key(self, chain: list[np.ndarray]) -> np.ndarray:
        """Low bits that the next cell must have."""
        return ((chain[-1] ^ chain[0]) >> self.p.d) ^ (chain[0] & self.p.overlap_mask)

    def by_piece(self, part: int, parts: int, first: int = 0, of: int = 1) -> Iterator[Found]:
        """Full chains by the lowest piece of their address, so that all chains of an address are in one part; of pieces first, first + of, ... only."""
        zero, size = self.cols[0], 1 << self.p.w
        at = np.full(size, -1, np.int64)
        at[self.cols[1]] = np.arange(len(self.cols[1]))
        pieces = np.arange(first + part * of, size, parts * of)
        step = max(1, BLOCK // max(1, len(zero) * len(self.cols[1]) // size, len(zero) // 16))
        if self.one_chain and self.work(len(zero) * len(self.cols[1]) // size, 1.0) * LISTED_COST > 1 << ADDRESS_BITS - self.p.w:
            step = 1  # each piece may be listed
        for low in range(0, len(pieces), step):
            met = at[pieces[low : low + step, None] ^ zero]
            a = np.nonzero(met >= 0)[1]
            yield self._pairs(a, met[met >= 0], 0, (lambda k=int(pieces[low]): self.of_piece(k)) if step == 1 else None)

    def by_root(self, part: int, parts: int) -> Iterator[Found]:
        """Full chains depth first from one cell of row 0 at a time."""
        n = len(self.cols[1])
        for a in range(part, len(self.cols[0]), parts):
            yield self._pairs(np.full(n, a), np.arange(n), 1, lambda k=int(self.cols[0][a]): ((c, np.full(len(c), k)) for c in [of_root(k, self.p.w)]))

    def of_piece(self, piece: int) -> Iterator[tuple[np.ndarray, np.ndarray]]:
        """All addresses with a lowest piece, in blocks, and their roots. Bits below it are counted on first."""
        top, below = 1 << ADDRESS_BITS - self.p.w, self.p.shift(1)
        a1, b1, a2, b2 = ROOT
        for low in range(0, top, LISTED):
            if low not in self.rests:  # what all pieces have in common: the other bits, and their part of the first round of the hash
                rest = np.arange(low, min(top, low + LISTED))
                rest = rest >> below << below + self.p.w | rest & ((1 << below) - 1)
                self.rests = {low: (rest, _mod(rest * a1))}
            rest, h = self.rests[low]
            h = h + ((piece << below) * a1 + b1) % PRIME
            h -= PRIME * (h >= PRIME)
            yield rest | piece << below, _mod((h ^ (h >> 15)) * a2 + b2) & self.p.mask

    def work(self, pairs: int, kept: float) -> float:
        """About how many comparisons growing takes from so many pairs of rows 0 and 1, if that share of them was kept."""
        total, n = 0.0, float(pairs)
        for i in range(2, self.n):
            n *= len(self.cols[i]) / (self.p.overlap_mask + 1)
            total += n / (LISTED_COST if self.rooted and i == self.n - 1 else 1)
            n *= kept**i
        return total

    def _pairs(self, a: np.ndarray, b: np.ndarray, row: int, listed: Callable[[], Iterator[tuple[np.ndarray, np.ndarray]]] | None) -> Found:
        """listed: all addresses, with their roots, that chains of these pairs can have, where the cell of `row` says which pair it is."""
        most = 1 << ADDRESS_BITS - self.p.w
        held = self._kept(a, b)
        if listed and self.one_chain and self.work(len(a), 1.0) * LISTED_COST > most:
            held = list(held)
            n = sum(len(h[0]) for h in held)
            if self.work(n, n / len(a)) * LISTED_COST > most:
                x, y, both = (np.concatenate([h[i] for h in held]) for i in range(3))
                pair = np.full(1 << self.p.w, -1, np.int32)
                pair[self.cols[row][y if row else x]] = np.arange(n, dtype=np.int32)
                for core, c0 in listed():
                    yield from self.tested(core, c0, pair[((core >> self.p.shift(1)) ^ c0) & self.p.mask if row else c0], both)
                return
        for x, y, both, n in held:
            yield from self.finish([self.cols[0][x], self.cols[1][y]], both, n, self.key)

    def _kept(self, a: np.ndarray, b: np.ndarray) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]]:
        """Pairs of cells of rows 0 and 1 that share enough, with what they share, in blocks."""
        for low in range(0, len(a), BLOCK):
            x, y = a[low : low + BLOCK], b[low : low + BLOCK]
            keep, both, n = self.shared(self.bits[0], x, self.bits[1], y)
            yield x[keep], y[keep], both, n

    def tested(self, core: np.ndarray, c0: np.ndarray, pair: np.ndarray, both: np.ndarray) -> Found:
        """Addresses with their roots and the numbers of their pairs of rows 0 and 1 (-1: none) -> those whose cells share enough, and what they share."""
        keep = np.flatnonzero(pair >= 0)
        core, c0, pair = core[keep], c0[keep], pair[keep]
        cells = []
        for i in range(2, self.n):
            cell = self.at[i][((core >> self.p.shift(i)) ^ c0) & self.p.mask]
            keep = np.flatnonzero(cell >= 0)
            if len(keep) < len(core):
                core, c0, pair, cells, cell = core[keep], c0[keep], pair[keep], [c[keep] for c in cells], cell[keep]
            cells.append(cell)
        for low in range(0, len(core), BLOCK):
            own, bits, n = slice(low, low + BLOCK), both, None
            at, k = np.arange(low, min(low + BLOCK, len(core))), pair[own]
            for i, cell in enumerate(cells, 2):
                keep, bits, n = self.shared(bits, k, self.bits[i], cell[at])
                at, k = at[keep], None
            if len(at):
                yield None, n, core[at]


def address(chain: list[np.ndarray], p: GridParams) -> np.ndarray:
    """What the cells of rows 1.. of a chain hold of the address."""
    core = np.zeros(len(chain[0]), np.int64)
    for i in range(1, len(chain)):
        core |= (chain[i] ^ chain[0]) << p.shift(i)
    return core


def rebuilt(chain: list[np.ndarray], touched: np.ndarray, p: GridParams) -> tuple[list[np.ndarray], np.ndarray, np.ndarray]:
    """Chains, their addresses after the pad and the root check, and their counts."""
    core = address(chain, p)
    keep = np.ones(len(core), bool)
    if p.literal_shift or p.pad_check:
        keep &= core < 1 << ADDRESS_BITS
    if p.literal_shift:  # the lowest d bits are in no piece and are searched
        keep = np.flatnonzero(keep)
        ends = [(at, core[at] | low) for low in range(1 << p.d) for at in [keep[root(core[keep] | low, p.w) == chain[0][keep]]]]
        own, core = (np.concatenate(x) for x in zip(*ends))
        return [c[own] for c in chain], core, touched[own]
    if p.root_check:
        keep &= root(core, p.w) == chain[0]
    return [c[keep] for c in chain], core[keep], touched[keep]


def widest(core: list[np.ndarray], touched: list[np.ndarray]) -> tuple[np.ndarray, np.ndarray]:
    """Each address once, with its largest count."""
    core, touched = np.concatenate(core), np.concatenate(touched)
    order = np.lexsort((-touched, core))
    core, touched = core[order], touched[order]
    first = np.ones(len(core), bool)
    first[1:] = core[1:] != core[:-1]
    return core[first], touched[first]


def _frames(cells: Cells, part: int, parts: int, how: str, full: bool, pieces: tuple[int, int] = (0, 1)) -> Iterator[pd.DataFrame]:
    p = cells.p.with_(root_check=False) if cells.rooted else cells.p  # rooted chains have passed this check
    once = (lambda *x: tuple(map(np.concatenate, x))) if cells.one_chain else widest
    for found in cells.by_root(part, parts) if how == "root" else cells.by_piece(part, parts, *pieces):
        cores, counts, held = [], [], 0
        for chain, touched, *listed in found:
            if listed:
                core = listed[0]
                if full:
                    c0 = root(core, p.w)
                    chain = [c0, *(((core >> p.shift(i)) ^ c0) & p.mask for i in range(1, p.r))]
            else:
                chain, core, touched = rebuilt(chain, touched, p)
            if full:
                if len(core):
                    yield pd.DataFrame({f"c{i}": c for i, c in enumerate(chain)} | {"core": core, "touched": touched})
                continue
            cores.append(core)
            counts.append(touched)
            held += len(core)
            if held > 1 << 20:
                core, touched = once(cores, counts)
                if cells.one_chain:
                    yield pd.DataFrame({"core": core, "touched": touched})
                    cores, counts, held = [], [], 0
                    continue
                cores, counts, held = [core], [touched], 0
        if held:
            core, touched = once(cores, counts)
            yield pd.DataFrame({"core": core, "touched": touched})


def over_parts(bits: DataFrame, p: GridParams, by: tuple[str, ...], out: str, work: Callable[[pd.DataFrame, int, int], Iterator[pd.DataFrame]]) -> DataFrame:
    """Runs work(cells, part, parts) for every part of every grid. The cells go to all tasks, or by a shuffle where they are too many."""
    spark = bits.sparkSession
    kinds = {f.name: f.dataType.simpleString() for f in bits.schema.fields}
    out = ", ".join([*(f"{b} {kinds[b]}" for b in by), out])
    size = bits.agg(F.count("*"), F.max(F.size("bits")), F.count_distinct(*by) if by else F.lit(1)).first()
    parts = max(1, 4 * spark.sparkContext.defaultParallelism // max(1, size[2]))

    def named(found: Iterator[pd.DataFrame], key: tuple) -> Iterator[pd.DataFrame]:
        for f in found:
            for i, (b, v) in enumerate(zip(by, key)):
                f.insert(i, b, v)
            yield f

    if size[0] * 8 * (size[1] or 0) <= BITS_SEND:
        cells = bits.toArrow().to_pandas()
        grids = {k if isinstance(k, tuple) else (k,): g.reset_index(drop=True) for k, g in cells.groupby(list(by))} if by else {(): cells}
        sent = spark.sparkContext.broadcast(list(grids.items()))
        todo = spark.range(0, len(grids) * parts, 1, max(1, len(grids) * parts))

        def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
            for b in batches:
                for n in b["id"].tolist():
                    key, g = sent.value[n // parts]
                    yield from named(work(g, n % parts, parts), key)

        return todo.mapInPandas(run, out)

    # a group of its own for each grid and part
    def grouped(key: tuple[Any, ...], held: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        yield from named(work(pd.concat(list(held), ignore_index=True), int(key[-1]), parts), key[:-1])

    return bits.withColumn("_part", F.explode(F.sequence(F.lit(0), F.lit(parts - 1)))).groupBy(*by, "_part").applyInPandas(grouped, out)


def verified(state: DataFrame, hot: DataFrame, p: GridParams, by: tuple[str, ...] = (), how: str = "piece", full: bool = False, shards: int = 1) -> DataFrame:
    """(by, core, touched) of all chains that reach the cut-off, each address once in a part; with `full` a row for each chain, with its cells.

    Dealt by piece, an address is in one part only, so the rows are final. With `shards`, by is the residue of the address, which its lowest
    piece has where shards divide 2^w: other pieces are not tried.
    """
    out = (", ".join(f"c{i} long" for i in range(p.r)) + ", " if full else "") + "core long, touched long"
    known = shards > 1 and (1 << p.w) % shards == 0 and not p.literal_shift

    def work(b: pd.DataFrame, part: int, parts: int) -> Iterator[pd.DataFrame]:
        return _frames(Cells.of(b, p), part, parts, how, full, (int(b[by[0]].iloc[0]), shards) if known else (0, 1))

    return over_parts(cell_bits(state, hot, p.m, by), p, by, out, work)


def by_slices(bits: DataFrame, p: GridParams, by: tuple[str, ...] = ()) -> DataFrame:
    """(by, core, touched) of chains of bare slices in rows 1..r-1."""

    def work(b: pd.DataFrame, part: int, parts: int) -> Iterator[pd.DataFrame]:
        cells = Cells.of(b, p, 1)
        for at in range(part, len(cells.cols[0]), parts):
            one = cells.bits[0][at : at + 1]
            for chain, touched in cells.finish([cells.cols[0][at : at + 1]], one, np.bitwise_count(one).sum(axis=1, dtype=np.int64), lambda c: c[-1] >> p.d):
                core = np.zeros(len(touched), np.int64)
                for i, c in enumerate(chain, 1):
                    core |= c << p.shift(i)
                keep = core < 1 << ADDRESS_BITS
                yield pd.DataFrame({"core": core[keep], "touched": touched[keep]})

    return over_parts(bits, p, by, "core long, touched long", work)


def by_remainders(bits: DataFrame, p: GridParams, moduli: tuple[int, ...], by: tuple[str, ...] = ()) -> DataFrame:
    """(by, core, touched) of cells core mod each prime. Two remainders leave few addresses of 32 bits, and these name the cells of all further rows."""
    pair, inverse = moduli[0] * moduli[1], pow(moduli[0], -1, moduli[1])

    def work(b: pd.DataFrame, part: int, parts: int) -> Iterator[pd.DataFrame]:
        cells = Cells.of(b, p)
        at = [np.full(q, -1, np.int64) for q in moduli]
        for i, c in enumerate(cells.cols):
            at[i][c] = np.arange(len(c))
        steps = np.arange((1 << ADDRESS_BITS) // pair + 1) * pair
        for a in range(part, len(cells.cols[0]), parts):
            for low in range(0, len(cells.cols[1]), BLOCK):
                at1 = np.arange(low, min(low + BLOCK, len(cells.cols[1])))
                keep, both, touched = cells.shared(cells.bits[0], np.full(len(at1), a), cells.bits[1], at1)
                c0 = cells.cols[0][a]
                base = c0 + moduli[0] * ((cells.cols[1][low + keep] - c0) * inverse % moduli[1])
                every = base[:, None] + steps  # all addresses of the pairs at once
                own, k = np.nonzero(every < 1 << ADDRESS_BITS)
                core, n = every[own, k], touched[own]
                for i in range(2, len(moduli)):
                    cell = at[i][core % moduli[i]]
                    hot = np.flatnonzero(cell >= 0)
                    fits, both, n = cells.shared(both, own[hot], cells.bits[i], cell[hot])
                    core, own = core[hot][fits], np.arange(len(fits))
                if len(core):
                    yield pd.DataFrame({"core": core, "touched": n})

    return over_parts(bits, p, by, "core long, touched long", work)


def of_addresses(bits: DataFrame, cores: DataFrame, p: GridParams) -> DataFrame:
    """(core) different -> (core, touched) of those whose cells are all hot and share enough recorders: each is tested in place, without a join."""
    sent = bits.sparkSession.sparkContext.broadcast(bits.toArrow().to_pandas())

    def tested(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        cells = Cells.of(sent.value, p)
        at = [np.full(1 << p.w, -1, np.int64) for _ in range(p.r)]
        for i, c in enumerate(cells.cols):
            at[i][c] = np.arange(len(c))
        for b in batches:
            core = b["core"].to_numpy(np.int64)
            c0 = root(core, p.w)
            cell = np.stack([at[i][((core >> p.shift(i)) ^ c0) & p.mask if i else c0] for i in range(p.r)])
            hot = np.flatnonzero((cell >= 0).all(axis=0))
            for low in range(0, len(hot), BLOCK):
                own = hot[low : low + BLOCK]
                both = cells.bits[0][cell[0, own]]
                for i in range(1, p.r):
                    keep, both, n = cells.shared(both, np.arange(len(own)), cells.bits[i], cell[i, own])
                    own = own[keep]
                if len(own):
                    yield pd.DataFrame({"core": core[own], "touched": n})

    return cores.mapInPandas(tested, "core long, touched long")


def eager_levels(bits: DataFrame, p: GridParams) -> DataFrame:
    """Chains with `touched`, one stored table a level: those below the cut-off are not stored."""
    sent = bits.sparkSession.sparkContext.broadcast(bits.toArrow().to_pandas())
    cols = lambda i: [f"c{j}" for j in range(i + 1)]
    schema = lambda i: ", ".join(f"{c} long" for c in (*cols(i), "touched"))
    parts = 4 * bits.sparkSession.sparkContext.defaultParallelism

    def next_row(i: int):
        def grow(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
            cells = Cells.of(sent.value, p)
            at = [np.zeros(1 << p.w, np.int64) for _ in range(i)]
            for j in range(i):
                at[j][cells.cols[j]] = np.arange(len(cells.cols[j]))
            for b in batches:
                for low in range(0, len(b), BLOCK):
                    chain = [b[c].to_numpy(np.int64)[low : low + BLOCK] for c in cols(i - 1)]
                    bits = cells.bits[0][at[0][chain[0]]]
                    for j in range(1, i):
                        bits &= cells.bits[j][at[j][chain[j]]]
                    n = len(cells.cols[1])
                    every = ((np.repeat(np.arange(x, min(len(bits), x + 16)), n), np.tile(np.arange(n), min(len(bits), x + 16) - x)) for x in range(0, len(bits), 16))
                    for own, cell in every if i == 1 else cells.grown(chain, cells.key(chain)):
                        keep, _, touched = cells.shared(bits, own, cells.bits[i], cell)
                        own, cell = own[keep], cell[keep]
                        yield pd.DataFrame({c: v[own] for c, v in zip(cols(i), chain)} | {f"c{i}": cells.cols[i][cell], "touched": touched})

        return grow

    chains = bits.filter("row_id = 0").select(F.col("col_id").alias("c0"))
    for i in range(1, p.r):
        chains = stored(chains.repartition(parts, *cols(i - 1)).mapInPandas(next_row(i), schema(i)))
    return chains
