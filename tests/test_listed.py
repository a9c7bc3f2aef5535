"""Grids in which nearly all cells are hot: addresses are listed by their hash, chains are not grown."""

from __future__ import annotations

import numpy as np
import pytest

from fanout.functions.params import ADDRESS_BITS, GridParams
from fanout.operators import chains as Ch
from fanout.operators import grid as G
from fanout.operators import recover as V

P = GridParams(m=64, w=14, d=6, r=5, theta=60)


def dense(p: GridParams, share: float, seed: int = 1) -> tuple[np.ndarray, Ch.Cells]:
    """Bits of all cells with that share of recorders touched, all of them in the cells of addresses with root and piece 3, and those at the cut-off as cells."""
    bits = np.packbits(np.random.default_rng(seed).random((p.r, 1 << p.w, p.m)) < share, axis=2).view(np.uint64)
    core = Ch.of_root(3, p.w)
    core = core[(core >> p.shift(1)) & p.mask == 3]
    for i in range(p.r):
        bits[i, ((core >> p.shift(i)) ^ 3) & p.mask if i else 3] = np.uint64((1 << 64) - 1)
    rows, cols = np.nonzero(np.bitwise_count(bits).sum(axis=2) >= p.cutoff)
    return bits, Ch.Cells(rows, cols, bits[rows, cols], p, p.r, 2)


def of_addresses(core: np.ndarray, bits: np.ndarray, p: GridParams) -> dict[int, int]:
    """Every address tested on all its cells."""
    c0 = Ch.root(core, p.w)
    both = bits[0, c0]
    for i in range(1, p.r):
        both = both & bits[i, ((core >> p.shift(i)) ^ c0) & p.mask]
    n = np.bitwise_count(both).sum(axis=1)
    return {int(c): int(k) for c, k in zip(core, n) if k >= p.cutoff}


def rows(frames) -> dict[int, int]:
    out = [x for f in frames for x in zip(f["core"].tolist(), f["touched"].tolist())]
    assert len(out) == len(dict(out))
    return dict(out)


def test_hash_backwards():
    for w in (8, 14):
        core = Ch.of_root(5, w)
        assert len(np.unique(core)) == len(core) and (Ch.root(core, w) == 5).all()
        some = np.random.default_rng(2).integers(0, 1 << ADDRESS_BITS, 200_000)
        some = np.append(some[Ch.root(some, w) == 5], [c for c in (0, 1, Ch.PRIME, 2 * Ch.PRIME, 2 * Ch.PRIME + 1) if Ch.root(np.array([c]), w) == 5])
        assert np.isin(some, core).all() and len(some) > 5


@pytest.mark.parametrize("how, literal", [("piece", False), ("root", False), ("piece", True), ("root", True)])
def test_work_of_a_full_grid_is_bounded(how, literal, monkeypatch):
    p = P.with_(literal_shift=literal)
    bits, cells = dense(p, 0.9)
    assert len(cells.cols[0]) > 16_000
    compared, shared = [], Ch.Cells.shared
    monkeypatch.setattr(Ch.Cells, "shared", lambda self, b, own, other, at: compared.append(len(at)) or shared(self, b, own, other, at))
    got = rows(Ch._frames(cells, 77, 1 << P.w, how, False))
    core = np.arange(1 << 18) << P.w | 77 if how == "piece" else Ch.of_root(int(cells.cols[0][77]), P.w)
    if how == "piece" and literal:  # 6 bits below the piece and 12 above it
        core = (core >> P.w + 6) << P.w + 6 | 77 << 6 | (core >> P.w) & 63
    assert got == of_addresses(core, bits, p) and len(got) > 1_000
    assert sum(compared) < 4 << 18  # growing them compares 16,384 x 64 x 64 and more


@pytest.mark.parametrize("how, literal", [("piece", False), ("root", False), ("piece", True), ("root", True)])
def test_listed_and_grown_are_the_same(how, literal, monkeypatch):
    _, cells = dense(P.with_(theta=28, literal_shift=literal), 0.6)
    assert cells.cols[0][3] == 3 and cells.one_chain
    frames = lambda full: sorted(tuple(x) for f in Ch._frames(cells, 3, 1 << P.w, how, full) for x in f.to_numpy().tolist())
    monkeypatch.setattr(Ch.Cells, "work", lambda self, pairs, kept: 0.0)
    monkeypatch.setattr(Ch.Cells, "tested", None)
    grown = frames(False), frames(True)
    monkeypatch.undo()
    monkeypatch.setattr(Ch.Cells, "work", lambda self, pairs, kept: float("inf"))
    monkeypatch.setattr(Ch.Cells, "finish", None)
    assert (frames(False), frames(True)) == grown and len(grown[0]) >= 10


def test_shards_try_their_own_pieces(spark, monkeypatch):
    p = GridParams(m=64, w=8, d=3, r=10, theta=20)
    df = spark.range(4000).selectExpr("(id % 10) * 1640531541 % 4294967296 as core", "id as opp", "id as slot", "id % 2 as router")
    for g in (3, 4):
        state = G.scan_sharded(df, p, g)
        every = V.regain_levels(state, p, ("shard",)).filter(f"core % {g} = shard")
        rows = lambda t: sorted(map(tuple, t.collect()))
        assert rows(V.regain_sharded(state, p, g)) == rows(every) and every.count() >= 10
    _, cells = dense(P.with_(theta=28), 0.6)
    met = []
    monkeypatch.setattr(Ch.Cells, "_pairs", lambda self, a, b, row, listed: met.append(self.cols[0][a] ^ self.cols[1][b]))
    list(cells.by_piece(0, 2, 3, 4)), list(cells.by_piece(1, 2, 3, 4))
    assert set(np.concatenate(met) % 4) == {3}
