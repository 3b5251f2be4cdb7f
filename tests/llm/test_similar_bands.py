"""The range join of segment counts behind the pipeline's near-duplicate stage."""

import math
import random

import numpy as np
import pytest

from redgraph.llm import similar_documents as sd


def vector(x):
    return [(x >> 2 * g & 3).bit_count() for g in range(32)]


def test_segment_counts_bound_the_hamming_distance():
    rng = random.Random(3)
    words = [rng.getrandbits(64) for _ in range(50)] + [0, (1 << 64) - 1]
    packed = sd.segment_counts(np.array(words, np.uint64)).tolist()
    for x, p in zip(words, packed, strict=True):
        assert [p >> 2 * g & 3 for g in range(32)] == vector(x)
        y = words[0]
        assert sum(abs(a - b) for a, b in zip(vector(x), vector(y), strict=True)) <= (x ^ y).bit_count()


def test_distance_one_on_a_band_shares_a_cell(spark):
    """Flips inside one block of each band: the cell that leaves the block out still holds both texts."""
    for nodes in (10, 200_000):
        for band in sd.bands(nodes, 0.8):
            assert len(band) == sd.BLOCKS and len({g for b in band for g in b}) == sum(map(len, band))
    rng = random.Random(1)
    base = [rng.getrandbits(64) for _ in range(2)]
    band = sd.bands(2, 0.8)[0]
    rows = [(1, *base)]
    for k, g in enumerate(g for block in band for g in block):
        near = list(base)
        near[g // 32] ^= 1 << 2 * (g % 32)
        rows.append((2 + k, *near))
    signed = lambda x: x - (1 << 64) if x >> 63 else x
    nodes = spark.createDataFrame([(k, signed(lo), signed(hi), 9) for k, lo, hi in rows], "key long, lo long, hi long, n long")
    got = {(r.a, r.b) for r in sd.candidates(nodes, 0.8).collect()}
    assert {(1, k) for k, *_ in rows[1:]} <= got


@pytest.mark.parametrize("pairs, meet", [(8, 256), (2, 5)])
def test_cells_equal_brute_force_and_stay_linear(pairs, meet):
    rng = random.Random(7)
    n = 300
    base = rng.getrandbits(64)
    lo = np.array([base ^ (1 << rng.randrange(64)) for _ in range(n)], np.uint64).view(np.int64)
    hi = np.array([rng.getrandbits(64) if k % 3 else 5 for k in range(n)], np.uint64).view(np.int64)
    cell = np.sort(np.array([rng.randrange(40) for _ in range(n)], np.int64))
    rows = {"cell": cell, "key": np.arange(n), "lo": lo, "hi": hi, "n": np.full(n, 9)}
    want = set()
    for i in range(n):
        for j in range(i):
            bits = int(np.bitwise_count((lo[i] ^ lo[j]).view(np.uint64))) + int(np.bitwise_count((hi[i] ^ hi[j]).view(np.uint64)))
            if cell[i] == cell[j] and bits <= 30:
                want.add((j, i))
    got = set(zip(*map(np.ndarray.tolist, sd.met(rows, 30, 0.8, pairs, meet, False)[:2]), strict=True))
    assert got <= want
    assert got == want or meet < 256
    # one group of one root makes nothing, however large
    assert not len(sd.met(rows | {"root": np.zeros(n, np.int64)}, 30, 0.8, pairs, meet, False)[0])
    many = {"cell": np.zeros(3000, np.int64), "key": np.arange(3000), "lo": np.zeros(3000, np.int64), "hi": np.arange(3000) % 7, "n": np.full(3000, 9)}
    assert len(sd.met(many, 30, 0.8, 8, 256, False)[0]) <= 3000 * (1 + math.ceil(sd.SEGMENTS / sd.FINER))
    assert len(sd.met(many, 30, 0.8, 8, 256, True)[0]) <= 3000 * (1 + math.ceil(sd.SEGMENTS / sd.FINER))


def test_bands_reach_the_recall():
    """Of vectors that differ as texts at the threshold do, as many as stated share a cell."""
    rng = np.random.default_rng(2)
    for nodes in (1000, 200_000):
        masks = [sd._mask([g for k, block in enumerate(band) if k != left for g in block]) for band in sd.bands(nodes, 0.8) for left in range(sd.BLOCKS)]
        words = rng.integers(0, 1 << 63, (2, 4000), dtype=np.uint64) * np.uint64(2) + rng.integers(0, 2, (2, 4000), dtype=np.uint64)
        flips = np.packbits(rng.random((2, 4000, 64)) < sd.flip_chance(0.8), axis=2, bitorder="little").view("<u8").reshape(2, 4000)
        mine, other = sd.segment_counts(words), sd.segment_counts(words ^ flips)
        hit = np.zeros(4000, bool)
        for low, high in masks:
            hit |= ((mine[0] ^ other[0]) & low == 0) & ((mine[1] ^ other[1]) & high == 0)
        assert hit.mean() >= 0.93
