import numpy as np
import pytest

from hitcodec.operators import bins, frames, tans


def brute(v, n, min_val):
    """Widths grown bit by bit."""
    values = np.repeat(v, n)
    s, out = int(v[0]), []
    while (values >= s).any():
        w = 0
        while ((values >= s) & (values < s + (1 << w))).sum() <= min_val and s + (1 << w) <= values[-1]:
            w += 1
        out.append((s, w, int(((values >= s) & (values < s + (1 << w))).sum())))
        s += 1 << w
    return out


@pytest.mark.parametrize("seed", range(6))
def test_greedy_is_the_growing_rule(seed):
    rng = np.random.default_rng(seed)
    v = np.unique((rng.pareto(1.0, 300) * 40).astype(np.int64))
    n = rng.integers(1, 9, len(v))
    for least in (0, 1, 7, 40, 10**6):
        got = bins.greedy_bins(v, n, least)
        assert got == brute(v, n, least)
        assert sum(b[2] for b in got) == n.sum()
        assert all(a[0] + (1 << a[1]) == b[0] for a, b in zip(got, got[1:]))


def test_zero_gets_a_bin_of_its_own():
    v, n = np.array([0, 5, 6, 90]), np.array([50, 3, 3, 1])
    assert bins.greedy_bins(v, n, 10)[0] == (0, 0, 50)
    special = bins.greedy_bins(v, n, 1000, special=[5])
    assert (5, 0, 3) in special and sum(b[2] for b in special) == 57
    assert all(a[0] + (1 << a[1]) <= b[0] for a, b in zip(special, special[1:]))


@pytest.mark.parametrize("size", [1, 3, 50, 1000])
def test_streamed_bins(size):
    rng = np.random.default_rng(size)
    for least in (0, 1, 20, 10_000):
        for strict in (True, False):
            v = np.unique(rng.integers(-500, 2**rng.integers(2, 40), 400))
            n = rng.integers(1, 30, len(v))
            s = bins.GreedyStream(int(n.sum()), least, strict)
            got = [b for k in range(0, len(v), size) for b in s.feed(v[k : k + size], n[k : k + size])]
            assert got == bins.greedy_bins(v, n, least, strict)


def test_optimal_is_not_above_greedy():
    rng = np.random.default_rng(4)
    v = np.arange(60)
    n = rng.integers(1, 50, 60)
    g = bins.greedy_bins(v, n, 200)
    cost = sum(c * (w - np.log2(c / n.sum())) for _, w, c in g)
    assert bins.optimal_bins(v, n, len(g))[0] <= cost + 1e-9


def test_lookup_table_holds_every_bin():
    b = bins.greedy_bins(np.array([3, 4, 900, 70_000]), np.array([9, 9, 9, 9]), 5)
    starts, widths = [x[0] for x in b], [x[1] for x in b]
    table, levels, bits = bins.lookup_table(starts, widths)
    for v in [3, 4, 5, 10, 899, 900, 901, 69_999, 70_000]:
        x, node = v - starts[0], 0
        for level in range(levels):
            e = table[(node << 8) + ((x >> (8 * (levels - 1 - level))) & 255)]
            if e >= 0:
                break
            node = -e
        assert e == np.searchsorted(starts, v, "right") - 1


def test_fused_table():
    m = tans.fit([3, 1, 4])
    fused = bins.fuse_bins(m, [0, 8, 24], [3, 4, 5])
    assert (fused["start"] == np.array([0, 8, 24])[m["dec"]["sym"]]).all() and len(fused["width"]) == 1 << m["r"]


def test_bit_fields():
    v, w = np.array([0, 5, 1023, 0, 2**40 - 1]), np.array([0, 3, 10, 4, 40])
    assert frames.unpack_bits(frames.pack_bits(v, w), w).tolist() == v.tolist()
    assert frames.unpack_bits(b"", np.zeros(0, np.int64)).tolist() == []


def test_frame_values_and_back():
    rng = np.random.default_rng(3)
    e, c = rng.integers(8, 12, 60), rng.integers(0, 5, 60)
    r = rng.integers(-50, 2**34, 60)
    f = r + rng.integers(0, 99, 60)
    refs, v, _ = frames.frame_values(e, c, r, f, 8, 4, 5)
    back = frames.frame_hits(frames.unpack_refs(refs, 4), v, 8, 5)
    assert sorted(zip(*map(list, back))) == sorted(zip(e, c, r, f))
    refs, v, _ = frames.frame_values(*[np.zeros(0, np.int64)] * 4, 0, 2, 5)
    assert [len(x) for x in frames.frame_hits(frames.unpack_refs(refs, 2), v, 0, 5)] == [0, 0, 0, 0]


def test_references():
    big = np.iinfo(np.int64)
    for refs, used in (([5, 9, 9, -3], [1, 1, 1, 1]), ([7, 0, 0, 8], [0, 1, 0, 1]), ([big.min, big.max, 0], [1, 1, 1]), ([4], [1]), ([4, 4], [0, 0])):
        refs, used = np.array(refs, np.int64), np.array(used, bool)
        with np.errstate(over="ignore"):
            assert (frames.unpack_refs(frames.pack_refs(refs, used), len(refs))[used] == refs[used]).all()
    assert len(frames.pack_refs(np.arange(64) * 1000 + 10**15, np.ones(64, bool))) < 64 * 3  # about 11 bits each


def test_joined_models():
    rng = np.random.default_rng(8)
    models = [tans.fit(c, 6) for c in ([5, 1, 1], [1, 9], [3, 3, 3, 3])]
    joined = tans.join_models(models)
    which = [rng.integers(0, 3, n) for n in (0, 1, 500, 90)]
    local = [np.array([rng.integers(0, len(models[k]["quota"])) for k in w], np.int64) for w in which]
    symbols = [x + joined["first"][w] for x, w in zip(local, which)]
    for backward in (False, True):
        coded = tans.encode_frames(symbols, joined, None, backward)
        back, starts = tans.decode_frames([(*c, len(s)) for c, s in zip(coded, symbols)], joined, backward, which)
        assert all((a == b).all() for a, b in zip(back, symbols)) and starts == [64] * 4
    with pytest.raises(ValueError):
        tans.join_models([tans.fit([1, 1], 3), tans.fit([1, 1], 4)])


def test_expgolomb_words():
    v = np.array([0, 1, 2, 6, 65_535, 70_000, 2**40])
    word, width = frames.expgolomb_words(v)
    assert frames.read_expgolomb(frames.pack_bits(word, width), len(v)).tolist() == v.tolist()
    assert width.tolist()[:4] == [1, 3, 3, 5]
