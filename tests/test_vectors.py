"""Printed examples and what follows from printed numbers."""

import numpy as np
import pytest

from hitcodec.operators import fec, prefix, rangecoder, tans

P = [0.8825, 0.06591, 0.01948, 0.009375, 0.01503, 0.00653, 0.00101, 0.00013, 0.000002]


def test_four_state_tables():
    m = tans.model_of(np.array([0, 1, 0, 0]), 2)
    assert m["dec"]["sym"].tolist() == [0, 1, 0, 0]
    assert m["dec"]["nbits"].tolist() == [1, 2, 0, 0]
    assert m["dec"]["base"].tolist() == [2, 0, 0, 1]
    assert m["enc"]["nb"].tolist() == [2, 12]
    assert m["enc"]["off"].tolist() == [-3, 2]
    assert m["enc"]["next"].tolist() == [4, 6, 7, 5]


def test_message():
    m = tans.model_of(np.array([0, 1, 0, 0]), 2)
    msg = np.array([1, 0, 0, 0, 0, 1, 1])
    [(data, bits, state)] = tans.encode_frames([msg], m, [4])
    assert (format(data[0], "08b"), bits, state) == ("00100001", 8, 5)
    back, start = tans.decode_frames([(data, bits, state, 7)], m)
    assert back[0].tolist() == msg.tolist() and start == [4]


def test_stationary_and_loss():
    m = tans.model_of(np.array([0, 1, 0, 0]), 2)
    assert np.allclose(tans.stationary(m, [0.75, 0.25]), [0.3214, 0.25, 0.2411, 0.1875], atol=1e-4)
    assert abs(tans.loss(m, [0.75, 0.25])["loss"] - 0.0102) < 1e-4
    assert abs(tans.spread_best([6, 2], 3, np.array([0.75, 0.25]))[1] - 0.0018) < 1e-4


def test_huffman_of_printed_frequencies():
    lengths = prefix.huffman_lengths({k: int(p * 1e9) for k, p in enumerate(P)})
    assert [lengths[k] for k in range(9)] == [1, 2, 3, 5, 4, 6, 7, 8, 8]
    assert abs(sum(p * lengths[k] for k, p in enumerate(P)) / sum(P) - 1.2271) < 1e-3
    assert prefix.kraft_sum(lengths.values()) == 1


def test_costs_of_printed_frequencies():
    p = np.array(P) / sum(P)
    assert abs(-(p * np.log2(p)).sum() - 0.7418) < 1e-3
    golomb = [2 * (k + 1).bit_length() - 1 for k in range(9)]
    assert abs((p * golomb).sum() - 1.2993) < 1e-3
    assert abs(-np.log2(0.8825) - 0.18) < 1e-3
    assert round(np.log2(9), 2) == 3.17
    assert abs(48 * 4 + 5.64 * 28 + 11.02 * 27 + (11.02 - 5.64) * 28 - 798) / 798 < 0.015
    assert round(1170 / 437, 2) in (2.67, 2.68)


@pytest.mark.parametrize("kind", ["step", "block", "reverse", "precise"])
@pytest.mark.parametrize("r", [3, 4, 5, 8, 11])
def test_spreads_keep_quotas(kind, r):
    q = tans.quotas([5, 1, 900, 33], r)
    assert q.sum() == 1 << r and q.min() >= 1
    assert (np.bincount(tans.spread(q, r, kind), minlength=4) == q).all()


def test_quotas_refuse():
    with pytest.raises(ValueError):
        tans.quotas([1] * 9, 3)
    with pytest.raises(ValueError):
        tans.quotas([1, 0], 3)


@pytest.mark.parametrize("backward", [False, True])
@pytest.mark.parametrize("counts", [[1], [3, 1], [10**6, 2, 2], list(range(1, 60))])
def test_tans_round_trip(counts, backward):
    rng = np.random.default_rng(1)
    p = np.array(counts) / sum(counts)
    model = tans.fit(counts, max(2, tans.choose_r(len(counts))))
    frames = [rng.choice(len(counts), size=n, p=p) for n in (0, 1, 2, 777, 64)]
    size = 1 << model["r"]
    start = [size + k % size for k in range(5)]
    coded = tans.encode_frames(frames, model, start, backward)
    back, starts = tans.decode_frames([(*c, len(f)) for c, f in zip(coded, frames)], model, backward)
    assert all((a == b).all() for a, b in zip(back, frames)) and starts == start


def test_range_coder_is_close_to_entropy():
    rng = np.random.default_rng(2)
    p = np.array(P) / sum(P)
    f = rng.choice(9, size=20_000, p=p)
    cum = rangecoder.model(np.bincount(f, minlength=9) + 1)
    [data] = rangecoder.range_encode([f], cum)
    assert (rangecoder.range_decode([data], [len(f)], cum)[0] == f).all()
    q = np.bincount(f, minlength=9) / len(f)
    h = -(q[q > 0] * np.log2(q[q > 0])).sum() * len(f)
    assert abs(len(data) * 8 - h) < 0.01 * h + 64


def test_depth_limit_and_escape():
    lengths = prefix.huffman_lengths({k: 2**k for k in range(12)}, 5)
    assert max(lengths.values()) == 5 and prefix.kraft_sum(lengths.values()) == 1
    assert prefix.huffman_lengths({7: 5}) == {7: 1}
    counts, escape = prefix.with_escape({0: 5, 1: 3, 9: 2}, 3)
    assert escape == 4 and counts == {0: 5, 1: 3, 4: 2}
    codes = prefix.canonical_codes(prefix.huffman_lengths({0: 5, 1: 3, 4: 2}))
    data, bits = prefix.encode_bits(np.array([0, 4, 1, 0]), codes)
    assert prefix.decode_bits(data, 4, codes).tolist() == [0, 4, 1, 0] and bits == sum(codes[s][0] for s in (0, 4, 1, 0))


def test_forward_error_correction():
    data = bytes(range(50))
    coded = fec.hamming_encode(data)
    for at in range(0, len(coded) * 8 - 5, 37):
        bad = bytearray(coded)
        bad[at // 8] ^= 1 << (at % 8)
        assert fec.hamming_decode(bytes(bad), len(data))[0] == data
    blocks = [b"abc", b"de", b"fghij"]
    parity = fec.parity_encode(blocks)
    assert fec.parity_repair([b"abc", None, b"fghij"], [3, 2, 5], parity) == blocks
    with pytest.raises(ValueError):
        fec.parity_repair([None, None, b"x"], [3, 2, 1], parity)


def test_symbols_beyond_the_alphabet():
    from hitcodec.functions.udfs import decode_udtf

    decode = decode_udtf(3).func().eval
    assert list(decode("1010011")) == [(0, 0), (1, 1), (2, 2)]
    with pytest.raises(ValueError):
        list(decode("100100"))
