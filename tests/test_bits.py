import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from hcube.functions.bits import BitVec, Dac, dac_best_width, dac_bits, unzigzag, zigzag
from hcube.functions.louds import Louds
from hcube.operators.measures import separation, welch_z

# A walk with all its positions known.
T_A = "1001110001001010000100001010010"
T_C = "111111110111011111011011111111011111111011111111011111011101110100"


@settings(max_examples=60, deadline=None)
@given(st.lists(st.integers(0, 1), min_size=1, max_size=300))
def test_rank_and_select(bits):
    v = BitVec(bits)
    ones = [i for i, b in enumerate(bits) if b]
    zeros = [i for i, b in enumerate(bits) if not b]
    assert [v.get(i) for i in range(len(bits))] == bits
    assert [v.rank1(i) for i in range(len(bits))] == list(np.cumsum(bits))
    assert [v.select1(j + 1) for j in range(len(ones))] == ones
    assert [v.select0(j + 1) for j in range(len(zeros))] == zeros
    assert BitVec.from_bytes(v.to_bytes(), len(bits)).words.tolist() == v.words.tolist()


@settings(max_examples=60, deadline=None)
@given(st.lists(st.integers(-(2**40), 2**40), min_size=1, max_size=60), st.integers(1, 16))
def test_dac_round_trip(values, width):
    coded = zigzag(np.array(values))
    d = Dac(coded, width)
    assert unzigzag(d.all()).tolist() == values
    assert d.size_bits() == dac_bits(coded, width)
    assert dac_bits(coded, dac_best_width(coded)) <= dac_bits(coded, width)


def test_known_walk():
    ta, tc = BitVec(T_A), BitVec(T_C)
    assert ta.get(5) == 1 and ta.rank1(5) == 4 and tc.select0(4) + 1 == 22
    assert ta.get(24) == 1 and ta.rank1(24) == 9 and tc.select0(9) + 1 == 59
    # One zero for each node with children: the root and every occupied slot.
    assert T_C.count("0") == T_A.count("1") + 1 and len(T_C) == 66


@settings(max_examples=60, deadline=None)
@given(st.lists(st.integers(0, 4), min_size=1, max_size=25))
def test_louds_identities(wanted):
    degrees, open_ = [], 1
    for d in wanted:
        degrees.append(d)
        open_ += d - 1
        if open_ == 0:
            break
    degrees += [0] * open_
    t = Louds(degrees)
    assert len(t.bits) == 2 * len(degrees) - 1
    for number, d in enumerate(degrees):
        i = t.node(number)
        assert t.degree(i) == d and t.number(i) == number
        for k in range(1, d + 1):
            child = t.child(i, k)
            assert t.parent(child) == i and t.ordinal(child) == k and t.path(child) == [*t.path(i), k - 1]


def test_first_degree():
    assert "".join(str(Louds([3, 0, 0, 0]).bits.get(i)) for i in range(4)) == "1110"


def test_significance():
    assert separation(5.1, 1.75, 0.447, 0.55) == pytest.approx(4.727, abs=1e-3)
    assert welch_z(5.1, 1.75, 0.447, 0.55, 20) == pytest.approx(21.1, abs=0.05)


def test_batches_equal_single_steps():
    rng = np.random.default_rng(5)
    for n in (1, 63, 64, 65, 128, 1000):
        bits = rng.integers(0, 2, n)
        bits[0] = 0
        v = BitVec.from_bytes(BitVec(bits).to_bytes(), n)
        at = np.arange(n)
        assert v.get_many(at).tolist() == [bool(v.get(i)) for i in at]
        assert v.rank1_many(at).tolist() == [v.rank1(i) for i in at]
        ranks = np.arange(1, n - bits.sum() + 1)
        assert v.select0_many(ranks).tolist() == [v.select0(j) for j in ranks]
    values = np.r_[rng.integers(0, 9, 500), rng.integers(0, 2**62, 20), 0].astype(np.uint64)
    for width in (1, 4, 7, 16):
        code = Dac.from_bytes(Dac(values, width).to_bytes())
        assert code.all().tolist() == values.tolist() == [code.get(i) for i in range(len(values))]
        assert code.size_bits() == dac_bits(values, width)
