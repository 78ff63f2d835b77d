import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from couponspark.operators import codec as C
from couponspark.operators.simulate import sample_state


@pytest.mark.parametrize("name", list(C.CODECS))
@pytest.mark.parametrize("ratio", [0.01, 1, 10, 3000.0])
def test_round_trip(name, ratio):
    w = sample_state(512, 512 * ratio, np.random.default_rng(1))
    encode, decode = C.CODECS[name]
    assert (decode(encode(w)) == w).all()


@pytest.mark.parametrize("name", list(C.REGISTER_CODECS))
def test_registers(name):
    regs = C.registers_of(sample_state(1024, 1e6, np.random.default_rng(2)))
    encode, decode = C.REGISTER_CODECS[name]
    assert (decode(encode(regs)) == regs).all()


@settings(max_examples=40, deadline=None)
@given(st.lists(st.integers(0, (1 << 62) - 1), min_size=16, max_size=16))
def test_any_words(words):
    w = np.array(words, np.int64)
    for encode, decode in (C.CODECS["window_zstd"], C.CODECS["golomb"]):
        assert (decode(encode(w)) == w).all()


def test_rotation_and_window():
    w = np.zeros(64, np.int64)
    w[3] = 1 << 60  # beyond the window
    assert (C.decode_window(C.encode_window(w)) == w).all()
    for rotate in (True, False):
        s = sample_state(256, 256 * 8.0, np.random.default_rng(3))
        assert (C.decode_window(C.encode_window(s, rotate=rotate)) == s).all()


def test_sizes():
    """Bits a row: 5.2 for the matrix, little above the entropy for registers; the finer codes lie between."""
    w = sample_state(32768, 32768 * 64.0, np.random.default_rng(4))
    assert 8 * len(C.encode_window(w)) / 32768 == pytest.approx(5.2, abs=0.15)
    assert 8 * len(C.encode_window(w, rotate=False)) > 8 * len(C.encode_window(w))
    regs = C.registers_of(w)
    assert 2.83 < 8 * len(C.encode_register_zstd(regs)) / 32768 < 3.3
    small = sample_state(8192, 8192 * 64.0, np.random.default_rng(5))
    arithmetic, prefix = (8 * len(C.CODECS[n][0](small)) / 8192 for n in ("arithmetic", "prefix"))
    assert arithmetic == pytest.approx(4.70, abs=0.06) and arithmetic < prefix < 5.05
