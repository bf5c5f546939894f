import numpy as np

from densecount.functions import codec


def test_sizes():
    assert [codec.registers_for(m) for m in (256, 512, 1024, 2048, 4096)] == [352, 704, 1408, 2816, 5632]
    assert (codec.round_up(2048), codec.words_for(2057)) == (2057, 187)


def test_all_states_round_trip():
    s = np.arange(codec.RADIX)
    assert (codec.states_np(codec.EXPONENT, codec.HISTORY) == s).all()


def test_words_match_big_integers():
    rng = np.random.default_rng(3)
    states = rng.integers(0, 56, 1408)
    words = codec.pack(states)
    for i in range(0, 1408, 11):
        want = sum(int(x) * 56**k for k, x in enumerate(states[i : i + 11]))
        assert int(words[i // 11]) % 2**64 == want
    assert (codec.unpack(words, 1408) == states).all()


def test_extremes_and_known_words():
    assert int(codec.pack(np.full(11, 55))[0]) % 2**64 == 56**11 - 1 == 16985107389382393855
    assert int(codec.pack(np.array([0, 0, 7, 0, 0, 3, 1, 3, 1, 11, 0]))[0]) == 59679795018913216
    assert int(codec.pack(np.array([15, 1, 14, 8, 15, 10, 31, 10, 20, 14, 5]))[0]) == 1594306396661222343


def test_digit_replacement():
    words = codec.pack(np.zeros(22, int))
    codec.replace_digit(words, 13, 55)
    assert codec.read_digit(words, 13) == 55
    codec.replace_digit(words, 13, 3)
    assert codec.unpack(words, 22).tolist() == [0] * 13 + [3] + [0] * 8


def test_promotion_keeps_margin():
    r = np.array([5, 6, 9, 14])
    states, floor = codec.promote(codec.states_np(r, np.array([1, 2, 3, 0])), -1)
    assert floor == 2 and codec.EXPONENT[states].tolist() == [2, 3, 6, 11]
    assert codec.HISTORY[states].tolist() == [1, 2, 3, 0]
