import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from seqvault import blocks, cipher
from seqvault.alphabet import Alphabet, scramble_key

KEY = bytes(range(64))


def test_cipher_known_answer():
    key = bytes([0x80] + [0] * 31)
    want = "E3BE8FDD8BECA2E3EA8EF9475B29A6E7003951E1097A5C38D23B7A5FAD9F6844B22C97559E2723C7CBBD3FE4FC8D9A0744652A83E72A9C461876AF4D7EF1A117"
    assert cipher.salsa20_words(key, 0, 16).astype("<u4").tobytes().hex().upper() == want


def test_quarter_round_vector():
    x = [np.array([v], np.uint32) for v in (1, 0, 0, 0)]
    y = [*x, *[np.zeros(1, np.uint32)] * 12]
    cipher._apply(y, ((1, 0, 3, 7), (2, 1, 0, 9), (3, 2, 1, 13), (0, 3, 2, 18)))
    assert [int(v[0]) for v in y[:4]] == [0x08008145, 0x00000080, 0x00010200, 0x20500000]


def test_stream_continues_and_counters_agree():
    whole = cipher.salsa20_words(KEY[:32], 7, 100)
    assert (cipher.salsa20_words(KEY[:32], 7, 36, start=4) == whole[64:]).all()
    stream = cipher.KeyStream(KEY[:32], 7)
    assert (np.concatenate([stream.words(n) for n in (1, 50, 49)]) == whole).all()


def test_draws_are_in_bounds_and_equal_one_by_one():
    bounds = np.array([3, 1_000_000_007, 2, 3_000_000_000, 5] * 20)
    many = cipher.KeyStream(KEY[:32], 1).below(bounds)
    one = cipher.KeyStream(KEY[:32], 1)
    assert many.tolist() == [int(one.below(np.array([b]))[0]) for b in bounds]
    assert (many < bounds).all()


@pytest.mark.parametrize("size", [1, 2, 3, 49, 2401])
def test_permutation_keeps_zero(size):
    order = scramble_key(KEY, size)
    assert order[0] == 0 and sorted(order) == list(range(size))
    assert (scramble_key(KEY, size) == order).all()
    if size > 40:
        assert (scramble_key(KEY[::-1], size) != order).any()


def test_hand_cases():
    assert blocks.mtf(np.array([0, 0, 1, 1, 0, 2]), 3).tolist() == [0, 0, 1, 0, 1, 2]
    assert blocks.rle0(np.array([0, 0, 0, 2, 0])).tolist() == [0, 0, 3, 0]
    assert blocks.unrle0(np.array([0, 0, 3, 0])).tolist() == [0, 0, 0, 2, 0]


@settings(max_examples=120, deadline=None)
@given(st.lists(st.integers(0, 12), min_size=1, max_size=300), st.sampled_from(["add", "xor"]), st.booleans(), st.sampled_from([20, 15, 12, 8]))
def test_blocks_open_again(values, mode, encrypt, rounds):
    syms = np.array(values)
    coding = blocks.Coding(encrypt, mode, rounds)
    sealed = blocks.encode_block(syms, 9, KEY[32:], coding)
    assert (blocks.decode_block(sealed, 9, KEY[32:], coding) == syms).all()
    assert len(blocks.decode_block(sealed, 9, bytes(32), coding)) == len(syms)


def test_payload_differs_from_plain_and_by_block():
    syms = np.arange(400) % 7
    plain = blocks.encode_block(syms, 1, KEY[32:], blocks.Coding(False)).payload
    a, b = (blocks.encode_block(syms, n, KEY[32:], blocks.Coding()).payload for n in (1, 2))
    assert len({plain, a, b}) == 3
    assert a == blocks.encode_block(syms, 1, KEY[32:], blocks.Coding()).payload


def test_huffman_bits():
    assert blocks.huffman_bits(np.array([0, 0, 0, 1, 2])) == 3 + 2 + 2
    assert blocks.huffman_bits(np.array([4, 4])) == 2


def test_shard_keys_differ():
    keys = {cipher.block_key(KEY, b"salt", s, "scoped") for s in range(5)} | {cipher.block_key(KEY, b"other", 0, "scoped"), cipher.block_key(KEY, b"salt", 0, "paper")}
    assert len(keys) == 7
    with pytest.raises(ValueError):
        cipher.key_from_hex("00")
    assert len(cipher.new_key()) == 64


def test_alphabet_text_round_trip():
    alphabet = Alphabet(tuple("$&AB\U0001f600"), 3)
    for text in ("", "$", "A&B$", "\U0001f600A"):
        assert alphabet.text(alphabet.to_digits(alphabet.blocks(text)).reshape(-1)) == text
    assert alphabet.digits("AX").tolist() == [4, -1]
