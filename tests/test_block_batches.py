"""Blocks coded many at once are those that are coded one by one."""

from __future__ import annotations

import time

import numpy as np

from seqvault import blocks as B
from seqvault import cipher

KEY = bytes(range(32))


def _texts():
    rng = np.random.default_rng(5)
    yield rng.integers(0, 300, 4000)
    yield np.repeat(rng.integers(0, 5, 900), rng.integers(1, 40, 900))
    yield np.zeros(1000, np.int64)
    yield np.array([7], np.int64)
    yield np.concatenate([np.arange(64), np.arange(64)[::-1], np.zeros(64, np.int64)])


def test_batches_equal_single_blocks():
    for text in _texts():
        for bs in (1, 64, 100, 4096):
            for coding in (B.Coding(), B.Coding(encrypt=False), B.Coding(mode="xor"), B.Coding(rounds=7)):
                if bs == 1 and len(text) > 1000:
                    continue
                single = [B.encode_block(text[i : i + bs], i // bs, KEY, coding) for i in range(0, len(text), bs)]
                many = B.encode_blocks(text, bs, KEY, coding)
                assert [(b.n, b.comp_len, b.bits, b.alpha.tolist(), b.counts.tolist(), b.payload) for b in many] == [(b.n, b.comp_len, b.bits, b.alpha.tolist(), b.counts.tolist(), b.payload) for b in single]
                assert np.concatenate(B.decode_blocks(many, 0, KEY, coding)).tolist() == text.tolist()
                assert [x.tolist() for x in B.decode_blocks(many[1:], 1, KEY, coding)] == [text[i : i + bs].tolist() for i in range(bs, len(text), bs)]


def test_wrong_key_gives_the_same_other_symbols():
    for text in _texts():
        many = B.encode_blocks(text, 100, KEY, B.Coding())
        wrong = B.decode_blocks(many, 0, bytes(32), B.Coding())
        assert [len(x) for x in wrong] == [b.n for b in many]


def test_skipped_words_move_later_ones_up():
    m = np.array([(1 << 31) + 1, 5, (1 << 31) + 1])  # nearly half of the words are skipped
    sizes = np.array([40, 30, 20])
    codes = np.concatenate([np.arange(n) % x for n, x in zip(sizes, m, strict=True)])
    got = cipher.add_many(codes, sizes, KEY, np.array([3, 4, 1 << 33]), m, 20, 1)
    want = np.concatenate([cipher.seal_add(np.arange(n) % x, cipher.KeyStream(KEY, v), int(x)) for n, x, v in zip(sizes.tolist(), m.tolist(), (3, 4, 1 << 33), strict=True)])
    assert got.tolist() == want.tolist()
    assert cipher.add_many(got, sizes, KEY, np.array([3, 4, 1 << 33]), m, 20, -1).tolist() == codes.tolist()


def test_a_transform_with_many_changes_is_not_coded_block_by_block():
    text = np.random.default_rng(6).integers(0, 300, 1 << 16)
    began = time.process_time()
    [B.encode_block(text[i : i + 1024], i // 1024, KEY, B.Coding()) for i in range(0, len(text), 1024)]
    single, began = time.process_time() - began, time.process_time()
    B.encode_blocks(text, 1024, KEY, B.Coding())
    assert time.process_time() - began < single / 2
