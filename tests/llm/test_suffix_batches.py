import numpy as np

from seqvault.llm import suffix_dedup


def letters(rng, n):
    return rng.integers(97, 123, n, dtype=np.uint8)


def test_runs_do_not_depend_on_neighbours_or_pieces(monkeypatch):
    rng = np.random.default_rng(7)
    text = letters(rng, 3_000)
    one = lambda x: (x, np.array([0]), np.array([len(x)]))
    want = [c.tolist() for c in suffix_dedup.window_runs(*one(text), 100)]
    for piece in (1, 7, 64, 500):
        monkeypatch.setattr(suffix_dedup, "PIECE", piece)
        assert [c.tolist() for c in suffix_dedup.window_runs(*one(text), 100)] == want
        data = np.concatenate([letters(rng, 333), text, letters(rng, 150)])
        h, start, count, rel = suffix_dedup.window_runs(data, np.array([0, 333, 333, 3_333]), np.array([333, 333, 3_333, 3_483]), 100)
        mine = (start >= 333) & (start < 3_333)
        assert [h[mine].tolist(), (start[mine] - 333).tolist(), count[mine].tolist(), rel[mine].tolist()] == want
