"""Sizes against a reference, beside the plain way with a dictionary of all seeds."""

from __future__ import annotations

import random
import zlib

from seqvault.baselines import compressors as C


def plain_size(text: str, base: str, seed: int) -> int:
    spots: dict[str, int] = {}
    for i in range(0, max(0, len(base) - seed + 1)):
        spots.setdefault(base[i : i + seed], i)
    out, i, plain = [], 0, []
    while i < len(text):
        at = spots.get(text[i : i + seed], -1)
        if at < 0:
            plain.append(text[i])
            i += 1
            continue
        n = seed
        while i + n < len(text) and at + n < len(base) and text[i + n] == base[at + n]:
            n += 1
        out.append(f"{''.join(plain)}|{at},{n};")
        plain, i = [], i + n
    return len(zlib.compress(("".join(out) + "".join(plain)).encode(), 9))


def _cases():
    rng = random.Random(4)
    base = "".join(rng.choices("ACGTN", k=3000))
    base += base[100:900] + "A" * 200 + base[2000:2100]
    texts = [base, base[:40] + "C" + base[41:], "".join(c if rng.random() > 0.01 else rng.choice("ACGT") for c in base), "A" * 500, base[-30:] + base[:500], "", "ACG", base[5:28]]
    return base, [*texts, "né" + base[60:300] + "\U0001f600"]


def test_sizes_are_those_of_the_plain_way(spark, monkeypatch):
    base, texts = _cases()
    monkeypatch.setattr(C, "STRETCH", 100)
    for reference in (base, base + "é" + base[:50], base[:10], ""):
        table = C.SeedTable(reference, 24, *C.SeedTable.make(reference, 24))
        assert [C.referential_bytes(t, table) for t in texts] == [plain_size(t, reference, 24) for t in texts]


def test_seeds_that_share_a_hash_are_told_apart(monkeypatch):
    base, texts = _cases()
    monkeypatch.setattr(C, "seed_hashes", lambda points, seed: (points[: max(0, len(points) - seed + 1)].astype("<u8") % 3) << C.np.uint64(61))
    table = C.SeedTable(base, 24, *C.SeedTable.make(base, 24))
    assert [C.referential_bytes(t, table) for t in texts] == [plain_size(t, base, 24) for t in texts]


def test_the_reference_never_reaches_the_driver(spark):
    base, texts = _cases()
    items = spark.createDataFrame(list(enumerate(texts)), "item_no long, seq string")
    ref = spark.createDataFrame([(base,)], "seq string")
    ref.first = ref.collect = ref.toPandas = None
    got = sorted(map(tuple, C.referential_size(items, ref).collect()))
    assert got == [(i, len(t), plain_size(t, base, 24)) for i, t in enumerate(texts)]
    assert C.referential_size(items, ref).dtypes == [("item_no", "bigint"), ("raw", "int"), ("packed", "int")]
