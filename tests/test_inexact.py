import random

from seqvault.index import IndexParams, build_index
from seqvault.inexact import CODES, locate_codes, locate_inexact
from seqvault.operators.barrier import scratch_path

KEY = bytes(range(64))


def test_mismatches_and_codes_equal_brute_force(spark):
    rnd = random.Random(4)
    items = [(i, "".join(rnd.choice("ACGT") for _ in range(rnd.randint(0, 60)))) for i in range(10)]
    index = build_index(spark.createDataFrame(items, "item_no long, seq string"), IndexParams(k=3, bs=16, mark_pct=25), KEY, scratch_path(spark, "inexact"))
    patterns = [(i, "".join(rnd.choice("ACGT") for _ in range(n))) for i, n in enumerate([3, 4, 6, 7, 8])] + [(9, items[2][1][:9] or "ACG")]
    asked = spark.createDataFrame(patterns, "pattern_id long, pattern string")
    for e in (0, 1, 2):
        want = sorted((p, i, o, m) for p, x in patterns for i, s in items for o in range(len(s) - len(x) + 1) if (m := sum(a != b for a, b in zip(s[o : o + len(x)], x, strict=True))) <= e)
        assert sorted(map(tuple, locate_inexact(index, asked, e).collect())) == want
    coded = [(0, "RYN"), (1, "ACB"), (2, "SSW")]
    want = sorted((p, i, o) for p, x in coded for i, s in items for o in range(len(s) - len(x) + 1) if all(c in CODES[y] for c, y in zip(s[o : o + len(x)], x, strict=True)))
    assert sorted(map(tuple, locate_codes(index, spark.createDataFrame(coded, "pattern_id long, pattern string")).collect())) == want
