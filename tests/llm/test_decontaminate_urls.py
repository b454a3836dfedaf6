import random
from collections import Counter

import duckdb
import numpy as np
import pytest
import regex

from seqvault.llm import decontaminate, url_rules
from seqvault.plans import inspect

DOCS = "doc_id long, text string, lang string, source string, n_chars long"
BENCH = "item_id long, text string"


def words(text):
    plain = regex.sub(r"[^\p{L}\p{N}]+", " ", (text or "").lower()).strip()
    return plain.split(" ") if plain else []


def brute(docs, items, k=5, least=0.8):
    """Best weighted similarity of any item-sized window, by trying all."""
    out = {}
    for d, text in docs:
        w = words(text)
        for i, passage in items:
            p = words(passage)
            if not p:
                continue
            q = min(k, len(p))
            want = Counter(tuple(p[a : a + q]) for a in range(len(p) - q + 1))
            size, best = min(len(p), len(w)), 0.0
            for s in range(len(w) - size + 1):
                have = Counter(tuple(w[s + a : s + a + q]) for a in range(size - q + 1))
                both = sum((want & have).values())
                best = max(best, both / (sum(want.values()) + sum(have.values()) - both))
            if best >= least:
                out[(d, i)] = best
    return out


@pytest.fixture(scope="module")
def corpus():
    rnd = random.Random(4)
    vocabulary = [f"word{i}" for i in range(300)] + ["é", "Straße", "2024"]
    make = lambda n: " ".join(rnd.choices(vocabulary, k=n))
    items = [(i, make(n)) for i, n in enumerate([3, 4, 5, 9, 20, 38, 38, 59, 60])] + [(20, None), (21, "?!"), (22, "a a a a a a a a")]
    docs = []
    for i in range(60):
        text = make(rnd.randint(0, 150))
        if i % 2:
            part = words(rnd.choice(items[:9])[1])
            cut = rnd.choice(["whole", "head", "tail", "change", "shift"])
            if cut == "head":
                part = part[max(1, len(part) // 15) :]
            elif cut == "tail":
                part = part[: -max(1, len(part) // 12)]
            elif cut == "change":
                part[rnd.randrange(len(part))] = "other"
            elif cut == "shift":
                part.insert(len(part) // 2, "extra")
            text = f"{make(rnd.randint(0, 30))}. {' - '.join(part).upper()}! {text}"
        docs.append((i, text))
    docs += [(100, None), (101, ""), (102, "a a a a a a a a a a"), (103, words(items[7][1])[0]), (104, " ".join(words(items[8][1])[:56])), (105, (items[6][1] + " ") * 40)]
    return docs, items


def test_windows_equal_brute_force(spark, corpus):
    docs, items = corpus
    frame = spark.createDataFrame([(d, t, "en", "s", 0) for d, t in docs], DOCS).selectExpr("*", "1 AS _id", "2 AS item_id", "3 AS w")
    bench = spark.createDataFrame(items, BENCH)
    want = brute(docs, items)
    assert len(want) > 15
    got = {(r["_id"], r["item_id"]): r["similarity"] for r in decontaminate.contaminated(frame, bench).collect()}
    assert got.keys() == want.keys()
    assert all(abs(got[k] - want[k]) < 1e-9 for k in want)
    report = decontaminate.report(frame, bench)
    rows = {r["doc_id"]: r for r in report.collect()}
    assert len(rows) == len(docs) and {d for d, r in rows.items() if r["contaminated"]} == {d for d, _ in want}
    assert all(rows[d]["n_items"] == sum(k[0] == d for k in want) for d in rows)
    kept = decontaminate.decontaminated(frame, bench)
    assert kept.columns == frame.columns and {r["doc_id"] for r in kept.collect()} == {d for d, _ in docs} - {d for d, _ in want}
    assert not inspect.uses_python(kept) and not inspect.has_cartesian(kept)


def test_odd_tables(spark, corpus):
    docs, items = corpus
    text = items[5][1]
    frame = spark.createDataFrame([(1, text, None, None, None), (1, text, None, None, None), (1, "clean", "", "", 0), (None, text, "", "", 0), (None, "clean", "", "", 0)], DOCS)
    bench = spark.createDataFrame(items, BENCH)
    flags = sorted((r["doc_id"] or 0, r["contaminated"]) for r in decontaminate.report(frame, bench).collect())
    assert flags == [(0, False), (0, True), (1, False), (1, True), (1, True)]
    assert decontaminate.report(frame.limit(0), bench).count() == 0
    assert {r["contaminated"] for r in decontaminate.report(frame, bench.limit(0)).collect()} == {False}
    assert decontaminate.decontaminated(frame, bench.limit(0)).count() == 5


def test_blocks_find_every_pair_within_the_radius(spark):
    rnd = random.Random(8)
    base = [rnd.getrandbits(64) for _ in range(5)]
    other = []
    for i, f in enumerate(base):
        for bits in (0, 1, 10, 19, 20, 20, 20, 24, 40):
            other.append((i, f ^ sum(1 << b for b in rnd.sample(range(64), bits))))
    signed = lambda x: x - (1 << 64) if x >> 63 else x
    F = url_rules.F
    left = spark.createDataFrame([(k, signed(f)) for k, (_, f) in enumerate(other)], "k long, fp long").withColumn("x", F.explode(decontaminate.blocks(F.col("fp")))).select("k", "x.*")
    right = decontaminate.near_blocks(spark.createDataFrame([(i, signed(f)) for i, f in enumerate(base)], "i long, fp long"), 20)
    got = {tuple(r) for r in left.join(right, ["block", "value"]).select("k", "i").distinct().collect()}
    assert got >= {(k, i) for k, (_, f) in enumerate(other) for i, g in enumerate(base) if (f ^ g).bit_count() <= 20}
    row = spark.range(1).select(decontaminate.blocks(F.lit(-1).cast("long")).alias("b")).first()[0]
    assert len(row) == decontaminate.BLOCKS and sum(bin(x["value"]).count("1") for x in row) == 64


def test_recall_of_the_radius():
    """Windows whose similarity to an item is 0.8 or little more: share within the radius of 20 bits."""
    rng = np.random.default_rng(5)
    missed, pairs = 0, 4_000
    for _ in range(pairs):
        n = int(rng.integers(20, 200))
        shared = -(-8 * n // 9)  # of n shingles each: similarity just over 0.8
        a = rng.integers(0, 1 << 63, n, dtype=np.uint64)
        b = np.concatenate([a[:shared], rng.integers(0, 1 << 63, n - shared, dtype=np.uint64)])
        bits = [np.unpackbits(x.view(np.uint8).reshape(n, 8), axis=1).sum(0) * 2 > n for x in (a, b)]
        missed += int((bits[0] != bits[1]).sum() > 20)
    assert missed / pairs < 0.002


def test_a_very_long_text(spark):
    rnd = random.Random(3)
    item = " ".join(f"w{rnd.randrange(500)}" for _ in range(40))
    text = " ".join(f"w{rnd.randrange(500)}" for _ in range(150_000))
    docs = spark.createDataFrame([(1, f"{text} {item} {text}", "", "", 0), (2, text, "", "", 0)], DOCS)
    rows = decontaminate.report(docs, spark.createDataFrame([(1, item), (2, "two words"), (3, "w1 w2 w3")], BENCH)).collect()
    flags = {r["doc_id"]: (r["contaminated"], r["best_item"]) for r in rows}
    assert flags[1][0] and flags[1][1] in (1, 3) and not (flags[2][0] and flags[2][1] != 3)


URLS = [None, "", "no scheme", "http://net", "http://net/", "HTTP://A.NET/x", "http://a.b.example.net/en/1?x=/fr/", "http://example.net/en", "http://xexample.net/en/1", "https://m.example.com/de/q#x", "https://example.com?/de/", "ftp://x.org/fr/", "x://org/fr/y://net/", "http://a-net/", "http://net.org/fr/", "http://u:p@shop.example.net/en/", "http://shop.example.net:80/en/", "http://example.net./en/", "://net/", "http://a\nb.net/x", "http:///en/"] + [f"http://h{i % 5}.example.net/en/{i}" for i in range(40)]


def slow_verdict(url, rules):
    at = (url or "").find("://")
    host, path = "", ""
    if at >= 0:
        rest = url[at + 3 :]
        cut = min([rest.find(c) for c in "/?#" if c in rest], default=len(rest))
        host, tail = rest[:cut], rest[cut:]
        path = tail[: min([tail.find(c) for c in "?#" if c in tail], default=len(tail))]
        host = "".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in host)
    fits = [(len(h + p), h + p, v) for v, h, p in rules if (host == h or host.endswith("." + h)) and path.startswith(p)]
    best = max(fits, default=None)
    return host, path, best and best[1], best[2] if best else "allow"


@pytest.mark.parametrize("extra", [[], [("allow", "b.example.net", "/"), ("block", "a.b.example.net", "/en/1"), ("block", "example.net", "/en/2"), ("block", "com", "/"), ("allow", "h1.example.net", "/")]])
def test_urls_equal_brute_force(spark, extra):
    rules = url_rules.RULES + extra
    pages = spark.createDataFrame(list(enumerate(URLS)), "page_id long, url string").selectExpr("*", "1 AS key", "2 AS stack", "'h' AS html")
    judged = url_rules.judge(pages, url_rules.rule_table(spark, rules))
    got = {r["page_id"]: tuple(r)[1:] for r in judged.collect()}
    assert got == {i: slow_verdict(u, rules) for i, u in enumerate(URLS)}
    assert not inspect.uses_python(judged)


def test_urls_repeated_rows_and_sql(spark):
    rules = url_rules.rule_table(spark, url_rules.RULES)
    twice = spark.createDataFrame([(None, "http://net/"), (None, "http://net/"), (3, None)], "page_id long, url string")
    assert sorted(r["verdict"] for r in url_rules.judge(twice, rules).collect()) == ["allow", "block", "block"]
    assert url_rules.judge(twice.limit(0), rules).count() == 0
    con = duckdb.connect()
    con.execute("CREATE TABLE pages (page_id BIGINT, url VARCHAR)")
    con.executemany("INSERT INTO pages VALUES (?, ?)", list(enumerate(URLS)))
    assert {r[0]: r[1:] for r in con.execute(url_rules.JUDGE_SQL).fetchall()} == {i: slow_verdict(u, url_rules.RULES) for i, u in enumerate(URLS)}
