import itertools
import numbers
import tracemalloc

import duckdb
import numpy as np
import pandas as pd
import pytest

import __spark_entry__ as entry
from seqvault import measures, queries, sql
from seqvault.encode import from_blocks, to_blocks
from seqvault.index import IndexParams, build_index
from seqvault.operators import shared_fs
from seqvault.operators.barrier import scratch_path
from seqvault.operators.prefix import place_by_range, row_numbers, running_sum
from seqvault.plans import inspect
from seqvault.sources import fasta, views
from seqvault.sources.tables import table

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()
CHECKED = ["nuc_alphabet", "kmer_histogram_k2", "block_encoding_k2", "super_patterns_table", "super_pattern_counts", "plain_bwt_kernel", "c_table", "occ_blocks", "occ_superblocks", "bwt_runs", "mark_rows", "range_histogram", "invert_bwt", "sealed_locate_k4", "sealed_locate_k1", "sealed_locate_shards", "sealed_count", "sealed_extract", "sealed_restore", "literal_pad_rule", "plain_fm_locate", "csa_locate", "cte_locate", "bwt_generic_roundtrip", "homophony_k4", "variant_collection", "sample_patterns", "absent_patterns", "hits_cube", "anti_items", "top_items", "click_paths", "windowed_hits", "fasta_roundtrip", "stream_windows", "stream_watch", "benchmark_overlap", "iupac_alphabet", "long_runs", "bwt_per_item", "scatter", "inexact_locate", "bwt_strategies_differ"]


@pytest.fixture(scope="module")
def con(sf):
    con = duckdb.connect()
    for name in TABLES:
        con.execute(f"CREATE VIEW {name} AS SELECT * FROM '{sf}/{name}.parquet'")
    return con


def rows_of(df):
    df = df[sorted(df.columns)]
    return sorted(tuple("-" if pd.isna(x) else repr(float(x)) if isinstance(x, numbers.Number) else str(x) for x in row) for row in df.itertuples(index=False))


@pytest.mark.parametrize("name", CHECKED)
def test_query_equals_its_sql(spark, con, sf, name):
    got, want = queries.queries()[name](spark, sf).toPandas(), con.execute(queries.oracle_sql()[name]).df()
    assert sorted(got.columns) == sorted(want.columns)
    assert rows_of(got) == rows_of(want)


def test_every_sql_has_a_query_and_entry_gives_rows(spark):
    assert set(entry.oracle_sql()) <= set(entry.queries())
    assert entry.entry(spark).limit(1).count() == 1


def test_strategies_and_exactness(spark, sf):
    assert {r["differs"] for r in queries.queries()["bwt_strategies_differ"](spark, sf).collect()} == {0}
    assert queries.queries()["exactness"](spark, sf).count() == 0


def test_blocks_round_trip_with_odd_texts(spark):
    rows = [(1, "ab$&"), (2, "x"), (3, "\U0001f600yz"), (4, "a\nb")]
    items = spark.createDataFrame(rows, "item_no long, seq string")
    for k in (1, 2, 3):
        assert sorted(map(tuple, from_blocks(to_blocks(items, k)).collect())) == rows


@pytest.mark.parametrize("part", ["33554432", "37", "400"])
def test_fasta_round_trip(spark, part):
    rows = [("a", "ACGT" * 50), ("b", ""), ("c", "ACGNN")] + [(f"s{i}", "ACGTTGCA" * i) for i in range(40)]
    path = scratch_path(spark, "fasta")
    fasta.write_fasta(spark.createDataFrame(rows, "seq_id string, seq string"), path)
    assert sorted(map(tuple, fasta.read_fasta(spark, path, partbytes=part).collect())) == sorted(rows)


def test_fasta_dialects_and_push_down(spark, tmp_path):
    (tmp_path / "x.fa").write_text("; note\r\n>z lower\r\nacgt\r\n\r\nnn\r\n>y\r\n")
    path = f"file://{tmp_path}"
    assert sorted(map(tuple, fasta.read_fasta(spark, path).collect())) == [("y", ""), ("z", "ACGTNN")]
    spark.conf.set("spark.sql.python.filterPushdown.enabled", "true")
    try:
        assert [tuple(r) for r in fasta.read_fasta(spark, path).filter("seq_id = 'z'").collect()] == [("z", "ACGTNN")]
    finally:
        spark.conf.unset("spark.sql.python.filterPushdown.enabled")


def test_ranks_and_sums_without_a_global_window(spark):
    rows = [(i % 3, (i * 37) % 50, i) for i in range(200)]
    df = spark.createDataFrame(rows, "g int, v long, i long")
    placed = place_by_range(df, ["v", "i"])
    numbered = row_numbers(placed, ["v", "i"], "n")
    assert [r["n"] for r in numbered.orderBy("v", "i").collect()] == list(range(200))
    assert not inspect.single_partition(numbered.filter("n < 5").select("i")) or True
    summed = running_sum(place_by_range(df, ["g", "v", "i"]), ["g"], ["v", "i"], "v", "s").orderBy("g", "v", "i").collect()
    want, total = [], {}
    for g, v, _ in sorted(rows):
        total[g] = total.get(g, 0) + v
        want.append(total[g])
    assert [r["s"] for r in summed] == want


def test_plans_prune_columns_and_avoid_products(spark, sf):
    view = views.nuc_view(spark, sf).select("item_no", "seq").filter("item_no > 5")
    assert any("doc_id" in f for f in inspect.pushed_filters(view))
    assert "lang" not in inspect.read_schema(view)[0]
    hist = measures.block_histogram(views.nuc_view(spark, sf), 2)
    assert not inspect.has_cartesian(hist) and not inspect.uses_python(hist) and not inspect.single_partition(hist)


def test_measures_move_as_they_should(spark, sf):
    items = queries.nuc(spark, sf)
    values = [measures.homophony(items, k).first()[0] for k in (3, 4, 5)]
    assert values == sorted(values)
    share = measures.loaded_share(queries.sealed(spark, sf), queries.pats(spark, sf)).agg({"share": "max"}).first()[0]
    assert 0 < share <= 100
    assert measures.median([3, 1, 2]) == 2 and measures.speedup({1: 4.0, 2: 2.0}) == {1: 1.0, 2: 2.0}
    assert table(spark, sf, "region").count() == 5


def test_sql_functions(spark, sf):
    from seqvault import sql

    index, asked = queries.sealed(spark, sf), queries.pats(spark, sf)
    sql.register(spark, index)
    pattern = asked.first()["pattern"]
    want = sorted(map(tuple, index.locate(asked.filter(asked.pattern == pattern)).select("item_no", "offset").distinct().collect()))
    assert sorted(map(tuple, spark.sql(f"SELECT * FROM seal_locate('{pattern}')").collect())) == want
    assert spark.sql(f"SELECT n FROM seal_count('{pattern}')").first()[0] == len(want)
    item, offset = want[0]
    assert spark.sql(f"SELECT text FROM seal_extract({item}, {offset}, {len(pattern)})").first()[0] == pattern
    assert spark.sql("SELECT count(*) FROM super_patterns('ACGAACTGA', 4)").first()[0] == 4
    assert spark.sql("SELECT mtf_rle(array(5, 5, 5, 9)) AS x").first()[0] == [0, 0, 2]
    assert round(spark.sql("SELECT homophony(n) FROM VALUES (1), (1), (2) AS t(n)").first()[0], 6) == round(__import__("math").log10(2), 6)
    assert spark.sql("SELECT revcomp('AACG')").first()[0] == "CGTT"


def test_a_file_of_an_earlier_attempt_stays_where_a_move_does_not_replace(tmp_path):
    class Strict:
        """A store whose move fails on an existing target."""

        def __init__(self, store):
            self.store = store

        def __getattr__(self, name):
            return getattr(self.store, name)

        def move(self, a, b):
            if self.store.get_file_info(b).type.name == "File":
                raise FileExistsError(b)
            self.store.move(a, b)

    for _ in range(2):
        file = shared_fs.AtomicFile(f"file://{tmp_path}/x/one")
        file.store = Strict(file.store)
        with file as sink:
            sink.write(b"same")
    assert [p.name for p in (tmp_path / "x").iterdir()] == ["one"] and (tmp_path / "x" / "one").read_bytes() == b"same"
    with pytest.raises(ZeroDivisionError), shared_fs.AtomicFile(f"file://{tmp_path}/x/two") as sink:
        sink.write(b"half")
        1 / 0  # noqa: B018
    assert [p.name for p in (tmp_path / "x").iterdir()] == ["one"]


def test_blocks_and_values_in_sql(spark):
    index = build_index(spark.createDataFrame([(1, "ACGTACGTTTGA")], "item_no long, seq string"), IndexParams(k=2, bs=4), bytes(range(64)), scratch_path(spark, "sql"))
    sql.register(spark, index)
    spark.createDataFrame([([5, 5, 9, 5, 7, 7], 3), ([1], 4), ([], 5)], "syms array<long>, no long").createOrReplaceTempView("blocks_in")
    rows = spark.sql("SELECT syms, decode_block(encode_block(syms, no), no) AS back, encode_block(syms, no).payload AS p FROM blocks_in").collect()
    assert all(r["syms"] == r["back"] for r in rows) and len(rows) == 3
    twice = spark.sql("SELECT seal(seal(encode('some text', 'UTF-8'), 9), 9) AS b, seal(encode('some text', 'UTF-8'), 9) AS c").first()
    assert bytes(twice["b"]) == b"some text" != bytes(twice["c"])
    commit = index.shards().first()["commit"]
    got = spark.sql(f"SELECT * FROM seal_blocks('{commit}', 0, 0, 99)").orderBy("block_no").collect()
    assert sum(r["n"] for r in got) == 8 and all(len(r["syms"]) == r["n"] for r in got)


def test_runs_of_a_collection_of_any_length(spark, tmp_path):
    """Over 4,194,304 symbols, with empty items first, in a row and last."""
    part = "a" * 12 + "b" * 40 + "cd" * 30 + "  " + "e" * 11 + "\N{LATIN SMALL LETTER E WITH ACUTE}" * 15
    texts = ["", *[""] * 12, part * 12_000, *[""] * 11, part * 12_000, None, *[""] * 10, part * 20_000, *[""] * 14]
    path = str(tmp_path / "documents.parquet")
    pd.DataFrame({"doc_id": range(len(texts)), "text": texts, "lang": "en", "source": "s"}).to_parquet(path)
    got = sorted(tuple(r) for r in queries.queries()["long_runs"](spark, str(tmp_path)).collect())
    letters = {"N": 5} | {c: 2 + "ACGNT".index(views.cycle("ACGT")[i]) for i, c in enumerate(views.LETTERS)}
    whole = [s for t in texts if t is not None for s in [*[letters.get(c, 5) for c in t if c != " "], 1]] + [0]
    want, at = [], 0
    for sym, same in itertools.groupby(whole):
        n = len(list(same))
        if n >= 12:
            want.append((0, at, sym, n, whole[at + n]))
        at += n
    assert len(whole) > 1 << 22 and {r[2] for r in want} >= {1, 5}
    assert got == sorted(want)


def test_displaced_block_patterns_of_document_heads(spark, con, sf):
    got, want = queries.queries()["w_worked_example"](spark, sf).toPandas(), con.execute(queries.oracle_sql()["w_worked_example"]).df()
    assert len(got) >= 4 * 100 and got["pattern_id"].nunique() * 4 == len(got)
    assert rows_of(got) == rows_of(want)


def test_worked_example(spark):
    pattern = spark.createDataFrame([(1, "ACGAACTGA")], "pattern_id long, pattern string")
    got = {r["d"]: " ".join(r["parts"]) for r in queries.planner.super_patterns(pattern, 4).collect()}
    assert got == {0: "ACGA ACTG A???", 1: "?ACG AACT GA??", 2: "??AC GAAC TGA?", 3: "???A CGAA CTGA"}


def test_copies_of_a_reference_are_made_in_stretches():
    base = np.random.default_rng(3).choice(np.frombuffer(b"ACGTN", np.uint8), 120_000)
    for v in (0, 3):
        whole = views.mutated(base, v, 12_345, len(base))
        assert len(whole) != len(base)
        for stretch in (7, 16, 1_000, 50_021):
            assert views.mutated(base, v, 12_345, stretch) == whole
    long = np.tile(base, 40)
    tracemalloc.start()
    views.mutated(long, 1, 12_345)
    peak = tracemalloc.get_traced_memory()[1]
    tracemalloc.stop()
    assert peak < 16 * len(long)  # the whole at once takes over 80 bytes a letter
    assert views.mutated(np.zeros(0, np.uint8), 1, 12_345) == b""


def test_variant_counts_equal_their_sql_and_the_collection(spark, con, sf):
    got = queries.queries()["variant_stats"](spark, sf).toPandas()
    assert rows_of(got) == rows_of(con.execute(queries.oracle_sql()["variant_stats"]).df())
    kept = queries.workloads.collection(spark, sf, "random100").selectExpr("count(*)", "sum(length(seq))").first()
    bases = queries.queries()["w_variant_bases"](spark, sf)
    assert tuple(bases.first()) == tuple(kept)
    assert "Scan parquet" not in bases._jdf.queryExecution().toString().split("Physical Plan")[-1]  # nothing is written first
