import random
import time

import pytest
from pyspark.sql import functions as F

from suffixloom.functions.alphabet import DNA, DNA_N, Alphabet, Bytes, max_prefix_width
from suffixloom.functions.refs import RefLayout
from suffixloom.operators import grouping, partitioning, search, single, suffixes
from suffixloom.operators.refine import rank_doubling, refine_until_unique
from suffixloom.operators.store import BroadcastStore
from suffixloom.operators.validate import validate_order
from suffixloom.plans import build, measures, published
from suffixloom.scratch import stored
from suffixloom.sources import reads as src
from suffixloom.streaming import incremental

EDGE = ["", "A", "ACG", "ACGT", "ACGTA", "ACGTACGTAC" * 3, "AAAAAAAAAAAAAAAAAAAAAAAAAAAAAA", "ACG", "T"]


def brute(reads):
    """References in order of suffix bytes, then reference."""
    every = [(s[o:].encode(), i * 1000 + o) for i, s in reads for o in range(len(s) + 1)]
    return [ref for _, ref in sorted(every)]


def frame(spark, reads):
    return spark.createDataFrame(reads, "read_id long, seq string").repartition(3)


def order_of(sa):
    rows = sorted((r["pos"], r["ref"]) for r in sa.collect())
    assert [p for p, _ in rows] == list(range(len(rows)))
    return [ref for _, ref in rows]


@pytest.fixture(scope="module")
def dna():
    rng = random.Random(1)
    return list(enumerate(EDGE + ["".join(rng.choice("ACGT") for _ in range(rng.randint(0, 60))) for _ in range(40)]))


@pytest.fixture(scope="module")
def words():
    rng = random.Random(2)
    return list(enumerate(["", "$", "é", "日本語 text", "a\nb", "zz$$"] + ["".join(rng.choice("ab$ é\n日") for _ in range(rng.randint(0, 30))) for _ in range(30)]))


@pytest.mark.parametrize(
    "options",
    [{}, {"width": 3}, {"width": 13, "int_key": True}, {"short_rule": False, "singleton_rule": False}, {"whole_reads": True, "width": 4}, {"explicit_ranges": True, "parts": 5, "per_part": 20}, {"store": "broadcast"}, {"store": "placed"}, {"store": "placed", "width": 3}, {"store": "shuffle", "parts": 2}, {"store": "bucketed", "width": 4}, {"width": 2, "longer_above": 5}, {"width": 3, "longer_above": 20, "short_rule": False}],
)
def test_indexed_is_the_brute_order(spark, dna, options):
    assert order_of(build.indexed_suffix_array(frame(spark, dna), DNA, **({"width": 23, "parts": 4} | options))) == brute(dna)


def test_all_constructions_agree(spark, dna):
    want = brute(dna)
    assert order_of(build.materialized_suffix_array(frame(spark, dna), parts=4)) == want
    assert order_of(build.refined_suffix_array(frame(spark, dna), DNA, 7, parts=4)) == want
    passes = build.suffix_array_in_passes(frame(spark, dna), [5**22, 3 * 5**22], DNA, 23, 1)
    assert [r["ref"] for p in passes for r in p.collect()] == want


@pytest.mark.parametrize("width", [1, 3, 7])
def test_byte_codes_order_any_text(spark, words, width):
    assert order_of(build.indexed_suffix_array(frame(spark, words), Bytes, width, parts=3)) == brute(words)
    if width == 3:
        assert order_of(build.refined_suffix_array(frame(spark, words), Bytes, width, parts=3)) == brute(words)


def test_dense_alphabet(spark, words):
    reads = frame(spark, words)
    learned = Alphabet.learn(reads)
    assert list(learned.symbols) == sorted({c for _, s in words for c in s})
    assert order_of(build.indexed_suffix_array(reads, learned, max_prefix_width(learned.base, 64) - 1, parts=3)) == brute(words)


def test_rank_doubling(spark, words):
    ascii_words = [(i, s) for i, s in words if s.isascii()]
    ranks = {r["ref"]: r["rank"] for r in rank_doubling(frame(spark, ascii_words)).collect()}
    text = {i * 1000 + o: s[o:] for i, s in ascii_words for o in range(len(s) + 1)}
    assert set(ranks) == set(text)
    by_rank = sorted(text, key=lambda r: (ranks[r], r))
    assert [text[r] for r in by_rank] == sorted(text.values())
    assert all((ranks[a] == ranks[b]) == (text[a] == text[b]) for a, b in zip(by_rank, by_rank[1:]))


def test_empty_and_rejects(spark):
    none = frame(spark, [])
    assert order_of(build.indexed_suffix_array(none, DNA, 5, parts=2)) == []
    with pytest.raises(ValueError):
        RefLayout().check(frame(spark, [(1, "A" * 1000)]))
    with pytest.raises(ValueError):
        RefLayout().check(frame(spark, [(1, None)]))
    with pytest.raises(ValueError):
        src.reads_from(frame(spark, [(1, "A"), (1, "C")]), "read_id", "seq", validate=True)
    with pytest.raises(Exception, match="longer"):
        suffixes.expand_suffixes(frame(spark, [(1, "A" * 1001)])).collect()


def test_unsound_reads_are_refused(spark):
    """By both constructions, where they would otherwise give a wrong order or lose rows."""
    refs = lambda rows, alphabet=DNA: suffixes.expand_refs(frame(spark, rows), alphabet, 5).collect()
    for rows, alphabet in (([(1, "ANG")], DNA), ([(1, "acgt")], DNA), ([(1, "a\0b")], Bytes), ([(1, None)], DNA), ([(None, "A")], DNA), ([(1, "A" * 1500)], DNA), ([(-1, "A")], DNA), ([(10**16, "A")], DNA)):
        with pytest.raises(Exception, match="a read"):
            refs(rows, alphabet)
    for row in ((1, None), (1, "A" * 1000), (-5, "A")):
        with pytest.raises(Exception, match="a read"):
            suffixes.expand_suffixes(frame(spark, [row])).collect()
    with pytest.raises(Exception, match="pieces"):
        src.chunk_reads(frame(spark, [(1, "A" * 2001)]), "read_id", "seq", 2).collect()
    assert src.fit_stride(frame(spark, [(1, "A" * 2001)]), "seq", 2) == 10000
    with_n = [(1, "ANG"), (2, "NNA"), (3, "TNN"), (4, "")]
    assert order_of(build.indexed_suffix_array(frame(spark, with_n), DNA_N, 2, parts=2)) == brute(with_n)


def test_long_reads_keep_their_references_and_prefixes(spark):
    layout = RefLayout.fit(5000)
    reads = [(1, "AC" * 2500), (2, "AC" * 2499), (3, "C")]
    want = [r for _, r in sorted((s[o:], i * layout.stride + o) for i, s in reads for o in range(len(s) + 1))]
    sa = build.indexed_suffix_array(frame(spark, reads), DNA, 23, parts=3, layout=layout, emit="ref")
    assert order_of(sa) == want
    texts = {i * layout.stride + o: s[o:] for i, s in reads for o in range(len(s) + 1)}
    whole = spark.createDataFrame([(p, r, texts[r]) for p, r in enumerate(want) if len(texts[r]) > 4990 or p < 5], "pos long, ref long, suffix string")
    lcp = sorted((r["pos"], r["lcp"]) for r in search.common_prefix_with_previous(whole).collect())
    assert max(n for _, n in lcp) >= 4990


def test_oversize_codes_come_from_a_sample(spark):
    reads = frame(spark, [(i, "A" * 60 + "CGT"[i % 3]) for i in range(200)])
    assert build.oversize_codes(reads, DNA, 3, 4, 100, RefLayout()) == [31]
    assert build.oversize_codes(reads, DNA, 3, 4, 10**6, RefLayout()) == []


def test_accumulation_by_range_against_brute_force(spark):
    rng = random.Random(4)
    rows = [(r, c, rng.randint(1, 9)) for r in range(4) for c in range(rng.choice((0, 1, 50, 20_000)) if r else 30_000)]
    got = sorted(tuple(x) for x in grouping.accumulate_groups(spark.createDataFrame(rows, "r long, code long, n long"), 25, range_col="r").collect())
    want, state = [], {}
    for r, _, n in rows:
        k, groups, total = state.get(r, (0, 0, 0))
        groups, total = groups + 1, total + n
        if total > 25:
            want.append((r, k, groups, total))
            state[r] = (k + 1, 0, 0)
        else:
            state[r] = (k, groups, total)
    assert got == sorted(want + [(r, *x) for r, x in state.items() if x[1]])


def test_key_limits_and_codes(spark):
    assert (max_prefix_width(5, 32), max_prefix_width(5, 64)) == (13, 27)
    with pytest.raises(ValueError):
        DNA.encode(F.lit("A"), 14, int_key=True)
    row = spark.range(1).select(DNA.encode(F.lit("T" * 27), 27).alias("top"), DNA.decode(DNA.encode(F.lit("ACG"), 9), 9).alias("back")).first()
    assert (row["top"], row["back"]) == (5**27 - 1, "ACG")


def test_worked_example_and_groups(spark):
    row = spark.createDataFrame([("ECDCBA",)], "t string").select(single.suffix_array_col(F.col("t")).alias("sa")).first()
    assert row["sa"] == [6, 5, 4, 3, 1, 2, 0]
    reads = frame(spark, list(enumerate(["ATGAC", "ATGCA", "ATGGT", "ATGTT"])))
    at0 = lambda w: suffixes.expand_refs(reads, DNA, w).where("ref % 1000 = 0").groupBy("code").count().count()
    assert (at0(3), at0(4)) == (1, 4)
    _, left = refine_until_unique(frame(spark, [(i, "AT" * 100) for i in range(5)]), DNA, 23)
    assert left[-1] == 0 and len(left) <= 10


def test_boundaries_keep_groups_whole(spark, dna):
    refs = suffixes.expand_refs(frame(spark, dna), DNA, 10)
    cuts = partitioning.sample_boundaries(refs, 6, 50)
    small = partitioning.assign_partition(refs, cuts)
    assert small.groupBy("code").agg(F.count_distinct("part").alias("n")).where("n > 1").count() == 0
    many = partitioning.assign_partition(refs, sorted(set(cuts) | set(range(300))))
    assert many.groupBy("code").agg(F.count_distinct("part").alias("n")).where("n > 1").count() == 0


def test_accumulation_closes_after_the_limit(spark):
    groups = spark.createDataFrame([(i, n) for i, n in enumerate([3, 3, 9, 1, 1, 1, 8, 2])], "code long, n long")
    rows = sorted(tuple(r) for r in grouping.accumulate_groups(groups, 5).collect())
    assert rows == [(0, 2, 6), (1, 1, 9), (2, 4, 11), (3, 1, 2)]


def test_measures_against_printed_figures():
    units = measures.scheme_units(16, 200, 50)
    assert all(abs(units[side, counter] - printed) < 0.02 for side, counter, printed in published.INDEXED_UNITS)
    assert measures.placement_plan([gb for gb, _ in published.DISKS], 3) == [1, 1, 2, 3]
    large = measures.reduce_side_units(1.03 * published.LARGE_GB / 32, published.LARGE_HEAP_GB)
    assert abs(large - dict((x[:2], x[2]) for x in published.LARGE_UNITS)["reduce", "local_read"]) < 0.03
    assert round(sum(measures.phase_split(284.2, published.TIME_SPLIT).values()), 6) == 284.2


def test_merge_model():
    assert [measures.merged_segments(n) for n in (6, 13, 19, 26, 31, 35, 50)] == [0, 4, 10, 18, 24, 28, 45]
    for variant, (reducers, heap) in published.REDUCERS.items():
        for case in range(5):
            modelled = measures.reduce_side_units(1.03 * published.SIZES[case + 1][0] / reducers, heap)
            assert abs(modelled - published.REDUCE_UNITS[variant][case]) <= 0.11, (variant, case)
    assert round(measures.reducer_disk_need(111.38, 1.88)) == 644
    assert measures.predict(2.0, 1.0, 5.0, 5.0) is None and measures.predict(2.0, 1.0, 4.0, 5.0) == 9.0


def test_references_ship_less_than_suffixes(spark):
    reads = frame(spark, [(i, "ACGT" * 50) for i in range(5)])
    plan = suffixes.expand_refs(reads, DNA, 23).repartition("code")._jdf.queryExecution().executedPlan().toString()
    exchange = plan[plan.index("Exchange hashpartitioning(code") :].splitlines()
    assert "seq" not in exchange[1].split("AS ref")[-1]
    n, sizes = 201, suffixes.self_expansion(reads).first()
    assert abs(16 * n * 5 / sizes["suffix_bytes"] - 0.16) < 0.01


def test_search_against_brute_force(spark, dna, tmp_path):
    patterns = [(0, "ACGT"), (1, "AAAA"), (2, "GGGGGGGGGG"), (3, "A"), (4, "CG"), (5, "ACGTACGTACA"), (6, "T" * 70)]
    got = sorted(tuple(r) for r in search.search(frame(spark, dna), spark.createDataFrame(patterns, "pattern_id int, pattern string"), DNA, 4).collect())
    assert got == sorted((k, i * 1000 + o) for k, p in patterns for i, s in dna for o in range(len(s)) if s.startswith(p, o))
    assert search.search(frame(spark, dna), spark.createDataFrame([(0, ""), (1, None)], "pattern_id int, pattern string"), DNA, 4).count() == 0
    search.store_index(frame(spark, dna), DNA, 4, str(tmp_path / "index"), parts=3)
    by_index = search.search_index(spark, str(tmp_path / "index"), frame(spark, dna), [*patterns, (7, "XYZ")], DNA, 4)
    assert sorted(tuple(r) for r in by_index.collect()) == got
    search.store_index(frame(spark, dna[:20]), DNA, 4, str(tmp_path / "day1"), parts=2)
    search.store_index(frame(spark, dna[20:]), DNA, 4, str(tmp_path / "day2"), parts=2)
    incremental.merge_runs(spark, [str(tmp_path / "day1"), str(tmp_path / "day2")], str(tmp_path / "merged"), parts=3)
    assert sorted(map(tuple, spark.read.parquet(str(tmp_path / "merged")).collect())) == sorted(map(tuple, spark.read.parquet(str(tmp_path / "index")).collect()))
    sa = build.indexed_suffix_array(frame(spark, dna), DNA, 5, parts=3, emit="suffix")
    src.write_suffix_array(sa, str(tmp_path / "sa"))
    assert order_of(spark.read.parquet(str(tmp_path / "sa"))) == brute(dna)
    assert validate_order(sa).first()["violations"] == 0


def test_stream_equals_table(spark, tmp_path, dna):
    for k in range(3):
        frame(spark, dna[k::3]).write.parquet(str(tmp_path / "in"), mode="append")
    stream = incremental.read_stream(spark, str(tmp_path / "in"), "read_id long, seq string")
    run = incremental.stream_refs(stream, DNA, 10).writeStream.format("memory").queryName("refs_seen").trigger(availableNow=True).start()
    run.awaitTermination(120)
    seen = sorted(tuple(r) for r in spark.table("refs_seen").collect())
    assert seen == sorted(tuple(r) for r in suffixes.expand_refs(frame(spark, dna), DNA, 10).collect())


def test_read_files(spark, tmp_path):
    (tmp_path / "a.fa").write_text(">one x\nACGT\nAC\n>two\nGG\n")
    assert sorted(r["seq"] for r in src.load_reads(spark, str(tmp_path / "a.fa"), "fasta").collect()) == ["ACGTAC", "GG"]
    (tmp_path / "q").mkdir()
    (tmp_path / "q" / "a.fq").write_text("@one\nACGT\n+\n@III\n@two\nGG\n+two\n@@\n")
    (tmp_path / "q" / "b.fq").write_text("@three\nTTT\n+\n+@I\n")
    assert sorted(tuple(r) for r in src.load_reads(spark, str(tmp_path / "q"), "fastq").collect()) == [(0, "ACGT"), (1, "GG"), (2, "TTT")]
    (tmp_path / "a.csv").write_text("7,ACGT\n8,GG\n")
    (tmp_path / "a.json").write_text('{"read_id": 7, "seq": "ACGT"}\n{"read_id": 8, "seq": "GG"}\n')
    for kind in ("csv", "json"):
        assert sorted(tuple(r) for r in src.load_reads(spark, str(tmp_path / f"a.{kind}"), kind).collect()) == [(7, "ACGT"), (8, "GG")]
    (tmp_path / "a.txt").write_text("1\tACGT\n2\tGG\n")
    assert [tuple(r) for r in src.load_reads(spark, str(tmp_path / "a.txt"), "text").collect()] == [(1, "ACGT"), (2, "GG")]


def test_set_queries_read_whole_documents(spark):
    """Grams of every suffix of a read, by hand; the heads alone are only a part of them."""
    import re

    from suffixloom.plans.workloads import QUERIES

    sf, grams = "/root/testdata/sf0.001", {"en": set(), "de": set()}
    for r in spark.read.parquet(f"{sf}/documents.parquet").where("lang IN ('en', 'de')").collect():
        dna = re.sub("[^A-Za-z]", "", r["text"] or "").lower().translate(str.maketrans("abcdefghijklmnopqrstuvwxyz", ("ACGT" * 7)[:26]))
        reads = [dna[i : i + 200] for i in range(0, len(dna), 200)]
        grams[r["lang"]] |= {x[i : i + 12] for x in reads for i in range(len(x) - 11)}
    en, de = grams["en"], grams["de"]
    for op, want in (("union", en | de), ("intersect", en & de), ("except", en - de)):
        got = [r["gram"] for r in QUERIES[f"op_set_{op}_suffixes"](spark, sf).collect()]
        assert len(got) == len(set(got)) and set(got) == want, op


def test_copied_passages_of_any_length(spark):
    texts = spark.createDataFrame([(1, "abcabcdefgh"), (2, "ab"), (3, ""), (4, None), (5, "xxabcdefghyy")], "id long, text string")
    items = spark.createDataFrame([(1, "abc"), (2, "abcdefgh"), (3, "b"), (4, ""), (5, None), (6, "abcdefgz")], "item long, text string")
    found = {tuple(r) for r in search.copied_passages(texts, items, "id", "item", 5).collect()}
    bodies = {r["id"]: r["text"] for r in texts.collect() if r["text"]}
    assert found == {(r["item"], i) for r in items.collect() if r["text"] for i, body in bodies.items() if r["text"] in body}


def test_only_small_stores_are_broadcast(spark):
    """60,000 reads of 200 symbols were, which took more of the driver than it had for many short reads."""
    reads = spark.range(60_000).select(F.col("id").alias("read_id"), F.repeat(F.lit("A"), F.lit(200)).alias("seq"))
    assert not BroadcastStore(reads).everywhere()
    assert not BroadcastStore(spark.range(400_000).select(F.col("id").alias("read_id"), F.lit("ACGT").alias("seq"))).everywhere()
    assert BroadcastStore(reads.limit(1_000)).everywhere()


def test_stores_leave_no_shuffles_and_few_codes(spark, dna, monkeypatch):
    """Shuffles go when what they were made for is written, and settled references are written without their codes."""
    left = lambda: spark._jvm.org.apache.spark.SparkEnv.get().blockManager().diskBlockManager().getAllFiles().mkString(" ").count("shuffle_")
    before = left()
    stored(spark.range(1_000).groupBy((F.col("id") % 7).alias("k")).count(), "groups").collect()
    for _ in range(50):  # they go in the background
        if left() <= before:
            break
        time.sleep(0.1)
    assert left() <= before
    seen, whole = [], build.with_positions
    monkeypatch.setattr(build, "with_positions", lambda df, label: seen.append(df) or whole(df, label))
    assert order_of(build.indexed_suffix_array(frame(spark, dna), DNA, 4, parts=4)) == brute(dna)
    assert seen[0].where("NOT needs").count() and not seen[0].where("NOT needs AND code IS NOT NULL").count() and not seen[0].where("needs AND code IS NULL").count()
