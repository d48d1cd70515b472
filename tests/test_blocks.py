import random
from collections import Counter

import duckdb
import pytest

from suffixloom.functions.alphabet import DNA, DNA_N, Bytes
from suffixloom.functions.refs import RefLayout
from suffixloom.operators import blocks, partitioning, search, store, suffixes
from suffixloom.plans import build
from suffixloom.plans.workloads import QUERIES, SQL


@pytest.fixture(scope="module")
def at(spark, tmp_path_factory):
    rng, path = random.Random(11), str(tmp_path_factory.mktemp("blocks"))
    words = ["".join(rng.choice("abcdefgh é") for _ in range(40)) for _ in range(12)]
    docs = [(i, " ".join(rng.choice(words) for _ in range(rng.randint(0, 12))) if i % 5 else "a" * 600) for i in range(40)]
    spark.createDataFrame(docs, "doc_id long, text string").repartition(3).write.parquet(f"{path}/documents.parquet")
    spark.createDataFrame(docs, "page_id long, html string").repartition(3).write.parquet(f"{path}/pages.parquet")
    return path


def compare(spark, at, name):
    rows = sorted(map(tuple, QUERIES[name](spark, at).collect()), key=str)
    con = duckdb.connect()
    for t in ("documents", "pages"):
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM '{at}/{t}.parquet/*.parquet'")
    assert rows and rows == sorted(con.sql(SQL[name]).fetchall(), key=str)


def plan_of(df):
    return df._jdf.queryExecution().executedPlan().toString()


@pytest.mark.parametrize("block", (7, 1 << 20))
def test_codes_met_again_in_later_blocks(spark, block, monkeypatch):
    """A code is told whether its suffixes meet in one block or in several, and a hot one passes as it comes."""
    monkeypatch.setattr(blocks, "BLOCK", block)
    rng = random.Random(1)
    seqs = ["A" * 60, "A" * 40, ""] + ["".join(rng.choice("ACGT") for _ in range(rng.randint(0, 50))) for _ in range(40)]
    reads = spark.createDataFrame(list(enumerate(seqs)), "read_id long, seq string").repartition(4)
    every = [(s[o : o + 4], i * 1000 + o, len(s)) for i, s in enumerate(seqs) for o in range(len(s) - 3)]
    times = Counter(head for head, _, _ in every)
    for shares in (1, 3):
        found = [r for i in range(shares) for r in blocks.shared_codes(reads, DNA, 4, RefLayout(), 5, (i, shares) if shares > 1 else None).collect()]
        assert sorted((r["ref"], r["n"]) for r in found) == sorted((ref, n) for head, ref, n in every if times[head] > 1)
    with pytest.raises(Exception, match="beside the alphabet"):
        blocks.shared_codes(spark.createDataFrame([(1, "ACGTN")], "read_id long, seq string"), DNA, 4, RefLayout(), 5, None).collect()


@pytest.mark.parametrize("name", ("block_fetch_bytes", "fetch_requests", "fetch_tail_vs_whole"))
def test_fetches_deal_blocks(spark, at, name):
    """References travel in blocks, and lengths of reads with them: nothing is sorted or joined row by row."""
    compare(spark, at, name)
    plan = plan_of(QUERIES[name](spark, at))
    assert "Join" not in plan and "Sort [" not in plan and "body" in plan


def suffixes_of(seqs):
    return [ref for _, ref in sorted((s[o:].encode(), i * 1000 + o) for i, s in enumerate(seqs) for o in range(len(s) + 1))]


@pytest.mark.parametrize("alphabet, width, letters", ((DNA, 5, "ACGT"), (Bytes, 3, "aé€😀"), (DNA_N, 24, "N")))
@pytest.mark.parametrize("options", ({}, {"longer_above": 5, "parts": 4}, {"short_rule": False}, {"explicit_ranges": True, "parts": 3}), ids=str)
def test_arrays_from_blocks(spark, alphabet, width, letters, options, monkeypatch):
    """Shares, parts, slices and pieces end everywhere; hot codes have parts of their own, and vast groups are sorted row by row."""
    rng = random.Random(len(letters) + width)
    seqs = ["", letters[0] * 70] * 2 + ["".join(rng.choice(letters) for _ in range(rng.randint(0, 90))) for _ in range(20)]
    seqs += seqs[:9]
    reads = spark.createDataFrame(list(enumerate(seqs)), "read_id long, seq string").repartition(3)
    vast, ask = [], blocks.positions_of
    for name, value in (("GROUP", 8), ("PART", 200), ("SLICE", 300), ("BLOCK", 50)):
        monkeypatch.setattr(blocks, name, value)
    monkeypatch.setattr(suffixes, "FETCH_SUFFIXES", 1_000)
    monkeypatch.setattr(blocks, "positions_of", lambda table, kind, *rest: vast.append(kind) or ask(table, kind, *rest))
    found = build.indexed_suffix_array(reads, alphabet, width, store="placed", **options).collect()
    assert sorted((r["pos"], r["ref"]) for r in found) == list(enumerate(suffixes_of(seqs)))
    assert blocks.VAST in vast and blocks.SETTLED in vast


@pytest.mark.parametrize("name", ("idx_sa_paired", "idx_sa_dna", "idx_sa_html_longer", "idx_sa_placed_store", "idx_sa_text_w3"))
def test_arrays_are_dealt_in_blocks(spark, at, name, monkeypatch):
    """No reference is a row before it has its position, unless its group is vast; the array is the same as DuckDB's."""
    monkeypatch.setattr(store, "BROADCAST_BYTES", -1)
    seen, stored = [], blocks.stored
    monkeypatch.setattr(blocks, "stored", lambda df, label: seen.append(plan_of(df)) or stored(df, label))
    compare(spark, at, name)
    assert len(seen) == 1 and "body" in seen[0] and "Sort [" not in seen[0]


def test_what_fills_a_part_has_one_of_its_own():
    assert partitioning._with_those_apart([3, 7, 7, 7, 9]) == [3, 6, 7, 9]
    assert blocks.apart([3, 6, 7, 9]) == [False, False, True, False, False]
    assert blocks.apart(partitioning._with_those_apart([(3, 0), (7, 5), (7, 5), (8, 6)])) == [False, False, True, False, False]


@pytest.mark.parametrize("alphabet, letters", ((DNA, "ACGT"), (DNA_N, "ACGNT"), (Bytes, "aé€😀")))
def test_codes_of_packed_reads(spark, alphabet, letters):
    """Codes of any width, within any span, are those that expand_refs makes row by row, and the zeros behind a read are no suffixes."""
    rng = random.Random(5)
    seqs = ["", letters[-1]] + ["".join(rng.choice(letters) for _ in range(rng.randint(0, 30))) for _ in range(30)]
    reads = spark.createDataFrame(list(enumerate(seqs)), "read_id long, seq string")
    rows = blocks.packed(reads, alphabet, RefLayout(), 3, 2).collect()
    assert sorted(r["slice"] for r in rows) == [0, 1, 2]
    for width in (1, 2, 5, 7):
        every = {(r["code"], r["ref"]) for r in suffixes.expand_refs(reads, alphabet, width).collect()}
        low, high = (sorted(c for c, _ in every)[len(every) // i] for i in (4, 2))
        for span in ((None, None), (None, low), (low, high), (high, None), (-1, high)):
            found = set()
            for r in rows:
                own = blocks.PackedReads(r["n"], r["body"], alphabet)
                at, read, code = own.within(width, span)
                found |= set(zip(code.tolist(), (own.ids[read] * 1000 + own.offsets(at, read)).tolist()))
                assert (own.places(read, own.offsets(at, read)) == at).all()
            assert found == {(c, ref) for c, ref in every if (span[0] is None or c > span[0]) and (span[1] is None or c <= span[1])}
    with pytest.raises(Exception, match="NUL|beside|null"):
        blocks.packed(spark.createDataFrame([(1, "A\0")], "read_id long, seq string"), alphabet, RefLayout(), 1, 1).collect()


def test_shares_of_a_large_input_are_few(spark, monkeypatch):
    """Each share goes over all reads: their number has a bound, reads are packed once, and every suffix keeps its place."""
    rng = random.Random(8)
    seqs = ["".join(rng.choice("ACGT") for _ in range(40)) for _ in range(30)]
    reads = spark.createDataFrame(list(enumerate(seqs)), "read_id long, seq string")
    monkeypatch.setattr(suffixes, "FETCH_SUFFIXES", 10)
    monkeypatch.setattr(build, "MOST_SHARES", 3)
    dealt, packed, place, pack = [], [], blocks.place, blocks.packed
    monkeypatch.setattr(blocks, "place", lambda *a: dealt.append(a) or place(*a))
    monkeypatch.setattr(blocks, "packed", lambda *a: packed.append(a) or pack(*a))
    found = build.indexed_suffix_array(reads, DNA, 4, store="placed", parts=2).collect()
    assert sorted((r["pos"], r["ref"]) for r in found) == list(enumerate(suffixes_of(seqs)))
    assert len(packed) == 1 and 2 <= len(dealt) <= 3


@pytest.mark.parametrize("letters", ("ab", "aé€😀", "a\0"))
@pytest.mark.parametrize("most", (500, 1 << 30))
def test_repeats_in_blocks(spark, letters, most, monkeypatch):
    """Grams of several lengths in bytes, shares, blocks and parts that end everywhere; NUL has no code, but counts."""
    rng = random.Random(9)
    seqs = ["", letters * 20] + ["".join(rng.choice(letters) for _ in range(rng.randint(0, 60))) for _ in range(40)]
    reads = spark.createDataFrame(list(enumerate(seqs)), "read_id long, seq string").repartition(3)
    for name, value in (("PART", 100), ("SLICE", 300), ("BLOCK", 50)):
        monkeypatch.setattr(blocks, name, value)
    monkeypatch.setattr(suffixes, "FETCH_SUFFIXES", most)
    want = Counter(s[o : o + 8] for s in seqs for o in range(len(s) - 7))
    found = search.repeats(reads, 8)
    assert sorted(map(tuple, found.collect())) == sorted((g, n) for g, n in want.items() if n > 1)
    assert ("body" in plan_of(search.repeats(reads, 8))) == (most > 500 and "\0" not in letters)


@pytest.mark.parametrize("name", ("idx_sa_no_rules", "fetch_whole_same_result", "idx_sa_bucketed_store", "idx_sa_nosuffix", "idx_sa_sampled_ranges", "idx_sa_text", "idx_sa_text_w5"))
def test_all_stores_and_rules_are_dealt_in_blocks(spark, at, name, monkeypatch):
    """Whatever the store, and with tails or whole reads fetched for every suffix, no reference is a row before it has its position."""
    monkeypatch.setattr(store, "BROADCAST_BYTES", -1)
    seen, stored = [], blocks.stored
    monkeypatch.setattr(blocks, "stored", lambda df, label: seen.append(plan_of(df)) or stored(df, label))
    compare(spark, at, name)
    assert len(seen) == 1 and "body" in seen[0] and "Sort [" not in seen[0]
