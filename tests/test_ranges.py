import os
import random

import duckdb
import pytest
from pyspark.sql import functions as F

from suffixloom.functions.alphabet import DNA, DNA_N, Bytes
from suffixloom.operators import positions, suffixes, validate
from suffixloom.operators.grouping import mark_groups
from suffixloom.plans import build
from suffixloom.plans.workloads import QUERIES, SQL
from suffixloom.sources import reads as src

NAMES = ("idx_sa_no_rules", "idx_sa_paired", "idx_sa_sampled_ranges", "validate_order", "idx_sa_dna", "idx_sa_html_longer", "idx_sa_placed_store", "idx_sa_text_w3")
FETCHES = ("block_fetch_bytes", "fetch_requests", "fetch_tail_vs_whole")


@pytest.fixture(scope="module")
def at(spark, tmp_path_factory):
    rng, path = random.Random(7), str(tmp_path_factory.mktemp("ranges"))
    words = ["".join(rng.choice("abcdefgh é") for _ in range(40)) for _ in range(12)]
    docs = [(i, " ".join(rng.choice(words) for _ in range(rng.randint(0, 12)))) for i in range(40)]
    spark.createDataFrame(docs, "doc_id long, text string").coalesce(1).write.parquet(f"{path}/documents.parquet")
    spark.createDataFrame(docs, "page_id long, html string").coalesce(1).write.parquet(f"{path}/pages.parquet")
    return path


def compare(spark, at, name):
    rows = sorted(map(tuple, QUERIES[name](spark, at).collect()), key=str)
    con = duckdb.connect()
    for t in ("documents", "pages"):
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM '{at}/{t}.parquet/*.parquet'")
    assert rows and rows == sorted(con.sql(SQL[name]).fetchall(), key=str)


@pytest.mark.parametrize("name", NAMES)
def test_shares_of_codes_give_the_whole_array(spark, at, name, monkeypatch):
    """Consecutive codes a share: each is summed up before the next begins, and what it wrote goes."""
    taken, stored, gone = [], build.stored, []
    monkeypatch.setattr(suffixes, "FETCH_SUFFIXES", 3_000)
    monkeypatch.setattr(build, "stored", lambda df, label: taken.append(label) or stored(df, label))
    monkeypatch.setattr(build, "discard", lambda *tables, go=build.discard: go(*tables) or gone.extend(t.scratch for t in tables))
    compare(spark, at, name)
    assert len(taken) > 2 and len(gone) == len(taken) and not any(os.path.exists(p.removeprefix("file:")) for p in gone)


@pytest.mark.parametrize("name", FETCHES)
def test_fetches_come_in_smaller_shares(spark, at, name, monkeypatch):
    taken, stored = [], suffixes.stored
    monkeypatch.setattr(suffixes, "FETCH_SUFFIXES", 3_000)
    monkeypatch.setattr(suffixes, "stored", lambda df, label: taken.append(label) or stored(df, label))
    compare(spark, at, name)
    assert len(taken) > 2


@pytest.mark.parametrize("alphabet, width, letters", ((DNA, 23, "ACGT"), (DNA, 5, "ACGT"), (DNA_N, 2, "ACGNT"), (Bytes, 7, "aé€😀"), (Bytes, 3, "ab\x7f")))
def test_codes_from_bytes(spark, alphabet, width, letters, monkeypatch):
    """As by the column function, one suffix at a time, with pieces that end within a batch; spans part the references."""
    monkeypatch.setattr(suffixes, "_PIECE", 50)
    rng = random.Random(1)
    reads = spark.createDataFrame([(i, "".join(rng.choice(letters) for _ in range(rng.randint(0, 70)))) for i in range(60)], "read_id long, seq string").coalesce(2)
    each = reads.select("read_id", "seq", F.explode(F.sequence(F.lit(0), F.length("seq"))).alias("off"))
    head = alphabet.window(F.substring(F.col("seq"), F.col("off") + 1, F.length("seq")), 0, width)
    want = sorted(map(tuple, each.select(alphabet.encode(head, width), F.col("read_id") * 1000 + F.col("off"), alphabet.units(head)).collect()))
    assert sorted(map(tuple, suffixes.expand_refs(reads, alphabet, width).collect())) == want
    a, b = want[len(want) // 3][0], want[2 * len(want) // 3][0]
    parted = [sorted(map(tuple, suffixes.expand_refs(reads, alphabet, width, span=s).collect())) for s in ((None, a), (a, b), (b, None))]
    assert all(parted) and sum(parted, []) == want
    with pytest.raises(ValueError):
        suffixes.expand_refs(reads, alphabet, 28)


def test_order_is_checked_where_ranges_meet(spark):
    sa = lambda *rows: validate.order_of_range(spark.createDataFrame(list(rows), "pos long, ref long, suffix string"))
    joined = lambda *ranges: tuple(validate.joined_orders(ranges[0].unionByName(ranges[1])).first())
    low, none = sa((0, 5, "a"), (1, 6, "b")), sa((9, 9, "z")).where("false")
    assert joined(low, sa((2, 7, "b"), (3, 1, "c"))) == (0, 4, 19)
    assert joined(low, sa((2, 6, "b"))) == joined(low, sa((2, 1, "b")))[:2] + (17,) == (1, 3, 17)
    assert joined(low, none) == (0, 2, 11) and joined(none, none) == (0, 0, 0)


@pytest.mark.parametrize("rows_a_batch", (1, 3, 10_000))
def test_groups_are_told_as_rows_pass(spark, rows_a_batch):
    """Also where a group begins in one batch and ends in another, and where none is asked for."""
    rng, name = random.Random(2), "spark.sql.execution.arrow.maxRecordsPerBatch"
    rows = [(rng.choice((1, 1, 1, 5, rng.randint(10, 60))), rng.choice((0, 0, 3)), ref) for ref in range(120)]
    rows = [(*r, r[0] != 5) for r in rows]
    want, groups = [], {}
    for code, more, ref, full in sorted(rows):
        groups.setdefault((code, more), []).append(ref)
    for (code, _), refs in sorted(groups.items()):
        want += [(ref, i if len(refs) > 1 and code != 5 else None) for i, ref in enumerate(refs)]
    before = spark.conf.get(name)
    spark.conf.set(name, str(rows_a_batch))
    try:
        at = spark.createDataFrame(rows, "code long, more long, ref long, full boolean").coalesce(1).sortWithinPartitions("code", "more", "ref")
        assert [tuple(r) for r in mark_groups(at, ["code", "more"], "full").collect()] == want
        assert mark_groups(at.where("false"), ["code"], keep_keys=True).collect() == []
    finally:
        spark.conf.set(name, before)


def plan_of(df):
    return df._jdf.queryExecution().executedPlan().toString()


def test_text_stays_where_it_lies_while_order_is_checked(spark):
    """Rows out of order are found within batches, between them, and between files; none are dealt anew with their text."""
    rng, name = random.Random(4), "spark.sql.execution.arrow.maxRecordsPerBatch"
    order = sorted((("".join(rng.choice("ab") for _ in range(rng.randint(0, 5)))), ref) for ref in range(300))
    rows = [(pos, ref, s) for pos, (s, ref) in enumerate(order)]
    wrong = list(rows)
    for i in (10, 99, 149, 298):
        (p, r, s), (q, t, u) = wrong[i], wrong[i + 1]
        wrong[i], wrong[i + 1] = (p, t, u), (q, r, s)
    count = lambda x: sum((a[2], a[1]) >= (b[2], b[1]) for a, b in zip(x, x[1:]))
    before = spark.conf.get(name)
    spark.conf.set(name, "7")
    try:
        for some in (rows, wrong):
            for files in (some, some[150:] + some[:150], rng.sample(some, 300)):
                sa = spark.createDataFrame(files, "pos long, ref long, suffix string").coalesce(3)
                found = validate.order_of_range(sa)
                assert tuple(validate.joined_orders(found).first()) == (count(some), 300, sum(r[1] for r in rows))
                ends = found.first()
                assert (ends["first"]["pos"], ends["last"]["pos"]) == (0, 299)
        assert count(wrong) >= 4 and "Window" not in plan_of(found) and "violations" in plan_of(found).split("Exchange")[-1]
    finally:
        spark.conf.set(name, before)


def test_references_are_sorted_by_code_before_anything_else(spark):
    """A part's number is the same in all rows of a task: first in the order, it would leave the sort without a prefix to compare."""
    forward = spark.createDataFrame([(i, "ACGTTGCA" * (i % 5)) for i in range(40)], "read_id long, seq string")
    reads, seen, stored = src.pair_reads(forward, src.reverse_reads(forward)), [], positions.stored
    with pytest.MonkeyPatch.context() as patch:
        patch.setattr(positions, "stored", lambda df, label: seen.append(plan_of(df)) or stored(df, label))
        found = [r["ref"] for r in build.indexed_suffix_array(reads, DNA, 5, parts=3).orderBy("pos").collect()]
    every = [(r["seq"][o:], r["read_id"] * 1000 + o) for r in reads.collect() for o in range(len(r["seq"]) + 1)]
    assert found == [ref for _, ref in sorted(every)]
    assert len(seen) == 1 and "Window" not in seen[0] and "Sort [code" in seen[0] and "Sort [part" not in seen[0]


@pytest.mark.parametrize("name", FETCHES)
def test_fetches_tell_groups_without_a_window(spark, at, name):
    plan = plan_of(QUERIES[name](spark, at))
    assert "Window" not in plan and plan.count("MapInArrow") >= 2
