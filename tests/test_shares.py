import os
import random

import duckdb
import pytest
from pyspark.sql import functions as F

from suffixloom.functions.alphabet import DNA, Bytes
from suffixloom.operators import search, suffixes
from suffixloom.plans.workloads import QUERIES, SQL

NAMES = ("batched_fetch", "fetch_tail_vs_whole", "fetch_requests", "access_profile", "block_fetch_bytes", "app_repeats")


@pytest.fixture(scope="module")
def at(spark, tmp_path_factory):
    rng, path = random.Random(3), str(tmp_path_factory.mktemp("shares"))
    words = ["".join(rng.choice("abcdefgh é") for _ in range(40)) for _ in range(12)]
    docs = [(i, " ".join(rng.choice(words) for _ in range(rng.randint(0, 12)))) for i in range(40)]
    spark.createDataFrame(docs, "doc_id long, text string").coalesce(1).write.parquet(f"{path}/documents.parquet")
    return path


@pytest.mark.parametrize("name", NAMES)
@pytest.mark.parametrize("most", (3_000, 200_000_000))
def test_shares_give_the_whole_result(spark, at, name, most, monkeypatch):
    """Of many suffixes a share at a time is dealt out; every one is in one share."""
    taken, stored = [], suffixes.stored
    monkeypatch.setattr(suffixes, "SHARE_SUFFIXES", most)
    monkeypatch.setattr(suffixes, "stored", lambda df, label: taken.append(label) or stored(df, label))
    rows = sorted(map(tuple, QUERIES[name](spark, at).collect()), key=str)
    con = duckdb.connect()
    con.execute(f"CREATE VIEW documents AS SELECT * FROM '{at}/documents.parquet/*.parquet'")
    assert rows and rows == sorted(con.sql(SQL[name]).fetchall(), key=str)
    assert (len(taken) > 2) == (most == 3_000)


@pytest.mark.parametrize("alphabet, width", ((DNA, 5), (Bytes, 4)))
def test_shares_part_the_references(spark, alphabet, width):
    reads = spark.createDataFrame([(i, "ACGTTGCA" * i) for i in range(9)], "read_id long, seq string")
    every = [tuple(r) for i in range(3) for r in suffixes.expand_refs(reads, alphabet, width, share=(i, 3)).collect()]
    assert sorted(every) == sorted(map(tuple, suffixes.expand_refs(reads, alphabet, width).collect()))


def test_longer_prefixes_from_digits(spark):
    """Made from one string of digits a read, as one by one from heads."""
    reads = spark.createDataFrame([(i, s) for i, s in enumerate(["", "A", "ACG", "ACGTACGTACGA", "AAAAAAA", "ACGTT"])], "read_id long, seq string")
    longer = [r["code"] for r in suffixes.expand_refs(reads, DNA, 3).select("code").distinct().where("code % 2 = 1").collect()]
    for r in suffixes.expand_refs(reads, DNA, 3, longer=longer).join(reads, F.expr("ref div 1000 = read_id")).collect():
        s = r["seq"][r["ref"] % 1000 :]
        code = lambda t: sum(("ACGT".index(c) + 1) * 5 ** (2 - i) for i, c in enumerate(t[:3]))
        far = code(s) in longer
        assert (r["code"], r["far"], r["slen"], r["more"]) == (code(s), far, min(len(s), 6 if far else 3), code(s[3:6]) if far else 0)


def test_index_meets_nested_and_equal_patterns(spark, tmp_path):
    """Patterns within others, twice the same one, beyond the width, and of other symbols: each has all its places."""
    rng = random.Random(5)
    reads = spark.createDataFrame([(i, "".join(rng.choice("AC") for _ in range(40))) for i in range(30)], "read_id long, seq string")
    patterns = [(i, p) for i, p in enumerate(["A", "AC", "ACC", "AC", "CCCC", "T", "ACACACA", "N", "C" * 6, "AAAA"])]
    search.store_index(reads, DNA, 4, str(tmp_path / "index"), 5)
    found = search.search_index(spark, str(tmp_path / "index"), reads, patterns, DNA, 4).collect()
    want = [(i, r["read_id"] * 1000 + o) for i, p in patterns for r in reads.collect() for o in range(41) if r["seq"].startswith(p, o)]
    assert sorted(map(tuple, found)) == sorted(want)
    assert search._spans([(1, 2), (3, 4), (9, 9), (20, 30), (22, 24)], 2) == [(1, 9), (20, 30)]
