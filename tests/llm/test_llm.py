import hashlib
import random
import re
import time
import zlib

import numpy as np
import pytest
import xxhash
from pyspark.sql import functions as F

from suffixloom.llm import bpe, licenses, line_dedup, neighbours, packing, quality_rules, queries, secrets, simhash, urls, warc
from suffixloom.llm.components import connected_components

SF = "/root/testdata/sf0.001"
LONG = "word " * 4000 + "x" * 30000
TEXTS = [(1, "a b c d"), (1, "a b c d"), (2, ""), (3, None), (None, "a b c d"), (4, LONG), (5, "é ü\u00a0ß\n\n\t x"), (6, " lead\ntail \n"), (7, "A B C D")]


def docs(spark, rows=None, extra=True):
    rows = TEXTS if rows is None else rows
    df = spark.createDataFrame(rows, "doc_id long, text string").repartition(3)
    return df.withColumns({"key": F.lit("k"), "n_lines": F.lit(-1), "fp": F.lit(0), "keys": F.lit(1), "source": F.lit(None).cast("string")}) if extra else df


def tiles(pieces):
    """Pieces of each document follow each other without gaps."""
    at = {}
    for p in sorted(pieces, key=lambda p: (p["doc_id"] is None, p["doc_id"] or 0, p["start"])):
        at.setdefault(p["doc_id"], []).append(p)
    return at


# --- 1
def test_warc_round_trip_with_tiny_chunks(spark):
    body = "x" * 150
    rows = [(3, body), (1, body), (2, body), (4, "short"), (5, "short"), (6, None), (7, "é" * 5000), (None, body), (8, "a\r\n\r\nWARC/1.1\r\nb" * 20), (7, "é" * 5000)]
    pages = spark.createDataFrame(rows, "page_id long, html string").withColumn("digest", F.lit("clash")).repartition(2)
    got = warc.archive_round_trip(pages, sizes=warc.ArchiveSizes(chunk=64, archive=300)).collect()
    assert len(got) == len(rows)
    by = {}
    for r in got:
        by.setdefault(r["page_id"], []).append(r)
    for page, html in rows:
        data = (html or "").encode()
        assert all(r["payload_bytes"] == len(data) and r["payload_digest"] == hashlib.sha256(data).hexdigest() for r in by[page])
    kinds = {p: {(r["record_type"], r["refers_to"]) for r in v} for p, v in by.items()}
    assert kinds[1] == {("response", None)} and kinds[2] == kinds[3] == kinds[None] == {("revisit", 1)}
    assert kinds[4] == kinds[5] == kinds[6] == kinds[7] == {("response", None)}


# --- 2
def brute_spans(text):
    out = []
    for order, (kind, pattern, group, least) in enumerate(secrets.BASE):
        out += [(m.start(), order, f"{kind}:{m.start()}:{m.end()}") for m in re.finditer(pattern, text, re.ASCII) if len(m.group(group)) >= least]
    base = ",".join(x[2] for x in sorted(out))
    for order, c in enumerate(secrets.CLASSES, len(secrets.BASE)):
        for m in re.finditer(f"[{c.chars}]{{{c.window},}}", text):
            v = m.group()
            if all(re.search(p, v) for p in c.need) and not any(re.search(p, v) for p in secrets.ALLOWED_RUNS):
                sums = [sum(round(n * np.log2(n) * secrets.SCALE) for n in np.unique(list(v[i : i + c.window]), return_counts=True)[1]) for i in range(len(v) - c.window + 1)]
                at = sums.index(min(sums))
                if min(sums) <= c.max_sum and not any(re.search(p, v[at : at + c.window]) for p in secrets.ALLOWED_WINDOWS):
                    out.append((m.start(), order, f"{c.kind}:{m.start()}:{m.end()}"))
    return base, ",".join(x[2] for x in sorted(out))


def test_secret_spans(spark):
    rng = random.Random(3)
    noise = "".join(rng.choice("ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789+/") for _ in range(48))
    rows = [*TEXTS, (20, f"é PassWord='abc123x' token=token: abcdef secret=ab AKIA{'A1' * 9} {'0af' * 10}"), (21, f"key {noise} end"), (22, "example" + noise), (23, "0123456789ABCDEF" * 3 + " F00DBABE12345678C0FFEE9A7D41E3B256"), (24, f"sample/{noise}"), (25, "x q7k2wz9trb4m0v8hs1ny t 2020-01-02/Some-Title-of-a-Page/12345 " + "ab1" * 30), (26, "a=" + "".join(rng.choice("ghijklmnop0123456789") for _ in range(300)))]
    got = {(r["doc_id"], r["spans"], r["base_sha256"]) for r in secrets.secret_spans(docs(spark, rows)).collect()}
    want = {(i, brute_spans(t or "")[1], hashlib.sha256(brute_spans(t or "")[0].encode()).hexdigest()) for i, t in rows}
    assert got == want
    found = {i: s for i, s, _ in got}
    assert "entropy_base64" in found[21] and "entropy_base64" in found[24] and found[22] and "entropy_alnum:2:22" in found[25] and "entropy_base64" not in found[25]
    clean = {r["doc_id"]: r["text"] for r in secrets.redact(docs(spark, rows)).collect()}
    assert noise not in clean[21] and clean[3] is None and clean[4] == LONG and "[secret]" in clean[20]


def test_secrets_in_very_long_texts(spark):
    """Megabytes of runs, paths and findings: no recursion, and time in proportion to the text."""
    rng = random.Random(15)
    many = "".join(f"é token={rng.getrandbits(40):x}zz;\n" for _ in range(40_000))
    rows = [(1, "aA" + "/bB" * 1_500_000 + "1"), (2, many), (3, "x" * 3_000_000), (4, "aA1/" * 300_000), (5, "password" + " " * 2_000_000)]
    began = time.time()
    got = {r["doc_id"]: r for r in secrets.secret_spans(docs(spark, rows)).collect()}
    clean = {r["doc_id"]: r["text"] for r in secrets.redact(docs(spark, rows)).collect()}
    assert time.time() - began < 240
    spans = [m.span() for m in re.finditer(r"token=[0-9a-z]+", many)]
    assert got[2]["n_assign"] == len(spans) == 40_000
    assert got[2]["base_sha256"] == hashlib.sha256(",".join(f"assign:{a}:{b}" for a, b in spans).encode()).hexdigest()
    assert clean[2] == re.sub(r"token=[0-9a-z]+", "[secret]", many) and clean[1] == rows[0][1] and clean[3] == rows[2][1]


def test_scan_is_sequential(spark):
    from suffixloom.llm.scans import scan

    for n in (0, 1, 64, 65, 1000):
        row = spark.range(1).select(scan(F.sequence(F.lit(1), F.lit(n)) if n else F.expr("cast(array() as array<int>)"), F.lit(0).cast("long"), lambda s, x: s + x, lambda s, x: s * 2 + x, "bigint").alias("out")).first()
        assert row["out"] == [k * (k - 1) + k for k in range(1, n + 1)]


# --- 3
def test_bpe_equals_tiktoken(spark):
    import tiktoken

    files = queries.tokenizer_files()
    own = bpe.ByteBpe.from_file(files.path("byte_bpe_50k.tiktoken"), files.PATTERN)
    other = tiktoken.Encoding("own", pat_str=files.PATTERN, mergeable_ranks=own.ranks, special_tokens={})
    rng = random.Random(4)
    texts = [t or "" for _, t in TEXTS] + ["".join(rng.choice("ab cé\n 1'st日²") for _ in range(rng.randint(0, 80))) for _ in range(300)] + ["".join(rng.choice("abcdefg") for _ in range(5000)), "a" * 5000]
    for text in texts:
        assert own.encode(text) == other.encode_ordinary(text)
        assert own.decode(own.encode(text)) == text.encode()
    rows = queries.op3_bpe_round_trip(spark, SF).collect()
    text = {r["doc_id"]: r["text"] for r in spark.read.parquet(f"{SF}/documents.parquet").collect()}
    for r in rows:
        assert r["ids_sha256"] == hashlib.sha256(" ".join(map(str, other.encode_ordinary(text[r["doc_id"]]))).encode()).hexdigest()
        assert r["decoded_sha256"] == hashlib.sha256(text[r["doc_id"]].encode()).hexdigest()


# --- 4
def test_url_rules_and_forest(spark):
    rows = [(1, "https://A.Example.org/en/12?x"), (2, "http://example.org"), (3, None), (4, "no scheme"), (5, "ftp://x.com/fr/a#b"), (6, "https://notexample.org.net/"), (7, "a://b.example.org/es/q")]
    pages = spark.createDataFrame(rows, "page_id long, url string").withColumn("host", F.lit("clash"))
    labelled = spark.createDataFrame([(f"https://good.net/a/{i}", 1) for i in range(200)] + [(f"https://bad.biz/{i}{i}{i}{i}?a=1&b=2&c={i}", 0) for i in range(200)], "url string, label int")
    got = {r["page_id"]: r for r in urls.judge_urls(pages, labelled, queries.RULES).collect()}
    assert (got[1]["host"], got[1]["path"], got[1]["rule"], got[1]["verdict"]) == ("a.example.org", "/en/12", "example.org/en/1", "block")
    assert (got[2]["host"], got[2]["path"], got[2]["rule"]) == ("example.org", "", None)
    assert [(got[i]["host"], got[i]["path"], got[i]["rule"]) for i in (3, 4)] == [("", "", None)] * 2
    assert (got[5]["rule"], got[5]["verdict"], got[6]["rule"], got[7]["rule"]) == ("com/fr/", "allow", None, "example.org/es/")
    held = spark.createDataFrame([(i, f"https://good.net/b/{i}") for i in range(50)] + [(100 + i, f"https://bad.biz/{i}9{i}8{i}?a=1&b=2&c=3") for i in range(50)], "page_id long, url string")
    right = sum((r["verdict"] == "allow") == (r["page_id"] < 100) for r in urls.judge_urls(held, labelled, []).collect())
    assert right >= 95
    assert urls.judge_urls(pages.limit(0), labelled.limit(0), queries.RULES).count() == 0


def test_url_scores_say_no_more_than_labels_do(spark):
    """Held-out area under the curve: high where hosts tell the label, about a half where nothing does, though many suffixes have one row."""
    rng = random.Random(17)
    told = [(f"https://{h}.net/{i}", int(h == "good")) for i in range(300) for h in ("good", "bad")]
    random_ = [(f"https://h{rng.randrange(400)}.org/{rng.randrange(10**6)}", rng.randint(0, 1)) for _ in range(1500)]
    for rows, low, high in ((told, 0.95, 1.0), (random_, 0.4, 0.6)):
        labelled = spark.createDataFrame(rows, "url string, label int")
        auc = urls.held_out_auc(urls.lexical_features(labelled.withColumn("id", F.lit(0)), "id", "url"), labelled)
        assert low <= auc <= high
    both = [("https://one.net/1", 1), ("https://one.net/1", 0)]
    assert urls.judge_urls(spark.createDataFrame([(1, "https://one.net/1")], "page_id long, url string"), spark.createDataFrame(both, "url string, label int"), []).count() == 1


def test_url_parts_and_rules_by_brute_force(spark):
    pages = spark.read.parquet(f"{SF}/pages.parquet").select("page_id", "url")
    odd = spark.createDataFrame([(-1, "http://Ü.COM/de/x?y"), (-2, "a://b://c/d"), (-3, "://x.org/"), (-4, "http://org/x"), (-5, "http://a.com/fr"), (-6, "x?://h.com/fr/#"), (-7, "")], "page_id long, url string")
    for r in urls.judge_urls(pages.union(odd), spark.createDataFrame([], "url string, label int"), queries.RULES).join(pages.union(odd), "page_id").collect():
        after = r["url"].split("://", 1)[1] if "://" in r["url"] else ""
        host = re.match(r"[^/?#]*", after).group()
        path = re.match(r"[^?#]*", after[len(host) :]).group()
        host = re.sub("[A-Z]", lambda m: m.group().lower(), host)
        fits = [x for x in queries.RULES if (host == x.rule.split("/")[0] or host.endswith("." + x.rule.split("/")[0])) and path.startswith(x.rule[x.rule.index("/") :])]
        best = max(fits, key=lambda x: len(x.rule), default=None)
        assert (r["host"], r["path"], r["rule"]) == (host, path, best.rule if best else None)
        assert r["verdict"] == (best.verdict if best else "allow")


# --- 5
def check_packing(pieces, lengths, window=packing.WINDOW):
    sequences = {}
    for doc, own in tiles(pieces).items():
        copies = lengths.get(doc, [])
        assert sum(p["length"] for p in own) == sum(copies), doc
    for p in pieces:
        sequences.setdefault(p["sequence_id"], []).append((p["offset"], p["length"]))
    for s in sequences.values():
        at = 0
        for offset, length in sorted(s):
            assert offset == at
            at += length
        assert at == window or (at < window and at & (at - 1) == 0)


def test_packing(spark):
    files = queries.tokenizer_files()
    encode = packing.file_encoder(files.path("byte_bpe_50k.json"))
    table = spark.read.parquet(f"{SF}/documents.parquet").repartition(4)
    pieces = packing.pack(table, encode, 1, with_ids=True).collect()
    from tokenizers import Tokenizer

    library = Tokenizer.from_file(files.path("byte_bpe_50k.json"))
    want = {r["doc_id"]: [*library.encode(r["text"], add_special_tokens=False).ids, 1] for r in table.collect()}
    check_packing(pieces, {k: [len(v)] for k, v in want.items()})
    for doc, own in tiles(pieces).items():
        assert np.frombuffer(b"".join(p["ids"] for p in own), "<u4").tolist() == want[doc]
        assert all(p["ids_crc32"] == zlib.crc32(p["ids"]) and p["doc_tokens"] == len(want[doc]) for p in own)
    source = {r["doc_id"]: r["source"] for r in table.collect()}
    share = sum(len(want[d]) for d in want if source[d] == "src0") / sum(map(len, want.values()))
    first = [sum(p["length"] for p in pieces if p["sequence_id"] == k and source[p["doc_id"]] == "src0") for k in range(20)]
    assert max(abs(x - share * packing.WINDOW) for x in first) < 6
    edge = packing.pack(docs(spark), encode, 1).collect()
    lengths = {}
    for i, t in TEXTS:
        lengths.setdefault(i, []).append(len(library.encode(t or "", add_special_tokens=False).ids) + 1)
    check_packing(edge, lengths)
    assert packing.pack(docs(spark, []), encode, 1).count() == 0


def test_packing_ids_are_the_librarys(spark, tmp_path):
    """Strings of added tokens keep their ids; files that the fast engine doesn't fit go to the library."""
    import json

    from tokenizers import Tokenizer

    files = queries.tokenizer_files()
    path = files.path("byte_bpe_50k.json")
    whole = json.load(open(path, encoding="utf-8"))
    names = [t["content"] for t in whole["added_tokens"]]
    texts = [x for n in names for x in (n, f"a {n} b", f"{n}{n}\n", f"é{n[:-1]} {n}", n.upper())] + ["", " 1 a's\n\n x"]
    changed = dict(whole, added_tokens=[*whole["added_tokens"], dict(whole["added_tokens"][0], id=50257, content="<sep>", lstrip=True)])
    (tmp_path / "strips.json").write_text(json.dumps(changed))
    (tmp_path / "split.json").write_text(json.dumps(dict(whole, pre_tokenizer={"type": "Sequence", "pretokenizers": [{"type": "Split", "pattern": {"Regex": r"\d|\D+"}, "behavior": "Isolated", "invert": False}, {"type": "ByteLevel", "add_prefix_space": False, "trim_offsets": True, "use_regex": False}]})))
    (tmp_path / "prefix.json").write_text(json.dumps(dict(whole, pre_tokenizer={"type": "ByteLevel", "add_prefix_space": True, "trim_offsets": True, "use_regex": True})))
    for file, fast in ((path, True), (tmp_path / "strips.json", False), (tmp_path / "split.json", True), (tmp_path / "prefix.json", False), (files.path("word_bpe_49k.json"), False)):
        own, library = packing.FileTokenizer(str(file)), Tokenizer.from_file(str(file))
        assert own.ranked == fast
        for text in [*texts, "a  <sep> b12 c"]:
            assert np.frombuffer(own.encode(text), "<u4").tolist() == library.encode(text, add_special_tokens=False).ids, (file, text)


@pytest.mark.parametrize("seed", range(4))
def test_schedule_uses_every_token(seed):
    rng = np.random.default_rng(seed)
    totals = rng.integers(0, 30000, 7)
    phases, rest = packing.schedule(totals, rng.random(7) * (totals > 0) + 1e-9 * (totals > 0), 64, 8)
    placer = packing.Placer(phases, rest, 64)
    assert sum(n for q in range(7) for _, n, _, _ in placer.pieces(q, 0, int(totals[q]))) == totals.sum()


# --- 6
def test_neighbours(spark):
    rng = np.random.default_rng(5)
    centres = rng.normal(size=(8, 12)) * 3
    x = (centres[rng.integers(0, 8, 5000)] + rng.normal(size=(5000, 12))).astype(np.float32)
    x[100:400] = x[100]
    rows = [(i, v.tolist()) for i, v in enumerate(x)] + [(9000, None), (9100, [0.0] * 12), (9200, [float("nan")] * 12), (9300, [None] * 12), (None, [1.0] * 12), (9400, [1.0])]
    df = spark.createDataFrame(rows, "vec_id long, embedding array<float>").withColumn("part", F.lit("clash"))
    got = {}
    for r in neighbours.nearest(df, df.where("vec_id % 100 = 0")).collect():
        got.setdefault(r["query_id"], []).append((r["rank"], r["vec_id"], r["score"]))
    y, hits = x.astype(np.float64), 0
    assert set(got) == set(range(0, 5000, 100))
    for q, found in got.items():
        d = np.sqrt(((y - y[q]) ** 2).sum(1))
        d[q] = np.inf
        want = np.lexsort((np.arange(5000), d))[:10].tolist()
        assert [r for r, _, _ in sorted(found)] == list(range(1, 11)) and all(s == d[v] for _, v, s in found)
        hits += len({v for _, v, _ in found} & set(want))
        if q in (100, 200):
            assert [v for _, v, _ in sorted(found)] == want
    assert hits >= 0.9 * 10 * len(got)
    assert neighbours.nearest(df.limit(0), df.limit(0)).count() == 0


def test_neighbours_in_small_blocks_and_of_few_candidates(spark, monkeypatch):
    rng = np.random.default_rng(6)
    x = rng.normal(size=(700, 6))
    df = spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(x)], "vec_id long, embedding array<double>")
    monkeypatch.setattr(neighbours, "BLOCK_ROWS", 100)
    got = sorted(tuple(r) for r in neighbours.nearest(df, df, k=3).collect())
    d = np.sqrt(((x[:, None] - x[None]) ** 2).sum(2))
    np.fill_diagonal(d, np.inf)
    assert [(q, v) for q, _, v, _ in got] == [(q, int(v)) for q in range(700) for v in np.argsort(d[q], kind="stable")[:3]]
    few = df.where("vec_id < 4")
    assert sorted((r["query_id"], r["rank"]) for r in neighbours.nearest(few, few, k=10).collect()) == [(q, k) for q in range(4) for k in (1, 2, 3)]


# --- 7
def test_quality_counts(spark):
    words = re.compile(r"[^\x20\x09-\x0D]+")
    table = spark.read.parquet(f"{SF}/documents.parquet").select("doc_id", "text")
    for df in (table, docs(spark)):
        texts = {}
        for r in df.collect():
            texts.setdefault(r["doc_id"], []).append(r["text"] or "")
        for r in quality_rules.quality_report(df).collect():
            ok = False
            for text in texts[r["doc_id"]]:
                w = words.findall(text)
                where = {}
                for i in range(len(w) - 2):
                    where.setdefault(tuple(w[i : i + 3]), []).append(i)
                covered = {i + j for v in where.values() if len(v) > 1 for i in v for j in range(3)}
                lines = [x for x in text.split("\n") if words.search(x)]
                want = (len(w), sum(map(len, w)), len(re.findall(r"[#*$%&|<>]", text)), len(lines) - len(set(lines)), len(covered))
                ok |= (r["n_words"], r["word_chars"], r["n_symbols"], r["n_dup_lines"], r["n_repeat_words"]) == want and r["base_failed"] == (len(w) < 50 or 100 * len(covered) > 50 * len(w))
            assert ok and not (r["base_failed"] and r["kept"])
    assert quality_rules.keep_good(docs(spark)).columns == docs(spark).columns


def test_compression_bands():
    judge = quality_rules.TextJudge(quality_rules.CompressionRule())
    rng = random.Random(6)
    prose = " ".join(rng.choice("the of and river stone walking quietly under morning light they carried baskets through village".split()) + rng.choice("abcdefgh") * rng.randint(0, 2) for _ in range(2000))
    assert judge.compression(prose.encode())[3]
    assert not judge.compression(b"again and again " * 500)[3]
    assert not judge.compression(rng.randbytes(20000))[3]
    assert judge.compression(b"short")[3]


# --- 8
def test_line_dedup(spark):
    rows = [(i, f"unique {i}\n  Common LINE\t\n\nnear {i % 9}") for i in range(12)] + [(1, "common line"), (None, "common line\nx"), (50, ""), (51, None)]
    done = line_dedup.drop_common_lines(docs(spark, rows).withColumn("n_dropped", F.lit("mine")))
    assert "n_lines_" in done.columns and "n_dropped_" in done.columns
    got = {(r["doc_id"], r["text"], r["n_lines_"], r["n_dropped_"]) for r in done.collect()}
    want = {(i, f"unique {i}\n\nnear {i % 9}", 4, 1) for i in range(12)} | {(1, "", 1, 1), (None, "x", 2, 1), (50, "", 1, 0), (51, None, 1, 0)}
    assert got == want
    spared = {r["doc_id"]: r["text"] for r in line_dedup.drop_common_lines(docs(spark, [(i, "all of it is shared") for i in range(20)]), spare_share=0.5).collect()}
    assert set(spared.values()) == {"all of it is shared"}


# --- 9
def brute_print(text):
    w = (text or "").encode().lower().split()
    grams = [b" ".join(w[i : i + 3]) for i in range(len(w) - 2)] or ([b" ".join(w)] if w else [])
    hashes = [xxhash.xxh64_intdigest(g, seed=42) for g in grams]
    return sum(1 << b for b in range(64) if 2 * sum(h >> b & 1 for h in hashes) > len(hashes))


@pytest.mark.parametrize("small", [16, 2])
def test_near_pairs_lose_no_link(spark, small):
    rng = random.Random(7)
    prints = {rng.getrandbits(64) for _ in range(60)}
    for base in list(prints)[:6]:
        for _ in range(12):
            prints.add(base ^ sum(1 << b for b in rng.sample(range(64), rng.randint(1, 3))))
    signed = [simhash._signed(x) for x in prints]
    df = spark.createDataFrame([(x,) for x in signed], "fp long")
    for radius in (2, 4):
        root = {r["node"]: r["root"] for r in connected_components(simhash.near_pairs(df, radius, small)).collect()}
        group = {x: x for x in signed}

        def find(x):
            while group[x] != x:
                x = group[x]
            return x

        for a in signed:
            for b in signed:
                if ((a ^ b) & (1 << 64) - 1).bit_count() <= radius:
                    group[max(find(a), find(b))] = min(find(a), find(b))
        assert {x: root.get(x, x) for x in signed} == {x: find(x) for x in signed}


def test_masks_cover_every_pair():
    masks = simhash.covering_masks(2)
    assert len(masks) == 7 and all(any(not (m >> a & 1 or m >> b & 1) for m in masks) for a in range(64) for b in range(64))


def test_components_and_fingerprints(spark):
    got = {(r["doc_id"], r["fp"], r["component_id"]) for r in simhash.near_components(docs(spark)).collect()}
    assert {(i, simhash._signed(brute_print(t))) for i, t in TEXTS} == {(i, fp) for i, fp, _ in got}
    by = {i: c for i, _, c in got}
    assert by[1] == by[7] == by[None] == 1 and by[2] == by[3] == 2
    assert simhash.near_components(docs(spark, [])).count() == 0


def test_keep_one(spark):
    rng = random.Random(8)
    vocabulary = ["w%d" % i for i in range(3000)]
    base = [rng.choice(vocabulary) for _ in range(400)]
    rows = [(100, " ".join(base))] * 2 + [(101 + i, " ".join(base[: 20 * i] + ["changed"] + base[20 * i + 1 :])) for i in range(18)] + [(500 + i, " ".join(rng.choice(vocabulary) for _ in range(300))) for i in range(20)]
    kept = simhash.keep_one(docs(spark, rows))
    assert kept.columns == docs(spark, rows).columns
    assert sorted(r["doc_id"] for r in kept.collect()) == [100, *range(500, 520)]
    assert sorted((r["doc_id"] is None, r["doc_id"] or 0) for r in simhash.keep_one(docs(spark)).collect()) == [(False, i) for i in (1, 2, 4, 5, 6)]


def test_keep_one_finds_scattered_edits_and_tells_orders_apart(spark):
    """Texts with 3 to 5 words of 200 changed (similarity 0.8 and more) go; the same words in another order stay."""
    rng = random.Random(10)
    vocabulary = ["w%d" % i for i in range(3000)]
    rows, n = [], 60
    for i in range(n):
        words = [rng.choice(vocabulary) for _ in range(200)]
        rows.append((i, " ".join(words)))
        edited = list(words)
        for at in rng.sample(range(0, 200, 10), 3 + i % 2):
            edited[at] = "new%d" % at
        rows.append((1000 + i, " ".join(edited)))
        rows.append((2000 + i, " ".join(sorted(words))))
    kept = {r["doc_id"] for r in simhash.keep_one(docs(spark, rows)).collect()}
    assert {*range(n), *range(2000, 2000 + n)} <= kept
    assert len(kept - {*range(n), *range(2000, 2000 + n)}) <= 1


def brute_keep(rows, similarity=0.8):
    """Ids that stay when every two texts are compared."""
    sets = [{tuple(w[i : i + 5]) for i in range(max(1, len(w) - 4))} for w in (t.lower().split() for _, t in rows)]
    group = list(range(len(rows)))

    def find(x):
        while group[x] != x:
            x = group[x]
        return x

    for i in range(len(rows)):
        for j in range(i):
            if len(sets[i] & sets[j]) >= similarity * len(sets[i] | sets[j]):
                a, b = find(i), find(j)
                group[max(a, b)] = min(a, b)
    return sorted({min(rows[k][0] for k in range(len(rows)) if find(k) == find(i)) for i in range(len(rows))})


def test_keep_one_finds_every_pair_of_the_similarity(spark):
    """A changed block, an addition and scattered edits, up to the very limit of the similarity."""
    rng = random.Random(12)
    rows = []
    for i in range(60):
        words = ["w%d" % rng.randrange(3000) for _ in range(rng.randint(20, 300))]
        n = len(words) // 10
        edits = (["new%d" % k for k in range(n)] + words[n:], words + ["more%d" % k for k in range(2 * n)], [w if k % 50 else "x%d" % k for k, w in enumerate(words)])
        rows += [(i, " ".join(words)), *((1000 * k + i, " ".join(e)) for k, e in enumerate(edits, 1))]
    assert sorted(r["doc_id"] for r in simhash.keep_one(docs(spark, rows)).collect()) == brute_keep(rows)


@pytest.mark.parametrize("short", [4096, 295, 10])
def test_keep_one_in_a_crowd_and_among_equal_fingerprints(spark, monkeypatch, short):
    """Copies of one text that are alike in chains, in buckets of many; two near copies of which one has another text's words in another order.
    Crowds are compared by sets, by sets and sketches, and by sketches."""
    monkeypatch.setattr(simhash, "_SHORT", short)
    rng = random.Random(14)
    base, rows = ["w%d" % rng.randrange(3000) for _ in range(300)], []
    for i in range(60):
        rows.append((i, " ".join("e%d_%d" % (i, k) if k in set(rng.sample(range(300), 5)) and rng.random() < 0.9 else w for k, w in enumerate(base))))
    words = ["v%d" % k for k in range(200)]
    rows += [(500, " ".join(words)), (501, " ".join(reversed(words))), (502, " ".join(["other", *list(reversed(words))[1:]]))]
    want = brute_keep(rows)
    assert 500 in want and 501 in want and 502 not in want
    assert sorted(r["doc_id"] for r in simhash.keep_one(docs(spark, rows)).collect()) == want


def test_crowds_give_a_forest_with_the_components_of_all_links(spark):
    """1,300 sets, in more than one block: near copies that are mostly a little less alike than the limit, some in chains."""
    rng = np.random.default_rng(21)
    base, rows, sets = np.arange(200, dtype=np.uint64), [], []
    for i in range(1300):
        own = base.copy()
        gone = rng.choice(200, int(rng.integers(8, 22)), replace=False)
        own[gone] = rng.integers(1 << 20, 1 << 62, len(gone), np.uint64)
        sets.append(np.sort(own))
        rows.append((5, 1300, i, i, sets[-1].tobytes()))
    crowds = spark.createDataFrame([(t, n, a, r, bytearray(x)) for t, n, a, r, x in rows], "token long, n long, node long, root long, shingles binary")
    found = simhash.linked_in_crowds(crowds, 0.8).collect()
    above = list(range(1300))

    def find(x):
        while above[x] != x:
            x = above[x]
        return x

    for r in found:
        assert simhash.similar(sets[r["a"]], sets[r["b"]], 0.8)
        above[find(r["a"])] = find(r["b"])
    assert 0 < len(found) < 6 * 1300
    for i in range(1300):
        for j in range(i):
            if find(i) != find(j):
                assert not simhash.similar(sets[i], sets[j], 0.8)


def test_sketches_never_rule_out_similar_sets():
    rng = np.random.default_rng(14)
    for n in (1, 5, 200, 300, 3000, 40_000):
        both = np.unique(rng.integers(0, 1 << 63, 3 * n, np.uint64))
        rng.shuffle(both)
        for k in (0, n // 18, n // 9, n):
            x, y = np.sort(both[:n]), np.sort(both[k : n + k])
            p, q = simhash.sketch(x), simhash.sketch(np.sort(np.concatenate([y, both[2 * n : 2 * n + n // 10]])))
            size = min(len(p), len(q))
            apart = int(np.bitwise_count(simhash.folded(p, size) ^ simhash.folded(q, size)).sum())
            assert apart <= 2 * k + n // 10 and (k < n or n < 100 or apart > 0.23 * n)


def test_prefixes_meet_at_the_limit_in_any_order():
    rng = np.random.default_rng(13)
    for n in range(1, 120):
        both = np.unique(rng.integers(0, 1 << 63, 2 * n, np.uint64))
        rng.shuffle(both)
        for k in range(n + 1):
            x, y = np.sort(both[:n]), np.sort(both[k : n + k])
            if n - k >= 0.8 * (n + k):
                for some in (0, n // 2, n):
                    common = np.sort(both[:some])
                    a, b = (simhash.prefix(z, 0.8, common, np.arange(some)) for z in (x, y))
                    assert len(np.intersect1d(a, b))


# --- 10
def brute_license(text):
    words = re.findall(r"[^\x00-\x2f\x3a-\x60\x7b-\x7f]+", re.sub("[A-Z]", lambda m: m.group().lower(), text or ""))
    joined = " " + "".join(w + " " for w in words)
    at = lambda i: joined.count(" ", 0, i)

    def found(pattern):
        return [(at(m.start()) - 1, at(m.end()), m.group()) for m in re.finditer(f"(?<= )(?:{pattern})(?= )", joined, re.ASCII)]

    base = [(s, e, label) for phrase, label in licenses.BASE for s, e, _ in found(phrase)]
    hits = []
    for sig in licenses.SIGNATURES:
        rules = sorted(sig.rules, key=lambda r: -r[0])
        for s, e, v in found("|".join(p for _, p in rules)):
            hits.append((s, e, next(p for p, r in rules if re.fullmatch(r, v)), sig.label))
    kept = [h for h in hits if not any(o[0] <= h[0] and o[1] >= h[1] and (o[2] > h[2] or o[2] == h[2] and o[1] - o[0] > h[1] - h[0]) for o in hits)]
    covered = {w for s, e, *_ in [*base, *kept] for w in range(s, e)}
    starts = [s for s, _, _ in base]
    labels = {x for *_, x in base}
    return len(words), len(base), min(starts, default=None), max(starts, default=None), ",".join(sorted(labels)), ",".join(sorted(labels | {h[3] for h in kept})), round(len(covered) / len(words), 9) if words else 0.0


def test_licenses_against_brute_force(spark):
    rng = random.Random(16)
    pieces = [*(p for p, _ in licenses.BASE), "Licensed under the Apache License, Version 2.0", "SPDX-License-Identifier: GPL-3.0-only", "SPDX-License-Identifier: MIT-0", "the MIT license", "Creative Commons Attribution Non-Commercial Share-Alike 4.0", "CC BY-NC-SA 4.0", "cc by", "BSD-3-Clause license", "new BSD License", "GNU Lesser General Public License v2.1", "GNU General Public License", "GPLv3", "under GPLv2", "copyright 2020 some body; all rights reserved", "is in the public domain", "Mozilla Public License 2.0", "word", "é naïve", "...", "under", "license"]
    rows = [*TEXTS, *((100 + i, rng.choice(" \n").join(rng.choice(pieces) for _ in range(rng.randint(1, 40)))) for i in range(150)), (300, "Apache License, Version 2.0. " * 3000 + "the mit license " * 3000), (301, "cc by nc " * 2000)]
    got = sorted([(r["doc_id"] or -1, *r[1:-1], round(r["score"], 9)) for r in licenses.license_labels(docs(spark, rows)).collect()], key=str)
    assert got == sorted([(i or -1, *brute_license(t)) for i, t in rows], key=str)
    rules = [r for s in licenses.SIGNATURES for r in s.rules]
    assert len(rules) > 200 and len({r for _, r in rules}) > 190


def test_licenses(spark):
    rows = [(30, "x Under The MIT License. under the mit license"), (31, "Licensed under the Apache License, Version-2.0; CC BY-NC 4.0"), (32, "SPDX-License-Identifier: GPL-3.0"), (33, "the gpl and cc by nc")]
    got = {r["doc_id"]: r for r in licenses.license_labels(docs(spark, rows)).collect()}
    assert (got[30]["n_base"], got[30]["first_word"], got[30]["last_word"], got[30]["labels"]) == (2, 1, 5, "mit")
    assert (got[31]["base_labels"], got[31]["labels"]) == ("apache-2,cc-by-nc", "apache-2,cc-by-nc")
    assert (got[32]["n_base"], got[32]["first_word"], got[32]["labels"]) == (0, None, "gpl-3")


# --- pipeline
def test_pipeline_stages(spark):
    import corpus_pipeline

    table = spark.read.parquet(f"{SF}/documents.parquet")
    before, ids = table, None
    for name, stage in corpus_pipeline.STAGES[:-1]:
        after = stage(spark, before, SF)
        assert after.columns == table.columns, name
        kept = {r["doc_id"] for r in after.select("doc_id").collect()}
        assert ids is None or kept <= ids
        before, ids = after, kept
    assert 0 < len(ids) < table.count()
    pieces = corpus_pipeline.run(spark, SF).collect()
    assert {p["doc_id"] for p in pieces} == ids


def test_pipeline_stages_on_edge_cases(spark):
    """Nulls, empty and very long texts, repeated rows, no rows, and columns with the operators' own names go through all stages."""
    import corpus_pipeline

    prose = " ".join(f"{a}{b}" for a in ("stone", "river", "light", "walk", "quiet", "north") for b in ("", "ing", "ed", "ward", "less", "ful", "some", "ly", "ish", "er"))
    rows = [(1, prose, "en", "a"), (1, prose, "en", "a"), (2, prose.upper(), None, None), (None, prose + " more", "en", "a"), (3, None, "en", "a"), (4, "", "en", "a"), (5, (prose + "\n") * 2 + "x" * 500_000, "en", "b"), (6, prose.replace("stone", "brick") + " token=abcdef123", "de", "b")]
    frame = spark.createDataFrame(rows, "doc_id long, text string, lang string, source string").withColumn("n_chars", F.length("text").cast("long"))
    extra = frame.withColumns({c: F.lit(7) for c in ("fp", "row", "words", "kept", "node", "n_lines", "n_dropped", "owner", "keys", "assign", "hex", "part", "queue")})
    for df in (frame, extra, frame.limit(0)):
        before = df
        for name, stage in corpus_pipeline.STAGES[:-1]:
            after = stage(spark, before, SF)
            assert after.columns == df.columns, name
            left = after.collect()
            before = spark.createDataFrame(left, df.schema)
        ids = [r["doc_id"] for r in left]
        assert len(ids) == len(set(ids)) and set(ids) <= {1, 6} and (not df.count() or ids)
        assert all("abcdef123" not in r["text"] for r in left)
        pieces = corpus_pipeline.STAGES[-1][1](spark, before, SF).collect()
        assert {p["doc_id"] for p in pieces} == set(ids)
