"""SimHash near-duplicates by covering locality-sensitive hashing.

Every bit position gets a non-zero vector over GF(2) of radius + 1 entries; the table of a non-zero vector v keeps the
bits whose vector has an odd product with v. Up to radius differing bits span less than the whole space, so some v is
orthogonal to all of them, and the two fingerprints agree on that table's key: no pair within the radius is missed.

Within a bucket links are exact. A small bucket is compared pair by pair. In a large one each fingerprint is
sent to all points within radius / 2 flips; those that meet at a point are within the radius of
each other, so they are linked as a star. A point's group is bounded by the size of that ball, not by the data.

Defined results: a text without words (null, empty, blank) has fingerprint zero and is linked like others; exact copies share
a fingerprint; rows with a null id get a fingerprint and component but are never its smallest id; an empty table gives an empty one.
"""

from __future__ import annotations

import math
import random
from itertools import accumulate, combinations

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import arrow_map, discard, maybe_broadcast, slices, stored, utf8
from .components import connected_components

BITS = 64
SEED = 42
#: Shingles hashed and counted at a time: bounds the memory of a very long text.
_SLICE = 1 << 16
#: Fingerprints to a task where each is spread over the tables.
_DEALT = 10_000
#: Shingles that a task holds at a time, and texts whose prefixes meet in one.
_HELD, _MET = 1 << 21, 5_000
#: Bits of a sketch at least.
_SKETCH = 256
#: Bytes of a sketch at most where those of a block are compared with each other.
_WIDEST = 2048
#: Nodes of a crowded bucket to a block, and of a small bucket at most.
_BLOCK, _FEW = 512, 16
#: Shingles of a text at most whose set itself goes to crowded blocks; longer ones send sketches there, as a text has more
#: tokens the longer it is, so that its sets' bytes grow with the square of its length.
_SHORT = 512
#: Words whose hashes a worker remembers, and texts with a shingle beyond which it is dealt to all tasks.
_WORDS, _HOT = 1 << 17, 1 << 16


def shingle_hashes(data: bytes, width: int):
    """Arrays of big-endian XXH64 bytes of the width-word shingles, a slice at a time; of the whole if it has fewer words."""
    words = data.lower().split()
    if not words:
        return
    joined, digest = b" ".join(words), xxhash.xxh64_digest
    if len(words) <= width:
        yield np.frombuffer(digest(joined, SEED), np.uint8).reshape(1, 8)
        return
    ends = list(accumulate(map(len, words), lambda at, n: at + 1 + n))
    starts = [0, *(x + 1 for x in ends)]
    for i in range(0, len(words) - width + 1, _SLICE):
        spans = zip(starts[i : i + _SLICE], ends[i + width - 1 : i + width - 1 + _SLICE])
        yield np.frombuffer(b"".join([digest(joined[a:b], SEED) for a, b in spans]), np.uint8).reshape(-1, 8)


def fingerprint(data: bytes, width: int = 3) -> int:
    """Signed 64-bit SimHash; a bit is set if it is in over half of the shingle hashes."""
    total, counts = 0, np.zeros(BITS, np.int64)
    for hashes in shingle_hashes(data, width):
        total += len(hashes)
        counts += np.unpackbits(hashes, axis=1).sum(axis=0, dtype=np.int64)
    return int.from_bytes(np.packbits(2 * counts > total).tobytes(), "big", signed=True)


def fingerprints(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", width: int = 3) -> DataFrame:
    """(doc_id, fp) of every row."""

    def rows(batch: pa.RecordBatch) -> dict[str, list]:
        return {"doc_id": batch.column(0).to_pylist(), "fp": [fingerprint(x, width) for x in utf8(batch.column(1))]}

    return arrow_map(docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("string").alias("text")), rows, "doc_id long, fp long")


def covering_masks(radius: int, seed: int = 7) -> list[int]:
    """2^(radius+1) - 1 masks of BITS bits; for any set of radius positions one mask has none of them.

    Where there are more vectors than bits, those of first entry one are dealt, so that no mask keeps few bits: at
    radius 6 all keep 32, but for one that keeps all 64.
    """
    top = 1 << radius
    vectors = list(range(1, 2 * top))
    pool = vectors if len(vectors) <= BITS else [v | top for v in range(top)]
    dealer = random.Random(seed)
    if len(pool) > BITS:
        dealer.shuffle(pool)
    dealt = (pool * (BITS // len(pool) + 1))[:BITS]
    dealer.shuffle(dealt)
    return [sum(1 << i for i, m in enumerate(dealt) if (m & v).bit_count() & 1) for v in vectors]


def _signed(x: int) -> int:
    return x - (1 << BITS) if x >> BITS - 1 else x


def near_pairs(fps: DataFrame, radius: int = 2, small: int = 16) -> DataFrame:
    """Edges (a, b) that connect distinct fingerprints fp within radius of each other; it is even.

    Edges are links themselves; links left out are implied by a chain of edges, so components are exact.
    """
    if radius < 2 or radius % 2:
        raise ValueError("radius must be even and positive")
    # one number names a table and its key; two that share it only cause comparisons
    keys = F.array(*(F.xxhash64(F.lit(t), F.col("fp").bitwiseAND(F.lit(_signed(m)))) for t, m in enumerate(covering_masks(radius))))
    # a task makes at most a few million keys, so that their aggregation stays in memory
    dealt = fps.repartition(max(8, fps.count() // _DEALT + 1), "fp")
    keyed = dealt.select("fp", F.explode(keys).alias("key"))
    # a bucket of two is known by its least and greatest, so only larger ones are met again
    sizes = stored(keyed.groupBy("key").agg(F.count("*").alias("n"), F.min("fp").alias("low"), F.max("fp").alias("high")).where("n > 1"), "simhash-buckets")
    crowded = maybe_broadcast(sizes.where("n > 2").select("key", "n"), 48)
    members = stored(keyed.join(crowded, "key"), "simhash-members")

    close = lambda a, b: F.bit_count(a.bitwiseXOR(b)) <= radius
    two = sizes.where((F.col("n") == 2) & close(F.col("low"), F.col("high"))).select(F.col("low").alias("a"), F.col("high").alias("b"))
    each = F.col("all")
    pairs = F.flatten(F.transform(each, lambda a: F.transform(F.filter(each, lambda b: (b > a) & close(a, b)), lambda b: F.struct(a.alias("a"), b.alias("b")))))
    few = members.where(F.col("n") <= small).groupBy("key").agg(F.collect_list("fp").alias("all")).select(F.explode(pairs).alias("e")).select("e.a", "e.b")

    # two of a large bucket that differ in up to radius bits share a point, each within half of that; one ball serves all tables
    ball = F.array(*(F.lit(_signed(sum(c))) for k in range(radius // 2 + 1) for c in combinations([1 << i for i in range(BITS)], k)))
    crowd = members.where(F.col("n") > small)
    points = crowd.select("fp").distinct().select("fp", F.explode(ball).alias("flip")).select("fp", F.col("fp").bitwiseXOR(F.col("flip")).alias("point"))
    stars = points.groupBy("point").agg(F.collect_set("fp").alias("all")).where(F.size("all") > 1)
    many = stars.select(F.array_min("all").alias("a"), F.explode("all").alias("b")).where("a <> b")
    return two.union(few).union(many)


def near_components(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", width: int = 3, radius: int = 2) -> DataFrame:
    """(doc_id, fp, component_id) of every row; component_id is the smallest id reachable over links."""
    prints = stored(fingerprints(docs, id_col, text_col, width), "simhash-prints")
    nodes = prints.groupBy("fp").agg(F.min("doc_id").alias("least"))
    roots = connected_components(near_pairs(nodes.select("fp"), radius))
    labelled = stored(nodes.join(roots, nodes["fp"] == roots["node"], "left").select("fp", "least", F.coalesce("root", "fp").alias("root")), "simhash-roots")
    whole = labelled.groupBy("root").agg(F.min("least").alias("component_id"))
    labels = labelled.select("fp", "root").join(whole, "root").select("fp", "component_id")
    return prints.join(labels, "fp").select("doc_id", "fp", "component_id")


class WordNumbers(dict):
    """XXH64 of words, kept for a bounded number of them."""

    def __missing__(self, word: bytes) -> int:
        if len(self) >= _WORDS:
            self.clear()
        self[word] = number = xxhash.xxh64_intdigest(word, SEED)
        return number


_numbers = WordNumbers()


def shingle_numbers(data: bytes, width: int) -> np.ndarray:
    """A 64-bit number for each width-word shingle, in order, made of its words' hashes; of the whole if it has fewer words."""
    words = data.lower().split()
    if not words:
        return np.empty(0, np.uint64)
    each = np.fromiter(map(_numbers.__getitem__, words), np.uint64, len(words))
    n = max(1, len(words) - width + 1)
    out = np.full(n, len(words) if len(words) < width else width, np.uint64)
    for k in range(min(width, len(words))):
        out = out * np.uint64(0x9E3779B97F4A7C15) + each[k : k + n]
        out ^= out >> np.uint64(32)
    out *= np.uint64(0xD6E8FEB86659FD93)
    out ^= out >> np.uint64(32)
    return out


def shingle_set(data: bytes, width: int) -> np.ndarray:
    """The distinct shingle numbers of a text, sorted."""
    return np.unique(shingle_numbers(data, width))


def print_of(numbers: np.ndarray) -> int:
    """Signed 64-bit SimHash of shingle numbers; a bit is set if it is in over half of them."""
    counts = np.zeros(BITS, np.int64)
    for i in range(0, len(numbers), _SLICE):
        own = numbers[i : i + _SLICE].astype(">u8").view(np.uint8).reshape(-1, 8)
        counts += np.unpackbits(own, axis=1).sum(axis=0, dtype=np.int64)
    return int.from_bytes(np.packbits(2 * counts > len(numbers)).tobytes(), "big", signed=True)


def similar(x: np.ndarray, y: np.ndarray, similarity: float) -> bool:
    """Whether two shingle sets have at least that Jaccard similarity; two empty ones are alike."""
    common = len(np.intersect1d(x, y, assume_unique=True))
    return common >= similarity * (len(x) + len(y) - common)


def similar_edges(edges: DataFrame, texts: DataFrame, width: int, similarity: float) -> DataFrame:
    """The edges between nodes of texts (node, text) whose shingle sets have at least that Jaccard similarity.

    Texts travel rather than sets, as they are a third as long when compressed; a set is made where an edge ends.
    """

    def run(batches):
        for batch in slices(batches, 256):
            (a, b), x, y = (c.to_pylist() for c in batch.columns[:2]), utf8(batch.column(2)), utf8(batch.column(3))
            known: dict[int, np.ndarray] = {}
            fine = []
            for i, j, s, t in zip(a, b, x, y):
                # edges of one text stand together, so what is kept at a time is two sets
                if i not in known:
                    known = {i: shingle_set(s, width)}
                fine.append(similar(known[i], shingle_set(t, width), similarity))
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(fine, pa.bool_())], names=["a", "b", "fine"])

    with_b = edges.join(texts.select(F.col("node").alias("b"), F.col("text").alias("tb")), "b")
    both = with_b.join(texts.select(F.col("node").alias("a"), F.col("text").alias("ta")), "a").select("a", "b", "ta", "tb")
    return both.mapInArrow(run, "a long, b long, fine boolean").where("fine").select("a", "b")


def sketch(shingles: np.ndarray) -> bytes:
    """Parities of how many shingles fall on each of m bits, m the power of two from their number on, and _SKETCH at least."""
    m = max(_SKETCH, 1 << (len(shingles) - 1).bit_length()) if len(shingles) else _SKETCH
    return np.packbits(np.bincount((shingles & np.uint64(m - 1)).astype(np.int64), minlength=m).astype(np.uint8) & 1, bitorder="little").tobytes()


def folded(bits: bytes, n: int) -> np.ndarray:
    """A sketch as n bytes: the parities over fewer bits follow from those over more."""
    out = np.frombuffer(bits, np.uint8)
    while len(out) > n:
        out = out[: len(out) // 2] ^ out[len(out) // 2 :]
    return out


def sketches(texts: DataFrame, width: int) -> DataFrame:
    """(node, size, bits): how many distinct shingles a text (node, text) has, and their sketch."""

    def rows(batch: pa.RecordBatch) -> dict[str, list]:
        sets = [shingle_set(data, width) for data in utf8(batch.column(1))]
        return {"node": batch.column(0).to_pylist(), "size": [len(x) for x in sets], "bits": [sketch(x) for x in sets]}

    return arrow_map(texts.select("node", "text"), rows, "node long, size long, bits binary")


def possible_edges(edges: DataFrame, drawn: DataFrame, similarity: float) -> DataFrame:
    """The edges without those that sizes or sketches show to be less similar; no similar pair goes.

    Each bit in which two sketches differ stands for a shingle that only one text has, of which similar texts have
    at most (1 - similarity) / (1 + similarity) of their sizes' sum.
    """
    most = (1 - similarity) / (1 + similarity)

    def may(m: int, n: int, x: bytes, y: bytes) -> bool:
        if min(m, n) < similarity * max(m, n) - 1e-6:
            return False
        k = min(len(x), len(y))
        return int(np.bitwise_count(folded(x, k) ^ folded(y, k)).sum()) <= most * (m + n) + 1e-6

    def rows(batch: pa.RecordBatch) -> dict[str, list]:
        a, b, *sides = (c.to_pylist() for c in batch.columns)
        return {"a": a, "b": b, "fine": [may(*each) for each in zip(*sides)]}

    with_a = edges.join(drawn.select(F.col("node").alias("a"), F.col("size").alias("m"), F.col("bits").alias("x")), "a")
    both = with_a.join(drawn.select(F.col("node").alias("b"), F.col("size").alias("n"), F.col("bits").alias("y")), "b").select("a", "b", "m", "n", "x", "y")
    return arrow_map(both, rows, "a long, b long, fine boolean").where("fine").select("a", "b")


def common_shingles(texts: DataFrame, width: int, most: int = 1 << 16) -> tuple[np.ndarray, np.ndarray]:
    """The shingles that some task finds in more than two texts (node, text), the most frequent if there are many, sorted, and their counts."""

    def run(batches):
        held, size = [], 0
        for batch in slices(batches, 256):
            held += [shingle_set(x, width) for x in utf8(batch.column(1))]
            size += sum(map(len, held[-batch.num_rows :]))
            if size > _HELD:
                yield counted(held)
                held, size = [], 0
        if held:
            yield counted(held)

    def counted(held):
        tokens, n = np.unique(np.concatenate(held), return_counts=True)
        return pa.RecordBatch.from_arrays([pa.array(tokens[n > 2].view(np.int64)), pa.array(n[n > 2])], names=["token", "n"])

    found = texts.mapInArrow(run, "token long, n long").groupBy("token").agg(F.sum("n").alias("n")).orderBy(F.desc("n"), "token").limit(most).collect()
    tokens, n = np.array([r[0] for r in found], np.int64).view(np.uint64), np.array([r[1] for r in found], np.int64)
    order = np.argsort(tokens)
    return tokens[order], n[order]


def shared_tokens(texts: DataFrame, width: int, pick, parts: int, hot: np.ndarray = np.empty(0, np.uint64)) -> DataFrame:
    """(token, low, node): the nodes of each token that pick keeps of the shingles of texts (node, text) and that several have; low is one of them.

    Tokens travel packed, sixteen bytes to each with its node, dealt by hash; those of one node end in the task that reads
    them. A token in hot (sorted) is dealt to all tasks, each of which has a low of its own.
    """
    kinds = 4 * parts

    def pack(batches):
        held, nodes, size = [], [], 0
        for batch in slices(batches, 256):
            held += [pick(shingle_set(x, width)) for x in utf8(batch.column(1))]
            nodes += batch.column(0).to_pylist()
            size += sum(map(len, held[-batch.num_rows :]))
            if size > _HELD:
                yield packed(held, nodes)
                held, nodes, size = [], [], 0
        if held:
            yield packed(held, nodes)

    def packed(held, nodes):
        tokens = np.concatenate(held)
        owners = np.repeat(np.array(nodes, np.int64), [len(x) for x in held])
        both = np.stack([tokens.view(np.int64), owners], axis=1)
        spread = np.where(among(tokens, hot), owners.view(np.uint64) * np.uint64(0x9E3779B97F4A7C15) >> np.uint64(16), tokens)
        kind = (spread % np.uint64(kinds)).astype(np.int32)
        order = np.argsort(kind, kind="stable")
        found, starts = np.unique(kind[order], return_index=True)
        return pa.RecordBatch.from_arrays([pa.array(found), pa.array([x.tobytes() for x in np.split(both[order], starts[1:])] if len(found) else [], pa.binary())], names=["kind", "pairs"])

    def meet(batches):
        blobs = [x for batch in batches for x in batch.column(1).to_pylist()]
        if not blobs:
            return
        token, node = np.frombuffer(b"".join(blobs), np.int64).reshape(-1, 2).T
        # the exclusive or deals the first place to another node for each token
        order = np.lexsort((token ^ node, token))
        token, node = token[order], node[order]
        _, starts, n = np.unique(token, return_index=True, return_counts=True)
        low, n = np.repeat(node[starts], n), np.repeat(n, n)
        wanted = (n > 1) | among(token.view(np.uint64), hot)
        for at in np.array_split(np.flatnonzero(wanted), len(token) // 100_000 + 1):
            yield pa.RecordBatch.from_arrays([pa.array(x[at]) for x in (token, low, node)], names=["token", "low", "node"])

    return texts.mapInArrow(pack, "kind int, pairs binary").repartition(parts, "kind").mapInArrow(meet, "token long, low long, node long")


def among(tokens: np.ndarray, some: np.ndarray) -> np.ndarray:
    """Which of the tokens are in a sorted array."""
    if not len(some):
        return np.zeros(len(tokens), bool)
    return some[np.minimum(np.searchsorted(some, tokens), len(some) - 1)] == tokens


def prefix(shingles: np.ndarray, similarity: float, common: np.ndarray, counts: np.ndarray) -> np.ndarray:
    """The first shingles in one order of all shingles, rare before common, that any set of that similarity shares one of.

    Sets of that Jaccard similarity share at least similarity * n of the n shingles of either, so the first n - similarity * n + 1
    of both meet, whatever the order is; it only decides how often others meet.
    """
    if not len(shingles):
        return shingles
    weight = np.zeros(len(shingles), np.int64)
    if len(common):
        at = np.minimum(np.searchsorted(common, shingles), len(common) - 1)
        weight = np.where(common[at] == shingles, counts[at], 0)
    must_share = math.ceil(similarity * len(shingles) - 1e-9)
    return shingles[np.lexsort((shingles, weight))[: len(shingles) - must_share + 1]]


def alike(node: np.ndarray, root: np.ndarray, block: np.ndarray, ends: tuple[int, int], size: np.ndarray, bits: list[bytes], similarity: float) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Places x and y of the pairs between two blocks (ends) whose roots differ and whose sketches don't rule them out, and their differing bits."""
    most = (1 - similarity) / (1 + similarity)
    long = np.minimum([len(x) for x in bits], _WIDEST)
    found = [(np.empty(0, np.int64), np.empty(0, np.int64), np.empty(0, np.float32))]
    for k in np.unique(long):
        # sizes that are alike have sketches that differ twofold in length at most; the shorter length decides
        near = (long == k) | (long == 2 * k)
        left, right = np.flatnonzero(near & (block == ends[0])), np.flatnonzero(near & (block == ends[1]))
        if not len(left) or not len(right):
            continue
        p, q = (np.unpackbits(np.array([folded(bits[r], k) for r in side]), axis=1).astype(np.float32) for side in (left, right))
        apart = p.sum(1)[:, None] + q.sum(1)[None, :] - 2 * p @ q.T
        m, n = size[left][:, None], size[right][None, :]
        fine = (root[left][:, None] != root[right][None, :]) & ((long[left][:, None] == k) | (long[right][None, :] == k))
        fine &= (apart <= most * (m + n) + 1e-6) & (np.minimum(m, n) >= similarity * np.maximum(m, n) - 1e-6)
        if ends[0] == ends[1]:
            fine &= node[left][:, None] < node[right][None, :]
        x, y = np.nonzero(fine)
        found.append((left[x], right[y], apart[x, y]))
    return tuple(np.concatenate(each) for each in zip(*found))


def in_blocks(crowds: DataFrame) -> DataFrame:
    """Rows of tokens (token, n, node, ...) dealt to block pairs (token, i, j): some 2 * _BLOCK nodes each however large a token's group is."""
    blocks = F.ceil(F.col("n") / _BLOCK).cast("int")
    own = crowds.withColumns({"blocks": blocks, "block": F.pmod(F.xxhash64("node"), blocks).cast("int")})
    dealt = own.withColumn("other", F.explode(F.sequence(F.lit(0), F.col("blocks") - 1))).drop("n", "blocks")
    return dealt.withColumns({"i": F.least("block", "other"), "j": F.greatest("block", "other")}).drop("other")


def linked_in_crowds(crowds: DataFrame, similarity: float) -> DataFrame:
    """(a, b): links between nodes of one token (token, n, node, root, shingles) with different roots, as a forest for each block pair.

    Pairs that sketches leave are compared by their shingles in place, likeliest first, unless links found there already join
    them; so a block pair gives fewer links than it has roots, and its components are exact.
    """

    def meet(group: pa.Table) -> pa.Table:
        node, root, block, i, j = (group.column(c).to_numpy() for c in ("node", "root", "block", "i", "j"))
        sets = [np.frombuffer(x, np.uint64) for x in group.column("shingles").to_pylist()]
        x, y, apart = alike(node, root, block, (i[0], j[0]), np.array([len(s) for s in sets]), [sketch(s) for s in sets], similarity)
        above: dict[int, int] = {}

        def top(r: int) -> int:
            while (up := above.get(r, r)) != r:
                above[r] = above.get(up, up)
                r = up
            return r

        a, b = [], []
        order = np.argsort(apart, kind="stable")
        for p, q in zip(x[order].tolist(), y[order].tolist()):
            r, s = top(int(root[p])), top(int(root[q]))
            if r != s and similar(sets[p], sets[q], similarity):
                above[max(r, s)] = min(r, s)
                a.append(min(node[p], node[q]))
                b.append(max(node[p], node[q]))
        return pa.table({"a": pa.array(a, pa.int64()), "b": pa.array(b, pa.int64())})

    return in_blocks(crowds).groupBy("token", "i", "j").applyInArrow(meet, "a long, b long").distinct()


def met_in_crowds(crowds: DataFrame, similarity: float, best: bool, over: int = 0) -> DataFrame:
    """(a, b): pairs of nodes of one token (token, n, node, root, size, bits) with different roots that may be similar.

    At least one of a pair has more than over shingles. With best, only the likeliest partner of a node in each other component comes out.
    """

    def meet(group: pa.Table) -> pa.Table:
        node, root, size, block, i, j = (group.column(c).to_numpy() for c in ("node", "root", "size", "block", "i", "j"))
        x, y, apart = alike(node, root, block, (i[0], j[0]), size, group.column("bits").to_pylist(), similarity)
        wanted = np.maximum(size[x], size[y]) > over
        x, y, apart = x[wanted], y[wanted], apart[wanted]
        if best and len(x):
            order = np.lexsort((apart, root[y], x))
            x, y = x[order], y[order]
            head = np.r_[True, (x[1:] != x[:-1]) | (root[y[1:]] != root[y[:-1]])]
            x, y = x[head], y[head]
        return pa.table({"a": np.minimum(node[x], node[y]), "b": np.maximum(node[x], node[y])})

    return in_blocks(crowds).groupBy("token", "i", "j").applyInArrow(meet, "a long, b long").distinct()


def met_in_small_groups(few: DataFrame) -> DataFrame:
    """(a, b): all pairs of nodes with different roots in groups of at most _FEW nodes of a token (token, node, root)."""
    each = F.col("all")
    pairs = F.flatten(F.transform(each, lambda a: F.transform(F.filter(each, lambda b: (b["node"] > a["node"]) & (b["root"] != a["root"])), lambda b: F.struct(a["node"].alias("a"), b["node"].alias("b")))))
    met = few.groupBy("token").agg(F.collect_list(F.struct("node", "root")).alias("all"))
    return met.select(F.explode(pairs).alias("e")).select("e.a", "e.b").distinct()


def similar_links(members: DataFrame, likely: DataFrame, texts: DataFrame, width: int, similarity: float) -> DataFrame:
    """Edges (a, b) between nodes whose texts are similar, enough of them for exact components.

    likely: edges to be looked at first. Nodes of members (token, low, node) that share a token are a bucket; each is
    compared with the bucket's low, and where a bucket's nodes are then in several components, every two of different
    components are compared. What an earlier step has joined is not looked at again, so copies of one text cost one edge each.
    """
    spark = texts.sparkSession
    star = stored(members.where("node <> low").select(F.least("node", "low").alias("a"), F.greatest("node", "low").alias("b")).distinct(), "near-stars")
    ends = stored(members.select("node").union(likely.select(F.explode(F.array("a", "b")))).distinct(), "near-ends")
    own = texts.join(maybe_broadcast(ends, 16), "node").select("node", "text")
    drawn = stored(sketches(own, width), "near-sketches")
    links = spark.createDataFrame([], "a long, b long")
    used = []

    def check(edges: DataFrame, label: str) -> bool:
        """Add the edges that are links; whether there were any."""
        nonlocal links
        left = stored(possible_edges(edges, drawn, similarity), f"near-{label}")
        used.append(left)
        if not left.count():
            return False
        held = texts.join(maybe_broadcast(stored(left.select(F.explode(F.array("a", "b")).alias("node")).distinct(), "near-held"), 16), "node").select("node", "text")
        found = stored(similar_edges(left, held, width, similarity), f"near-{label}-links")
        links = links.union(found)
        return found.count() > 0

    def apart(edges: DataFrame, roots: DataFrame) -> DataFrame:
        """The edges between different components."""
        side = lambda name: roots.select(F.col("node").alias(name), F.col("root").alias(f"{name}_root"))
        named = edges.join(side("a"), "a", "left").join(side("b"), "b", "left")
        return named.where(F.coalesce("a_root", "a") != F.coalesce("b_root", "b")).select("a", "b")

    # an edge for each node first: most components are whole after that
    check(likely.union(star.groupBy("b").agg(F.min("a").alias("a")).select("a", "b")).distinct(), "first")
    roots = connected_components(links)
    if check(apart(star, roots), "stars"):
        roots = connected_components(links)
    sizes = members.groupBy("token").agg(F.count("*").alias("n")).where("n > 2")
    named = members.select("token", "node").join(sizes, "token").join(roots.withColumnRenamed("node", "own"), F.col("node") == F.col("own"), "left").select("token", "n", "node", F.coalesce("root", "node").alias("root"))
    named = stored(named, "near-named")
    mixed = stored(named.groupBy("token").agg(F.min("root").alias("x"), F.max("root").alias("y")).where("x <> y").select("token"), "near-unsettled")
    rest = named.join(maybe_broadcast(mixed, 16), "token", "left_semi")
    if check(met_in_small_groups(rest.where(F.col("n") <= _FEW)), "small"):
        roots = connected_components(links)
    rooted = lambda df, roots: df.join(roots.select(F.col("node").alias("own"), "root"), F.col("node") == F.col("own"), "left").withColumn("root", F.coalesce("root", "node")).drop("own")
    crowds = stored(rest.where(F.col("n") > _FEW).drop("root").join(drawn.select("node", "size"), "node"), "near-crowds")
    # sets of bounded size are compared in place, which gives a forest of links rather than pairs
    short = crowds.where(F.col("size") <= _SHORT)
    held = texts.join(maybe_broadcast(stored(short.select("node").distinct(), "near-short"), 16), "node").select("node", "text")
    sets = arrow_map(held, lambda batch: {"node": batch.column(0).to_pylist(), "shingles": [shingle_set(x, width).tobytes() for x in utf8(batch.column(1))]}, "node long, shingles binary")
    found = stored(linked_in_crowds(rooted(short.drop("size").join(sets, "node"), roots), similarity), "near-crowd-links")
    links = links.union(found)
    if crowds.where(F.col("size") > _SHORT).limit(1).count():
        # longer ones meet each other, and shorter ones of a like size, by sketches
        long = stored(crowds.where(F.col("size") >= math.floor(similarity * _SHORT)).join(drawn.select("node", "bits"), "node"), "near-long")
        used.append(long)
        check(met_in_crowds(rooted(long, connected_components(links)), similarity, best=True, over=_SHORT), "best")
        check(met_in_crowds(rooted(long, connected_components(links)), similarity, best=False, over=_SHORT), "every")
    used.append(crowds)
    discard(star, ends, drawn, named, mixed, *used)
    return links


def keep_one(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", width: int = 5, similarity: float = 0.8, radius: int = 2) -> DataFrame:
    """docs, all columns, with one row of each group of near duplicates: the one of the smallest id.

    Rows of equal words are one node, named by the number of its least row; copies are never paired with each other.
    Nodes are linked if their texts have the given Jaccard similarity on width-word shingles. Candidates come from the covering
    tables of their fingerprints, within radius bits; and as fingerprints of similar texts may be farther apart, from a
    prefix filter, by which every pair of that similarity shares a shingle. Among rows of equal id and text one stays.
    """
    # a row's own number tells repeated rows apart; it is fixed by writing the rows
    prints = stored(numbered_rows(docs, id_col, text_col, width).withColumn("row", F.monotonically_increasing_id()), "near-prints")
    order = F.struct(F.col("doc_id").isNull().alias("none"), F.col("doc_id").alias("id"), F.col("row").alias("row"))
    nodes = stored(prints.groupBy("words").agg(F.count("*").alias("n"), F.min(order).alias("least"), F.min("fp").alias("fp")), "near-nodes")
    heads = nodes.select(F.col("least.row").alias("row"))
    # copies are the fewer rows: they are taken out rather than the others joined
    copies = stored(prints.select("row", "words").join(nodes.where("n > 1").select("words", "least"), "words").where("row <> least.row").select("row"), "near-copies")
    texts = prints.join(maybe_broadcast(copies, 16), "row", "left_anti").select(F.col("row").alias("node"), F.col(f"kept.`{text_col}`").cast("string").alias("text"))
    likely = stored(fingerprint_edges(nodes.select(F.col("least.row").alias("node"), "fp"), radius), "near-likely")
    common, counts = common_shingles(texts, width)
    members = stored(shared_tokens(texts, width, lambda s: prefix(s, similarity, common, counts), max(8, nodes.count() // _MET + 1), common[counts > _HOT]), "near-members")
    roots = connected_components(similar_links(members, likely, texts, width, similarity))
    named = nodes.join(roots, nodes["least.row"] == roots["node"], "left").select("least", F.coalesce("root", "least.row").alias("root"))
    chosen = named.groupBy("root").agg(F.min("least").alias("least")).select("least.row")
    gone = stored(heads.join(chosen, "row", "left_anti").union(copies), "near-gone")
    discard(nodes, copies, likely, members)
    return prints.join(maybe_broadcast(gone, 16), "row", "left_anti").select("kept.*")


def fingerprint_edges(nodes: DataFrame, radius: int) -> DataFrame:
    """(a, b): candidates among nodes (node, fp): those of one fingerprint with its least, and the least ones of near fingerprints."""
    least = stored(nodes.groupBy("fp").agg(F.min("node").alias("head"), F.count("*").alias("n")), "near-fingerprints")
    same = nodes.join(least.where("n > 1").drop("n"), "fp").where("node <> head").select(F.col("head").alias("a"), F.col("node").alias("b"))
    side = lambda name: least.select(F.col("fp").alias(name), F.col("head").alias(f"{name}_head"))
    near = near_pairs(least.select("fp"), radius).join(side("a"), "a").join(side("b"), "b")
    return same.union(near.select(F.least("a_head", "b_head").alias("a"), F.greatest("a_head", "b_head").alias("b"))).distinct()


def numbered_rows(docs: DataFrame, id_col: str, text_col: str, width: int) -> DataFrame:
    """(doc_id, kept, words, fp): kept is the whole row as a struct, words a hash of the lower-cased words in order, fp their SimHash."""
    from pyspark.sql import types as T

    packed = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.struct(*(F.col(f"`{c}`") for c in docs.columns)).alias("kept"), F.col(text_col).cast("string").alias("text"))
    schema = T.StructType([*packed.schema.fields[:2], T.StructField("words", T.LongType()), T.StructField("fp", T.LongType())])

    def run(batches):
        for batch in slices(batches):
            data = utf8(batch.column(2))
            words = pa.array([xxhash.xxh64_intdigest(b" ".join(x.lower().split())) for x in data], pa.uint64()).view(pa.int64())
            prints = pa.array([print_of(shingle_numbers(x, width)) for x in data], pa.int64())
            yield pa.RecordBatch.from_arrays([*batch.columns[:2], words, prints], names=[*batch.schema.names[:2], "words", "fp"])

    return packed.mapInArrow(run, schema)
