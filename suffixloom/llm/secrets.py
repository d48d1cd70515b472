"""Secret scans: fixed patterns, and high-entropy strings by a sliding window, with column functions only.

Candidate strings are runs of the characters of a class. A window slides over each: two counts change at each step, and
with them the sum of n log n over the window's characters, from which Shannon's entropy follows. That sum is kept
in whole numbers (a table of round(n * log2(n) * 2^20)), so that results are exact and alike everywhere. A candidate
is a finding if some window's entropy reaches its class's limit and no allow-list pattern fits it.

Defined results: a null or empty text has no findings; positions are code points, end exclusive; repeated rows get
repeated results; other columns are not read by ``secret_spans`` and pass unchanged through ``redact``.
"""

from __future__ import annotations

import math
import re
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .scans import bound, scan

#: Kinds in order, pattern, group whose length counts, least length.
BASE = (
    ("assign", r"""(?i)(password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", 2, 6),
    ("access", r"AKIA[A-Z0-9]+", 0, 20),
    ("hex", r"[0-9a-f]+", 0, 24),
)

SCALE = 1 << 20


@dataclass(frozen=True)
class EntropyClass:
    """Runs of chars of at least a window's length, judged by windows; need: patterns that all must occur in the run."""

    kind: str
    chars: str
    window: int
    min_bits: float
    need: tuple[str, ...] = ()

    @property
    def max_sum(self) -> int:
        """The entropy of a window is log2(window) - sum / window; this is the largest sum that reaches min_bits."""
        return math.floor(self.window * (math.log2(self.window) - self.min_bits) * SCALE)

    @property
    def symbols(self) -> str:
        return "".join(chr(i) for i in range(128) if re.match(f"[{self.chars}]", chr(i)))


CLASSES = (
    EntropyClass("entropy_hex", "0-9A-F", 24, 3.0, ("[0-9]", "[A-F]")),
    EntropyClass("entropy_base64", "A-Za-z0-9+/_=-", 20, 3.8, ("[0-9]", "[A-Z]", "[a-z]")),
    EntropyClass("entropy_alnum", "a-z0-9", 20, 3.6, ("[0-9][^0-9]*[0-9]", "[g-z]")),
)

#: Whole runs that look random and are no secrets: UUIDs, and paths, dates and identifiers whose parts are a word or a number each.
#: Repetitions of groups are possessive, so that no text makes the pattern recurse.
ALLOWED_RUNS = (
    r"^[0-9a-f]{8}-[0-9a-f]{4}-[0-9a-f]{4}-[0-9a-f]{4}-[0-9a-f]{12}$",
    r"^[+/_=-]*+(?:[A-Za-z]{1,24}|[0-9]{1,12})(?:[+/_=-]++(?:[A-Za-z]{1,24}|[0-9]{1,12}))*+[+/_=-]*+$",
)
#: Windows that are no secrets, though random enough: placeholders and the alphabet.
ALLOWED_WINDOWS = (
    r"(?i)example|sample|placeholder|dummy|changeme|xxxx",
    r"abcdefghij|ABCDEFGHIJ|0123456789",
)

_SPAN = "struct<start: bigint, end: bigint, at: bigint, to: bigint, value: string, size: int>"


def spans_of(text: Column, pattern: str, group: int, least: int) -> Column:
    """Spans (start, end in code points, at, to in bytes, value) of leftmost matches whose group has at least `least` code points.

    A text is parted by the pattern; parts and matches alternate, so their lengths add up to positions.
    """
    matches = F.regexp_extract_all(text, F.lit(pattern), F.lit(0))
    values = matches if group == 0 else F.regexp_extract_all(text, F.lit(pattern), F.lit(group))
    whole = F.zip_with(F.split(text, pattern, -1), F.zip_with(matches, values, lambda m, v: F.struct(m.alias("m"), v.alias("v"))), lambda gap, x: F.struct(F.length(gap).cast("long").alias("gap"), F.octet_length(gap).cast("long").alias("gap_bytes"), x["m"].alias("m"), x["v"].alias("v")))
    zero = F.lit(0).cast("long")
    points = lambda x: F.coalesce(F.length(x["m"]), F.lit(0))
    octets = lambda x: F.coalesce(F.octet_length(x["m"]), F.lit(0))

    def step(state: Column, x: Column) -> Column:
        return F.struct((state["start"] + x["gap"] + points(x)).alias("start"), (state["at"] + x["gap_bytes"] + octets(x)).alias("at"))

    def emit(state: Column, x: Column) -> Column:
        start, at = state["start"] + x["gap"], state["at"] + x["gap_bytes"]
        return F.struct(start.alias("start"), (start + points(x)).alias("end"), at.alias("at"), (at + octets(x)).alias("to"), x["m"].alias("value"), F.length(x["v"]).alias("size"))

    return F.filter(scan(whole, F.struct(zero.alias("start"), zero.alias("at")), step, emit, _SPAN), lambda s: F.coalesce(s["size"] >= least, F.lit(False)))


def _none() -> Column:
    return F.expr(f"cast(array() as array<{_SPAN}>)")


def base_spans(text: Column, lowered: Column) -> list[Column]:
    """Spans of the fixed kinds in order; a cheap test keeps the patterns from texts that can't match."""
    assign, access, hexes = BASE
    hints = [F.contains(lowered, F.lit(x)) for x in ("passw", "secret", "token", "apikey", "api_key")]
    can_assign = hints[0] | hints[1] | hints[2] | hints[3] | hints[4]
    return [
        F.when(can_assign, spans_of(text, *assign[1:])).otherwise(_none()),
        F.when(F.contains(text, F.lit("AKIA")), spans_of(text, *access[1:])).otherwise(_none()),
        # runs below the least length fail whole, so matching only long runs gives the same spans
        F.when(text.rlike(f"[0-9a-f]{{{hexes[3]}}}"), spans_of(text, f"[0-9a-f]{{{hexes[3]},}}", 0, hexes[3])).otherwise(_none()),
    ]


#: Counters to a 64-bit number, and bits of each: a window holds less than 32 characters.
_TO_A_WORD, _BITS = 12, 5


def best_window(value: Column, one: EntropyClass) -> Column:
    """(least, at): the smallest sum of n log2 n (scaled) over the windows of a run, and where the first such window ends.

    Counts are packed, twelve to a number. A step changes two of them, and the sum by four looked-up terms.
    """
    window, symbols = one.window, one.symbols
    if window >= 1 << _BITS:
        raise ValueError(f"a window must have less than {1 << _BITS} characters")
    words = -(-len(symbols) // _TO_A_WORD)
    rank = {c: i for i, c in enumerate(symbols)}
    place = [divmod(rank.get(chr(i), 0), _TO_A_WORD) for i in range(128)]
    literal = lambda xs, kind: F.array(*(F.lit(x).cast(kind) for x in xs))
    word_of, unit_of = literal([w for w, _ in place], "int"), literal([1 << _BITS * k for _, k in place], "long")
    terms = literal([round(n * math.log2(n) * SCALE) if n else 0 for n in range(window + 2)], "long")
    term = lambda n: F.get(terms, n.cast("int"))
    codes = F.transform(F.split(value, ""), lambda c: F.ascii(c))
    moves = bound(codes, lambda all_: F.zip_with(all_, F.slice(F.concat(F.array_repeat(F.lit(None).cast("int"), window), all_), F.lit(1), F.size(all_)), lambda new, old: F.struct(new.alias("new"), old.alias("old"), F.get(word_of, new).alias("w"), F.get(unit_of, new).alias("u"), F.get(word_of, old).alias("v"), F.get(unit_of, old).alias("t"))))
    zero = F.lit(0).cast("long")
    init = F.struct(zero.alias("i"), F.array_repeat(zero, words).alias("counts"), zero.alias("sum"), F.lit(None).cast("long").alias("least"), zero.alias("at"))

    def step(state: Column, x: Column) -> Column:
        counts = state["counts"]
        held = lambda w, u: F.call_function("div", F.get(counts, w), u).bitwiseAND((1 << _BITS) - 1)

        def changed(terms_: Column) -> Column:
            same = x["old"].eqNullSafe(x["new"])
            total = state["sum"] + F.when(same, zero).otherwise(term(terms_["n"] + 1) - term(terms_["n"]) + F.when(x["old"].isNull(), zero).otherwise(term(terms_["m"] - 1) - term(terms_["m"])))
            return F.struct((state["i"] + 1).alias("i"), F.when(same, counts).otherwise(F.transform(counts, lambda c, k: c + F.when(k == x["w"], x["u"]).otherwise(zero) - F.when(k == x["v"], x["t"]).otherwise(zero))).alias("counts"), total.alias("sum"))

        def judged(new: Column) -> Column:
            better = (new["i"] >= window) & (state["least"].isNull() | (new["sum"] < state["least"]))
            return F.struct(new["i"].alias("i"), new["counts"].alias("counts"), new["sum"].alias("sum"), F.when(better, new["sum"]).otherwise(state["least"]).alias("least"), F.when(better, new["i"]).otherwise(state["at"]).alias("at"))

        return bound(bound(F.struct(held(x["w"], x["u"]).alias("n"), held(x["v"], x["t"]).alias("m")), changed), judged)

    return F.aggregate(moves, init, step, lambda state: F.struct(state["least"].alias("least"), state["at"].cast("int").alias("at")))


def entropy_spans(text: Column, one: EntropyClass) -> Column:
    runs = f"(?<![{one.chars}])[{one.chars}]{{{one.window},}}"

    def wanted(span: Column) -> Column:
        v, ok = span["value"], F.lit(True)
        for p in one.need:
            ok = ok & v.rlike(p)
        for p in ALLOWED_RUNS:
            ok = ok & ~v.rlike(p)

        def fits(best: Column) -> Column:
            inside, free = F.substring(v, best["at"] - one.window + 1, F.lit(one.window)), F.lit(True)
            for p in ALLOWED_WINDOWS:
                free = free & ~inside.rlike(p)
            return F.coalesce((best["least"] <= one.max_sum) & free, F.lit(False))

        return F.when(ok, bound(best_window(v, one), fits)).otherwise(False)

    return F.when(text.rlike(runs), F.filter(spans_of(text, runs, 0, one.window), wanted)).otherwise(_none())


def _joined(kinds: list[tuple[str, Column]]) -> Column:
    """kind:start:end of all spans by start, then kind as listed."""
    def tagged(i: int, kind: str, spans: Column) -> Column:
        return F.transform(spans, lambda s: F.struct(s["start"].alias("start"), F.lit(i).alias("order"), s["end"].alias("end"), F.lit(kind).alias("kind")))

    every = F.array_sort(F.concat(*(tagged(i, kind, spans) for i, (kind, spans) in enumerate(kinds))))
    return F.array_join(F.transform(every, lambda s: F.concat_ws(":", s["kind"], s["start"].cast("string"), s["end"].cast("string"))), ",")


def with_spans(docs: DataFrame, text_col: str, names: list[str]) -> DataFrame:
    """docs with one array of spans for each kind, in columns of the given names."""
    text = F.coalesce(F.col(text_col).cast("string"), F.lit(""))
    found = [*base_spans(text, F.lower(text)), *(entropy_spans(text, c) for c in CLASSES)]
    return docs.withColumns(dict(zip(names, found)))


KINDS = [*(b[0] for b in BASE), *(c.kind for c in CLASSES)]


def secret_spans(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, counts of the base kinds, digest of the base spans, and all spans."""
    picked = docs.select(F.col(id_col).alias("doc_id"), F.col(text_col).cast("string").alias("text"))
    found = with_spans(picked, "text", KINDS).select("doc_id", *KINDS)
    base = [(k, F.col(k)) for k in KINDS[: len(BASE)]]
    return found.select(
        "doc_id",
        *(F.size(k).cast("long").alias(f"n_{k}") for k in KINDS[: len(BASE)]),
        F.sha2(_joined(base).cast("binary"), 256).alias("base_sha256"),
        _joined([(k, F.col(k)) for k in KINDS]).alias("spans"),
    )


def redact(docs: DataFrame, text_col: str = "text", mark: str = "[secret]") -> DataFrame:
    """docs with every finding in text_col replaced by mark; overlapping findings become one. Null texts stay null."""
    names = KINDS
    taken = {c.lower() for c in docs.columns}
    columns = []
    for n in names:
        while n.lower() in taken:
            n += "_"
        taken.add(n.lower())
        columns.append(n)
    text = F.col(text_col).cast("string")
    spans = F.array_sort(F.concat(*(F.transform(c, lambda s: F.struct(s["at"].alias("at"), s["to"].alias("to"))) for c in columns)))
    reach = lambda state, s: F.greatest(state, s["to"])
    gap = lambda state, s: F.struct(state.alias("after"), (s["at"] - state).alias("n"))

    def parted(data: Column, all_: Column) -> Column:
        """The bytes between findings, which are cut where they stand, and a mark for each run of overlapping ones."""
        gaps = scan(all_, F.lit(0).cast("long"), reach, gap, "struct<after: bigint, n: bigint>")
        pieces = F.transform(F.filter(gaps, lambda g: (g["n"] >= 0)), lambda g: F.concat(F.substring(data, (g["after"] + 1).cast("int"), g["n"].cast("int")).cast("string"), F.lit(mark)))
        end = F.array_max(F.transform(all_, lambda s: s["to"]))
        return F.concat(F.array_join(pieces, ""), F.substring(data, (end + 1).cast("int"), F.octet_length(data)).cast("string"))

    cleaned = F.when(F.size(spans) > 0, bound(F.struct(text.cast("binary").alias("data"), spans.alias("spans")), lambda x: parted(x["data"], x["spans"]))).otherwise(text)
    return with_spans(docs, text_col, columns).withColumn(text_col, cleaned).select(*(F.col(f"`{c}`") for c in docs.columns))
