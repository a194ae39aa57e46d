"""Secrets in texts, in JVM-side expressions only.

Base kinds: ``assign`` (a credential word, a separator and a value of six or more), ``access`` (access-key ids) and ``hex`` (24
or more hexadecimal digits), as the leftmost non-overlapping matches of their patterns that pass.

The method adds ``entropy`` spans. Candidate strings are runs of 20 or more of the base64 and identifier
characters that hold a digit and a letter. A window of 20 characters slides over a candidate; its Shannon
entropy is kept up to date from the counts of the character that leaves and the one that enters. The
span goes from the first to the last window above its threshold. An entropy span may lie inside or across a base span; it then
corroborates it. The threshold belongs to a character class (hexadecimal digits, one letter case with digits, or mixed), and an
allow-list holds documentation placeholders, counting sequences, long repeats and UUIDs. Both are applied in two ways:

- by window (the query): every window has the class of its own characters. Matches of the allow-list cut a candidate into
  sections, so that just the windows that overlap a match are left out, and each section has a span of its own. A candidate
  that is a UUID as a whole is suppressed.
- by candidate: the class is that of the whole candidate, and any match of the allow-list suppresses all of it.

Offsets count code points, ends are exclusive. A null text is an empty one and gives no span; rows are independent, so ids may
be null or repeat.
"""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from concord.llm.native import let, matches

KINDS = ("assign", "access", "hex", "entropy")
ASSIGN = r"((?i:password|passwd|secret|token|api_?key))[\"']?\x20*[:=]\x20*[\"']?([A-Za-z0-9+/_.=-]+)"
ACCESS = r"AKIA[A-Z0-9]{16,}"
HEX = r"[0-9a-f]{24,}"
CANDIDATE = r"[A-Za-z0-9+/_=-]{20,}"
ALLOWED = ("example", "sample", "placeholder", "changeme", "dummy", "your_", r"(.)\1{7,}", "abcdefgh", "01234567", "12345678", "98765432")
ALLOWED_WHOLE = "^[0-9a-f]{8}-[0-9a-f]{4}-[0-9a-f]{4}-[0-9a-f]{4}-[0-9a-f]{12}$"
ALLOW = "(?i)" + "|".join((*ALLOWED, ALLOWED_WHOLE))
ALLOW_PART = "(?i)" + "|".join(ALLOWED)
WINDOW = 20
#: Windows of a block, the characters before and behind its windows that decide which of them the allow-list's matches overlap, and the blocks as a pattern.
BLOCK, MARGIN = 256, 32
PAD = "#$" * (MARGIN // 2)
BLOCKS = f"(?s)(?=(.{{1,{MARGIN + BLOCK + WINDOW - 1 + MARGIN}}})).{{1,{BLOCK}}}"
#: Bits below which a window of a character class is not taken for random.
LEAST_BITS = (("^[0-9a-f]+$|^[0-9A-F]+$", 3.0), ("^[^a-z]+$|^[^A-Z]+$", 3.5), ("", 3.8))


def _weight(count: Column) -> Column:
    """count * log2(count), 0 for 0."""
    return F.when(count > 1, count * F.log2(count.cast("double"))).otherwise(F.lit(0.0))


def _count(window: Column, char: Column) -> Column:
    return F.length(window) - F.length(F.replace(window, char, F.lit("")))


def _most(bits: float) -> float:
    """entropy >= bits  <=>  sum of count*log2(count) <= this"""
    return WINDOW * (math.log2(WINDOW) - bits) + 1e-9


def _bound(text: Column, by_window: bool) -> Column:
    """The greatest weight of a window that counts as random: by the class of the whole text, or the widest one where each window has its own class."""
    if by_window:
        return F.lit(_most(LEAST_BITS[0][1]))
    most = F.lit(_most(LEAST_BITS[-1][1]))
    for pattern, bits in reversed(LEAST_BITS[:-1]):
        most = F.when(text.rlike(pattern), F.lit(_most(bits))).otherwise(most)
    return most


def _hot(text: Column, most: Column, by_window: bool) -> Column:
    """struct(first, last): 0-based starts of the first and last window above its threshold in a text of bounded length; nulls if none is."""
    opening = F.substring(text, 1, WINDOW)
    letters = F.array_distinct(F.filter(F.split(opening, ""), lambda c: c != ""))
    weight = F.aggregate(letters, F.lit(0.0), lambda acc, c: acc + _weight(_count(opening, c)))

    def slide(s: Column) -> Column:
        t, bound = s["t"], s["most"]

        def above(w: Column, k: Column) -> Column:
            if not by_window:
                return w <= bound
            # bits grow along LEAST_BITS, so a window passes by its own class exactly if it passes by any class it matches
            passes = w <= _most(LEAST_BITS[-1][1])
            for pattern, bits in LEAST_BITS[:-1]:
                passes = passes | ((w <= _most(bits)) & F.substr(t, k + 1, F.lit(WINDOW)).rlike(pattern))
            return (w <= bound) & passes

        first = F.when(above(s["w"], F.lit(0)), F.lit(0)).otherwise(F.lit(None).cast("int"))
        begin = F.struct(s["w"].alias("w"), first.alias("first"), first.alias("last"))

        def step(acc: Column, k: Column) -> Column:  # window k: character k leaves, character k + WINDOW enters
            inner = F.substr(t, k + 1, F.lit(WINDOW - 1))
            out, into = _count(inner, F.substr(t, k, F.lit(1))), _count(inner, F.substr(t, k + WINDOW, F.lit(1)))
            w = let(F.struct(out.alias("o"), into.alias("i")), lambda c: acc["w"] - _weight(c["o"] + 1) + _weight(c["o"]) + _weight(c["i"] + 1) - _weight(c["i"]))
            judged = let(w, lambda v: F.struct(v.alias("w"), above(v, k).alias("hot")))
            return let(
                judged,
                lambda v: F.struct(
                    v["w"].alias("w"),
                    F.when(acc["first"].isNull() & v["hot"], k).otherwise(acc["first"]).alias("first"),
                    F.when(v["hot"], k).otherwise(acc["last"]).alias("last"),
                ),
            )

        moves = F.when(F.length(t) > WINDOW, F.sequence(F.lit(1), F.length(t) - WINDOW)).otherwise(F.array().cast("array<int>"))
        return F.aggregate(moves, begin, step)

    return let(F.struct(text.alias("t"), most.alias("most"), weight.alias("w")), slide)


SPAN = "array<struct<start:int,rank:int,kind:string,end:int>>"


def _spans(found: Column, rank: int) -> Column:
    return F.transform(found, lambda m: F.struct(m["start"].alias("start"), F.lit(rank).alias("rank"), F.lit(KINDS[rank]).alias("kind"), m["end"].alias("end")))


def _base(text: Column) -> Column:
    assign = F.filter(matches(text, ASSIGN, 2), lambda m: F.length(m["value"]) >= 6)
    return F.array_sort(F.concat(_spans(assign, 0), _spans(matches(text, ACCESS), 1), _spans(matches(text, HEX), 2)))


def _every(part: str) -> str:
    """A pattern whose matches also cover the occurrences of a word that overlap: example, then xample after it."""
    border = next((n for n in range(len(part) - 1, 0, -1) if part[:n] == part[-n:]), 0)
    return f"(?i){part}(?:{part[border:]})*" if border else f"(?i){part}"


def _pieces(block: Column, off: Column) -> Column:
    """array<struct<at, joined, text>>: the stretches of a block's own region between the allow-list's matches that hold a window.

    ``at`` counts from the candidate's start; ``joined`` says that the stretch goes on from the block before.
    """
    found = lambda p: F.transform(matches(block, p), lambda m: F.struct(m["start"].alias("start"), m["end"].alias("end")))
    size = F.length(block)
    till = F.least(size, F.lit(MARGIN + BLOCK + WINDOW - 1))

    def between(spans: Column) -> Column:
        before = ~F.exists(spans, lambda m: (m["start"] < MARGIN) & (m["end"] >= MARGIN))
        ends = F.array_append(spans, F.struct(till.alias("start"), size.alias("end")))
        begin = F.struct(F.lit(MARGIN).alias("pos"), F.array().cast("array<struct<at:int,joined:boolean,text:string>>").alias("out"))

        def step(acc: Column, m: Column) -> Column:
            stop = F.least(m["start"], till)
            free = F.struct((acc["pos"] - MARGIN + off).alias("at"), ((acc["pos"] == MARGIN) & (off > 0) & before).alias("joined"), F.substr(block, acc["pos"] + 1, stop - acc["pos"]).alias("text"))
            out = F.when(stop - acc["pos"] >= WINDOW, F.array_append(acc["out"], free)).otherwise(acc["out"])
            return F.struct(F.greatest(acc["pos"], m["end"]).alias("pos"), out.alias("out"))

        return F.aggregate(ends, begin, step, lambda acc: acc["out"])

    whole = F.array(F.struct(off.alias("at"), (off > 0).alias("joined"), F.substr(block, F.lit(MARGIN + 1), F.lit(BLOCK + WINDOW - 1)).alias("text")))
    return F.when(~block.rlike(ALLOW_PART), whole).otherwise(let(F.array_sort(F.concat(*[found(_every(p)) for p in ALLOWED])), between))


def _random(m: Column, by_window: bool) -> Column:
    """array<struct<start, end>>: from the first to the last window above its threshold, for each section of one candidate.

    The candidate is read in blocks of bounded length, so that the work grows with its length only.
    """
    padded = F.concat(F.lit(PAD), m["text"])
    blocks = F.transform(F.regexp_extract_all(padded, F.lit(BLOCKS), F.lit(1)), lambda b, i: F.struct(b.alias("text"), (i * BLOCK).alias("off")))
    held = F.filter(blocks, lambda b: F.length(b["text"]) >= MARGIN + WINDOW)
    if by_window:
        pieces = F.flatten(F.transform(held, lambda b: _pieces(b["text"], b["off"])))
    else:
        pieces = F.transform(held, lambda b: F.struct(b["off"].alias("at"), (b["off"] > 0).alias("joined"), F.substr(b["text"], F.lit(MARGIN + 1), F.lit(BLOCK + WINDOW - 1)).alias("text")))

    def judged(most: Column) -> Column:
        told = F.transform(pieces, lambda p: let(_hot(p["text"], most, by_window), lambda h: F.struct(p["joined"].alias("joined"), (p["at"] + h["first"]).alias("first"), (p["at"] + h["last"]).alias("last"))))
        nothing = F.lit(None).cast("int")
        begin = F.struct(nothing.alias("first"), nothing.alias("last"), F.array().cast("array<struct<start:int,end:int>>").alias("out"))
        span = lambda acc: F.struct((m["at"] + acc["first"]).alias("start"), (m["at"] + acc["last"] + WINDOW).alias("end"))
        closed = lambda acc: F.when(acc["first"].isNotNull(), F.array_append(acc["out"], span(acc))).otherwise(acc["out"])

        def step(acc: Column, p: Column) -> Column:
            on = F.struct(F.coalesce(acc["first"], p["first"]).alias("first"), F.coalesce(p["last"], acc["last"]).alias("last"), acc["out"].alias("out"))
            return F.when(p["joined"], on).otherwise(F.struct(p["first"].alias("first"), p["last"].alias("last"), closed(acc).alias("out")))

        return F.aggregate(told, begin, step, closed)

    return let(_bound(m["text"], by_window), judged)


def _entropy(text: Column, by_window: bool) -> Column:
    allowed = lambda m: m["text"].rlike(f"(?i){ALLOWED_WHOLE}") if by_window else m["text"].rlike(ALLOW)
    mixed = lambda m: m["text"].rlike("[0-9]") & m["text"].rlike("[A-Za-z]") & ~allowed(m)
    found = F.transform(F.filter(matches(text, CANDIDATE), mixed), lambda m: F.struct(m["start"].alias("at"), m["text"].alias("text")))
    return _spans(F.flatten(F.transform(found, lambda m: _random(m, by_window))), 3)


def find_secrets(docs: DataFrame, by_window: bool = False) -> DataFrame:
    """(doc_id, base, added): the base spans by start, then kind, and the spans that the entropy scan adds."""
    text = F.coalesce(docs["text"].cast("string"), F.lit(""))
    one = docs.select(docs["doc_id"].alias("doc_id"), text.alias("text"))
    return one.select("doc_id", _base(F.col("text")).alias("base"), _entropy(F.col("text"), by_window).alias("added"))


def _listed(spans: Column) -> Column:
    return F.array_join(F.transform(spans, lambda s: F.concat_ws(":", s["kind"], s["start"].cast("string"), s["end"].cast("string"))), ",")


def secrets(docs: DataFrame, by_window: bool = False) -> DataFrame:
    """Counts and digests of the spans of every whole text."""
    number = lambda kind: F.size(F.filter("base", lambda s: s["kind"] == kind)).cast("long").alias(f"n_{kind}")
    return find_secrets(docs, by_window).select(
        "doc_id", *[number(k) for k in KINDS[:3]],
        F.sha2(_listed(F.col("base")).cast("binary"), 256).alias("base_sha256"),
        _listed(F.array_sort(F.concat("base", "added"))).alias("spans"),
    )
