"""SimHash near-duplicate components by pigeonring filtering.

A document's fingerprint is the bitwise majority of the XXH64 values of its word shingles. Fingerprints
within ``REACH`` differing bits are linked; a component is everything reachable over links.

Candidate search. The 64 bits form a ring of four 16-bit segments. If two fingerprints differ in at most
three bits, then on some segment of the ring a chain starts whose cumulative differences stay within the
proportional budget after every step: 0 on the first segment, at most 1 on the first two, at most 2 on
three, at most 3 on all four. The first two budgets become an equi-join: one side gives, for each start, the 32
bits of the first two segments, the other side gives those bits and the 16 values that differ from them in
one bit of the second segment. The join condition then tries the third budget, which prunes most of what has met, and behind it the
full Hamming check, so only links leave the join, each from its first viable chain. Nothing is capped.

Exact copies of a fingerprint are merged before the join, so the join sees distinct fingerprints
only, and the size of a group of copies never enters it. Tables of fingerprints or ids grow with the documents, so their joins are sort-merge joins:
a broadcast would collect them on the driver. Defined results: a null text is an empty one;
a text without words has fingerprint zero and is linked like any other; ids may repeat; a null id counts
for a component only if it has no other id.
"""

from __future__ import annotations

import numpy as np
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from concord.llm.rows import map_text
from concord.operators.graph import weak_components
from concord.runtime import keep

LOWER = bytes.maketrans(b"ABCDEFGHIJKLMNOPQRSTUVWXYZ", b"abcdefghijklmnopqrstuvwxyz")
SEED = 42
REACH = 3
BLOCK = 1 << 14


def fingerprint(text: str | None, shingle: int = 3) -> int:
    """Majority fingerprint of the word shingles, repeats included; 0 without words."""
    words = (text or "").encode().translate(LOWER).split()  # of bytes, split() parts at 09-0D and 20 only
    if not words:
        return 0
    digest = xxhash.xxh64_intdigest
    n = max(1, len(words) - shingle + 1)
    votes = np.zeros(64, dtype=np.int64)
    for at in range(0, n, BLOCK):
        part = words[at : at + BLOCK + shingle - 1] if n > 1 else words
        grams = map(b" ".join, zip(*(part[k:] for k in range(shingle)))) if len(part) >= shingle else [b" ".join(part)]
        hashes = np.array([digest(g, SEED) for g in grams], dtype=">u8")
        votes += np.unpackbits(hashes.view(np.uint8).reshape(-1, 8), axis=1).sum(axis=0, dtype=np.int64)
    return int(np.packbits(2 * votes > n).view(">u8")[0])


def fingerprints(docs: DataFrame, shingle: int = 3) -> DataFrame:
    """(doc_id, fp) with fp the fingerprint as a signed long."""

    def start():
        def one(text: str | None) -> tuple:
            f = fingerprint(text, shingle)
            return (f - (1 << 64) if f >> 63 else f,)

        return one

    return map_text(docs, start, "fp long")


def _turned(c: str, k: int) -> str:
    """SQL: the ring read from segment k on."""
    return c if k == 0 else f"(shiftleft({c}, {16 * k}) | shiftrightunsigned({c}, {64 - 16 * k}))"


X = "(a ^ b)"
#: Differences on segment k: the leading 16 bits of that turn of the ring.
SEGMENT = [f"bit_count({_turned(X, k)} & -281474976710656)" for k in range(4)]
#: The budgets of a chain that starts at segment k: none on its first segment, one on two, two on three.
VIABLE = [f"({SEGMENT[k]} = 0 and {SEGMENT[(k + 1) % 4]} <= 1 and {SEGMENT[(k + 1) % 4]} + {SEGMENT[(k + 2) % 4]} <= 2)" for k in range(4)]


def _met(prints: DataFrame) -> DataFrame:
    """(a, b, start): pairs of distinct fingerprints, a < b, that keep the first two budgets of the chain from a start."""
    ring = prints.select("fp").select("fp", F.posexplode(F.array(*[F.expr(_turned("fp", k)) for k in range(4)])).alias("start", "turn"))
    # key: chain start, first segment, second segment
    key = "shiftleft(cast(start as bigint), 32) | shiftrightunsigned(turn, 32)"
    left = ring.select(F.col("fp").alias("a"), F.expr(key).alias("key"))
    flips = F.array(F.lit(0).cast("long"), *[F.lit(1 << b).cast("long") for b in range(16)])
    right = ring.select(F.col("fp").alias("b"), F.expr(key).alias("key")).select("b", F.explode(F.transform(flips, lambda m: F.col("key").bitwiseXOR(m))).alias("key"))
    return left.join(right.hint("merge"), "key").where("a < b").withColumn("start", F.expr("shiftright(key, 32)"))


def links(prints: DataFrame) -> DataFrame:
    """All pairs (a, b), a < b, of distinct fingerprints in column ``fp`` that differ in at most three bits."""
    third = "case start " + " ".join(f"when {k} then {v}" for k, v in enumerate(VIABLE)) + " end"
    first = "case " + " ".join(f"when {v} then {k}" for k, v in enumerate(VIABLE)) + " end"
    # the chain goes before the full check, and a pair leaves from its first viable chain only
    return _met(prints).where(f"{third} and bit_count(a ^ b) <= {REACH} and {first} = start").select("a", "b")


def pruning(prints: DataFrame) -> DataFrame:
    """Cost measure: (met, chained, linked): pairs that keep two budgets, three budgets, and that are links, each counted for every start."""
    third = "case start " + " ".join(f"when {k} then {v}" for k, v in enumerate(VIABLE)) + " end"
    return _met(prints.select("fp").distinct()).agg(F.count("*").alias("met"), F.count_if(F.expr(third)).alias("chained"), F.count_if(F.expr(f"{third} and bit_count(a ^ b) <= {REACH}")).alias("linked"))


def components(prints: DataFrame) -> DataFrame:
    """(fp, component_id) of every distinct fingerprint in (doc_id, fp): the least id reachable over links."""
    nodes = prints.groupBy("fp").agg(F.min("doc_id").alias("least"))
    groups = weak_components(links(nodes), "a", "b")
    joined = nodes.join(groups.select(F.col("node").alias("fp"), "comp_id").hint("merge"), "fp", "left").withColumn("comp_id", F.coalesce("comp_id", "fp"))
    least = joined.groupBy("comp_id").agg(F.min("least").alias("component_id"))
    return joined.select("fp", "comp_id").join(least.hint("merge"), "comp_id").select("fp", "component_id")


def near_duplicates(docs: DataFrame, shingle: int = 3) -> DataFrame:
    """One row per document: doc_id, fingerprint (16 hex digits), component_id."""
    prints = keep(fingerprints(docs, shingle))
    return prints.join(keep(components(prints)).hint("merge"), "fp").select("doc_id", F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint"), "component_id")


def first_of_each(docs: DataFrame, shingle: int = 3) -> DataFrame:
    """The documents that are the least of their component; all columns stay.

    Rows that repeat such an id give one row. Rows without an id stay, all of them: nothing says which to prefer.
    """
    own = {c: docs[c] for c in docs.columns}
    near = near_duplicates(docs.select("doc_id", "text"), shingle).select("doc_id", "component_id")
    chosen = near.where("doc_id = component_id").select("doc_id").distinct()
    with_id = docs.where(own["doc_id"].isNotNull()).join(chosen.hint("merge"), "doc_id", "left_semi").select(*docs.columns)
    again = not docs.where(own["doc_id"].isNotNull()).groupBy("doc_id").count().where("count > 1").isEmpty()
    if again:
        with_id = with_id.dropDuplicates(["doc_id"])
    return with_id.unionByName(docs.where(own["doc_id"].isNull()))
