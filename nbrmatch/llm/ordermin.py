"""Document fingerprints by Order MinHash, in DataFrame functions alone.

A text's k-mers are runs of WORDS words (of CHARACTERS characters where a script has no spaces), one from each place on,
numbered by occurrence, so that repeats count. For each of HASHES orders the two least occurrence-numbered k-mers are
selected, put back in text order and hashed as a tuple. Likeness is the share of equal tuples. It falls with the edit
distance: a tuple survives only if its k-mers and their order do.

An order is one of SEEDS seeded hashes, begun at a random value: k-mers go by hash from that value on, around to it. So
each order has minimisers of its own, whatever the length of the text, and they are found by binary search in a sorted
array: a k-mer is hashed SEEDS times, not HASHES times.
"""

from __future__ import annotations

import random
from collections.abc import Callable

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from .common import fresh, materialise

WORDS, CHARACTERS = 3, 8
HASHES, SEEDS = 64, 8
#: Places take the low bits of a long: as many as an array can have. The hash has the others.
PLACE_BITS = 31
#: Rows of a block of neighbouring ids, about, and the most blocks there are.
BLOCK_ROWS, BLOCKS = 512, 1 << 16


def let(value: Column, body: Callable[[Column], Column]) -> Column:
    """body(value), with the value worked out once however often the body uses it."""
    return F.get(F.transform(F.array(value), body), F.lit(0))


def kmers_of(text: Column) -> Column:
    """Hashes of the k-mers from each place on: of words between white space; where words are long on average (scripts without spaces), of characters."""
    plain = F.translate(F.coalesce(text, F.lit("")), "\n\t\r", "   ")
    long = lambda w: F.size(w) * 24 < F.char_length(plain)
    kmer = lambda w, k, n: F.shiftright(F.xxhash64(*(F.get(w, k + j) for j in range(n))), PLACE_BITS)
    kmers = lambda w, n: F.transform(F.sequence(F.lit(0), F.greatest(F.size(w) - n, F.lit(0))), lambda k: kmer(w, k, n))
    return let(F.split(plain, " "), lambda w: F.when(long(w), let(F.split(plain, ""), lambda c: kmers(c, CHARACTERS))).otherwise(kmers(w, WORDS)))


def _place(x: Column) -> Column:
    return x.bitwiseAND(F.lit((1 << PLACE_BITS) - 1))


def _packed(h: Column, place: Column) -> Column:
    return F.shiftleft(h, PLACE_BITS).bitwiseOR(place.cast("long"))


def numbered(h: Column) -> Column:
    """(hash of the k-mer and its occurrence, place) in one long, for each of the k-mers h. Not in text order where k-mers repeat."""

    def runs(s: Column) -> Column:
        """s: (k-mer, place) in one long, sorted. Runs of a k-mer give its occurrences in text order."""
        same = lambda a, b: F.shiftright(a, PLACE_BITS) == F.shiftright(b, PLACE_BITS)
        starts = F.filter(F.sequence(F.lit(0), F.size(s) - 1), lambda k: (k == 0) | ~same(F.get(s, k), F.get(s, k - 1)))
        # Never null; said so, as arrays without nulls are sorted as plain longs.
        one = lambda at, k: F.coalesce(_packed(F.xxhash64(F.shiftright(F.get(s, k), PLACE_BITS), k - at), _place(F.get(s, k))), F.lit(0))
        return let(starts, lambda r: F.flatten(F.transform(r, lambda at, j: F.transform(F.sequence(at, F.coalesce(F.get(r, j + 1), F.size(s)) - 1), lambda k: one(at, k)))))

    single = F.transform(h, lambda x, k: _packed(F.xxhash64(x, F.lit(0)), k))
    repeats = let(F.sort_array(F.transform(h, _packed)), runs)
    return F.when(F.size(F.array_distinct(h)) == F.size(h), single).otherwise(repeats)


def _begins() -> list[list[int]]:
    """For each seed the fixed values at which its orders begin, as signed longs."""
    rng = random.Random(20)
    return [[rng.getrandbits(64) - (1 << 63) for _ in range(HASHES // SEEDS)] for _ in range(SEEDS)]


def _tuple(s: Column, steps: Column, begin: Column) -> Column:
    """The hash, as an int, of the two entries of s (hash, place; sorted) from `begin` on, in text order. A single entry counts twice."""
    search = F.aggregate(steps, F.lit(0), lambda low, step: F.when(F.get(s, low + step - 1) < begin, low + step).otherwise(low))
    value = lambda x: F.shiftright(x, PLACE_BITS)
    hashed = lambda a, b: F.when(_place(a) < _place(b), F.xxhash64(value(a), value(b))).otherwise(F.xxhash64(value(b), value(a)))
    return let(search, lambda k: F.shiftright(hashed(F.get(s, k % F.size(s)), F.get(s, (k + 1) % F.size(s))), 32).cast("int"))


def with_fingerprint(df: DataFrame, text: str, out: str) -> DataFrame:
    """df with the fingerprint of each whole text in column `out`: HASHES integers. Narrow: no shuffle.

    A null text counts as empty. An empty text is one k-mer, the empty word; so is a text of fewer words than a k-mer.
    The steps are projections of their own, so that each array is made once.
    """
    keep = [F.col(f"`{c}`") for c in df.columns if c != out]
    kmers, steps, *seeds = fresh([*df.columns, out], "kmers", "steps", *(f"seed{s}" for s in range(SEEDS)))
    first = df.select(*keep, kmers_of(F.col(f"`{text}`")).alias(kmers)).select(*keep, numbered(F.col(kmers)).alias(kmers))
    rehash = lambda s: F.transform(kmers, lambda m: _packed(F.xxhash64(F.shiftright(m, PLACE_BITS), F.lit(s)), _place(m)))
    powers = F.transform(F.sequence(F.floor(F.log2(F.size(kmers))).cast("int"), F.lit(0)), lambda b: F.call_function("shiftleft", F.lit(1), b))
    sorted_ = first.select(*keep, powers.alias(steps), *(F.sort_array(rehash(s)).alias(c) for s, c in enumerate(seeds)))
    tuples = [_tuples(c, steps, at) for c, at in zip(seeds, _begins(), strict=True)]
    return sorted_.select(*keep, F.concat(*tuples).alias(out))


def _tuples(seed: str, steps: str, begins: list[int]) -> Column:
    return F.transform(F.array(*map(F.lit, begins)), lambda begin: _tuple(F.col(seed), F.col(steps), begin))


def likeness(a: Column, b: Column) -> Column:
    """Share of the tuples that are equal in both fingerprints (0 to 1)."""
    return F.size(F.filter(F.zip_with(a, b, lambda x, y: x == y), lambda same: same)) / HASHES


def as_string(a: Column) -> Column:
    """A fingerprint as eight hex digits for each tuple."""
    return F.array_join(F.transform(a, lambda x: F.lpad(F.lower(F.hex(x.cast("long").bitwiseAND(F.lit(0xFFFFFFFF)))), 8, "0")), "")


def fingerprints(docs: DataFrame, text: str = "text", out: str = "fingerprint") -> DataFrame:
    """docs with the fingerprint of each whole text as a string; a column named as `out` is replaced. Narrow: no shuffle."""
    made = with_fingerprint(docs, text, out)
    return made.withColumn(out, as_string(F.col(f"`{out}`")))


def _ordered(n: Column) -> Column:
    """A long as 16 hex digits that sort as the numbers do."""
    return F.lpad(F.hex(n.bitwiseXOR(F.lit(-(1 << 63)))), 16, "0")


def with_next(rows: DataFrame) -> DataFrame:
    """rows (key, text, fp, ...) with next_text and next_fp: those of the row that follows by key; after the last row comes the first.

    rows must be written ones and their keys distinct. The keys alone are sorted first, and every BLOCK_ROWS-th (BLOCKS
    at most, further apart in larger tables) begins a block, so blocks are even whatever the keys are. Texts are shuffled
    once, to their block; a copy of each block's first row goes to the block before it.
    """
    n = rows.count()
    stride = max(BLOCK_ROWS, -(-n // BLOCKS))
    line = rows.select("key").repartitionByRange(max(1, n >> 20), "key").sortWithinPartitions("key")
    at = F.monotonically_increasing_id().bitwiseAND(F.lit((1 << 33) - 1))
    begins = sorted(r["key"] for r in line.select("key", at.alias("at")).where(F.col("at") % stride == 0).select("key").collect()) or [""]
    known = F.split(F.lit(",".join(begins)), ",")
    # Binary search: the last block that begins at or before the key.
    bits = max(1, (len(begins) - 1).bit_length())
    steps = F.array(*(F.lit(1 << b) for b in reversed(range(bits))))
    block = F.aggregate(steps, F.lit(0), lambda low, s: F.when(F.get(known, low + s) <= F.col("key"), low + s).otherwise(low))
    dealt = rows.withColumn("block", block).withColumn("extra", F.lit(False))
    heads = dealt.where(F.col("key") == F.get(known, F.col("block")))
    heads = heads.withColumn("block", F.pmod(F.col("block") - 1, F.lit(len(begins)))).withColumn("extra", F.lit(True))
    order = Window.partitionBy("block").orderBy("extra", "key")
    after = dealt.union(heads).select("*", F.lead("text").over(order).alias("next_text"), F.lead("fp").over(order).alias("next_fp"))
    return after.where("not extra").drop("block", "extra")


def edit_check(docs: DataFrame) -> DataFrame:
    """Fingerprints of each row of docs (doc_id, text) and of its edited text, and their likenesses.

    The edited text has its last half (rounded down) replaced by as many first code points of the next row's text. Rows go
    by descending doc_id, those without one last, those of one id by a hash of the text; equal rows stand together. Null
    texts count as empty. Texts with their fingerprints are written once; the rest reads that table.
    """
    own = docs.select(F.col("doc_id"), F.coalesce(F.col("text").cast("string"), F.lit("")).alias("text"), F.monotonically_increasing_id().alias("row"))
    down = F.when(F.col("doc_id").isNull(), "1").otherwise("0")
    key = F.concat(down, _ordered(F.bitwise_not(F.coalesce(F.col("doc_id").cast("long"), F.lit(0)))), _ordered(F.xxhash64("text")), _ordered(F.col("row")))
    printed = materialise(with_fingerprint(own.select("doc_id", "text", key.alias("key")), "text", "fp"), "printed", "zstd")
    n = F.char_length("text")
    half = F.floor(n / 2).cast("int")
    edited = F.concat(F.substr("text", F.lit(1), n - half), F.substr("next_text", F.lit(1), half))
    cut = with_next(printed).select("doc_id", n.cast("long").alias("n_chars"), "fp", "next_fp", edited.alias("edited"))
    both = with_fingerprint(cut, "edited", "edited_fp")
    return both.select(
        "doc_id", "n_chars", F.sha2("edited", 256).alias("edited_sha256"), as_string(F.col("fp")).alias("fingerprint"), as_string(F.col("edited_fp")).alias("edited_fingerprint"),
        likeness(F.col("fp"), F.col("edited_fp")).cast("double").alias("near_edited"), likeness(F.col("fp"), F.col("next_fp")).cast("double").alias("near_next"),
    )
