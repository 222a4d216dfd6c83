"""Near-duplicate groups by MinHash, with exact links.

1. Each document's set of distinct word shingles gives a digest of the set, a signature of hash minima, and one hash for
   each band of the signature. Equal sets are one class from here on; only classes are compared.
2. Classes that share a band's hash are candidates. Each such bucket has a hub, the class whose buckets hold the most
   (an original is in all of its copies' buckets), and every member is compared with its hubs on full sets.
3. Links are joined to components by alternating large-star and small-star.
4. A bucket whose members lie in one component needs no more. In the others, members outside the hub's component are
   compared with all members of other components, block against block: signatures first (which only mark the members
   that can have a link), then full sets. A pair that shares several bands is compared in the first of them only. No
   group is gathered in one task, and no row is made for a pair that has no link.

Buckets and hubs that hold a large share of the rows are not left to one task: see spread() and SHARE.

Bands follow from the least likeness that links, so that a pair at it is missed with a chance of 1e-6 at most: 24 bands
of 5 minima at 0.85 (8e-7), 35 at 0.8 (9e-7).
"""

from __future__ import annotations

import hashlib
import math
from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import discard, materialise, spread, without_gc, worker_cache

WORDS, ROWS = 5, 5
#: Chance that a pair of just the least likeness shares no band, at most.
MISSED = 1e-6
#: Members of a block of a bucket that step 4 compares at once.
BLOCK = 128
#: A hub's text goes out once for each so many of its pairs.
SHARE = 4096


def bands_for(percent: int) -> int:
    """The fewest bands that miss a pair of this likeness with a chance of MISSED at most."""
    same = (percent / 100) ** ROWS
    return 1 if same >= 1 else math.ceil(math.log(MISSED) / math.log1p(-same))


def least_agreeing(percent: int) -> float:
    """Signatures that agree in a smaller share can't belong to sets of this likeness (six standard deviations away)."""
    s = percent / 100
    return math.floor(100 * (s - 6 * math.sqrt(s * (1 - s) / (bands_for(percent) * ROWS)))) / 100


class _Hashes(dict):
    """64-bit hashes of words, filled on demand, emptied beyond a bound."""

    def __missing__(self, word: bytes) -> int:
        import xxhash

        if len(self) >= 400_000:
            self.clear()
        h = xxhash.xxh3_64_intdigest(word)
        if len(word) <= 64:
            self[word] = h
        return h


def _mix(h: np.ndarray) -> np.ndarray:
    h = (h ^ (h >> np.uint64(31))) * np.uint64(0x9E3779B97F4A7C15)
    return h ^ (h >> np.uint64(29))


def shingles(text: str | None, words: int = WORDS) -> np.ndarray:
    """Sorted distinct 64-bit hashes of a text's word shingles: A-Z in lower case, words apart at ASCII white space.

    Fewer words than a shingle: the whole sequence is one. No words: none.
    """
    found = (text or "").encode().lower().split()
    if not found:
        return np.empty(0, dtype=np.uint64)
    hashes = worker_cache(("minhash", "words"), _Hashes)
    h = np.fromiter(map(hashes.__getitem__, found), dtype=np.uint64, count=len(found))
    n = max(1, len(h) - words + 1)
    out = np.full(n, len(h) if len(h) < words else 0, dtype=np.uint64)
    with np.errstate(over="ignore"):
        for k in range(min(words, len(h))):
            out = _mix(out ^ h[k : k + n]) + np.uint64(k)
    return np.unique(out)


def _parameters(seed: int, n: int) -> tuple[np.ndarray, np.ndarray]:
    rng = np.random.default_rng(seed)
    return rng.integers(0, 2**32, n, dtype=np.uint32) | np.uint32(1), rng.integers(0, 2**32, n, dtype=np.uint32)


def signature(sets: np.ndarray, n: int, seed: int = 1) -> np.ndarray:
    """The least of each of n universal hashes over a set (uint32). An empty set has none."""
    times, plus = worker_cache(("minhash", seed, n), lambda: _parameters(seed, n))
    least = np.full(len(times), 2**32 - 1, dtype=np.uint32)
    low, high = sets.astype(np.uint32), (sets >> np.uint64(32)).astype(np.uint32)
    with np.errstate(over="ignore"):
        for k in range(0, len(sets), 512):
            h = times[:, None] * low[None, k : k + 512]
            h ^= h >> np.uint32(15)
            h += plus[:, None] * (high[None, k : k + 512] | np.uint32(1))
            np.minimum(least, h.min(axis=1), out=least)
    return least


def sketch(docs: DataFrame, n_bands: int, words: int = WORDS) -> DataFrame:
    """(doc_id, n_shingles, set_digest, signature, bands) of each row; bands is null where there are no words."""
    kind = dict(docs.dtypes)["doc_id"]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            sizes, digests, signatures, bands = [], [], [], []
            for t in batch.column("text").to_pylist():
                s = shingles(t, words)
                sizes.append(len(s))
                digests.append(hashlib.md5(s.tobytes()).digest())
                if not len(s):
                    signatures.append(None)
                    bands.append(None)
                    continue
                g = signature(s, n_bands * ROWS)
                signatures.append(g.tobytes())
                h = np.arange(n_bands, dtype=np.uint64)
                with np.errstate(over="ignore"):
                    for row in g.reshape(n_bands, ROWS).T:
                        h = _mix(h * np.uint64(31) + row)
                bands.append(h.view(np.int64))
            yield pa.RecordBatch.from_arrays(
                [batch.column("doc_id"), pa.array(sizes, pa.int64()), pa.array(digests, pa.binary()), pa.array(signatures, pa.binary()), pa.array(bands, pa.list_(pa.int64()))],
                ["doc_id", "n_shingles", "set_digest", "signature", "bands"],
            )

    return docs.select("doc_id", F.col("text").cast("string").alias("text")).mapInArrow(without_gc(run), f"doc_id {kind}, n_shingles long, set_digest binary, signature binary, bands array<long>")


def alike(a: np.ndarray, b: np.ndarray, percent: int) -> bool:
    """Whether 100 * |a and b| >= percent * |a or b|, of sorted distinct arrays."""
    if 100 * min(len(a), len(b)) < percent * max(len(a), len(b)):
        return False
    both = len(np.intersect1d(a, b, assume_unique=True))
    return 100 * both >= percent * (len(a) + len(b) - both)


def components(links: DataFrame, name: str = "components", rounds: int = 50) -> DataFrame:
    """(node, component) of the nodes of links (a, b): the least node of each connected component.

    Alternating large-star and small-star; both are aggregations and joins on a node, so a node of any degree spreads.
    Each round is written to the shared folder. Ends when nothing changes, which takes about log(diameter) rounds.
    """
    edges = materialise(links.select(F.greatest("a", "b").alias("u"), F.least("a", "b").alias("v")).where("u <> v").distinct(), name)
    before = None
    for _ in range(rounds):
        # Large-star: every larger neighbour of a node points to the least of the node's neighbourhood.
        both = edges.select("u", "v").union(edges.select(F.col("v").alias("u"), F.col("u").alias("v")))
        least = materialise(both.groupBy("u").agg(F.least(F.min("v"), F.col("u")).alias("m"), F.count("*").alias("n")), name)
        large = materialise(spread(both, least, ["u"], 2 * edges.count()).where("v > u").select(F.col("v").alias("u"), F.col("m").alias("v")).distinct(), name)
        # Small-star: a node and its smaller neighbours point to the least of them.
        small = large.groupBy("u").agg(F.min("v").alias("m"))
        after = large.join(small, "u").where("v <> m").select(F.col("v").alias("u"), F.col("m").alias("v")).union(small.select("u", F.col("m").alias("v"))).distinct()
        old, edges = edges, materialise(after, name)
        discard(old, least, large)
        state = tuple(edges.agg(F.count("*"), F.sum(F.col("v").cast("decimal(38,0)")), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)"))).first())
        if state == before:
            break
        before = state
    else:
        raise RuntimeError("components didn't settle")
    stars = edges.groupBy("u").agg(F.min("v").alias("component"))
    return stars.select(F.col("u").alias("node"), "component").union(stars.select(F.col("component").alias("node"), "component").distinct())


def _verified(pairs: DataFrame, texts: DataFrame, percent: int, words: int) -> DataFrame:
    """Of the pairs (a, b) of classes those whose full sets are alike."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        last, hub = None, np.empty(0, np.uint64)
        for batch in batches:
            keep = []
            for b, x, y in zip(*(batch.column(c).to_pylist() for c in ("b", "text_a", "text_b")), strict=True):
                if b != last:
                    last, hub = b, shingles(y, words)
                keep.append(alike(shingles(x, words), hub, percent))
            yield pa.RecordBatch.from_arrays([batch.column("a"), batch.column("b")], ["a", "b"]).filter(pa.array(keep))

    counts = materialise(pairs.groupBy("b").agg(F.count("*").alias("n")), "pair-counts")
    parts = F.ceil(F.col("n") / SHARE).cast("int")
    salted = spread(pairs, counts, ["b"], pairs.count()).select("a", "b", F.pmod(F.xxhash64("a"), parts).cast("int").alias("part"))
    hubs = counts.select("b", F.explode(F.sequence(F.lit(0), parts - 1)).alias("part")).join(texts.select(F.col("rep").alias("b"), F.col("text").alias("text_b")), "b")
    both = salted.join(texts.select(F.col("rep").alias("a"), F.col("text").alias("text_a")), "a").join(hubs, ["b", "part"])
    return both.select("a", "b", "text_a", "text_b").mapInArrow(without_gc(run), "a long, b long")  # a node may have several texts


def _blocks(members: DataFrame, bucket: list[str], payload: list[str]) -> DataFrame:
    """Members (a written table) dealt to pairs of blocks: (bucket..., qb, tb, rep, comp, side, payload); side q: asks, side t: is asked."""
    sizes = materialise(members.groupBy(*bucket).agg(F.sum(F.col("asks").cast("int")).alias("nq"), F.count("*").alias("n")), "block-sizes")
    blocks = lambda n: F.greatest(F.ceil(F.col(n) / BLOCK), F.lit(1)).cast("int")
    sized = spread(members, sizes.select(*bucket, "n", blocks("nq").alias("bq"), blocks("n").alias("bt")), bucket, members.count())
    own = lambda n, salt: F.pmod(F.xxhash64(F.lit(salt), "rep"), F.col(n)).cast("int")
    asking = sized.where("asks").select(*bucket, own("bq", 1).alias("qb"), F.explode(F.sequence(F.lit(0), F.col("bt") - 1)).alias("tb"), "rep", "comp", F.lit(True).alias("q"), *payload)
    asked = sized.select(*bucket, F.explode(F.sequence(F.lit(0), F.col("bq") - 1)).alias("qb"), own("bt", 2).alias("tb"), "rep", "comp", F.lit(False).alias("q"), *payload)
    return asking.union(asked)


def _compared(blocks: DataFrame, bucket: list[str], rows: int, least: float, schema: str, emit) -> DataFrame:
    """What emit(group, asking, asked, agree) gives for each pair of blocks; agree: which pairs of places to look at.

    Those are in different components, their signatures agree enough, and no band before the bucket's own is the same in
    both (if one is, they are looked at there: members of different components can't both be in the hub's). Many small
    blocks share one call to Python; which ones goes by a hash, so calls stay near `rows` rows.
    """
    keys = [*bucket, "qb", "tb"]
    n = max(1, -(-blocks.count() // rows))
    dealt = blocks.withColumn("g", F.pmod(F.xxhash64(*keys), F.lit(n)))

    def run(group: pd.DataFrame) -> pd.DataFrame:
        group = group.sort_values(keys, kind="stable")
        ids = group[keys].to_numpy()
        edges = np.flatnonzero((ids[1:] != ids[:-1]).any(axis=1)) + 1
        side, comp, bands = group.q.to_numpy(), group.comp.to_numpy(), group.band.to_numpy()
        signs = np.frombuffer(b"".join(group.signature), np.uint32).reshape(len(group), -1)
        out = []
        for at in np.split(np.arange(len(group)), edges):
            q, t = at[side[at]], at[~side[at]]
            if not len(q) or not len(t):
                continue
            same = signs[q][:, None, :] == signs[t][None, :, :]
            before = same[:, :, : bands[at[0]] * ROWS].reshape(len(q), len(t), -1, ROWS).all(axis=3).any(axis=2)
            agree = (same.mean(axis=2) >= least) & ~before
            agree &= comp[q][:, None] != comp[t][None, :]
            if agree.any():
                out += emit(group, q, t, agree)
        return pd.DataFrame(out, columns=[c.split()[0] for c in schema.split(", ")])

    return dealt.groupBy("g").applyInPandas(run, schema)


def _marked(members: DataFrame, bucket: list[str], least: float) -> DataFrame:
    """The members that have a partner in another component whose signature agrees enough."""

    def emit(group: pd.DataFrame, q: np.ndarray, t: np.ndarray, agree: np.ndarray) -> list[tuple]:
        of = group[bucket].iloc[q[0]].tolist()
        rep = group.rep.to_numpy()
        found = {(int(r), True) for r in rep[q[agree.any(axis=1)]]} | {(int(r), False) for r in rep[t[agree.any(axis=0)]]}
        return [(*of, r, asks) for r, asks in sorted(found)]

    types = dict(members.dtypes)
    schema = ", ".join([*(f"{c} {types[c]}" for c in bucket), "rep long, q boolean"])
    found = _compared(_blocks(members, bucket, ["signature"]), bucket, 4096, least, schema, emit)
    return found.groupBy(*bucket, "rep").agg(F.max("q").alias("asks"))


def _block_links(members: DataFrame, bucket: list[str], percent: int, words: int, least: float) -> DataFrame:
    """Links between members of different components of a bucket, by full sets; not all of them, but enough to join what they join."""

    def emit(group: pd.DataFrame, q: np.ndarray, t: np.ndarray, agree: np.ndarray) -> list[tuple]:
        rep, comp, text = group.rep.to_numpy(), group.comp.to_numpy(), group.text.to_numpy()
        sets: dict[int, np.ndarray] = {}
        known: dict[int, int] = {}

        def find(x: int) -> int:
            while known.get(x, x) != x:
                x = known[x]
            return x

        out = []
        for i, j in np.argwhere(agree):
            i, j = q[i], t[j]
            x, y = find(comp[i]), find(comp[j])
            if x == y:
                continue
            for k in (i, j):
                if k not in sets:
                    sets[k] = shingles(text[k], words)
            if alike(sets[i], sets[j], percent):
                known[max(x, y)] = min(x, y)
                out.append((int(rep[i]), int(rep[j])))
        return out

    return _compared(_blocks(members, bucket, ["signature", "text"]), bucket, 512, least, "a long, b long", emit)


def near_duplicates(docs: DataFrame, percent: int = 85, words: int = WORDS) -> DataFrame:
    """(doc_id, n_shingles, component_id, kept) of each row of docs (doc_id, text).

    Linked: 100 * |intersection| >= percent * |union| of the shingle sets. component_id is the least doc_id that is
    reached over links; kept marks the row whose own it is. Texts without words, and null texts, are linked with
    nothing. Rows that share a doc_id count as one node. A row without doc_id belongs to its set's class, and is never
    kept beside a row with one; a class of such rows only has a null component and is kept. Extra columns are ignored.
    """
    docs = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    least = least_agreeing(percent)
    rows = materialise(sketch(docs, bands_for(percent), words), "sketch")
    classes = rows.where("n_shingles > 0 and doc_id is not null").groupBy("set_digest").agg(F.min("doc_id").alias("rep"), F.min("bands").alias("bands"))
    classes = materialise(classes, "classes")  # signatures, most of a sketch's bytes, stay where they are
    bucket = ["band", "h"]
    banded = classes.select("rep", F.posexplode("bands").alias(*bucket))
    sizes = materialise(banded.groupBy(*bucket).agg(F.count("*").alias("n")).where("n > 1"), "sizes")
    sized = materialise(spread(banded, sizes, bucket, classes.count() * bands_for(percent)).select(*bucket, "rep", "n"), "sized")
    weight = sized.groupBy("rep").agg(F.sum("n").alias("w"))
    hubs = sized.join(weight, "rep").groupBy(*bucket).agg(F.max(F.struct(F.col("w"), (-F.col("rep")).alias("r"))).alias("m"), F.count("*").alias("n"))
    hubs = materialise(hubs.select(*bucket, (-F.col("m.r")).alias("hub"), "n"), "hubs")
    total = sized.count()
    members = materialise(spread(sized.drop("n"), hubs, bucket, total).select(*bucket, "rep", "hub", "n"), "members")
    stars = materialise(members.where("rep <> hub").select(F.col("rep").alias("a"), F.col("hub").alias("b")).distinct(), "stars")
    wanted = members.select("rep").distinct()
    first = classes.select("set_digest", "rep").join(wanted, "rep")
    texts = docs.join(first.select(F.col("rep").alias("doc_id"), "rep").distinct(), "doc_id").select("rep", "text").distinct()
    texts = materialise(texts, "texts")
    links = materialise(_verified(stars, texts, percent, words), "links")
    discard(sizes, sized, hubs, stars)
    found = components(links)
    # What the stars left open.
    placed = members.join(found.select(F.col("node").alias("rep"), "component"), "rep", "left").select(*bucket, "rep", "hub", "n", F.coalesce("component", "rep").alias("comp"))
    placed = materialise(placed, "placed")
    hub_at = materialise(placed.where("rep = hub").select(*bucket, F.col("comp").alias("hub_comp"), "n"), "hub-components")
    open_ = materialise(spread(placed.drop("n"), hub_at, bucket, total).select(*bucket, "rep", "comp", "hub_comp", "n"), "open")
    unsettled = materialise(open_.where("comp <> hub_comp").groupBy(*bucket).agg(F.max("n").alias("n")), "unsettled")
    ask = materialise(spread(open_.drop("n"), unsettled, bucket, total).select(*bucket, "rep", "comp", (F.col("comp") != F.col("hub_comp")).alias("asks")), "ask")
    discard(members, placed, hub_at, open_, unsettled)
    more = None
    if not ask.isEmpty():
        asked = classes.select("set_digest", "rep").join(ask.select("rep").distinct(), "rep")
        signs = rows.select("set_digest", F.col("doc_id").alias("rep"), "signature").join(asked, ["set_digest", "rep"], "left_semi").dropDuplicates(["set_digest", "rep"])
        signed = materialise(ask.join(signs.select("rep", "signature"), "rep"), "signed")
        marked = materialise(_marked(signed, bucket, least), "marked")
        again = materialise(marked.join(signed.select(*bucket, "rep", "comp", "signature"), [*bucket, "rep"]).join(texts, "rep"), "again")
        more = materialise(_block_links(again, bucket, percent, words, least), "more-links")
        discard(signed, marked, again)
    if more is not None and not more.isEmpty():
        found = components(links.union(more))
    # Rows with one doc_id are one node: their classes meet in it.
    node = rows.where("n_shingles > 0").join(classes.select("set_digest", "rep"), "set_digest", "left")
    ids = node.where("doc_id is not null and doc_id <> rep").groupBy("doc_id").agg(F.min("rep").alias("r1"), F.max("rep").alias("r2"))
    twice = ids.where("r1 <> r2").select(F.col("r1").alias("a"), F.col("r2").alias("b"))
    if not twice.isEmpty():
        all_links = links.union(more) if more is not None else links
        found = components(all_links.union(node.where("doc_id is not null").select(F.col("doc_id").alias("a"), F.col("rep").alias("b"))))
    of_class = classes.select("set_digest", "rep").join(found.select(F.col("node").alias("rep"), "component"), "rep", "left").select("set_digest", F.coalesce("component", "rep").alias("component"))
    out = rows.select("doc_id", "n_shingles", "set_digest").join(of_class, "set_digest", "left")
    component = F.when(F.col("n_shingles") > 0, F.col("component")).otherwise(F.col("doc_id"))
    return out.select("doc_id", "n_shingles", component.alias("component_id")).withColumn("kept", F.col("doc_id").eqNullSafe(F.col("component_id")))


def keep_one(docs: DataFrame, percent: int = 85, words: int = WORDS) -> DataFrame:
    """docs without the rows that near_duplicates() doesn't keep. Of rows that share a kept id one stays; rows without id all stay."""
    kept = near_duplicates(docs, percent, words).where("kept and doc_id is not null").groupBy("doc_id").agg(F.count("*").alias("n"))
    kept = materialise(kept, "kept")
    found = docs.join(kept.select("doc_id"), "doc_id", "left_semi").select(*docs.columns)
    if not kept.where("n > 1").isEmpty():
        found = found.dropDuplicates(["doc_id"])
    return found.union(docs.where(F.col("doc_id").isNull()))


def estimated(a: Column, b: Column, percent: int = 85) -> Column:
    """Share of agreeing minima of two signatures (binary columns) for `percent`: an estimate of the likeness of the sets."""
    n = bands_for(percent) * ROWS
    part = lambda c, k: F.substring(c, 4 * k + 1, 4)
    return sum((part(a, k) == part(b, k)).cast("int") for k in range(n)) / n
