"""Substring dedup by hashing lines or paragraphs, and the sentences in them.

Units are lines (or paragraphs) and, so that passages pasted into a line are found too, each line's sentences. Normal forms
(lower case, single spaces, trimmed) are hashed, once, and written as digests; of the units with one digest the earliest in
rank (doc_id, then place) stays and the rest go. A first count on 64 bits leaves the repeated digests; only their units are
then ranked by 128 bits. Digests and places alone are shuffled, those of very common units not even that: they meet a
broadcast table of at most COMMON rows. Texts stay where they are until each document's removals come back to it.
"""

from __future__ import annotations

import re
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import discard, fresh, materialise, release, spread

#: What separates units, as patterns of Java and of Python alike.
LINE, PARAGRAPH = "\n", "\n[ \t\r]*\n"
#: Sentences inside lines count from so many words or characters on (some scripts have no spaces); whole lines always do.
LEAST_WORDS, LEAST_CHARACTERS = 5, 20
SPACE = "[ \t\r\n\f\u000b]+"
#: Takes the place of the space after a sentence.
MARK = "\u0001"
ENDS = (". ", "! ", "? ")
#: Bits of a place that number the sentence; 0 stands for the whole line.
SENTENCE_BITS = 24


def normal(unit: Column) -> Column:
    return F.trim(F.regexp_replace(F.lower(unit), SPACE, " "))


def _marked(text: Column) -> Column:
    for end in ENDS:
        text = F.replace(text, F.lit(end), F.lit(end[0] + MARK))
    return text


def _key() -> Column:
    return F.xxhash64(F.coalesce("text", F.lit("")))


def units(docs: DataFrame, separator: str = LINE, least_words: int = LEAST_WORDS) -> DataFrame:
    """(doc_id, key, place, h1, h2) of every unit. place: line << SENTENCE_BITS | sentence from 1, or 0.

    Lines that aren't empty are units of any length; sentences are if they have enough words or characters.
    """
    lines = docs.select("doc_id", _key().alias("key"), F.posexplode(F.split(_marked(F.coalesce("text", F.lit(""))), separator, -1)).alias("line", "body"))
    parts = F.split("body", MARK, -1)
    whole = F.array(F.replace("body", F.lit(MARK), F.lit(" ")))
    each = lines.select("doc_id", "key", "line", F.posexplode(F.when(F.locate(MARK, F.col("body")) > 0, F.concat(whole, parts)).otherwise(whole)).alias("n", "unit"))
    each = each.select("doc_id", "key", "n", (F.shiftleft(F.col("line").cast("long"), SENTENCE_BITS) + F.col("n")).alias("place"), normal(F.col("unit")).alias("unit"))
    words = F.length("unit") - F.length(F.replace("unit", F.lit(" "), F.lit(""))) + 1
    counts = ((F.col("n") == 0) & (F.col("unit") != "")) | (F.length("unit") >= LEAST_CHARACTERS) | ((F.col("unit") != "") & (words >= least_words))
    return each.where(counts).select("doc_id", "key", "place", F.xxhash64("unit").alias("h1"), F.xxhash64(F.lit(7), "unit").alias("h2"))


def repeated_units(docs: DataFrame, separator: str = LINE, least_words: int = LEAST_WORDS) -> DataFrame:
    """(doc_id, key, gone): of each document with removals, the places of its units that go, in order.

    key tells documents of one doc_id apart (a hash of the text). Rows equal in id and text are one document.
    """
    every = materialise(units(docs, separator, least_words), "units")
    counts = materialise(every.groupBy("h1").agg(F.count("*").alias("n")).where("n > 1"), "counts")
    repeats = materialise(spread(every, counts, ["h1"], every.count()).drop("n"), "repeats")
    rank = F.struct("doc_id", "key", "place")
    firsts = materialise(repeats.groupBy("h1", "h2").agg(F.min(rank).alias("first"), F.count("*").alias("n")), "firsts")
    gone = spread(repeats, firsts, ["h1", "h2"], repeats.count()).where(~rank.eqNullSafe(F.col("first")))
    found = materialise(gone.groupBy("doc_id", "key").agg(F.array_sort(F.collect_set("place")).alias("gone")), "gone")
    discard(every, counts, repeats, firsts)
    return found


def cut_units(text: str, gone: list[int], separator: str = LINE) -> tuple[str, list[tuple[int, int]]]:
    """(text without the units, their spans in the original). A line goes with its separator, a sentence with the space before it."""
    marked = text
    for end in ENDS:
        marked = marked.replace(end, end[0] + MARK)
    out, spans, drop = [], [], set(gone)
    edges = [(m.start(), m.end()) for m in re.finditer(separator, marked)]
    starts, ends = [0, *(b for _, b in edges)], [*(a for a, _ in edges), len(marked)]
    for line, (start, end) in enumerate(zip(starts, ends, strict=True)):
        place = line << SENTENCE_BITS
        if place in drop:
            spans.append((start, end))
            continue
        body, at = [], start
        parts = marked[start:end].split(MARK)
        for k, part in enumerate(parts, 1):
            if len(parts) > 1 and place + k in drop:
                spans.append((at, at + len(part)))
            else:
                body.append((text[at - 1] if body else "") + text[at : at + len(part)])
            at += len(part) + 1
        if body:
            before = text[ends[line - 1] : start] if out else ""
            out.append(before + "".join(body))
    return "".join(out), spans


def deduplicate(docs: DataFrame, separator: str = LINE, least_words: int = LEAST_WORDS) -> DataFrame:
    """docs with repeated units taken out of `text`, and columns n_units (lines), n_removed, removed_spans.

    removed_spans: (start, end) of each removed unit in code points of the original text, end exclusive. A null text
    stays null; a text none of whose units go is unchanged; one all of whose units go becomes empty, and its row stays.
    Rows equal in doc_id and text are one document and end up alike. Rows without doc_id rank first. Other columns pass
    through; columns named as the new ones are replaced.
    """
    docs = docs.drop("n_units", "n_removed", "removed_spans")
    names = docs.columns
    places, at, key, own = fresh(names, "gone", "gone_id", "gone_key", "text_key")
    gone = repeated_units(docs.select("doc_id", "text"), separator, least_words)
    gone = gone.select(F.col("doc_id").alias(at), F.col("key").alias(key), F.col("gone").alias(places))
    joined = docs.withColumn(own, _key()).join(gone, F.col("doc_id").eqNullSafe(F.col(at)) & (F.col(own) == F.col(key)), "left").select(*(f"`{n}`" for n in names), places)
    schema = ", ".join([*(f"`{n}` {t}" for n, t in docs.dtypes), "n_units int, n_removed int, removed_spans array<struct<start:int,end:int>>"])
    span = pa.list_(pa.struct([("start", pa.int32()), ("end", pa.int32())]))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        release()
        for batch in batches:
            texts, counts, spans = batch.column("text").to_pylist(), [], []
            for k, (t, drop) in enumerate(zip(texts, batch.column(places).to_pylist(), strict=True)):
                counts.append(0 if t is None else len(re.findall(separator, t)) + 1)
                found: list[tuple[int, int]] = []
                if t is not None and drop:
                    texts[k], found = cut_units(t, drop, separator)
                spans.append([{"start": a, "end": b} for a, b in found])
            columns = [pa.array(texts, pa.string()) if n == "text" else batch.column(n) for n in names]
            yield pa.RecordBatch.from_arrays([*columns, pa.array(counts, pa.int32()), pa.array([len(s) for s in spans], pa.int32()), pa.array(spans, span)], [*names, "n_units", "n_removed", "removed_spans"])

    return joined.mapInArrow(run, schema)


def clean(docs: DataFrame, **options) -> DataFrame:
    """deduplicate() with the columns of docs alone, n_chars brought up to date where there is one. Columns n_units, n_removed and removed_spans of docs stay as they are."""
    clash = dict(zip(("n_units", "n_removed", "removed_spans"), fresh([*docs.columns, "n_units", "n_removed", "removed_spans"], "n_units", "n_removed", "removed_spans"), strict=True))
    kept = docs.withColumnsRenamed({c: clash[c] for c in clash if c in docs.columns})
    out = deduplicate(kept, **options)
    if "n_chars" in docs.columns:
        out = out.withColumn("n_chars", F.when(F.col("n_removed") > 0, F.char_length("text").cast(dict(docs.dtypes)["n_chars"])).otherwise(F.col("n_chars")))
    return out.select(*kept.columns).withColumnsRenamed({v: k for k, v in clash.items() if k in docs.columns})
