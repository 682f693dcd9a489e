"""Benchmark decontamination by spaced-seed hashing.

A mask is a row of word positions of which some are ignored, so a hash of the others survives
substituted words. Every place of a training text is hashed under every mask and joined with
the hashes of the benchmark's places; a hit fixes an alignment of a text with an item, and the
aligned words are compared. A text is contaminated if at least ``MIN_WORDS`` consecutive
aligned words (or the whole item, if it is shorter) agree in ``SHARE`` or more.

Items of up to ``BRIEF`` words have masks of four words of their own, items of fewer than five
words are one hash of the whole item, so an item of any length can be found.

Nothing of the benchmark is collected: its hashes are a table, and so are its words. Only bit
tables of fixed size travel, of the words and of the hashes it has; they spare places of the
texts that can't hit, the join decides. Words are told apart by 48 bits.

Defined cases: null or empty texts and items without words match nothing; repeated rows are
answered each; with an empty benchmark nothing is contaminated; an empty table gives an empty
result; only id and text are read on either side, so further columns can't clash.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import blocks, bound_batches, byte_list, materialise, mix64, one
from .hashing import words_by_part
from .linededup import BITS, binary_values, bit_table, held, slots

#: Fixed masks: 1 is compared, 0 ignored. Those of brief items, and those of all longer ones.
BRIEF_MASKS = ["1111", "11011", "10111", "11101"]
MASKS = ["11111", "111011", "110111", "1110011", "1100111", "10110101"]
#: Words from which an item has masks, and up to which it has the brief ones.
LEAST, BRIEF = 5, 7
MIN_WORDS, SHARE = 13, 0.8
PART = 12 << 20
#: Masks by number; whole items of 1, 2, 3 and 4 words follow.
ALL = [*BRIEF_MASKS, *MASKS, *("1" * k for k in range(1, LEAST))]
WHOLE = len(BRIEF_MASKS) + len(MASKS)


def hashes(words: np.ndarray, mask: int, ok: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Places where the mask fits into a text (ok: the text of each word) and 48-bit hashes of the compared words."""
    shape = ALL[mask]
    at = np.arange(max(0, len(words) - len(shape) + 1))
    at = at[ok[at] == ok[at + len(shape) - 1]]
    return at, _hashed(words, mask, at)


def _hashed(words: np.ndarray, mask: int, at: np.ndarray) -> np.ndarray:
    factor = mix64(np.arange(100 * mask + 1, 100 * mask + 1 + len(ALL[mask]))) | np.uint64(1)
    h = np.full(len(at), mask, np.uint64)
    for k, c in enumerate(ALL[mask]):
        if c == "1":
            h += words[at + k] * factor[k]
    return mix64(h) >> np.uint64(16)


def masks_of(n: int) -> list[int]:
    """The masks of an item of n words."""
    if n < LEAST:
        return [WHOLE + n - 1] if n else []
    brief = list(range(len(BRIEF_MASKS))) if n <= BRIEF else []
    return [*brief, *(k for k in range(len(BRIEF_MASKS), WHOLE) if len(ALL[k]) <= n)]


def item_hashes(items: DataFrame) -> DataFrame:
    """(h, row, at, n, words) of (row, text): a row per mask and place of every item, and with h null one per item with its words."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for table in blocks(batches, limit=PART):
            rows = table["row"].to_pylist()
            words, n, _ = words_by_part(byte_list(one(table["text"])), False)
            ends, out = np.cumsum(n), []
            for row, a, b in zip(rows, (ends - n).tolist(), ends.tolist(), strict=True):
                mine = words[a:b]
                out.append((None, row, None, b - a, mine.tobytes()))
                for mask in masks_of(b - a):
                    at, h = hashes(mine, mask, np.zeros(b - a, np.int8))
                    out += [(x, row, k, b - a, None) for x, k in zip(h.tolist(), at.tolist(), strict=True)]
                if len(out) > 50_000:
                    yield _batch(out)
                    out = []
            yield _batch(out)

    return items.mapInArrow(run, "h long, row long, at long, n long, words binary")


def _batch(rows: list[tuple]) -> pa.RecordBatch:
    columns = list(zip(*rows, strict=True)) or [()] * 5
    kinds = [pa.int64()] * 4 + [pa.binary()]
    return pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(columns, kinds, strict=True)], names=["h", "row", "at", "n", "words"])


def seen_words(items: DataFrame) -> DataFrame:
    """(slot) of all words of (words)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            if batch.num_rows:
                yield pa.RecordBatch.from_arrays([pa.array(np.unique(slots(binary_values(batch.column(0))[0])))], names=["slot"])

    return items.select("words").mapInArrow(run, "slot long").distinct()


def text_hits(rows: DataFrame, words_of: np.ndarray, hashes_of: np.ndarray) -> DataFrame:
    """(key, version, h, place) of places of (key, version, text) whose hash the benchmark seems to have."""
    told = rows.sparkSession.sparkContext.broadcast((words_of, hashes_of))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        known_words, known_hashes = told.value
        for table in blocks(batches, limit=PART):
            key, version = one(table["key"]), one(table["version"])
            words, n, _ = words_by_part(byte_list(one(table["text"])), False)
            doc, first = np.repeat(np.arange(len(n)), n), np.cumsum(n) - n
            known = np.append(held(known_words, slots(words)), np.zeros(8, bool))
            for mask, shape in enumerate(ALL):
                fits = known[: len(words)].copy()
                for k, c in enumerate(shape):
                    if c == "1" and k:
                        fits &= known[k : k + len(words)]
                at = np.flatnonzero(fits)
                at = at[at + len(shape) <= len(words)]
                at = at[doc[at] == doc[at + len(shape) - 1]]
                h = _hashed(words, mask, at)
                hit = held(known_hashes, slots(h))
                at, h = at[hit], h[hit]
                if len(at):
                    of = pa.array(doc[at])
                    yield pa.RecordBatch.from_arrays([key.take(of), version.take(of), pa.array(h.view(np.int64)), pa.array(at - first[doc[at]])], names=["key", "version", "h", "place"])

    return rows.mapInArrow(run, "key long, version long, h long, place long")


def overlap(same: np.ndarray, least: int, share: float = SHARE) -> tuple[int, int] | None:
    """The longest run of ``least`` or more places of which ``share`` or more agree."""
    n = len(same)
    if n < least:
        return None
    score = np.concatenate([[0], np.cumsum(np.where(same, 1 - share, -share))]) + 1e-9
    lowest = np.minimum.accumulate(score)  # falls, so the first place at or below a score is found by bisection
    first = np.searchsorted(-lowest, -score - 2e-9)
    size = np.arange(n + 1) - first
    best = int(np.argmax(size))
    if size[best] < least:
        return None
    a, b = int(first[best]), best
    while not same[a]:
        a += 1
    while not same[b - 1]:
        b -= 1
    return a, b


def windows(found: DataFrame) -> DataFrame:
    """(key, version, row, at, low, part) of texts with their alignments (row, at, n): the text's words that lie beside the item's."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        names = ["key", "version", "row", "at", "low", "part"]
        for batch in batches:
            out = []
            for key, version, text, spots in zip(*(batch.column(c).to_pylist() for c in ("key", "version", "text", "spots")), strict=True):
                words, _, _ = words_by_part([(text or "").encode()], False)
                for s in spots:
                    low, high = max(0, s["at"]), min(len(words), s["at"] + s["n"])
                    out.append((key, version, s["row"], s["at"], low, words[low:high].tobytes()))
                if len(out) > 2000:
                    yield pa.RecordBatch.from_arrays([pa.array(c) for c in zip(*out, strict=True)], names=names)
                    out = []
            if out:
                yield pa.RecordBatch.from_arrays([pa.array(c) for c in zip(*out, strict=True)], names=names)

    return found.mapInArrow(run, "key long, version long, row long, at long, low long, part binary")


def overlaps(pairs: DataFrame) -> DataFrame:
    """(key, version, item, start, stop) of (key, version, item, at, low, part, words) that hold."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            out = []
            for key, version, item, at, low, part, words in zip(*(c.to_pylist() for c in batch.columns), strict=True):
                mine, want = np.frombuffer(part, np.uint64), np.frombuffer(words, np.uint64)
                span = overlap(mine == want[low - at : low - at + len(mine)], min(MIN_WORDS, len(want)))
                if span:
                    out.append((key, version, item, low + span[0], low + span[1]))
            columns = list(zip(*out, strict=True)) or [()] * 5
            yield pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in columns], names=["key", "version", "item", "start", "stop"])

    return pairs.mapInArrow(run, "key long, version long, item long, start long, stop long")


def contamination(docs: DataFrame, benchmark: DataFrame, id_col: str = "doc_id", text_col: str = "text", item_col: str = "item_id", item_text: str = "text") -> DataFrame:
    """(id, contaminated, n_items, items, spans) for every row; spans are item:start:end in words."""
    bound_batches(docs.sparkSession)
    items = benchmark.select(F.col(item_col).cast("long").alias("item"), F.col(item_text).cast("string").alias("text")).distinct()
    items = materialise(items.withColumn("row", F.xxhash64("item", "text")), "items")
    told = materialise(item_hashes(items.select("row", "text")), "item-hashes")
    keyed, whole = told.where("h is not null").select("h", "row", F.col("at").alias("item_at"), "n"), told.where("h is null").select("row", "words")
    words_of = bit_table(seen_words(whole))
    hashes_of = bit_table(keyed.select(F.shiftright("h", 48 - BITS).alias("slot")).distinct())
    rows = docs.select(F.col(id_col).cast("long").alias("key"), F.xxhash64(F.col(text_col).cast("string")).alias("version"), F.col(text_col).cast("string").alias("text"))
    hits = text_hits(rows, words_of, hashes_of)
    spots = hits.join(keyed, "h").select("key", "version", "row", (F.col("place") - F.col("item_at")).alias("at"), "n").distinct()
    spots = materialise(spots.groupBy("key", "version").agg(F.collect_list(F.struct("row", "at", "n")).alias("spots")), "alignments")
    named = spots.select(F.col("key").alias("k"), F.col("version").alias("v"), "spots")
    found = rows.join(named, F.col("key").eqNullSafe(F.col("k")) & (F.col("version") == F.col("v"))).select("key", "version", "text", "spots")
    pairs = windows(found).distinct().join(whole, "row").join(items.select("row", "item"), "row").select("key", "version", "item", "at", "low", "part", "words")
    held_ = overlaps(pairs).distinct()
    spans = F.array_sort(F.collect_list(F.struct("item", "start", "stop")))
    by = held_.groupBy(F.col("key").alias("k"), F.col("version").alias("v")).agg(spans.alias("s"))
    by = by.select("k", "v", F.array_distinct(F.transform("s", lambda x: F.struct(x["item"].alias("item")))).alias("which"), "s")
    out = rows.select("key", "version").join(by, F.col("key").eqNullSafe(F.col("k")) & (F.col("version") == F.col("v")), "left")
    name = lambda x: F.coalesce(x["item"].cast("string"), F.lit("None"))
    return out.select(
        F.col("key").alias(id_col), F.col("s").isNotNull().alias("contaminated"), F.coalesce(F.size("which"), F.lit(0)).cast("long").alias("n_items"),
        F.coalesce(F.array_join(F.transform("which", name), ","), F.lit("")).alias("items"),
        F.coalesce(F.array_join(F.transform("s", lambda x: F.concat_ws(":", name(x), x["start"], x["stop"])), ","), F.lit("")).alias("spans"),
    )


def op5_benchmark_decontamination(spark, sf_dir: str) -> DataFrame:
    return contamination(spark.read.parquet(f"{sf_dir}/documents.parquet"), spark.read.parquet(f"{sf_dir}/benchmark.parquet"))
