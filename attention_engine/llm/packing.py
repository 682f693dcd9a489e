"""Conflict-constrained best-fit packing of texts into bins of ``capacity`` words.

A text longer than a bin is cut into pieces of ``capacity`` words and a rest. Pieces are
dealt into shards by a hash of their text; a shard packs its pieces in falling size. Open
bins are ordered by what is left in them and carry bitmaps of the sources and of the
duplicate clusters they hold; a piece goes to the tightest bin that has room for it and
neither its source nor its cluster, and the search goes on through the successors until
such a bin is found or a new one is opened. Residuals without a compatible bin are passed
over by counts per source, so a hot source doesn't make the search linear.

A cluster is a set of texts that are equal up to case and blanks, or, where ``clusters`` names
components of near duplicates by id, such a component; pieces of one text and of its copies
conflict like those of one source (``source_conflicts=False`` leaves sources
free). A shard holds about ``shard_pieces`` pieces at every size of input.

Defined cases: null or empty text takes no room and stands in no bin (bin_id null, one
row); a null source conflicts with nothing; repeated rows are packed each; ties in size
are broken by id, then by place; an empty table gives an empty result; only the columns
named are read, so further columns can't clash.
"""

from __future__ import annotations

from bisect import bisect_left
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import bound_batches, byte_list, materialise

CAPACITY = 2048
SHARD_PIECES = 4096
SCHEMA = "bin_id string, slot int, id long, source string, first_word long, n_words long, bin_words long"


def sized(docs: DataFrame) -> DataFrame:
    """(id, source, cluster, words) from (id, source, text)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            split = [t.lower().split() for t in byte_list(batch.column(2))]
            cluster = [xxhash.xxh3_128_digest(b" ".join(w)) for w in split]
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(cluster, pa.binary()), pa.array([len(w) for w in split], pa.int64())], names=["id", "source", "cluster", "words"])

    return docs.mapInArrow(run, "id long, source string, cluster binary, words long")


class Bins:
    """Open bins by residual, each with its bitmaps."""

    def __init__(self, capacity: int) -> None:
        self.capacity = capacity
        self.at: list[list[int]] = [[] for _ in range(capacity + 1)]
        self.left: list[int] = []
        self.sources: list[int] = []
        self.clusters: list[int] = []
        self.open = np.zeros(capacity + 1, np.int64)
        self.with_source: dict[int, np.ndarray] = {}

    def _move(self, b: int, residual: int) -> None:
        old = self.left[b]
        if old >= 0:
            self.at[old].pop(bisect_left(self.at[old], b))
            self.open[old] -= 1
        if residual:
            place = self.at[residual]
            place.insert(bisect_left(place, b), b)
            self.open[residual] += 1
        bits = self.sources[b]
        while bits:
            s = (bits & -bits).bit_length() - 1
            bits &= bits - 1
            if old >= 0:
                self.with_source[s][old] -= 1
            if residual:
                self.with_source[s][residual] += 1
        self.left[b] = residual

    def place(self, size: int, source: int, cluster: int) -> int:
        """Put a piece into the tightest compatible bin; source or cluster -1: none."""
        bit, mine = (1 << source if source >= 0 else 0), (1 << cluster if cluster >= 0 else 0)
        free = self.open[size:] if source < 0 else self.open[size:] - self.with_source.setdefault(source, np.zeros(self.capacity + 1, np.int64))[size:]
        chosen = -1
        for residual in (np.flatnonzero(free > 0) + size).tolist():
            chosen = next((b for b in self.at[residual] if not (self.sources[b] & bit or self.clusters[b] & mine)), -1)
            if chosen >= 0:
                break
        if chosen < 0:
            chosen = len(self.left)
            self.left.append(-1)
            self.sources.append(0)
            self.clusters.append(0)
            residual = self.capacity
        else:
            residual = self.left[chosen]
        self._move(chosen, residual - size)
        if bit:
            if residual - size:
                self.with_source[source][residual - size] += 1
            self.sources[chosen] |= bit
        self.clusters[chosen] |= mine
        return chosen


def pack(sizes: list[int], sources: list, clusters: list, capacity: int = CAPACITY) -> tuple[list[int], list[int]]:
    """Bin of each piece, pieces being given in the order of packing, and words in each bin."""
    numbers: dict = {}
    first: dict = {}
    twice: dict = {}
    for c in clusters:
        if c in first:
            twice.setdefault(c, len(twice))
        first[c] = True
    bins, out = Bins(capacity), []
    for size, source, cluster in zip(sizes, sources, clusters, strict=True):
        s = -1 if source is None else numbers.setdefault(source, len(numbers))
        out.append(bins.place(size, s, twice.get(cluster, -1)))
    return out, [capacity - x for x in bins.left]


def best_fit(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", source_col: str = "source", capacity: int = CAPACITY, source_conflicts: bool = True, shard_pieces: int = SHARD_PIECES, clusters: DataFrame | None = None) -> DataFrame:
    """A row per piece: bin_id, slot, id, source, first_word, n_words, bin_words. ``clusters``: (id, component_id), as near_duplicates or near_copies give them."""
    bound_batches(docs.sparkSession)
    rows = docs.select(F.col(id_col).cast("long").alias("id"), F.col(source_col).cast("string").alias("source"), F.col(text_col).cast("string").alias("text"))
    rows = sized(rows)
    if clusters is not None:
        named = clusters.where(F.col("component_id").isNotNull()).groupBy(F.col(id_col).alias("of")).agg(F.min("component_id").alias("component"))
        of = F.encode(F.concat(F.lit("component "), F.col("component").cast("string")), "UTF-8")
        rows = rows.join(named, rows.id == named.of, "left").select("id", "source", F.coalesce(of, "cluster").alias("cluster"), "words")
    rows = materialise(rows, "sizes")
    total = rows.agg(F.coalesce(F.sum(F.ceil(F.col("words") / capacity)), F.lit(0))).first()[0]
    shards = max(1, -(-int(total) // shard_pieces))
    places = F.when(F.col("words") > 0, F.sequence(F.lit(0).cast("long"), F.floor((F.col("words") - 1) / capacity)))
    pieces = rows.select("id", "source", "cluster", "words", F.explode_outer(places).alias("k")).select(
        "id", "source", "cluster", F.coalesce(F.col("k") * capacity, F.lit(0)).alias("first_word"), F.when(F.col("k").isNull(), 0).otherwise(F.least(F.lit(capacity), F.col("words") - F.col("k") * capacity)).alias("n_words"),
        F.pmod(F.xxhash64("id", "cluster", "k"), F.lit(shards)).alias("shard"),
    )

    def run(table: pa.Table) -> pa.Table:
        table = table.take(pa.compute.sort_indices(table, sort_keys=[("n_words", "descending"), ("id", "ascending"), ("first_word", "ascending"), ("source", "ascending"), ("cluster", "ascending")]))
        n = table["n_words"].to_pylist()
        some = sum(x > 0 for x in n)  # what takes no room comes last
        source = table["source"].to_pylist()
        of, filled = pack(n[:some], source[:some] if source_conflicts else [None] * some, table["cluster"].to_pylist()[:some], capacity)
        slot, seen = [], {}
        for b in of:
            slot.append(seen.get(b, 0))
            seen[b] = slot[-1] + 1
        shard, rest = table["shard"][0].as_py(), [None] * (len(n) - some)
        return pa.table(
            [pa.array([f"{shard}-{b}" for b in of] + rest, pa.string()), pa.array(slot + rest, pa.int32()), table["id"], table["source"], table["first_word"], table["n_words"], pa.array([filled[b] for b in of] + rest, pa.int64())],
            names=["bin_id", "slot", "id", "source", "first_word", "n_words", "bin_words"],
        )

    packed = pieces.groupBy("shard").applyInArrow(run, SCHEMA)
    return packed.withColumnsRenamed({"id": id_col, "source": source_col})


def op10_best_fit_packing(spark, sf_dir: str) -> DataFrame:
    return best_fit(spark.read.parquet(f"{sf_dir}/documents.parquet"))
