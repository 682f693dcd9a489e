"""Near duplicates by SimHash: tiled exact comparison of 64-bit fingerprints.

Fingerprints within ``radius`` bits agree on at least one of ``radius + 1`` disjoint
bit bands, so every link is found inside a (band, value) bucket and nothing else has
to meet. Rows are ordered by bucket and population count and cut into tiles, which may hold
several small buckets or a part of a large one; numpy compares tile with tile by exclusive-or
and bit counts, and a pair of tiles of one bucket whose counts differ by more than the radius
is skipped. What a task finds leaves it as stars, not pairs.

Defined cases: null or empty text has fingerprint zero and links like any other;
repeated rows share a fingerprint and hence a component; null ids take part but never
name a component (a component of null ids only has a null id); an empty table gives
an empty result; columns other than id and text are not read, so they can't clash.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import bound_batches, byte_list, materialise, one
from .components import connected_components

SEED = 42
ROWS = 1 << 14
#: Rows of a tile, and rows whose tiles are made together.
TILE, GROUPED = 64, 200_000


def fingerprint(text: bytes, shingle: int = 3) -> int:
    """Majority of the bits of the XXH64 of all word shingles of a whole text."""
    words = text.lower().split()
    n = len(words)
    if n == 0:
        return 0
    joined, digest = b" ".join(words), xxhash.xxh64_intdigest
    if n <= shingle:
        hashes = np.array([digest(joined, SEED)], np.uint64)
    else:
        sizes = np.fromiter(map(len, words), np.int64, n)
        ends = np.cumsum(sizes + 1) - 1
        starts = (ends - sizes)[: n - shingle + 1].tolist()
        hashes = np.array([digest(joined[a:b], SEED) for a, b in zip(starts, ends[shingle - 1 :].tolist(), strict=True)], np.uint64)
    counts = np.zeros(64, np.int64)
    for at in range(0, len(hashes), ROWS):
        part = hashes[at : at + ROWS]
        counts += np.add.reduce(np.unpackbits(part.view(np.uint8).reshape(-1, 8), axis=1, bitorder="little"), axis=0, dtype=np.uint32)
    return int(np.packbits(2 * counts > len(hashes), bitorder="little").view(np.uint64)[0])


def fingerprints(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", shingle: int = 3) -> DataFrame:
    """(id LONG, fp LONG: the 64 bits) per row."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            fps = np.array([fingerprint(t, shingle) for t in byte_list(batch.column(1))], np.uint64).view(np.int64)
            yield pa.RecordBatch.from_arrays([batch.column(0).cast(pa.int64()), pa.array(fps)], names=["id", "fp"])

    bound_batches(docs.sparkSession)
    return docs.select(F.col(id_col).cast("long").alias("id"), F.col(text_col).cast("string").alias("text")).mapInArrow(run, "id long, fp long")


class _Forest:
    """Union-find over fingerprints that have a link."""

    def __init__(self) -> None:
        self.up: dict[int, int] = {}

    def find(self, x: int) -> int:
        up = self.up
        root = x
        while (y := up.get(root, root)) != root:
            root = y
        while up.get(x, x) != root:
            up[x], x = root, up[x]
        return root

    def join(self, a: int, b: int) -> None:
        a, b = self.find(a), self.find(b)
        if a != b:
            self.up[max(a, b)] = min(a, b)

    def edges(self) -> tuple[np.ndarray, np.ndarray]:
        nodes = list(self.up)
        return np.array(nodes, np.uint64).view(np.int64), np.array([self.find(x) for x in nodes], np.uint64).view(np.int64)


def tiled_pairs(keys: np.ndarray, fps: np.ndarray, radius: int, tally: dict | None = None) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """Places (i, j) of fingerprints of equal key within ``radius`` bits, from rows ordered by key and population count.

    Rows are cut into tiles; a tile meets itself and the later ones that go on with the key it
    ends with, unless the counts of the key's rows differ beyond the radius between the two.
    ``tally`` counts tile pairs met and skipped.
    """
    n, size = len(keys), TILE
    if not n:
        return
    fill = -n % size
    tiles = np.concatenate([fps, np.zeros(fill, np.uint64)]).reshape(-1, size)
    names = np.concatenate([keys, np.full(fill, keys[-1])]).reshape(-1, size)
    pops = np.bitwise_count(fps).astype(np.int64)
    low, high = pops[::size], pops[np.minimum(np.arange(size - 1, n + fill, size), n - 1)]
    upper = np.triu(np.ones((size, size), bool), 1)
    tally = {} if tally is None else tally
    at = np.arange(len(tiles))
    for step in range(len(tiles)):
        if step:
            at = at[at + step < len(tiles)]
            at = at[names[at, -1] == names[at + step, 0]]
        if not len(at):
            return
        near = at[low[at + step] - high[at] <= radius] if step else at
        tally["met"], tally["skipped"] = tally.get("met", 0) + len(near), tally.get("skipped", 0) + len(at) - len(near)
        for a in range(0, len(near), 64):
            g = near[a : a + 64]
            close = np.bitwise_count(tiles[g][:, :, None] ^ tiles[g + step][:, None, :]) <= radius
            close &= names[g][:, :, None] == names[g + step][:, None, :]
            if not step:
                close &= upper
            of, i, j = np.nonzero(close)
            i, j = g[of] * size + i, (g[of] + step) * size + j
            real = j < n
            if real.any():
                yield i[real], j[real]


def whole_groups(batches: Iterator[pa.RecordBatch], rows: int) -> Iterator[pa.Table]:
    """Tables of ``rows`` rows or more that end where the first column, by which the rows are ordered, changes."""
    held: list[pa.RecordBatch] = []
    size = 0
    for batch in batches:
        if not batch.num_rows:
            continue
        key = batch.column(0).to_numpy()
        if size >= rows:
            last = held[-1].column(0)[-1].as_py()
            cut = int(np.argmax(key != last)) if key[-1] != last else len(key)
            if cut < len(key):
                yield pa.Table.from_batches([*held, batch.slice(0, cut)]).combine_chunks()
                held, size, batch = [], 0, batch.slice(cut)
        held.append(batch)
        size += batch.num_rows
    if held:
        yield pa.Table.from_batches(held).combine_chunks()


def links(distinct: DataFrame, radius: int = 3) -> DataFrame:
    """Star edges (u, v) that connect exactly the fingerprints within ``radius`` bits."""
    bands = radius + 1
    cuts = [64 * b // bands for b in range(bands + 1)]
    keys = F.array(*[F.shiftrightunsigned("fp", cuts[b]).bitwiseAND(F.lit((1 << (cuts[b + 1] - cuts[b])) - 1).cast("long")) * bands + b for b in range(bands)])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        forest = _Forest()
        for table in whole_groups(batches, GROUPED):
            fps = one(table["fp"]).to_numpy().view(np.uint64)  # of negative numbers numpy counts the bits of the amount
            for i, j in tiled_pairs(one(table["key"]).to_numpy(), fps, radius):
                for a, b in zip(fps[i].tolist(), fps[j].tolist(), strict=True):
                    forest.join(a, b)
        u, v = forest.edges()
        yield pa.RecordBatch.from_arrays([pa.array(u), pa.array(v)], names=["u", "v"])

    n = distinct.select(F.explode(keys).alias("key"), "fp")
    return n.repartition(F.col("key")).sortWithinPartitions("key", F.bit_count("fp")).mapInArrow(run, "u long, v long")


def near_duplicates(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", shingle: int = 3, radius: int = 3) -> DataFrame:
    """(doc_id, fingerprint, component_id) for every row of ``docs``."""
    fps = materialise(fingerprints(docs, id_col, text_col, shingle), "fingerprints")
    firsts = fps.groupBy("fp").agg(F.min("id").alias("first"))
    roots = connected_components(links(firsts.select("fp"), radius))
    named = firsts.join(roots, firsts.fp == roots.node, "left").select("fp", "first", F.coalesce("root", "fp").alias("root"))
    smallest = named.groupBy("root").agg(F.min("first").alias("component_id"))
    of = named.join(smallest, "root").select(F.col("fp").alias("key"), "component_id")
    return fps.join(of, fps.fp == of.key, "left").select(F.col("id").alias(id_col), F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint"), "component_id")


def op4_simhash_near_dedup(spark, sf_dir: str) -> DataFrame:
    return near_duplicates(spark.read.parquet(f"{sf_dir}/documents.parquet"))
