"""Near copies: SimHash tiles over word shingles, with every link verified.

A text is the set of its lower-cased shingles; two texts are linked if the Jaccard similarity
of their sets is at least ``NUM / DEN``. At 0.8 the 64-bit fingerprints of a pair differ in
about ten bits, so no band of bits is equal for sure. Fingerprints meet in buckets that a
linked pair can't miss, instead:
  - every shingle of every distinct set travels once, packed by ranges of its hash, to where
    it is counted. Linked sets share ``NUM / DEN`` of their shingles, so a set of which fewer
    occur elsewhere has no link and goes no further;
  - shingles are ordered, the common ones last; linked sets share one of their first
    n - ceil(t n) + 1 each. Those shingles are the buckets;
  - a bucket compares fingerprints by exclusive-or and bit counts, in tiles of rows ordered by
    population count; pairs within ``RADIUS`` bits and of fitting sizes are verified on the
    whole sets. A pair at 0.8 is farther apart than the radius about four times in a million,
    closer copies hardly ever;
  - first a row meets the row before it and the first one of its bucket only. What that links
    is merged, and only rows of different components meet again, all with all, so a large
    group of near copies costs a few pairs a set, and no link is left out.

Shingles are told apart by 48 bits of their hash, sets by 64. Bounds: a task holds one range
of hashes (of planned size but for a very common shingle), then one bucket at a time.

Defined cases: a text shorter than a shingle is one shingle; texts without words are equal;
null ids take part but never name a component; repeated rows share their component; an empty
table gives an empty result; columns other than id and text are not read.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import zstandard
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import blocks, bound_batches, byte_list, fresh_path, materialise, mix64, one
from .components import connected_components
from .hashing import BITS, LOW, words_by_part
from .linededup import DEN, FIRST, NUM, Common, _text, binary_values, bit_table, held, prefix_size, shared_words, slots
from .simhash import GROUPED, tiled_pairs, whole_groups

#: Bits in which fingerprints of linked sets may differ.
RADIUS = 22
#: Bytes of text worked on together, and texts, whose number has to fit beside a hash.
PART, ROWS = 8 << 20, 1 << 16
#: Shingles a range of hashes is planned for, and the share from which one is common.
BUCKET, RARE = 1_200_000, 1 / 200_000
SHARED, OFTEN = 0, 1


def shingle_sets(texts: list[bytes], shingle: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Signature and size of each text's set, and (text << 48 | shingle) of all, in order; at most ROWS texts."""
    words, n, _ = words_by_part(texts, False)
    doc = np.repeat(np.arange(len(n)), n)
    after = np.cumsum(n)[doc] - np.arange(len(doc))  # words from here to the text's end
    at = np.flatnonzero((after >= shingle) | (after == n[doc]))
    left = after[at]
    factors = mix64(np.arange(1, shingle + 1)) | np.uint64(1)
    words = np.concatenate([words, np.zeros(shingle, np.uint64)])
    h = words[at] * factors[0]
    for k in range(1, shingle):
        h += np.where(k < left, words[at + k], np.uint64(0)) * factors[k]
    keys = np.sort(doc[at].astype(np.uint64) << BITS | mix64(h) >> np.uint64(16))
    keys = keys[np.r_[True, keys[1:] != keys[:-1]]] if len(keys) else keys
    of = (keys >> BITS).astype(np.int64)
    size = np.bincount(of, minlength=len(n))
    ends = np.r_[np.uint64(0), np.cumsum(mix64((keys & LOW) + np.uint64(1)))]
    until = np.cumsum(size)
    sums = ends[until] - ends[until - size]
    return np.where(size > 0, mix64(sums + size.astype(np.uint64)), np.uint64(0)).view(np.int64), size, keys


def _parts(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.Table]:
    for table in blocks(batches, limit=PART):
        for a in range(0, table.num_rows, ROWS):
            yield table.slice(a, ROWS).combine_chunks()


def sizes(rows: DataFrame, shingle: int) -> DataFrame:
    """(id, sig, n): the set of every row of (id, text)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for table in _parts(batches):
            sig, n, _ = shingle_sets(byte_list(one(table["text"])), shingle)
            yield pa.RecordBatch.from_arrays([one(table["id"]), pa.array(sig), pa.array(n)], names=["id", "sig", "n"])

    return rows.mapInArrow(run, "id long, sig long, n long")


def packed(rows: DataFrame, shingle: int, buckets: int) -> DataFrame:
    """(bucket, block, sets, body): the shingles of a block's distinct sets in a range of hashes."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        press = zstandard.ZstdCompressor(level=1).compress
        for number, table in enumerate(_parts(batches)):
            block = TaskContext.get().partitionId() << 32 | number
            sig, n, keys = shingle_sets(byte_list(one(table["text"])), shingle)
            new = np.zeros(len(sig), bool)
            new[np.unique(sig, return_index=True)[1]] = True
            keys = keys[new[(keys >> BITS).astype(np.int64)]]
            keys = np.sort((keys & LOW) << np.uint64(16) | keys >> BITS)
            h, of = keys >> np.uint64(16), keys.astype(np.uint16)
            cuts = np.searchsorted((h >> np.uint64(16)) * np.uint64(buckets) >> np.uint64(32), np.arange(buckets + 1, dtype=np.uint64))
            told = press(np.stack([sig, n]).tobytes())
            out = []
            for b in np.flatnonzero(np.diff(cuts)).tolist():
                part, whose = h[cuts[b] : cuts[b + 1]], of[cuts[b] : cuts[b + 1]]
                steps = np.diff(part, prepend=np.uint64(0)).view(np.uint8).reshape(-1, 8).T.tobytes()
                out.append((b, block, told, press(steps + whose.tobytes())))
            if out:
                yield pa.RecordBatch.from_arrays([pa.array(x) for x in zip(*out, strict=True)], names=["bucket", "block", "sets", "body"])

    return rows.mapInArrow(run, "bucket long, block long, sets binary, body binary")


def unpacked(sets: bytes, body: bytes, expand: zstandard.ZstdDecompressor) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Shingles of a packed row, the number of each one's set in the block, and the signatures of the block's sets."""
    sig, _ = np.frombuffer(expand.decompress(sets), np.int64).reshape(2, -1)
    raw = np.frombuffer(expand.decompress(body), np.uint8)
    m = len(raw) // 10
    return np.cumsum(np.ascontiguousarray(raw[: 8 * m].reshape(8, m).T).view(np.int64).reshape(-1)), raw[8 * m :].view(np.uint16), sig


COUNTED = "block long, sets binary, body binary, h long, n long, kind int"


def counted(rows: DataFrame, least: int) -> DataFrame:
    """From packed rows: SHARED rows (block, sets, body) with how many shingles of each of a block's sets occur in other sets as well, and OFTEN rows (h, n) of shingles that occur ``least`` times."""

    def met(held_rows: list[tuple], expand: zstandard.ZstdDecompressor) -> Iterator[pa.RecordBatch]:
        parts = [unpacked(sets, body, expand) for _, sets, body in held_rows]
        first = np.cumsum([0, *(len(sig) for _, _, sig in parts)])
        h = np.concatenate([x for x, _, _ in parts])
        at = np.concatenate([of + np.int32(a) for (_, of, _), a in zip(parts, first.tolist(), strict=False)])
        sig = np.concatenate([x for _, _, x in parts])
        del parts
        order = np.argsort(h)
        h, at = h[order], at[order]
        del order
        start = np.flatnonzero(np.r_[True, h[1:] != h[:-1]]) if len(h) else np.zeros(0, np.int64)
        mine = sig[at]
        times = np.diff(np.r_[start, len(h)])
        other = np.minimum.reduceat(mine, start) != np.maximum.reduceat(mine, start)  # copies of one set in several blocks are no others
        n = np.bincount(at[np.repeat(other, times)], minlength=len(sig)).astype(np.int32)
        k = len(held_rows)
        press = zstandard.ZstdCompressor(level=1).compress
        bodies = [press(n[a:b].tobytes()) for a, b in zip(first[:-1].tolist(), first[1:].tolist(), strict=True)]
        none = pa.nulls(k, pa.int64())
        yield pa.RecordBatch.from_arrays([pa.array([x[0] for x in held_rows]), pa.array([x[1] for x in held_rows], pa.binary()), pa.array(bodies, pa.binary()), none, none, pa.array([SHARED] * k, pa.int32())], names=["block", "sets", "body", "h", "n", "kind"])
        often = np.flatnonzero(times >= least)
        k = len(often)
        if k:
            yield pa.RecordBatch.from_arrays([pa.nulls(k, pa.int64()), pa.nulls(k, pa.binary()), pa.nulls(k, pa.binary()), pa.array(h[start[often]]), pa.array(times[often]), pa.array([OFTEN] * k, pa.int32())], names=["block", "sets", "body", "h", "n", "kind"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        expand, waiting, now = zstandard.ZstdDecompressor(), [], None
        for batch in batches:
            for bucket, *row in zip(*(x.to_pylist() for x in batch.columns), strict=True):
                if bucket != now and waiting:
                    yield from met(waiting, expand)
                    waiting = []
                now = bucket
                waiting.append(row)
        if waiting:
            yield from met(waiting, expand)

    return rows.repartition(F.col("bucket")).sortWithinPartitions("bucket").mapInArrow(run, COUNTED)


def shared_enough(rows: DataFrame) -> DataFrame:
    """(sig) of sets of which ``NUM / DEN`` or more occurs elsewhere, from SHARED rows."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        expand, now, sets, total = zstandard.ZstdDecompressor(), None, b"", np.zeros(0, np.int64)

        def done() -> pa.RecordBatch:
            sig, n = np.frombuffer(expand.decompress(sets), np.int64).reshape(2, -1)
            return pa.RecordBatch.from_arrays([pa.array(sig[(total > 0) & (DEN * total >= NUM * n)])], names=["sig"])

        for batch in batches:
            for block, told, body in zip(*(x.to_pylist() for x in batch.columns[:3]), strict=True):
                n = np.frombuffer(expand.decompress(body), np.int32)
                if block != now:
                    if now is not None:
                        yield done()
                    now, sets, total = block, told, np.zeros(len(n), np.int64)
                total += n
        if now is not None:
            yield done()

    return rows.select("block", "sets", "body").repartition("block").sortWithinPartitions("block").mapInArrow(run, "sig long").distinct()


def fingerprint(hashes: np.ndarray) -> int:
    """Majority of the bits of all shingles of a set."""
    counts, at = np.zeros(64, np.int64), 0
    mixed = mix64(hashes)
    while at < len(mixed):
        counts += np.add.reduce(np.unpackbits(mixed[at : at + 4096].view(np.uint8).reshape(-1, 8), axis=1, bitorder="little"), axis=0, dtype=np.uint32)
        at += 4096
    return int(np.packbits(2 * counts > len(mixed), bitorder="little").view(np.int64)[0])


def arrays(rows: DataFrame, shingle: int, table: np.ndarray) -> DataFrame:
    """(sig, n, fp, words) of at least the texts whose ids the bit table holds."""
    told = rows.sparkSession.sparkContext.broadcast(table)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for table_ in _parts(batches):
            doc = one(table_["id"]).fill_null(FIRST).to_numpy()
            table_ = table_.filter(pa.array(held(told.value, slots(_text(doc))))).combine_chunks()
            if not table_.num_rows:
                continue
            sig, n, keys = shingle_sets(byte_list(one(table_["text"])), shingle)
            ends = np.cumsum(n)
            words = [keys[a:b] & LOW for a, b in zip((ends - n).tolist(), ends.tolist(), strict=True)]
            yield pa.RecordBatch.from_arrays([pa.array(sig), pa.array(n), pa.array([fingerprint(w) for w in words]), pa.array([w.tobytes() for w in words], pa.binary())], names=["sig", "n", "fp", "words"])

    return rows.mapInArrow(run, "sig long, n long, fp long, words binary")


def buckets_of(sets: DataFrame, common: Common) -> DataFrame:
    """(h, sig, n, fp, part): a row per prefix shingle of (sig, n, fp, part, words)."""
    told = sets.sparkSession.sparkContext.broadcast(common)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            if not batch.num_rows:
                continue
            words, n = binary_values(batch.column("words"))
            of = np.repeat(np.arange(len(n)), n)
            rank = told.value.ranks(words)
            order = np.lexsort((rank, of)) if (rank >= 0).any() else np.arange(len(of))  # rare ones stay in order of hash
            pos = np.arange(len(of)) - (np.cumsum(n) - n)[of]
            keep = pos < prefix_size(n)[of]
            mine = of[keep]
            yield pa.RecordBatch.from_arrays([pa.array(words[order][keep].view(np.int64)), *(pa.array(batch.column(c).to_numpy()[mine]) for c in ("sig", "n", "fp", "part"))], names=["h", "sig", "n", "fp", "part"])

    return sets.select("sig", "n", "fp", "part", "words").mapInArrow(run, "h long, sig long, n long, fp long, part long")


def near_pairs(rows: DataFrame, every: bool) -> DataFrame:
    """(u, v) of sets within the radius in a bucket: with the row before and the first one, or all of different parts."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for table in whole_groups(batches, GROUPED):
            h, sig, n, fp, part = (one(table[c]).to_numpy() for c in ("h", "sig", "n", "fp", "part"))
            start = np.flatnonzero(np.r_[True, h[1:] != h[:-1]])
            size = np.diff(np.r_[start, len(h)])
            if every:
                mixed = np.repeat(np.minimum.reduceat(part, start) != np.maximum.reduceat(part, start), size)
                h, sig, n, fp, part = (x[mixed] for x in (h, sig, n, fp, part))
                found = tiled_pairs(h, fp.view(np.uint64), RADIUS)
            else:
                rest = np.ones(len(h), bool)
                rest[start] = False
                j = np.flatnonzero(rest)
                first = np.repeat(start, size)[j]
                i, j = np.r_[j - 1, first], np.r_[j, j]
                close = np.bitwise_count(fp[i].view(np.uint64) ^ fp[j].view(np.uint64)) <= RADIUS
                found = iter([(i[close], j[close])])
            pairs = [np.zeros((0, 2), np.int64)]
            for i, j in found:
                fit = (DEN * np.minimum(n[i], n[j]) >= NUM * np.maximum(n[i], n[j])) & (sig[i] != sig[j])
                if every:
                    fit &= part[i] != part[j]
                a, b = sig[i[fit]], sig[j[fit]]
                pairs.append(np.stack([np.minimum(a, b), np.maximum(a, b)], axis=1))
            both = np.unique(np.concatenate(pairs), axis=0)
            yield pa.RecordBatch.from_arrays([pa.array(np.ascontiguousarray(both[:, k])) for k in (0, 1)], names=["u", "v"])

    return rows.repartition(F.col("h")).sortWithinPartitions("h", F.bit_count("fp"), "sig").mapInArrow(run, "u long, v long").distinct()


def linked(pairs: DataFrame, sets: DataFrame) -> DataFrame:
    """Those of the pairs (u, v) whose sets are similar."""
    one_, two = (sets.select(F.col("sig").alias(f"s{k}"), F.col("words").alias(f"w{k}")) for k in (1, 2))
    both = pairs.join(one_, F.col("u") == F.col("s1")).join(two, F.col("v") == F.col("s2")).select("u", "v", "w1", "w2")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            if batch.num_rows:
                common, n, m = shared_words(batch.column("w1"), batch.column("w2"))
                holds = pa.array((NUM + DEN) * common >= NUM * (n + m))
                yield pa.RecordBatch.from_arrays([batch.column(k).filter(holds) for k in (0, 1)], names=["u", "v"])

    return both.mapInArrow(run, "u long, v long")


def near_copies(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", shingle: int = 5) -> DataFrame:
    """(doc_id, component_id) for every row of ``docs``."""
    spark = docs.sparkSession
    bound_batches(spark)
    rows = docs.select(F.col(id_col).cast("long").alias("id"), F.col(text_col).cast("string").alias("text"))
    sets = materialise(sizes(rows, shingle), "shingle-sets")
    total = sets.agg(F.coalesce(F.sum("n"), F.lit(0))).first()[0]
    least = max(2, int(total * RARE))
    path = fresh_path(spark, "shingles")
    counted(packed(rows, shingle, 1 + total // BUCKET), least).write.partitionBy("kind").parquet(path)
    told = spark.read.schema(COUNTED).parquet(path)
    often = told.where(F.col("kind") == OFTEN).select("h", "n").toPandas()
    common = Common(often["h"].to_numpy(np.int64).view(np.uint64), often["n"].to_numpy(np.int64))
    likely = materialise(shared_enough(told.where(F.col("kind") == SHARED)), "likely")
    firsts = sets.groupBy("sig").agg(F.min("id").alias("first"))
    ids = firsts.join(likely, "sig", "left_semi").select(F.coalesce("first", F.lit(FIRST)).alias("id"))

    def marks(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            yield pa.RecordBatch.from_arrays([pa.array(np.unique(slots(_text(batch.column(0).to_numpy()))))], names=["slot"])

    table = bit_table(ids.mapInArrow(marks, "slot long").distinct())
    wholes = materialise(arrays(rows, shingle, table).join(likely, "sig", "left_semi").dropDuplicates(["sig"]), "shingle-arrays")
    tried = materialise(near_pairs(buckets_of(wholes.withColumn("part", F.col("sig")), common), False), "pairs")
    edges = materialise(linked(tried, wholes), "links")
    roots = connected_components(edges)
    parted = wholes.join(roots, wholes.sig == roots.node, "left").select("sig", "n", "fp", F.coalesce("root", "sig").alias("part"), "words")
    rest = materialise(near_pairs(buckets_of(parted, common), True).join(tried, ["u", "v"], "left_anti"), "pairs")
    more = materialise(linked(rest, wholes), "links")
    if not more.isEmpty():
        roots = connected_components(edges.union(more))
    named = firsts.join(roots, firsts.sig == roots.node, "left").select("sig", "first", F.coalesce("root", "sig").alias("top"))
    smallest = named.groupBy("top").agg(F.min("first").alias("component_id"))
    of = named.join(smallest, "top").select(F.col("sig").alias("key"), "component_id")
    return sets.join(of, sets.sig == of.key, "left").select(F.col("id").alias(id_col), "component_id")
