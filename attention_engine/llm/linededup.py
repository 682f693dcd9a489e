"""Line dedup by an exact set-similarity join.

A line is the set of its lower-cased words. A line is removed if an earlier line, by
(id, line number), has a Jaccard similarity of at least ``NUM / DEN`` with it, equal sets
included. The join:
  - words are 48-bit hashes, made for a whole block of text at once, and ordered by rarity:
    those below a share of ``RARE`` of all words first, by hash, then the others (at most
    1/RARE, so they may travel) by count;
  - a line of n words posts itself under the first n - ceil(t n) + 1 of them, leaving out
    words of one line only (a bit table of fixed size knows most of those);
  - postings travel packed, by ranges of the word's hash (buckets, of bounded size but for
    one very common word, whose distinct lines meet in one place);
  - where postings meet, lengths, positions, and bit maps that bound the symmetric
    difference from below discard pairs; groups are walked in order of length, pairs are
    not emitted before they pass;
  - of the pairs left, a line keeps per word its first ``MOST`` earlier partners and the one
    whose bit map is nearest; these are verified on the words themselves, fetched for those
    lines only. Lines for which none holds, and which had more, meet once more under their
    prefix words, and all their earlier partners that pass the same tests are verified.
To remove a line one earlier partner is enough, so large groups of near copies cost a few
pairs a line. Equal sets are one entry of the join, with their first place.

Defined cases: lines without a word stay; null or empty text has one such line; a null id
comes before all others; lines of repeated rows (equal id and line number) are not later
than each other, so neither removes the other; an empty table gives an empty result; only
id and text are read, other columns pass through ``deduplicated`` untouched.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
import zstandard
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import StringType

from .common import blocks, bound_batches, byte_list, fresh_path, materialise, mix64, one
from .hashing import BITS as PLACE
from .hashing import LOW, words_by_part

NUM, DEN = 4, 5
RARE = 1 / 200_000
BITS = 25
FIRST = -(1 << 63)
#: Lines of fewer words can only match equal sets.
LEAST = 4
MOST = 8
#: Bytes of text whose words are held at once, and lines, whose number has to fit beside a hash.
PART, ROWS = 12 << 20, 1 << 16
#: Postings packed at once, postings of one packed row, and postings a bucket is planned for.
CHUNK, PACKED, BUCKET = 400_000, 2048, 4_000_000


def slots(h: np.ndarray) -> np.ndarray:
    """Places of 48-bit hashes in a bit table."""
    return (h >> np.uint64(48 - BITS)).astype(np.int64)


def bit_table(rows: DataFrame) -> np.ndarray:
    """2**BITS bits from a column ``slot``; what reaches the driver is bounded by their number."""
    found = rows.groupBy(F.shiftright("slot", 6).alias("w")).agg(F.bit_or(F.expr("shiftleft(1L, cast(slot & 63 as int))")).alias("bits")).toPandas()
    out = np.zeros(1 << BITS - 6, np.int64)
    out[found["w"].to_numpy(np.int64)] = found["bits"].to_numpy(np.int64)
    return out.view(np.uint8)


def held(table: np.ndarray, slot: np.ndarray) -> np.ndarray:
    return (table[slot >> 3] >> (slot & 7).astype(np.uint8) & 1).astype(bool)


class Lines:
    """Lines with a word: places, signatures, sizes, and the ordered distinct hashes of each."""

    def __init__(self, doc: np.ndarray, line: np.ndarray, text: np.ndarray, words: np.ndarray, count: np.ndarray) -> None:
        self.doc, self.line, self.text = doc, line, text
        key = np.sort(np.repeat(np.arange(len(count), dtype=np.uint64) << PLACE, count) | words)
        new = np.ones(len(key), bool)
        np.not_equal(key[1:], key[:-1], out=new[1:])
        key = key[new]
        self.of, self.hashes = (key >> PLACE).astype(np.int64), key & LOW
        self.n = np.bincount(self.of, minlength=len(count))
        self.starts = np.cumsum(self.n) - self.n
        sums = (np.add.reduceat(mix64(self.hashes + np.uint64(x)), self.starts) for x in (1, 1 << 50))
        self.a, self.b = (mix64(x + self.n.astype(np.uint64)).view(np.int64) for x in sums)

    def distinct(self) -> "Lines":
        """One line per word set: that of the first place."""
        order = np.lexsort((self.line, self.doc, self.b, self.a))
        a, b = self.a[order], self.b[order]
        keep = np.zeros(len(a), bool)
        keep[order[np.r_[True, (a[1:] != a[:-1]) | (b[1:] != b[:-1])]]] = True
        return self.only(keep)

    def only(self, keep: np.ndarray) -> "Lines":
        out, words = object.__new__(Lines), keep[self.of]
        out.doc, out.line, out.text, out.a, out.b, out.n = (x[keep] for x in (self.doc, self.line, self.text, self.a, self.b, self.n))
        out.hashes, out.of = self.hashes[words], (np.cumsum(keep) - 1)[self.of[words]]
        out.starts = np.cumsum(out.n) - out.n
        return out

    def bitmaps(self) -> tuple[np.ndarray, np.ndarray]:
        """128 bits per line; a word toggles one of them."""
        spot = self.hashes & np.uint64(127)
        bit = np.uint64(1) << (spot & np.uint64(63))
        low = np.where(spot < 64, bit, np.uint64(0))
        return tuple(np.bitwise_xor.reduceat(x, self.starts).view(np.int64) for x in (low, low ^ bit))

    def packed_words(self) -> pa.Array:
        ends = np.r_[0, np.cumsum(self.n)].astype(np.int32) * 8
        return pa.Array.from_buffers(pa.binary(), len(self.n), [None, pa.py_buffer(ends), pa.py_buffer(np.ascontiguousarray(self.hashes))])


def lines_of(table: pa.Table) -> Iterator[Lines]:
    """The lines of a block of (doc, text), at most ROWS at once."""
    h, count, lines = words_by_part(byte_list(one(table["text"])), True)
    text = np.repeat(np.arange(len(lines)), lines)
    number = np.arange(len(text)) - (np.cumsum(lines) - lines)[text]
    doc, some = table["doc"].to_numpy(), np.flatnonzero(count)
    ends = np.cumsum(count)
    for lo in range(0, len(some), ROWS):
        at = some[lo : lo + ROWS]
        yield Lines(doc[text[at]], number[at], text[at], h[ends[at[0]] - count[at[0]] : ends[at[-1]]], count[at])


COUNT, PLACED = 0, 1
SURVEY = "doc long, version long, line long, a long, b long, body binary, kind int"
#: Least and most ranges into which a block's words are dealt for counting.
RANGES = (64, 4096)


def survey(rows: DataFrame) -> tuple[DataFrame, DataFrame]:
    """From (doc, version, text): (h, n) of words in two sets or more, and a row (null, n) with the sum of all counts of a range (a set of a line counts once a block); (doc, version, line, a, b) of every line with a word."""
    names = ["doc", "version", "line", "a", "b", "body", "kind"]

    bits = min(max(RANGES[0], int(rows.sparkSession.conf.get("spark.sql.shuffle.partitions"))), RANGES[1]).bit_length()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        press = zstandard.ZstdCompressor(level=1).compress
        for table in blocks(batches, limit=PART):
            version = table["version"].to_numpy()
            for lines in lines_of(table):
                k = len(lines.n)
                yield pa.RecordBatch.from_arrays([*map(pa.array, (lines.doc, version[lines.text], lines.line, lines.a, lines.b)), pa.nulls(k, pa.binary()), pa.array(np.full(k, PLACED, np.int32))], names=names)
                h = np.sort(lines.distinct().hashes)
                at = np.flatnonzero(np.r_[True, h[1:] != h[:-1]])
                n, h = np.diff(np.r_[at, len(h)]), h[at]
                cuts = np.searchsorted(h, np.arange((1 << bits) + 1, dtype=np.uint64) << np.uint64(48 - bits))
                some = np.flatnonzero(np.diff(cuts))
                bodies = [press(np.stack([np.diff(h[cuts[r] : cuts[r + 1]].view(np.int64), prepend=0), n[cuts[r] : cuts[r + 1]]]).view(np.uint8).reshape(-1, 8).T.tobytes()) for r in some.tolist()]
                none = pa.nulls(len(some), pa.int64())
                yield pa.RecordBatch.from_arrays([none, none, none, pa.array(some), none, pa.array(bodies, pa.binary()), pa.array(np.full(len(some), COUNT, np.int32))], names=names)

    def summed(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        expand, now, parts = zstandard.ZstdDecompressor(), None, []

        def done() -> pa.RecordBatch:
            h, n = (np.concatenate(x) for x in zip(*parts, strict=True))
            order = np.argsort(h)
            h, n = h[order], n[order]
            at = np.flatnonzero(np.r_[True, h[1:] != h[:-1]])
            n, h = np.add.reduceat(n, at), h[at]
            more = n > 1
            return pa.RecordBatch.from_arrays([pa.array([None, *h[more].tolist()], pa.int64()), pa.array(np.r_[n.sum(), n[more]])], names=["h", "n"])

        for batch in batches:
            for r, body in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
                if r != now and parts:
                    yield done()
                    parts = []
                now = r
                raw = np.frombuffer(expand.decompress(body), np.uint8).reshape(8, -1).T
                steps, n = np.ascontiguousarray(raw).view(np.int64).reshape(2, -1)
                parts.append((np.cumsum(steps), n))
        if parts:
            yield done()

    path = fresh_path(rows.sparkSession, "survey")
    rows.mapInArrow(run, SURVEY).write.partitionBy("kind").parquet(path)
    told = rows.sparkSession.read.schema(SURVEY).parquet(path)
    dealt = told.where(F.col("kind") == COUNT).select("a", "body").repartition("a").sortWithinPartitions("a")
    return dealt.mapInArrow(summed, "h long, n long"), told.where(F.col("kind") == PLACED).drop("kind", "body")


def prefix_size(n: np.ndarray) -> np.ndarray:
    return n - -(-NUM * n // DEN) + 1


class Common:
    """Ranks of the words that aren't rare, by count; a lookup starts where the hash's upper bits say."""

    UPPER = 20

    def __init__(self, h: np.ndarray, n: np.ndarray) -> None:
        rank = np.empty(len(h), np.int64)
        rank[np.lexsort((h, n))] = np.arange(len(h))
        order = np.argsort(h)
        self.h, self.rank = np.r_[h[order], LOW + np.uint64(1)], np.r_[rank[order], -1]
        self.first = np.searchsorted(self.h[:-1], np.arange(1 << self.UPPER, dtype=np.uint64) << np.uint64(48 - self.UPPER))

    def ranks(self, h: np.ndarray) -> np.ndarray:
        """The rank of each hash, -1 for rare ones."""
        at = self.first[(h >> np.uint64(48 - self.UPPER)).astype(np.int64)]
        low = np.flatnonzero(self.h[at] < h)
        while len(low):
            at[low] += 1
            low = low[self.h[at[low]] < h[low]]
        return np.where(self.h[at] == h, self.rank[at], -1)


def prefixes(lines: Lines, common: Common) -> tuple[np.ndarray, np.ndarray]:
    """Which of the lines' words are in the prefix, and the place of each of those in its line, both by word."""
    rank = common.ranks(lines.hashes)
    rare = rank < 0
    before = np.cumsum(rare) - rare
    pos = before - before[lines.starts][lines.of]
    rare_words = np.bincount(lines.of, rare, len(lines.n)).astype(np.int64)
    size = prefix_size(lines.n)
    rest = np.flatnonzero(~rare & (rare_words < size)[lines.of])
    if len(rest):
        of = lines.of[rest]
        rest = rest[np.argsort(of << 32 | rank[rest])]
        first = np.flatnonzero(np.r_[True, of[1:] != of[:-1]])
        pos[rest] = np.arange(len(rest)) - np.repeat(first, np.diff(np.r_[first, len(rest)])) + rare_words[of]
    keep = (pos < size[lines.of]) & (lines.n >= LEAST)[lines.of]
    keep &= rare | (rare_words < size)[lines.of]
    return keep, pos


def packed(columns: list[np.ndarray], buckets: int) -> Iterator[pa.RecordBatch]:
    """Postings as rows of up to PACKED of one bucket: signatures as they are, the rest by byte planes, compressed."""
    n = len(columns[0])
    if not n:
        return
    order = np.argsort(columns[0])
    h = columns[0][order]
    hashed = np.stack([columns[k][order] for k in (2, 3)])
    planes = np.ascontiguousarray(np.stack([columns[k][order] for k in (0, 1, 4, 5, 6, 7)]).view(np.uint8).reshape(6, n, 8).transpose(0, 2, 1))
    bucket = bucket_of(h, buckets)
    first = np.flatnonzero(np.r_[True, bucket[1:] != bucket[:-1]])
    press = zstandard.ZstdCompressor(level=1).compress
    rows: list[tuple] = []
    for a, b in zip(first.tolist(), [*first[1:].tolist(), n], strict=True):
        for lo in range(a, b, PACKED):
            hi = min(lo + PACKED, b)
            rows.append((int(bucket[lo]), hashed[:, lo:hi].tobytes(), press(planes[:, :, lo:hi].tobytes())))
            if len(rows) == 256:
                yield pa.RecordBatch.from_arrays([pa.array(x) for x in zip(*rows, strict=True)], names=["bucket", "hashed", "rest"])
                rows = []
    if rows:
        yield pa.RecordBatch.from_arrays([pa.array(x) for x in zip(*rows, strict=True)], names=["bucket", "hashed", "rest"])


def bucket_of(h: np.ndarray, buckets: int) -> np.ndarray:
    """Ranges of 48-bit hashes."""
    return (h.astype(np.uint64) >> np.uint64(16)) * np.uint64(buckets) >> np.uint64(32)


def unpacked(hashed: bytes, rest: bytes, expand: zstandard.ZstdDecompressor) -> list[np.ndarray]:
    """Columns h, np, a, b, doc, line, x0, x1 of a packed row."""
    a, b = np.frombuffer(hashed, np.int64).reshape(2, -1)
    n = len(a)
    planes = np.frombuffer(expand.decompress(rest), np.uint8).reshape(6, 8, n)
    h, np_, doc, line, x0, x1 = np.ascontiguousarray(planes.transpose(0, 2, 1)).view(np.int64).reshape(6, n)
    return [h, np_, a, b, doc, line, x0, x1]


def postings(rows: DataFrame, common: Common, twice: np.ndarray, buckets: int) -> DataFrame:
    """A posting per prefix word of every distinct line of a block, packed by ranges of the word's hash."""
    told = rows.sparkSession.sparkContext.broadcast((common, twice))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        known, table_of = told.value
        ready, size = [], 0
        for table in blocks(batches, limit=PART):
            for lines in lines_of(table):
                lines = lines.distinct()
                keep, pos = prefixes(lines, known)
                keep[keep] = held(table_of, slots(lines.hashes[keep]))
                of, x0, x1 = lines.of[keep], *lines.bitmaps()
                ready.append([lines.hashes[keep].view(np.int64), lines.n[of] << 32 | pos[keep], lines.a[of], lines.b[of], lines.doc[of], lines.line[of], x0[of], x1[of]])
                size += len(of)
                if size >= CHUNK:
                    yield from packed([np.concatenate(x) for x in zip(*ready, strict=True)], buckets)
                    ready, size = [], 0
        if size:
            yield from packed([np.concatenate(x) for x in zip(*ready, strict=True)], buckets)

    return rows.mapInArrow(run, "bucket long, hashed binary, rest binary")


def distinct(c: list[np.ndarray]) -> list[np.ndarray]:
    """Postings by word, length, signature; of equal ones that with the first place."""
    h, np_, a, b, doc, line = c[:6]
    coarse = h.astype(np.uint64) << np.uint64(16) | np.minimum(np_ >> 32, 0xFFFF).astype(np.uint64)
    order = np.lexsort((a, coarse))
    coarse, a, b = coarse[order], a[order], b[order]
    new = np.ones(len(h), bool)
    new[1:] = (coarse[1:] != coarse[:-1]) | (a[1:] != a[:-1]) | (b[1:] != b[:-1])
    if not new.all():
        group = np.cumsum(new)
        again = np.flatnonzero(~new | np.r_[~new[1:], False])
        mine = order[again]
        again = again[np.lexsort((line[mine], doc[mine], group[again]))]
        first = np.flatnonzero(np.r_[True, group[again][1:] != group[again][:-1]])
        chosen = order.copy()
        chosen[np.flatnonzero(new)[group[again[first]] - 1]] = order[again[first]]
        order = chosen[new]
    out = [x[order] for x in c]
    if (out[1] >> 32 >= 0xFFFF).any():  # lengths beyond what the order knows
        order = np.lexsort((out[1], out[0]))
        out = [x[order] for x in out]
    return out


def meet(c: list[np.ndarray], asked: np.ndarray | None = None) -> list[np.ndarray]:
    """Candidates (a1, b1, doc1, line1 of the later line; a2, b2, doc2, line2; partners the later line had) among postings as ``distinct`` gives them; all those of the asked lines, or a few of every line."""
    h, np_, a, b, doc, line, x0, x1 = c
    n, pos = np_ >> 32, np_ & 0xFFFFFFFF
    x0, x1 = x0.view(np.uint64), x1.view(np.uint64)  # of negative numbers numpy counts the bits of the amount
    at, later, earlier = np.arange(len(h)), [], []
    partners, best, nearest = np.zeros(len(h), np.int64), np.full(len(h), 1 << 30), np.full(len(h), -1)
    step = 0
    while True:
        step += 1
        at = at[at + step < len(h)]
        at = at[(h[at] == h[at + step]) & (DEN * n[at] >= NUM * n[at + step])]
        if not len(at):
            break
        of = at if asked is None else at[asked[at] | asked[at + step]]
        to = of + step
        need = -(-NUM * (n[of] + n[to]) // (NUM + DEN))
        room = np.minimum(n[of] - pos[of], n[to] - pos[to])
        apart = np.bitwise_count(x0[of] ^ x0[to]).astype(np.int64) + np.bitwise_count(x1[of] ^ x1[to])
        ok = (room >= need) & (apart <= n[of] + n[to] - 2 * need)
        if not ok.any():
            continue
        i, j, apart = of[ok], to[ok], apart[ok]
        forward = (doc[i] < doc[j]) | ((doc[i] == doc[j]) & (line[i] < line[j]))
        for late, early, d in ((j[forward], i[forward], apart[forward]), (i[~forward], j[~forward], apart[~forward])):
            few = partners[late] < MOST if asked is None else asked[late]
            later.append(late[few])
            earlier.append(early[few])
            partners[late] += 1
            closer = d < best[late]
            best[late[closer]], nearest[late[closer]] = d[closer], early[closer]
    some = np.flatnonzero(partners > MOST) if asked is None else np.zeros(0, np.int64)
    late, early = np.concatenate([some, *later]), np.concatenate([nearest[some], *earlier])
    return [x[k] for k in (late, early) for x in (a, b, doc, line)] + [partners[late]]


PAIR = ["a1", "b1", "doc1", "line1", "a2", "b2", "doc2", "line2", "partners"]


def candidates(posted: DataFrame, asked: np.ndarray | None = None) -> DataFrame:
    """Pairs of postings that pass; ``asked``: a bit table of the signatures whose partners are all wanted."""
    told = posted.sparkSession.sparkContext.broadcast(asked)

    def met(c: list[np.ndarray]) -> pa.RecordBatch:
        which = None if told.value is None else held(told.value, slots(_sig(c[2], c[3])))
        return pa.RecordBatch.from_arrays([pa.array(x) for x in meet(c, which)], names=PAIR)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        expand = zstandard.ZstdDecompressor()
        now, parts, size, limit = None, [], 0, CHUNK

        def whole() -> list[np.ndarray]:
            return distinct([np.concatenate(x) for x in zip(*parts, strict=True)])

        for batch in batches:
            for bucket, hashed, rest in zip(*(x.to_pylist() for x in batch.columns), strict=True):
                if parts and bucket != now:
                    yield met(whole())
                    parts, size, limit = [], 0, CHUNK
                now = bucket
                parts.append(unpacked(hashed, rest, expand))
                size += len(parts[-1][0])
                if size >= limit:  # copies of one line take room once
                    parts = [whole()]
                    size = len(parts[0][0])
                    limit = max(CHUNK, 2 * size)
        if parts:
            yield met(whole())

    dealt = posted.repartition("bucket").sortWithinPartitions("bucket")
    found = dealt.mapInArrow(run, ", ".join(f"{x} long" for x in PAIR))
    first, second = F.min(F.struct("doc1", "line1")), F.min(F.struct("doc2", "line2"))
    return found.groupBy("a1", "b1", "a2", "b2").agg(first.alias("p1"), second.alias("p2"), F.max("partners").alias("partners"))


def _place(doc: np.ndarray, line: np.ndarray) -> np.ndarray:
    return mix64(mix64(doc.astype(np.uint64)) + line.astype(np.uint64)) >> np.uint64(16)


def _text(doc: np.ndarray) -> np.ndarray:
    return mix64(doc.astype(np.uint64)) >> np.uint64(16)


def _sig(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    return mix64(a.view(np.uint64) ^ mix64(b.view(np.uint64))) >> np.uint64(16)


def wanted(places: DataFrame) -> tuple[np.ndarray, np.ndarray]:
    """Bit tables of the texts and of the lines in (doc, line)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            doc, line = batch.column(0).to_numpy(), batch.column(1).to_numpy()
            for kind, h in enumerate((_text(doc), _place(doc, line))):
                s = np.unique(slots(h))
                yield pa.RecordBatch.from_arrays([pa.array(np.full(len(s), kind, np.int32)), pa.array(s)], names=["kind", "slot"])

    bits = materialise(places.mapInArrow(run, "kind int, slot long").distinct(), "bits")
    return bit_table(bits.where("kind = 0")), bit_table(bits.where("kind = 1"))


def word_sets(rows: DataFrame, tables: tuple[np.ndarray, np.ndarray]) -> DataFrame:
    """(a, b, words: ordered hashes) of at least the wanted lines."""
    told = rows.sparkSession.sparkContext.broadcast(tables)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        texts_of, lines_of_ = told.value
        for table in blocks(batches, limit=PART):
            table = table.filter(pa.array(held(texts_of, slots(_text(table["doc"].to_numpy()))))).combine_chunks()
            if not table.num_rows:
                continue
            for lines in lines_of(table):
                lines = lines.only(held(lines_of_, slots(_place(lines.doc, lines.line))))
                if len(lines.n):
                    lines = lines.distinct()
                    yield pa.RecordBatch.from_arrays([pa.array(lines.a), pa.array(lines.b), lines.packed_words()], names=["a", "b", "words"])

    return rows.mapInArrow(run, "a long, b long, words binary").dropDuplicates(["a", "b"])


def binary_values(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """All 64-bit values of a column of packed lists, and how many each has."""
    ends = np.frombuffer(column.buffers()[1], np.int32)[column.offset : column.offset + len(column) + 1]
    return np.frombuffer(column.buffers()[2] or b"", np.uint8)[ends[0] : ends[-1]].view(np.uint64), np.diff(ends) // 8


def shared_words(left: pa.Array, right: pa.Array) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """How many words each pair shares, and the sizes of both sides."""
    (x, n), (y, m) = binary_values(left), binary_values(right)
    rows = np.arange(len(n), dtype=np.uint64) << PLACE
    key = np.sort(np.concatenate([np.repeat(rows, n) | x, np.repeat(rows, m) | y]))
    return np.bincount((key[1:][key[1:] == key[:-1]] >> PLACE).astype(np.int64), minlength=len(n)), n, m


def verified(both: DataFrame) -> DataFrame:
    """Pairs (a, b, doc1, line1, doc2, line2, partners, w1, w2) with ``holds`` in the place of words."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            if batch.num_rows:
                common, n, m = shared_words(batch.column("w1"), batch.column("w2"))
                yield pa.RecordBatch.from_arrays([*batch.columns[:7], pa.array((NUM + DEN) * common >= NUM * (n + m))], names=[*batch.schema.names[:7], "holds"])

    return both.mapInArrow(run, "a long, b long, doc1 long, line1 long, doc2 long, line2 long, partners long, holds boolean")


def partners_of(rows: DataFrame, counts: DataFrame) -> DataFrame:
    """(a, b, p): for every distinct word set that has an earlier partner, the place of one."""
    spark = rows.sparkSession
    counts = materialise(counts, "words")
    total = counts.where("h is null").agg(F.coalesce(F.sum("n"), F.lit(0))).first()[0]
    counts = counts.where("h is not null")
    often = counts.where(F.col("n") >= F.lit(max(2.0, total * RARE))).toPandas().astype({"h": np.int64, "n": np.int64})
    common = Common(often["h"].to_numpy().view(np.uint64), often["n"].to_numpy())
    twice = bit_table(counts.select(F.shiftright("h", 48 - BITS).alias("slot")))
    buckets = max(4 * int(spark.conf.get("spark.sql.shuffle.partitions")), -(-int(total) // BUCKET))
    told = materialise(answered(rows, candidates(postings(rows, common, twice, buckets))), "told")
    found = told.where("p is not null").select("a", "b", "p")
    open_ = told.where((F.col("p").isNull()) & (F.col("partners") > MOST)).select("a", "b", "own.*")
    if open_.isEmpty():
        return found
    words_of, sigs_of = asked_tables(open_.join(word_sets(rows, wanted(open_.select("doc1", "line1"))), ["a", "b"]), common)
    again = answered(rows, candidates(postings(rows, common, words_of, buckets), sigs_of))
    return found.unionByName(again.where("p is not null").select("a", "b", "p"))


def answered(rows: DataFrame, pairs: DataFrame) -> DataFrame:
    """(a, b, p: the first partner that holds or null, own: the place, partners) of the later lines of candidate pairs."""
    pairs = materialise(pairs, "pairs")
    places = pairs.select("p1.*").toDF("doc", "line").union(pairs.select("p2.*").toDF("doc", "line"))
    sets = materialise(word_sets(rows, wanted(places)), "sets")
    one_, two = (sets.select(F.col("a").alias(f"s{k}"), F.col("b").alias(f"t{k}"), F.col("words").alias(f"w{k}")) for k in (1, 2))
    both = pairs.join(one_, (F.col("a1") == F.col("s1")) & (F.col("b1") == F.col("t1"))).join(two, (F.col("a2") == F.col("s2")) & (F.col("b2") == F.col("t2")))
    told = verified(both.select(F.col("a1").alias("a"), F.col("b1").alias("b"), "p1.doc1", "p1.line1", "p2.doc2", "p2.line2", "partners", "w1", "w2"))
    return told.groupBy("a", "b").agg(F.min(F.when(F.col("holds"), F.struct("doc2", "line2"))).alias("p"), F.min(F.struct("doc1", "line1")).alias("own"), F.max("partners").alias("partners"))


def asked_tables(asked: DataFrame, common: Common) -> tuple[np.ndarray, np.ndarray]:
    """Bit tables of the prefix words and of the signatures of (a, b, words)."""
    told = asked.sparkSession.sparkContext.broadcast(common)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            if batch.num_rows:
                words, n = binary_values(batch.column("words"))
                zero = np.zeros(len(n), np.int64)
                lines = Lines(zero, zero, zero, words, n)
                keep, _ = prefixes(lines, told.value)
                sig = _sig(batch.column("a").to_numpy(), batch.column("b").to_numpy())
                for kind, h in enumerate((lines.hashes[keep], sig)):
                    s = np.unique(slots(h))
                    yield pa.RecordBatch.from_arrays([pa.array(np.full(len(s), kind, np.int32)), pa.array(s)], names=["kind", "slot"])

    bits = materialise(asked.select("a", "b", "words").mapInArrow(run, "kind int, slot long").distinct(), "asked")
    return bit_table(bits.where("kind = 0")), bit_table(bits.where("kind = 1"))


def removals(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc, version, removed: ordered line numbers) of texts that lose a line."""
    bound_batches(docs.sparkSession)
    rows = docs.select(F.coalesce(F.col(id_col).cast("long"), F.lit(FIRST)).alias("doc"), F.xxhash64(F.col(text_col).cast("string")).alias("version"), F.col(text_col).cast("string").alias("text"))
    counts, found = survey(rows)
    near = partners_of(rows, counts).groupBy("a", "b").agg(F.min(F.struct(F.col("p.doc2").alias("doc"), F.col("p.line2").alias("line"))).alias("near"))
    first = found.groupBy("a", "b").agg(F.min(F.struct("doc", "line")).alias("first"), F.count("*").alias("times")).join(near, ["a", "b"], "left")
    first = first.where((F.col("times") > 1) | F.col("near").isNotNull())
    # written, so that the join below deals both sides anew and splits a line that is everywhere
    first = materialise(first.select(F.col("a").alias("a0"), F.col("b").alias("b0"), F.least("first", "near").alias("since")), "firsts")
    late = found.join(first, (F.col("a") == F.col("a0")) & (F.col("b") == F.col("b0"))).where(F.struct("doc", "line") > F.col("since"))
    return late.groupBy("doc", "version").agg(F.array_sort(F.collect_set("line")).alias("removed"))


def _with_removals(docs: DataFrame, id_col: str, text_col: str) -> DataFrame:
    gone = removals(docs, id_col, text_col)
    keyed = docs.withColumns({"__doc": F.coalesce(F.col(id_col).cast("long"), F.lit(FIRST)), "__version": F.xxhash64(F.col(text_col).cast("string"))})
    return keyed.join(gone, (F.col("__doc") == F.col("doc")) & (F.col("__version") == F.col("version")), "left")


@F.pandas_udf(StringType())
def without_lines(text: pd.Series, removed: pd.Series) -> pd.Series:
    """A text without the lines of the given numbers (null: no text)."""
    out = []
    for t, gone in zip(text, removed, strict=True):
        if t is not None and gone is not None:
            gone = set(gone.tolist())
            t = "\n".join([x for k, x in enumerate(t.split("\n")) if k not in gone])
        out.append(t)
    return pd.Series(out, dtype=object)


def deduplicated(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``docs`` without later matching lines; all columns stay."""
    inner = docs.select(F.struct("*").alias("__row"), F.col(id_col).alias("__id"), F.col(text_col).cast("string").alias("__text"))
    left = without_lines(F.when(F.col("removed").isNotNull(), F.col("__text")), F.col("removed"))
    text = F.when(F.col("removed").isNull(), F.col("__text")).otherwise(left)
    out = _with_removals(inner, "__id", "__text")
    return out.select(*[(text if c == text_col else F.col("__row")[c]).alias(c) for c in docs.columns])


def line_report(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(id, n_lines, n_removed, removed) for every row; removed: line numbers from 0, comma-joined."""
    narrow = docs.select(F.col(id_col).cast("long").alias("__id"), F.xxhash64(F.col(text_col).cast("string")).alias("__version"), (F.length(F.coalesce(F.col(text_col).cast("string"), F.lit(""))) - F.length(F.replace(F.coalesce(F.col(text_col).cast("string"), F.lit("")), F.lit("\n"), F.lit(""))) + 1).cast("long").alias("n_lines"))
    gone = removals(docs, id_col, text_col)
    out = narrow.join(gone, (F.coalesce("__id", F.lit(FIRST)) == F.col("doc")) & (F.col("__version") == F.col("version")), "left")
    return out.select(F.col("__id").alias(id_col), "n_lines", F.coalesce(F.size("removed"), F.lit(0)).cast("long").alias("n_removed"), F.concat_ws(",", F.col("removed").cast("array<string>")).alias("removed"))


def op1_line_dedup(spark, sf_dir: str) -> DataFrame:
    return line_report(spark.read.parquet(f"{sf_dir}/documents.parquet"))
