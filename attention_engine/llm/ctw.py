"""Context-tree weighting over the bytes of texts.

A text is sent as its words, lower-cased, each with a closing blank, and a line feed as
its end. Each byte is sent as eight binary decisions. For every context of the last 0 to
``DEPTH`` bytes (they reach back over words; a text begins after a blank) and every
decision a Krichevsky-Trofimov estimator holds the two counts of the training part, and
the estimators of all depths are mixed with the weights of context-tree weighting. A
context that was never seen leaves its weight to the one it extends.

Texts are dealt into blocks. A block asks for each of its distinct words and (context,
byte) keys once, in packed lists dealt into buckets, so what is hot costs an entry per
block. Words meet by their hash, keys by the last three bytes of their contexts; there they
are summed and the code lengths computed. What lies above (at most 2**16 contexts of 255
decisions) is summed and sent back. The answers return to the blocks, which are read again
from the shared folder. Buckets follow the number of input partitions, lists are merged as
they come, and a bucket holds its distinct entries only.

Defined cases: null or empty text is the end token alone; a null id counts as an empty
string when the training part is chosen; repeated rows are scored and learnt each; without
training tokens every decision has probability one half; an empty table gives an empty
result; only id and text are read, so further columns can't clash.
"""

from __future__ import annotations

import math
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import zstandard
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import blocks, bound_batches, byte_list, fresh_path, intern, materialise, mix64, one

DEPTH = 5
#: Depth by which contexts are dealt out; those above are few.
TOP = 3
END = b"\n"
#: What stands before a text, so that all contexts are full.
LEAD = b"\0" * (DEPTH - 1) + b" "
BLOCK = 32 << 20
#: (context, byte) keys worked on together, and stream positions worked on together.
RUN, STEP = 120_000, 1 << 22
LOG2 = math.log(2)


def held_out(doc_id: int | None, folds: int = 7, fold: int = 2) -> bool:
    return zlib.crc32(b"" if doc_id is None else str(doc_id).encode()) % folds == fold


def _starts(sorted_values: np.ndarray) -> np.ndarray:
    return np.flatnonzero(np.r_[True, sorted_values[1:] != sorted_values[:-1]]) if len(sorted_values) else np.zeros(0, np.int64)


def _pack(data: bytes) -> bytes:
    return zstandard.compress(data, 1)


def _unpack(data: bytes) -> bytes:
    return zstandard.decompress(data)


def pack_words(words: list[bytes]) -> bytes:
    return _pack(b" ".join(words))


def unpack_words(data: bytes) -> list[bytes]:
    return _unpack(data).split(b" ")


def pack_keys(keys: np.ndarray) -> bytes:
    """Ordered keys by their differences."""
    return _pack(np.diff(keys, prepend=0).tobytes())


def unpack_keys(data: bytes) -> np.ndarray:
    return np.cumsum(np.frombuffer(_unpack(data), np.int64))


def pack_values(values: np.ndarray) -> bytes:
    return _pack(values.tobytes())


def stream(texts: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
    """The bytes sent for all texts, each after LEAD, and the places of those that are sent."""
    data = np.frombuffer(b"".join([x for t in texts for x in (LEAD, t, END)]), np.uint8)
    sizes = np.fromiter(map(len, texts), np.int64, len(texts)) + len(LEAD) + 1
    sent = np.ones(len(data), bool)
    starts = np.cumsum(sizes) - sizes
    for k in range(len(LEAD)):
        sent[starts + k] = False
    return data, np.flatnonzero(sent)


def keys_at(data: np.ndarray, at: np.ndarray, depth: int = DEPTH) -> np.ndarray:
    """The context of each place, latest byte highest, and the byte itself lowest."""
    key = data[at].astype(np.int64)
    for k in range(1, depth + 1):
        key |= data[at - k].astype(np.int64) << 8 * (depth + 1 - k)
    return key


def distinct_keys(texts: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
    """Ordered distinct keys of some texts, with their times."""
    data, at = stream(texts)
    key, n = np.zeros(0, np.int64), np.zeros(0, np.int64)
    for a in range(0, len(at), STEP):
        more = np.sort(keys_at(data, at[a : a + STEP]))
        first = _starts(more)
        key, n = merge_keys(key, n, more[first], np.diff(np.r_[first, len(more)]))
    return key, n


def merge_keys(key: np.ndarray, n: np.ndarray, more: np.ndarray, m: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """The union of two ordered lists, with the sums of their times."""
    both = np.concatenate([key, more])
    order = np.argsort(both, kind="stable")
    both, sums = both[order], np.concatenate([n, m])[order]
    first = _starts(both)
    return both[first], (np.add.reduceat(sums, first) if len(first) else sums)


LISTS = "kind int, block long, bucket int, id long, out boolean, data binary, times binary"
TEXT, WORDS, KEYS, TABLE = 0, 1, 2, -1


def asked(docs: DataFrame, buckets: int) -> DataFrame:
    """From (id, text): rows of TEXT (words lower-cased, a blank after each) and, by block and bucket, lists of distinct WORDS and KEYS with their times in the training part."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        def rows(kind: int, block: int, bucket: list, ids: pa.Array, out: list, data: list, times: list) -> pa.RecordBatch:
            k = len(data)
            return pa.RecordBatch.from_arrays([pa.array([kind] * k, pa.int32()), pa.array([block] * k), pa.array(bucket, pa.int32()), ids, pa.array(out, pa.bool_()), pa.array(data, pa.binary()), pa.array(times, pa.binary())], names=["kind", "block", "bucket", "id", "out", "data", "times"])

        for number, table in enumerate(blocks(batches, limit=BLOCK)):
            block, ids = TaskContext.get().partitionId() << 32 | number, one(table["id"])
            out = [held_out(i) for i in ids.to_pylist()]
            texts = [b" ".join([*t.lower().split(), b""]) for t in byte_list(one(table["text"]))]
            for a in range(0, len(texts), 1000):
                part = texts[a : a + 1000]
                yield rows(TEXT, block, [None] * len(part), ids.slice(a, 1000), out[a : a + 1000], part, [None] * len(part))
            vocabulary: dict[bytes, int] = {END: 0}
            train = [np.zeros(1, np.int64)]
            for t, o in zip(texts, out, strict=True):
                got = intern(t.split(), vocabulary)
                if not o:
                    train.append(got.astype(np.int32))
            n = np.bincount(np.concatenate(train), minlength=len(vocabulary))
            n[0] = len(train) - 1
            split: dict[int, tuple[list, list]] = {}
            for w, c in zip(vocabulary, n.tolist(), strict=True):
                words, times = split.setdefault(zlib.crc32(w) % buckets, ([], []))
                words.append(w)
                times.append(c)
            del vocabulary, train
            none = pa.nulls(len(split), pa.int64())
            yield rows(WORDS, block, list(split), none, [None] * len(split), [pack_words(w) for w, _ in split.values()], [pack_values(np.array(c, np.int64)) for _, c in split.values()])
            del split
            key, n = distinct_keys([t for t, o in zip(texts, out, strict=True) if not o])
            other, m = distinct_keys([t for t, o in zip(texts, out, strict=True) if o])
            key, n = merge_keys(key, n, other, 0 * m)
            bucket = (mix64(key >> 8 * (DEPTH + 1 - TOP)) % np.uint64(buckets)).astype(np.int64)
            found = np.unique(bucket).tolist()
            parts = [bucket == b for b in found]
            yield rows(KEYS, block, found, pa.nulls(len(found), pa.int64()), [None] * len(found), [pack_keys(key[p]) for p in parts], [pack_values(n[p]) for p in parts])

    return docs.mapInArrow(run, LISTS)


def _dealt(lists: DataFrame, buckets: int) -> DataFrame:
    return lists.select("bucket", "kind", "block", "data", "times").repartition(buckets, "bucket").sortWithinPartitions("bucket", "kind")


def _lists(batches: Iterator[pa.RecordBatch]) -> Iterator[tuple]:
    for batch in batches:
        yield from zip(*(c.to_pylist() for c in batch.columns), strict=True)


def merged_words(lists: DataFrame, buckets: int) -> DataFrame:
    """(bucket, data, times, n, kinds): all words of a bucket with their times."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        def done(bucket: int, held: dict) -> pa.RecordBatch:
            n = np.fromiter(held.values(), np.int64, len(held))
            return pa.RecordBatch.from_pylist([{"bucket": bucket, "data": pack_words(list(held)), "times": pack_values(n), "n": int(n.sum()), "kinds": int((n > 0).sum())}], schema=pa.schema([("bucket", pa.int32()), ("data", pa.binary()), ("times", pa.binary()), ("n", pa.int64()), ("kinds", pa.int64())]))

        now, held = None, {}
        for bucket, _, _, data, times in _lists(batches):
            if bucket != now:
                if held:
                    yield done(now, held)
                now, held = bucket, {}
            for w, c in zip(unpack_words(data), np.frombuffer(_unpack(times), np.int64).tolist(), strict=True):
                held[w] = held.get(w, 0) + c
        if held:
            yield done(now, held)

    return _dealt(lists, buckets).mapInArrow(run, "bucket int, data binary, times binary, n long, kinds long")


def merged_keys(lists: DataFrame, buckets: int) -> DataFrame:
    """(bucket, data, times): all keys of a bucket with their times."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        empty = np.zeros(0, np.int64)
        now, key, n = None, empty, empty
        waiting: list[tuple[np.ndarray, np.ndarray]] = []

        def done() -> pa.RecordBatch:
            return pa.RecordBatch.from_arrays([pa.array([now], pa.int32()), pa.array([pack_keys(key)], pa.binary()), pa.array([pack_values(n)], pa.binary())], names=["bucket", "data", "times"])

        def fold() -> None:
            nonlocal key, n
            if waiting:
                key, n = merge_keys(key, n, *merge_keys(np.concatenate([k for k, _ in waiting]), np.concatenate([m for _, m in waiting]), empty, empty))
                waiting.clear()

        for bucket, _, _, data, times in _lists(batches):
            if bucket != now:
                fold()
                if len(key):
                    yield done()
                now, key, n = bucket, empty, empty
            waiting.append((unpack_keys(data), np.frombuffer(_unpack(times), np.int64)))
            if sum(len(k) for k, _ in waiting) > max(1 << 20, len(key)):
                fold()
        fold()
        if len(key):
            yield done()

    return _dealt(lists, buckets).mapInArrow(run, "bucket int, data binary, times binary")


_SMALL = np.array([math.lgamma(k + 0.5) for k in range(256)])
_FACTORIAL = np.array([math.lgamma(k + 1.0) for k in range(256)])


def _lgamma(n: np.ndarray, shift: float, table: np.ndarray) -> np.ndarray:
    """Log gamma of n + shift, by Stirling's series above the table."""
    x = np.maximum(n + shift, 200.0)
    far = (x - 0.5) * np.log(x) - x + 0.5 * math.log(2 * math.pi) + 1 / (12 * x) - 1 / (360 * x**3)
    return np.where(n < 256, table[np.minimum(n, 255)], far)


def log_kt(zeros: np.ndarray, ones: np.ndarray) -> np.ndarray:
    """Log of the probability that the estimator gives to any order of so many zeros and ones."""
    return _lgamma(zeros, 0.5, _SMALL) + _lgamma(ones, 0.5, _SMALL) - math.log(math.pi) - _lgamma(zeros + ones, 1.0, _FACTORIAL)


class Level:
    """The decisions of all contexts of one depth, ordered by (context, place among the 255 decisions of a byte)."""

    def __init__(self, key: np.ndarray, zeros: np.ndarray, ones: np.ndarray) -> None:
        self.key, self.zeros, self.ones = key, zeros, ones
        self.kt = log_kt(zeros, ones)
        self.mixed = self.kt

    def below(self, parents: np.ndarray, logs: np.ndarray) -> None:
        """Mix with the contexts that extend these by a byte."""
        sums = np.bincount(np.searchsorted(self.key, parents), logs, len(self.key))
        self.mixed = np.logaddexp(self.kt, sums) - LOG2

    def parents(self) -> np.ndarray:
        return self.key >> 16 << 8 | self.key & 255

    def predict(self, key: np.ndarray, bit: np.ndarray, deeper: np.ndarray) -> np.ndarray:
        """Probability of ``bit``, given what deeper contexts say (NaN: none of them was seen)."""
        if not len(self.key):
            return deeper
        at = np.minimum(np.searchsorted(self.key, key), len(self.key) - 1)
        own = (np.where(bit, self.ones[at], self.zeros[at]) + 0.5) / (self.zeros[at] + self.ones[at] + 1)
        stop = np.exp(np.minimum(self.kt[at] - LOG2 - self.mixed[at], 0))
        out = np.where(np.isnan(deeper), own, stop * own + (1 - stop) * deeper)
        return np.where(self.key[at] == key, out, deeper)


def _decisions(context: np.ndarray, byte: np.ndarray, n: np.ndarray) -> Level:
    """The level of these (context, byte) counts, ordered and distinct."""
    keys, zeros, ones = [], [], []
    for j in range(8):
        node = context << 8 | 1 << j | byte >> 8 - j
        first = _starts(node)
        bit = byte >> 7 - j & 1
        keys.append(node[first])
        zeros.append(np.add.reduceat(n * (1 - bit), first))
        ones.append(np.add.reduceat(n * bit, first))
    key = np.concatenate(keys)
    order = np.argsort(key, kind="stable")
    return Level(key[order], np.concatenate(zeros)[order], np.concatenate(ones)[order])


def levels(key: np.ndarray, n: np.ndarray, low: int = TOP, depth: int = DEPTH) -> dict[int, Level]:
    """Levels from ``depth`` up to ``low``, mixed from below."""
    key, n = key[n > 0], n[n > 0]
    out: dict[int, Level] = {}
    if not len(key):
        return {d: Level(*(np.zeros(0, np.int64),) * 3) for d in range(low, depth + 1)}
    for d in range(depth, low - 1, -1):
        code = key >> 8 * (depth + 1 - d) << 8 | key & 255
        order = np.argsort(code, kind="stable")
        code = code[order]
        first = _starts(code)
        out[d] = _decisions(code[first] >> 8, code[first] & 255, np.add.reduceat(n[order], first))
        if d < depth:
            out[d].below(out[d + 1].parents(), out[d + 1].mixed)
    return out


def _runs(batches: Iterator[pa.RecordBatch]) -> Iterator[tuple[int, np.ndarray, np.ndarray]]:
    """(bucket, keys, times) of merged keys, cut only where the context's first bytes change."""
    prefix = 8 * (DEPTH + 1 - TOP)
    for batch in batches:
        for bucket, data, times in zip(*(c.to_pylist() for c in batch.columns), strict=True):
            key, n = unpack_keys(data), np.frombuffer(_unpack(times), np.int64)
            a = 0
            while a < len(key):
                b = len(key)
                if b - a > RUN:  # the last key of the run decides where its context ends
                    b = int(np.searchsorted(key, ((key[a + RUN] >> prefix) + 1) << prefix))
                yield bucket, key[a:b], n[a:b]
                a = b


def top_levels(rows: DataFrame) -> dict[int, Level]:
    """The levels above TOP, from the sums of what lies below them."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for _, key, n in _runs(batches):
            low = levels(key, n)[TOP]
            parent = low.parents()
            order = np.argsort(parent, kind="stable")
            parent = parent[order]
            at = _starts(parent)
            sums = [np.add.reduceat(x[order], at) if len(at) else x for x in (low.zeros, low.ones, low.mixed)]
            yield pa.RecordBatch.from_arrays([pa.array(parent[at]), *map(pa.array, sums)], names=["key", "zeros", "ones", "logs"])

    found = rows.mapInArrow(run, "key long, zeros long, ones long, logs double").groupBy("key").agg(*(F.sum(x).alias(x) for x in ("zeros", "ones", "logs"))).toPandas().sort_values("key")
    out, key, logs = {}, found["key"].to_numpy(np.int64), found["logs"].to_numpy(float)
    zeros, ones = found["zeros"].to_numpy(np.int64), found["ones"].to_numpy(np.int64)
    for d in range(TOP - 1, -1, -1):
        out[d] = Level(key, zeros, ones)
        if len(key):
            out[d].mixed = np.logaddexp(out[d].kt, logs) - LOG2
            parent = out[d].parents()
            key, at = np.unique(parent, return_inverse=True)
            zeros, ones = (np.bincount(at, x).astype(np.int64) for x in (zeros, ones))
            logs = np.bincount(at, out[d].mixed)
    return out


def key_logs(key: np.ndarray, n: np.ndarray, top: dict[int, Level]) -> np.ndarray:
    """Log10 of the probability of each key's byte in its context."""
    all_levels = top | levels(key, n)
    byte, total = key & 255, np.zeros(len(key))
    for j in range(8):
        p, bit = np.full(len(key), np.nan), (byte >> 7 - j & 1).astype(bool)
        for d in range(DEPTH, -1, -1):
            p = all_levels[d].predict((key >> 8 * (DEPTH + 1 - d)) << 8 | 1 << j | byte >> 8 - j, bit, p)
        total += np.log10(np.where(np.isnan(p), 0.5, p))
    return total


def key_log_table(keys: DataFrame) -> DataFrame:
    """(kind, bucket, data, times): the keys' code lengths in the place of their times."""
    top = keys.sparkSession.sparkContext.broadcast(top_levels(keys.select("bucket", "data", "times")))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for bucket, key, n in _runs(batches):
            yield pa.RecordBatch.from_arrays([pa.array([bucket], pa.int32()), pa.array([pack_keys(key)], pa.binary()), pa.array([pack_values(key_logs(key, n, top.value))], pa.binary())], names=["bucket", "data", "times"])

    return keys.select("bucket", "data", "times").mapInArrow(run, "bucket int, data binary, times binary")


def answers(lists: DataFrame, tables: DataFrame, buckets: int, kind: int) -> DataFrame:
    """(kind, block, data, times): the blocks' lists with the values that the tables hold."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        now, table, parts = None, None, []
        for bucket, which, block, data, times in _lists(batches):
            if bucket != now:
                now, table, parts = bucket, None, []
            if which == TABLE:
                parts.append((unpack_words(data), np.frombuffer(_unpack(times), np.int64).tolist()) if kind == WORDS else (unpack_keys(data), np.frombuffer(_unpack(times))))
                continue
            if table is None:
                table = {w: c for p in parts for w, c in zip(*p, strict=True)} if kind == WORDS else Table(*(np.concatenate(x) for x in zip(*parts, strict=True)))
                parts = []
            if kind == WORDS:
                got = np.fromiter(map(table.__getitem__, unpack_words(data)), np.int64)
            else:
                got = table.get(unpack_keys(data))
            yield pa.RecordBatch.from_arrays([pa.array([kind], pa.int32()), pa.array([block]), pa.array([data], pa.binary()), pa.array([pack_values(got)], pa.binary())], names=["kind", "block", "data", "times"])

    told = tables.select("bucket", F.lit(TABLE).alias("kind"), F.lit(None).cast("long").alias("block"), "data", "times")
    both = told.union(lists.select("bucket", "kind", "block", "data", "times"))
    return _dealt(both, buckets).mapInArrow(run, "kind int, block long, data binary, times binary")


class Table:
    """Values by 64-bit key, with linear probing over whole arrays."""

    def __init__(self, keys: np.ndarray, values: np.ndarray) -> None:
        self.bits = max(4, int(2 * len(keys)).bit_length())
        self.keys, self.values = np.full(1 << self.bits, -1, np.int64), np.zeros(1 << self.bits)
        left, slot = np.arange(len(keys)), self._slot(keys)
        while len(left):
            free = self.keys[slot] == -1
            self.keys[slot[free]] = keys[left[free]]
            self.values[slot[free]] = values[left[free]]
            again = self.keys[slot] != keys[left]
            left, slot = left[again], slot[again] + 1 & (1 << self.bits) - 1

    def _slot(self, keys: np.ndarray) -> np.ndarray:
        return (keys.astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15) >> np.uint64(64 - self.bits)).astype(np.int64)

    def get(self, keys: np.ndarray) -> np.ndarray:
        slot = self._slot(keys)
        missed = np.flatnonzero(self.keys[slot] != keys)
        while len(missed):
            slot[missed] = slot[missed] + 1 & (1 << self.bits) - 1
            missed = missed[self.keys[slot[missed]] != keys[missed]]
        return self.values[slot]


def answered(texts: DataFrame, got: list[DataFrame], total: int, kinds: int) -> DataFrame:
    """Scores of all texts, from a block's texts and the answers to its lists."""

    def run(table: pa.Table) -> pa.Table:
        kind = table["kind"].to_numpy()
        text, words, keys = (table.filter(pa.array(kind == k)) for k in (TEXT, WORDS, KEYS))
        del table
        vocabulary = {w: i for i, w in enumerate(w for x in words["data"].to_pylist() for w in unpack_words(x))}
        count = np.concatenate([np.frombuffer(_unpack(x), np.int64) for x in words["times"].to_pylist()])
        base = np.log10((count + 1) / (total + kinds + 1))
        logs = Table(np.concatenate([unpack_keys(x) for x in keys["data"].to_pylist()]), np.concatenate([np.frombuffer(_unpack(x)) for x in keys["times"].to_pylist()]))
        end, rows = vocabulary[END], []
        for batch in text.to_batches():
            for t in batch.column("data"):
                t = t.as_py()
                ids = np.fromiter(map(vocabulary.__getitem__, t.split()), np.int64)
                data, places = stream([t])
                score = sum(float(logs.get(keys_at(data, places[a : a + STEP])).sum()) for a in range(0, len(places), STEP))
                rows.append((len(ids) + 1, int((count[ids] > 0).sum() + (count[end] > 0)), float(base[ids].sum() + base[end]), score, len(places)))
        n, known, low, high, size = zip(*rows, strict=True) if rows else ((),) * 5
        bits = [-x * math.log2(10) / k for x, k in zip(high, size, strict=True)]
        return pa.table([text["id"], text["out"], pa.array(n, pa.int64()), pa.array(known, pa.int64()), pa.array([total] * len(n), pa.int64()), pa.array(low, pa.float64()), pa.array(high, pa.float64()), pa.array(size, pa.int64()), pa.array(bits, pa.float64())], names=["id", "held_out", "n_tokens", "n_known", "train_tokens", "base_score", "score", "n_bytes", "bits_per_byte"])

    rows = texts.select("block", "kind", "id", "out", "data", F.lit(None).cast("binary").alias("times"))
    for part in got:
        rows = rows.union(part.select("block", "kind", F.lit(None).cast("long"), F.lit(None).cast("boolean"), "data", "times"))
    return rows.groupBy("block").applyInArrow(run, "id long, held_out boolean, n_tokens long, n_known long, train_tokens long, base_score double, score double, n_bytes long, bits_per_byte double")


def score(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Base and model scores of every row, and the code length per byte sent (words with a closing blank each, and the end); the model learns from rows that aren't held out."""
    spark = docs.sparkSession
    bound_batches(spark)
    rows = docs.select(F.col(id_col).cast("long").alias("id"), F.col(text_col).cast("string").alias("text"))
    buckets = max(8, 2 * rows.rdd.getNumPartitions())
    path = fresh_path(spark, "lm")
    asked(rows, buckets).write.option("compression", "zstd").partitionBy("kind").parquet(path)
    all_rows = spark.read.schema(LISTS).parquet(path)
    texts, words, keys = (all_rows.where(F.col("kind") == k) for k in (TEXT, WORDS, KEYS))
    known = materialise(merged_words(words, buckets), "words")
    total, kinds = known.agg(F.coalesce(F.sum("n"), F.lit(0)), F.coalesce(F.sum("kinds"), F.lit(0))).first()
    logs = key_log_table(materialise(merged_keys(keys, buckets), "keys"))
    got = [answers(words, known, buckets, WORDS), answers(keys, logs, buckets, KEYS)]
    return answered(texts, got, int(total), int(kinds)).withColumnRenamed("id", id_col)


def op7_lm_scoring(spark, sf_dir: str) -> DataFrame:
    return score(spark.read.parquet(f"{sf_dir}/documents.parquet"))


