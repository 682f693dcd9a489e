"""Secret scans with an incremental ledger of blobs, in DataFrame functions only.

Every version of a text is a blob named by its SHA-256. The ledger holds (blob, rule
version) with the findings; only pairs it lacks are scanned, one text per blob, and the
findings are joined back to all ids that have the blob. A rule is changed by giving its set
a new version. ``scan`` takes a ledger and returns the new entries with the answer, so a
caller keeps it by appending those to a table.

Spans are found without Python: a text's matches and what stands between them become a row
each, and running sums of their lengths give starts and ends, in code points, end exclusive. Beside the base
kinds assign, access and hex there are pem, jwt and pat (private keys, signed tokens and
personal access tokens of known forms).

Defined cases: null text is an empty text and has no findings; repeated rows and copies are
scanned once and answered each; null ids are kept; an empty table gives an empty result;
only the two named columns are read, so further columns can't clash.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import materialise

RULE_VERSION = "1"
#: Fixed patterns: kind, pattern, and what a match must fit besides.
KINDS = [
    ("assign", r"""(?i:(?:password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?[A-Za-z0-9+/_.=-]+)""", r"""(?is)^(?:password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?[A-Za-z0-9+/_.=-]{12,}$"""),
    ("access", r"AKIA[A-Z0-9]{14,}", None),
    ("hex", r"[0-9a-f]{16,}", None),
    ("pem", r"-----BEGIN [A-Z ]{0,40}PRIVATE KEY-----", None),
    ("jwt", r"eyJ[A-Za-z0-9_-]{8,}\.eyJ[A-Za-z0-9_-]{8,}\.[A-Za-z0-9_-]{8,}", None),
    ("pat", r"(?:ghp|gho|ghs)_[A-Za-z0-9]{36,}", None),
]
BASE = 3


def matches_of(text: Column, number: int, pattern: str, fits: str | None) -> Column:
    """(kind, pos, gap, size, fits) of the leftmost non-overlapping matches: the lengths of what stands before each and of itself."""
    found = F.regexp_extract_all(text, F.lit(pattern), F.lit(0))
    gaps = F.slice(F.split(text, pattern, -1), 1, F.size(found))
    pairs = F.zip_with(gaps, found, lambda g, m: F.struct(F.length(g).alias("gap"), F.length(m).alias("size"), (F.lit(True) if fits is None else F.regexp_like(m, F.lit(fits))).alias("fits")))
    rows = F.transform(pairs, lambda p, i: F.struct(F.lit(number).alias("kind"), i.alias("pos"), p["gap"].alias("gap"), p["size"].alias("size"), p["fits"].alias("fits")))
    return F.when(F.size(found) > 0, rows)  # most texts are looked through once and never split


def spans_of(texts: DataFrame, kinds: list[tuple]) -> DataFrame:
    """(blob, spans: ordered (start, kind, end)) of the texts (blob, text) that have a span."""
    rows = texts.select("blob", F.explode(F.flatten(F.array_compact(F.array(*[matches_of(F.col("text"), n, p, f) for n, (_, p, f) in enumerate(kinds)])))).alias("m")).select("blob", "m.*").distinct()
    before = F.sum(F.col("gap") + F.col("size")).over(Window.partitionBy("blob", "kind").orderBy("pos").rowsBetween(Window.unboundedPreceding, -1))
    start = (F.coalesce(before, F.lit(0)) + F.col("gap")).cast("int")
    rows = rows.select("blob", start.alias("start"), "kind", (start + F.col("size")).alias("end"), "fits").where("fits")
    return rows.groupBy("blob").agg(F.array_sort(F.collect_list(F.struct("start", "kind", "end"))).alias("spans"))


def joined(spans: Column, kinds: list[tuple]) -> Column:
    names = F.array(*[F.lit(k) for k, _, _ in kinds])
    return F.concat_ws(",", F.transform(spans, lambda s: F.concat_ws(":", F.element_at(names, s["kind"] + 1), s["start"], s["end"])))


def scan(docs: DataFrame, ledger: DataFrame | None = None, id_col: str = "doc_id", text_col: str = "text", version: str = RULE_VERSION, kinds: list[tuple] = KINDS) -> tuple[DataFrame, DataFrame]:
    """(a row per row of ``docs``; the entries that the ledger lacked). ``kinds`` belong to the version; the first three are the base ones."""
    text = F.coalesce(F.col(text_col).cast("string"), F.lit(""))
    rows = docs.select(F.col(id_col).alias("id"), text.alias("text"), F.sha2(F.encode(text, "UTF-8"), 256).alias("blob"))
    versions = materialise(rows.select("id", "blob"), "blobs")
    blobs = versions.groupBy("blob").agg(F.min("id").alias("keeper"))
    if ledger is not None:
        seen = ledger.where(F.col("rule_version") == version)
        blobs = blobs.join(seen.select("blob"), "blob", "left_anti")
    todo = blobs.select(F.col("blob").alias("b"), "keeper").hint("shuffle_hash")
    texts = rows.join(todo, (F.col("blob") == F.col("b")) & F.col("id").eqNullSafe(F.col("keeper"))).select("blob", "text")
    found = spans_of(texts, kinds)

    def of_kind(n: int) -> Column:
        return F.size(F.filter("spans", lambda x: x["kind"] == n)).cast("long")

    counts = [of_kind(n).alias(f"n_{k}") for n, (k, _, _) in enumerate(kinds[:BASE])]
    entries = found.select("blob", *counts, joined(F.filter("spans", lambda x: x["kind"] < BASE), kinds).alias("base_spans"), joined(F.col("spans"), kinds).alias("spans"))
    entries = materialise(entries, "findings")
    fresh = blobs.select("blob", F.lit(version).alias("rule_version")).join(entries, "blob", "left")
    known = entries if ledger is None else entries.unionByName(seen.where("spans is not null").select(entries.columns))
    out = versions.join(known, "blob", "left")
    counts = [F.coalesce(f"n_{k}", F.lit(0).cast("long")).alias(f"n_{k}") for k, _, _ in kinds[:BASE]]
    return out.select(F.col("id").alias(id_col), *counts, F.sha2(F.coalesce("base_spans", F.lit("")), 256).alias("base_sha256"), F.coalesce("spans", F.lit("")).alias("spans")), fresh


def op9_secret_scans(spark, sf_dir: str) -> DataFrame:
    return scan(spark.read.parquet(f"{sf_dir}/documents.parquet"))[0]
