"""Language identification by fusing evidence in Bayes' rule.

The posterior of a language is proportional to the product of
  - the likelihood of the text's words under the language's byte trigram model, tempered
    by ``TEMPER`` because neighbouring bytes aren't independent,
  - the likelihood of the declared markup language (``<html lang=...>``) and of the last
    label of the address, given the language, smoothed, and
  - the prior of the host, smoothed towards its domain and that towards all rows.
Models come from all labelled texts; the tables of declared languages, suffixes, hosts and
domains are grouped counts of the languages that text alone would choose. Every
labelled language is a class of its own, however small its share.

Defined cases: null or empty text gives no text evidence, and a missing declaration,
address or host none either, so at worst the answer is the overall prior; repeated rows are
answered and counted each; with no labelled text the language is null; an empty table gives
an empty result; only the named columns are read, so further columns can't clash.
"""

from __future__ import annotations

import re
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import blocks, bound_batches, byte_list, intern, materialise, one
from .quality import framed, junctions, language_counts, train
from .urlrules import host_of

TEMPER = 0.1
#: Weights, in rows, of what a level of the host hierarchy is smoothed towards, and of a uniform likelihood.
HOST_WEIGHT, SMOOTH = 5.0, 1.0
HIDDEN = re.compile(rb"(?is)<(script|style)\b.*?</\1\s*>|<!--.*?-->|<[^>]*>")
DECLARED = r"(?is)<html\b[^>]*?\blang\s*=\s*[\x22']?([a-z]{2,3})\b"


def visible(html: bytes) -> bytes:
    return HIDDEN.sub(b" ", html)


def page_rows(pages: DataFrame, id_col: str = "page_id", url_col: str = "url", html_col: str = "html") -> DataFrame:
    """(id, text, markup, declared, suffix, host, domain)."""
    host = F.nullif(host_of(F.col(url_col).cast("string")), F.lit(""))
    html = F.col(html_col).cast("string")
    declared = F.nullif(F.lower(F.regexp_extract(F.coalesce(html, F.lit("")), DECLARED, 1)), F.lit(""))
    return pages.select(F.col(id_col).cast("long").alias("id"), html.alias("text"), F.lit(True).alias("markup"), declared.alias("declared"), F.substring_index(host, ".", -1).alias("suffix"), host.alias("host"), F.substring_index(host, ".", -2).alias("domain"))


def text_rows(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", source_col: str = "source") -> DataFrame:
    """The same of plain texts, whose host is their source."""
    none = F.lit(None).cast("string")
    return docs.select(F.col(id_col).cast("long").alias("id"), F.col(text_col).cast("string").alias("text"), F.lit(False).alias("markup"), none.alias("declared"), none.alias("suffix"), F.col(source_col).cast("string").alias("host"), none.alias("domain"))


def text_evidence(rows: DataFrame, models: dict, languages: list[str]) -> DataFrame:
    """Rows without text, with the log likelihoods of all languages and the best (null: no words)."""
    told = rows.sparkSession.sparkContext.broadcast([models[x] for x in languages])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for table in blocks(batches):
            vocabulary: dict[bytes, int] = {}
            texts = byte_list(one(table["text"]))
            split = [intern((visible(t) if m else t).split(), vocabulary) for t, m in zip(texts, table["markup"].to_pylist(), strict=True)]
            n = np.fromiter(map(len, split), np.int64, len(split))
            ids, doc = np.concatenate(split), np.repeat(np.arange(len(n)), n)
            logs = np.zeros((len(n), len(languages)))
            if len(vocabulary) and languages:
                codes, _, starts = framed(list(vocabulary))
                lead = junctions(list(vocabulary), ids, doc)
                for k, model in enumerate(told.value):
                    inside = model.score(codes)
                    inside[starts] = 0.0
                    logs[:, k] = np.bincount(doc, np.add.reduceat(inside, starts)[ids] + model.score(lead), len(n))
            best = [languages[k] if some else None for k, some in zip(logs.argmax(axis=1), n > 0, strict=True)] if languages else [None] * len(n)
            arrays = [one(table[c]) for c in ("id", "markup", "declared", "suffix", "host", "domain")]
            yield pa.RecordBatch.from_arrays([*arrays, pa.array(logs.tolist(), pa.list_(pa.float64())), pa.array(best, pa.string())], names=["id", "markup", "declared", "suffix", "host", "domain", "logs", "text_lang"])

    return rows.mapInArrow(run, "id long, markup boolean, declared string, suffix string, host string, domain string, logs array<double>, text_lang string")


def _counts(rows: DataFrame, key: str, languages: list[str]) -> DataFrame:
    """(key, n: array of counts by language)."""
    each = [F.count(F.when(F.col("text_lang") == x, 1)).cast("double") for x in languages]
    return rows.where(F.col(key).isNotNull()).groupBy(F.col(key).alias(f"of_{key}")).agg(F.array(*each).alias(f"n_{key}"))


def _total(counts: Column) -> Column:
    return F.aggregate(counts, F.lit(0.0), lambda a, x: a + x)


def identify(rows: DataFrame, labelled: DataFrame) -> DataFrame:
    """(id, markup, lang, confidence, text_lang, declared) for page_rows or text_rows; labelled: (text, lang)."""
    bound_batches(rows.sparkSession)
    counts, languages = language_counts(labelled.where(F.col("lang").isNotNull()))
    models = train(counts, languages)
    rows = materialise(text_evidence(rows, models, languages), "evidence")
    if not languages:
        return rows.select("id", "markup", F.lit(None).cast("string").alias("lang"), F.lit(None).cast("double").alias("confidence"), "text_lang", "declared")
    whole = rows.agg(*[F.count(F.when(F.col("text_lang") == x, 1)) for x in languages]).first()
    total = float(sum(whole))
    overall = [(n + 1) / (total + len(languages)) for n in whole]
    base = F.array(*map(F.lit, overall))
    facts = rows
    for key in ("host", "domain", "declared", "suffix"):
        # written: its size is known when the join is planned, and a hot value's rows may be split
        facts = facts.join(materialise(_counts(rows, key, languages), f"counts-{key}"), F.col(key) == F.col(f"of_{key}"), "left")

    def smoothed(counts: Column, towards: Column) -> Column:
        return F.when(counts.isNull(), towards).otherwise(F.zip_with(counts, towards, lambda n, p: (n + HOST_WEIGHT * p) / (_total(counts) + HOST_WEIGHT)))

    def likelihood(counts: Column) -> Column:
        """log P(value | language) up to a constant: how often a language has this value."""
        seen = F.array(*[F.lit(float(n)) for n in whole])
        return F.when(counts.isNull(), F.transform(base, lambda p: p * 0.0)).otherwise(F.zip_with(counts, seen, lambda n, s: F.log((n + SMOOTH) / (s + SMOOTH * len(languages)))))

    prior = F.transform(smoothed(F.col("n_host"), smoothed(F.col("n_domain"), base)), lambda p: F.log(p))
    score = F.transform("logs", lambda x: x * TEMPER)
    for more in (prior, likelihood(F.col("n_declared")), likelihood(F.col("n_suffix"))):
        score = F.zip_with(score, more, lambda a, b: a + b)
    facts = facts.withColumn("score", score).withColumn("top", F.array_max("score"))
    weight = F.aggregate("score", F.lit(0.0), lambda a, x: a + F.exp(x - F.col("top")))
    names = F.array(*map(F.lit, languages))
    lang = F.element_at(names, F.array_position("score", F.col("top")).cast("int"))
    return facts.select("id", "markup", lang.alias("lang"), F.round(1 / weight, 6).alias("confidence"), "text_lang", "declared")


def op6_language_id(spark, sf_dir: str) -> DataFrame:
    """All pages (page_id) and all documents (doc_id), each with its own evidence."""
    docs, pages = spark.read.parquet(f"{sf_dir}/documents.parquet"), spark.read.parquet(f"{sf_dir}/pages.parquet")
    out = identify(page_rows(pages).union(text_rows(docs)), docs.select("text", "lang"))
    return out.select(F.when(~F.col("markup"), F.col("id")).alias("doc_id"), F.when(F.col("markup"), F.col("id")).alias("page_id"), "lang", "confidence", "text_lang", "declared")
