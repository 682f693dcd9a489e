"""URL rules by hashed host-suffix and path-prefix expressions, in DataFrame functions only.

A rule is (host, path, verdict): it fits a URL whose host is the rule's or a subdomain of
it and whose path starts with the rule's. A URL is expanded into the expressions that some
rule could equal: one for each (number of host labels, path length) that occurs among the
rules. The expressions meet the rules on the first 32 bits of their SHA-256, the whole
digest confirms, and the longest rule wins (then block before allow, then the name).

Rules are a table (or a short list); the join deals both sides by hash, and Spark sends the
rules to all tasks only where it knows them to be small. What travels with the plan are the
shapes of rules, (number of host labels, path length); beyond ``MAX_SHAPES`` of them paths are
met by their first ``PREFIX`` characters and confirmed by the rest.

Defined cases: a null URL or one without "://" has an empty host and path and fits no
rule; so has an empty host; what fits no rule gets ``default``; repeated rows are kept,
an empty table gives an empty result, and only the two named columns are read.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

#: Shapes of rules that are tried one by one; beyond them all numbers of labels with up to PREFIX characters of the path.
MAX_SHAPES, PREFIX = 64, 12
UPPER, LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"
RULES = [("com", "/en/", "block"), ("example.com", "/en/7", "allow"), ("net", "/de/", "allow"), ("example.net", "/de/8", "block"), ("org", "/es/", "block")]
#: Bytes 0 can't stand in a host label or path of a rule.
JOIN = "\0"


def host_of(url: Column) -> Column:
    rest = F.when(F.instr(url, "://") > 0, F.substring(url, F.instr(url, "://") + 3, F.length(url)))
    return F.translate(F.regexp_extract(F.coalesce(rest, F.lit("")), r"\A([^/?#]*)", 1), UPPER, LOWER)


def path_of(url: Column) -> Column:
    rest = F.when(F.instr(url, "://") > 0, F.substring(url, F.instr(url, "://") + 3, F.length(url)))
    return F.regexp_extract(F.coalesce(rest, F.lit("")), r"\A[^/?#]*([^?#]*)", 1)


def judge(pages: DataFrame, rules: DataFrame | list[tuple[str, str, str]] = RULES, id_col: str = "page_id", url_col: str = "url", default: str = "allow") -> DataFrame:
    """(id, host, path, rule, verdict) for every row; ``rules``: (host, path, verdict)."""
    spark = pages.sparkSession
    if not isinstance(rules, DataFrame):
        rules = spark.createDataFrame(rules, "host string, path string, verdict string")
    book = rules.select(F.translate("host", UPPER, LOWER).alias("r_host"), F.coalesce("path", F.lit("")).alias("r_path"), F.col("verdict").alias("r_verdict")).where("r_host <> ''").distinct()
    labels = (F.length("r_host") - F.length(F.replace("r_host", F.lit("."), F.lit(""))) + 1).cast("int")
    found = book.select(labels.alias("labels"), F.length("r_path").alias("size")).distinct().orderBy("size", "labels").limit(MAX_SHAPES + 1).collect()
    if len(found) > MAX_SHAPES:  # paths are met on so many characters at most
        longest = PREFIX
        shapes = [(k, n) for k in range(1, book.agg(F.max(labels)).first()[0] + 1) for n in range(longest + 1)]
    else:
        longest = max((r["size"] for r in found), default=0)
        shapes = sorted((r["labels"], r["size"]) for r in found)
    head = F.substring("r_path", 1, longest) if longest else F.lit("")
    full = F.sha2(F.concat("r_host", F.lit(JOIN), head), 256)
    book = book.select(F.substring(full, 1, 8).alias("short"), full.alias("full"), "r_path", F.concat("r_host", "r_path").alias("name"), (F.length("r_host") + F.length("r_path")).alias("size"), (F.col("r_verdict") == "block").cast("int").alias("hard"), F.col("r_verdict").alias("verdict"))
    urls = pages.select(F.col(id_col).alias("id"), F.col(url_col).cast("string").alias("url")).groupBy("id", "url").agg(F.count("*").alias("times"))
    urls = urls.select("id", "url", "times", host_of(F.col("url")).alias("host"), path_of(F.col("url")).alias("path"))

    def expression(labels: int, size: int) -> Column:
        named = F.substring_index("host", ".", -labels)
        enough = (F.length("host") - F.length(F.replace("host", F.lit("."), F.lit(""))) >= labels - 1) & (F.length("path") >= size) & (F.col("host") != "")
        return F.when(enough, F.concat(named, F.lit(JOIN), F.substring("path", 1, size)))

    wanted = F.filter(F.array(*[expression(*s) for s in shapes]), lambda x: x.isNotNull())
    asked = urls.withColumn("e", F.explode_outer(wanted)).withColumn("digest", F.sha2(F.col("e"), 256)).withColumn("brief", F.substring("digest", 1, 8))
    met = asked.join(book, F.col("brief") == F.col("short"), "left")
    rule = F.when((F.col("digest") == F.col("full")) & F.startswith(F.col("path"), F.col("r_path")), F.struct("size", "hard", "name", F.col("verdict")))
    best = met.groupBy("id", "url", "times", "host", "path").agg(F.max(rule).alias("best"))
    out = best.select(F.col("id").alias(id_col), "host", "path", F.col("best.name").alias("rule"), F.coalesce("best.verdict", F.lit(default)).alias("verdict"), F.explode(F.sequence(F.lit(1).cast("long"), "times")).alias("copy"))
    return out.drop("copy")


def op3_url_filters(spark, sf_dir: str) -> DataFrame:
    return judge(spark.read.parquet(f"{sf_dir}/pages.parquet"))


SQL = """
WITH rules(host, path, verdict) AS (VALUES ('com', '/en/', 'block'), ('example.com', '/en/7', 'allow'), ('net', '/de/', 'allow'), ('example.net', '/de/8', 'block'), ('org', '/es/', 'block')),
rest AS (SELECT page_id, CASE WHEN instr(url, '://') > 0 THEN substr(url, instr(url, '://') + 3) ELSE '' END AS r FROM pages),
parts AS (SELECT page_id, row_number() OVER () AS n, translate(regexp_extract(r, '^([^/?#]*)', 1), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') AS host, regexp_extract(r, '^[^/?#]*([^?#]*)', 1) AS path FROM rest),
fits AS (
  SELECT p.n, r.host || r.path AS rule, r.verdict, row_number() OVER (PARTITION BY p.n ORDER BY length(r.host || r.path) DESC, r.verdict DESC) AS k
  FROM parts p JOIN rules r ON (p.host = r.host OR ends_with(p.host, '.' || r.host)) AND starts_with(p.path, r.path)
)
SELECT p.page_id, p.host, p.path, f.rule, coalesce(f.verdict, 'allow') AS verdict FROM parts p LEFT JOIN fits f ON p.n = f.n AND f.k = 1
"""
