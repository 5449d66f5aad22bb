"""Line dedup by site-relative frequency: lines on too large a share of a site's pages are boilerplate.

For each site (host) the pages that hold a line are counted and divided by the site's pages; lines over
``ratio``, on ``min_pages`` pages at least, are dropped from every page of the site. Lines are compared
without the spaces around them; blank lines stay. All DataFrame code.

Only 64-bit line hashes are exchanged, summed before the exchange. As the shares of a site's lines add up to its
mean lines per page, fewer than (mean lines / ratio) lines of a site can be boilerplate: their list per site
is short whatever the site's size. Lists of many sites go to their pages by a join on site and salt, so the texts of
a site with a third of all rows are spread over tasks.

An ordinary line is met on one page or on the few copies of that page; what templates put on pages shows on more than
one page in a hundred, even where a site has many sections. Null sites form one site. Null texts stay null; texts
all of boilerplate become empty. A page's own repeats of a line count once. Repeated rows count as pages of their own.
An empty table gives no rows. Very long texts are read whole. Columns of the input never clash with ours: they
travel in one struct.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from componentry.plans.storage import cut, small_side

RATIO = 0.01
MIN_PAGES = 5
SALTS = 64


def _lines(text: str):
    return F.split(F.col(text), "\n", -1)


def _key(line):
    return F.xxhash64(F.trim(line))


def site_lines(docs: DataFrame, site: str, min_pages: int = 1, text: str = "text") -> DataFrame:
    """(site, line, pages_with, pages): share counts of each line hash on ``min_pages`` pages of a site or more."""
    page = docs.select(F.col(site).alias("site"), F.array_distinct(F.transform(F.filter(_lines(text), lambda x: F.trim(x) != ""), _key)).alias("own"))
    pages = page.groupBy("site").agg(F.count(F.lit(1)).alias("pages"))
    with_line = page.select("site", F.explode("own").alias("line")).groupBy("site", "line").agg(F.count(F.lit(1)).alias("pages_with")).where(F.col("pages_with") >= min_pages)
    return with_line.join(small_side(cut(pages.withColumnRenamed("site", "_s"), "pages"), 48), F.col("site").eqNullSafe(F.col("_s"))).drop("_s")


def boilerplate(docs: DataFrame, site: str, ratio: float = RATIO, min_pages: int = MIN_PAGES, text: str = "text") -> DataFrame:
    """(site, drop): the hashes of each site's boilerplate lines."""
    over = site_lines(docs, site, min_pages, text).where(F.col("pages_with") > ratio * F.col("pages"))
    return over.groupBy("site").agg(F.sort_array(F.collect_list("line")).alias("drop"))


def _with_lists(rows: DataFrame, bad: DataFrame, most: int = 8192) -> DataFrame:
    """``rows`` (_row, _of) with the list of their site: broadcast up to ``most`` sites, else a salted join."""
    same = F.col("_of").eqNullSafe(F.col("_site"))
    if bad.limit(most + 1).count() <= most:
        return rows.join(F.broadcast(bad), same, "left")
    spread = bad.withColumn("_copy", F.explode(F.sequence(F.lit(0), F.lit(SALTS - 1))))
    salted = rows.withColumn("_salt", F.floor(F.rand(SALTS) * SALTS).cast("int"))
    return salted.join(spread, same & (F.col("_salt") == F.col("_copy")), "left")


def drop_boilerplate(docs: DataFrame, site: str = "source", ratio: float = RATIO, min_pages: int = MIN_PAGES, text: str = "text", count: str | None = None) -> DataFrame:
    """``docs``, all columns, with boilerplate lines cut from ``text``; ``count`` names a column for the lines dropped."""
    bad = cut(boilerplate(docs, site, ratio, min_pages, text), "boilerplate").select(F.col("site").alias("_site"), F.col("drop").alias("_drop"))
    packed = docs.select(F.struct(*(F.col(f"`{c}`") for c in docs.columns)).alias("_row"), F.col(site).alias("_of"))
    joined = _with_lists(packed, bad)
    stay = F.filter(_lines(f"_row.{text}"), lambda x: (F.trim(x) == "") | ~F.array_contains(F.col("_drop"), _key(x)))
    new = F.when(F.col("_drop").isNull(), F.col(f"_row.{text}")).otherwise(F.array_join(stay, "\n"))
    out = [(new.alias(text) if c == text else F.col(f"_row.`{c}`")) for c in docs.columns]
    if count:
        out.append(F.when(F.col("_drop").isNull(), F.lit(0)).otherwise(F.coalesce(F.size(_lines(f"_row.{text}")) - F.size(stay), F.lit(0))).cast("long").alias(count))
    return joined.select(*out)


def op10_line_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "source", "text")
    return drop_boilerplate(docs, count="n_dropped").select("doc_id", "text", "n_dropped")


OP10_SQL = f"""
WITH rows AS (SELECT row_number() OVER () AS rid, doc_id, source, text, string_split(text, chr(10)) AS ls FROM documents),
pages AS (SELECT source, count(*) AS pages FROM rows GROUP BY source),
own AS (SELECT DISTINCT rid, source, line FROM (SELECT rid, source, trim(unnest(ls), ' ') AS line FROM rows) WHERE line <> ''),
bad AS (SELECT o.source, o.line FROM own o JOIN pages p ON p.source IS NOT DISTINCT FROM o.source GROUP BY o.source, o.line, p.pages
        HAVING count(*) >= {MIN_PAGES} AND count(*) > {RATIO} * p.pages),
gone AS (SELECT source, list(line) AS g FROM bad GROUP BY source)
SELECT r.doc_id, CASE WHEN g.g IS NULL THEN r.text ELSE array_to_string(list_filter(r.ls, lambda x: trim(x, ' ') = '' OR NOT list_contains(g.g, trim(x, ' '))), chr(10)) END AS text,
       CASE WHEN g.g IS NULL THEN 0 ELSE coalesce(len(list_filter(r.ls, lambda x: trim(x, ' ') <> '' AND list_contains(g.g, trim(x, ' ')))), 0) END::BIGINT AS n_dropped
FROM rows r LEFT JOIN gone g ON g.source IS NOT DISTINCT FROM r.source
"""
