"""URL filters as a temporal join: what a capture is judged by is the list as it stood at its fetch time.

A list is dated entries (pattern, action, listed_on, entry_id): a pattern is a domain, which holds for all hosts
below it, or host/segment, a first path segment. Entries become validity intervals: each holds from its date until
the pattern's next entry; of several on one date the last ``entry_id`` wins. A capture's keys (its domains and its host
with the first segment) meet the intervals of equal pattern that hold its fetch date, which is an as-of join:
at most one interval of a pattern holds a date. Null urls and urls without a host match nothing; null dates
neither. Repeated captures are judged each. An empty list blocks nothing, an empty table gives no rows. A kept column
named like one of the answers (host, blocked, pattern, listed_on) comes back with ``_given`` behind its name. Hosts
are cut at every dot, however long.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from componentry.plans.storage import cut, small_side

_URL = r"^[a-z][a-z0-9+.-]*://(?:[^/?#@]*@)?([^/?#:]*)(?::[0-9]*)?/?([^/?#]*)"


def url_parts(url: str = "url") -> tuple:
    """(host, first path segment) expressions; the host in lower case."""
    text = F.lower(F.col(url))
    return F.regexp_extract(text, _URL, 1), F.regexp_extract(text, _URL, 2)


def intervals(entries: DataFrame) -> DataFrame:
    """(pattern, valid_from, valid_to) of the blocking times in ``entries``; valid_to is exclusive, null for ever."""
    w = Window.partitionBy("pattern").orderBy("listed_on", "entry_id")
    spans = entries.where("pattern is not null and listed_on is not null").withColumn("valid_to", F.lead("listed_on").over(w))
    return spans.where("action = 'add' and (valid_to is null or valid_to > listed_on)").select("pattern", F.col("listed_on").alias("valid_from"), "valid_to")


ANSWERS = ("host", "blocked", "pattern", "listed_on")


def judge(captures: DataFrame, entries: DataFrame, keep: list[str], on: str = "fetched_on", url: str = "url") -> DataFrame:
    """``keep`` columns with host, blocked, and the longest pattern that blocks with the date it was listed on."""
    host, segment = url_parts(url)
    spans = small_side(cut(intervals(entries), "intervals"), 96)
    # rows are numbered and then written: both uses below see the same numbers
    numbered = captures.select(F.monotonically_increasing_id().alias("_row"), F.struct(*(F.col(f"`{c}`") for c in keep)).alias("_keep"), F.col(on).alias("_on"), host.alias("host"), segment.alias("_segment"))
    rows = cut(numbered, "captures")
    labels = F.split("host", r"\.")
    n = F.size(labels)
    domains = F.when(n > 1, F.transform(F.sequence(F.lit(1), n - 1), lambda i: F.array_join(F.slice(labels, i, n), "."))).otherwise(F.array("host"))
    keys = F.when(F.col("host") != "", F.concat(domains, F.array(F.concat_ws("/", "host", "_segment"))))
    asked = rows.select("_row", "_on", F.explode(F.array_distinct(keys)).alias("_key"))
    held = (F.col("_key") == F.col("pattern")) & (F.col("_on") >= F.col("valid_from")) & (F.col("valid_to").isNull() | (F.col("_on") < F.col("valid_to")))
    met = asked.join(spans, held).groupBy("_row").agg(F.max(F.struct(F.length("pattern").alias("n"), "pattern", "valid_from")).alias("b"))
    kept = [F.col(f"_keep.`{c}`").alias(f"{c}_given" if c in ANSWERS else c) for c in keep]
    return rows.join(met, "_row", "left").select(*kept, "host", F.col("b").isNotNull().alias("blocked"), F.col("b.pattern").alias("pattern"), F.col("b.valid_from").alias("listed_on"))


def dated_list(hosts: DataFrame) -> DataFrame:
    """A dated list over ``hosts`` (host, segment) for the query: no list comes with the tables, so dates and actions come from digests of the names.

    About a third of the hosts are listed at some day of the year, half of those are taken off and some put on again;
    parent domains and first segments are listed likewise, more rarely.
    """
    day = lambda d, k: F.conv(F.substring(d, k, 4), 16, 10).cast("int")
    parent = F.regexp_replace("host", r"^[^.]*\.", "")
    names = hosts.select(F.explode(F.array(F.struct(F.col("host").alias("p"), F.lit(5).alias("most")), F.struct(parent.alias("p"), F.lit(1).alias("most")), F.struct(F.concat_ws("/", "host", "segment").alias("p"), F.lit(0).alias("most")))).alias("x"))
    names = names.select("x.p", "x.most").where("p like '%.%' and p not like '%/'").groupBy("p").agg(F.max("most").alias("most")).withColumn("d", F.md5("p"))
    first = day("d", 5) % 300
    listed = names.where(F.conv(F.substring("d", 1, 1), 16, 10).cast("int") <= F.col("most"))
    steps = F.array(
        F.struct(F.lit(1).alias("k"), F.lit("add").alias("action"), first.alias("day")),
        F.struct(F.lit(2).alias("k"), F.when(F.substring("d", 2, 1) < "8", F.lit("remove")).otherwise(F.lit("add")).alias("action"), (first + 10 + day("d", 9) % 60).alias("day")),
        F.struct(F.lit(3).alias("k"), F.lit("add").alias("action"), (first + 80 + day("d", 13) % 200).alias("day")),
    )
    rows = listed.select(F.col("p").alias("pattern"), F.explode(steps).alias("s"))
    return rows.select("pattern", "s.action", F.date_add(F.lit("2024-01-01").cast("date"), F.col("s.day")).alias("listed_on"), F.col("s.k").cast("long").alias("entry_id"))


def op7_url_filters(spark: SparkSession, sf_dir: str) -> DataFrame:
    pages = spark.read.parquet(f"{sf_dir}/pages.parquet").select("page_id", "url")
    host, segment = url_parts()
    # the table has no fetch time: a day of the year 2024 by page number
    captures = pages.withColumn("fetched_on", F.date_add(F.lit("2024-01-01").cast("date"), F.pmod("page_id", F.lit(366)).cast("int")))
    entries = dated_list(pages.select(host.alias("host"), segment.alias("segment")).distinct())
    return judge(captures, entries, ["page_id", "fetched_on"])


OP7_SQL = r"""
WITH caps AS (SELECT row_number() OVER () AS rid, page_id, CAST(DATE '2024-01-01' + CAST(page_id % 366 AS INTEGER) AS DATE) AS fetched_on,
  regexp_extract(lower(url), '^[a-z][a-z0-9+.-]*://(?:[^/?#@]*@)?([^/?#:]*)(?::[0-9]*)?/?([^/?#]*)', 1) AS host,
  regexp_extract(lower(url), '^[a-z][a-z0-9+.-]*://(?:[^/?#@]*@)?([^/?#:]*)(?::[0-9]*)?/?([^/?#]*)', 2) AS seg FROM pages),
hs AS (SELECT DISTINCT host, seg FROM caps),
raw AS (SELECT host AS p, 5 AS most FROM hs UNION ALL SELECT regexp_replace(host, '^[^.]*\.', ''), 1 FROM hs UNION ALL SELECT host || '/' || seg, 0 FROM hs),
names AS (SELECT p, max(most) AS most, md5(p) AS d FROM raw WHERE p LIKE '%.%' AND p NOT LIKE '%/' GROUP BY p),
listed AS (SELECT p, d, ('0x' || substr(d, 5, 4))::INTEGER % 300 AS f FROM names WHERE ('0x' || substr(d, 1, 1))::INTEGER <= most),
entries AS (
  SELECT p AS pattern, 'add' AS action, f AS day, 1 AS k FROM listed
  UNION ALL SELECT p, CASE WHEN substr(d, 2, 1) < '8' THEN 'remove' ELSE 'add' END, f + 10 + ('0x' || substr(d, 9, 4))::INTEGER % 60, 2 FROM listed
  UNION ALL SELECT p, 'add', f + 80 + ('0x' || substr(d, 13, 4))::INTEGER % 200, 3 FROM listed),
dated AS (SELECT pattern, action, k, CAST(DATE '2024-01-01' + day AS DATE) AS valid_from FROM entries),
spans AS (SELECT pattern, action, valid_from, lead(valid_from) OVER (PARTITION BY pattern ORDER BY valid_from, k) AS valid_to FROM dated),
keys AS (SELECT rid, unnest(list_distinct(list_append(list_transform(range(1, len(string_split(host, '.'))), lambda i: array_to_string(string_split(host, '.')[i:], '.')), host || '/' || seg))) AS key FROM caps WHERE host <> ''),
met AS (SELECT k.rid, max({'n': length(s.pattern), 'pattern': s.pattern, 'valid_from': s.valid_from}) AS b FROM keys k JOIN caps c ON c.rid = k.rid
  JOIN spans s ON s.pattern = k.key AND s.action = 'add' AND c.fetched_on >= s.valid_from AND (s.valid_to IS NULL OR c.fetched_on < s.valid_to) GROUP BY k.rid)
SELECT c.page_id, c.fetched_on, c.host, m.b IS NOT NULL AS blocked, m.b.pattern AS pattern, m.b.valid_from AS listed_on FROM caps c LEFT JOIN met m ON m.rid = c.rid
"""
