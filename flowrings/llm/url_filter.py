"""Dated URL lists: every capture is judged by the entries in force when it was fetched.

List entries are dated additions and removals of a key: a domain (``example.com``, which covers its
subdomains) or a path (``a.example.com/de``, which covers what lies below).  They become validity
intervals, and an as-of join finds for each capture and key the interval that holds its fetch time.
The longest key decides; of equally long keys, a blocking one.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

# Fixed value: scheme, user, host, port, path of an absolute URL.
URL = r"^\s*(?:[A-Za-z][A-Za-z0-9+.-]*:)?//(?:[^/?#@]*@)?([^/?#:]+)(?::[0-9]*)?([^?#]*)"
ENTRIES = "list_name string, key string, verdict string, event string, day date"


def host_of(url: Column) -> Column:
    return F.rtrim(F.lower(F.regexp_extract(F.coalesce(url, F.lit("")), URL, 1)), F.lit("."))


def keys_of(url: Column) -> Column:
    """All keys that could cover a URL: its domain suffixes of two labels or more, and its path prefixes."""
    host = host_of(url)
    labels, n = F.split(host, r"\."), F.size(F.split(host, r"\."))
    domains = F.transform(F.sequence(F.lit(1), F.greatest(n - 1, F.lit(1))), lambda i: F.array_join(F.slice(labels, i, n), "."))
    parts = F.filter(F.split(F.regexp_extract(F.coalesce(url, F.lit("")), URL, 2), "/"), lambda x: x != "")
    paths = F.when(F.size(parts) > 0, F.transform(F.sequence(F.lit(1), F.size(parts)), lambda i: F.concat_ws("/", host, F.array_join(F.slice(parts, F.lit(1), i), "/"))))
    none = F.array().cast("array<string>")
    return F.when(host == "", none).otherwise(F.array_distinct(F.concat(domains, F.coalesce(paths, none))))


def key_of_entry(key: Column) -> Column:
    """A list key in the form of ``keys_of``: the host part in lower case, the path as it is."""
    host = F.substring_index(key, "/", 1)
    return F.concat(F.lower(host), F.substr(key, F.length(host) + 1))


def intervals(entries: DataFrame) -> DataFrame:
    """(list_name, key, verdict, since, until): half-open days; until is null while the entry stands.

    Entries with a null key or day count for nothing.  On one day the addition comes after the
    removal, so it stands; repeated entries count once.
    """
    known = entries.filter("key IS NOT NULL AND day IS NOT NULL").select("list_name", key_of_entry(F.col("key")).alias("key"), "verdict", "event", "day")
    ordered = Window.partitionBy("list_name", "key").orderBy("day", F.col("event") == "add", "verdict")
    return (
        known.distinct().withColumn("until", F.lead("day").over(ordered)).filter("event = 'add' AND (until IS NULL OR until > day)")
        .select("list_name", "key", "verdict", F.col("day").alias("since"), "until")
    )


def timelines(entries: DataFrame) -> DataFrame:
    """(key, spans): the intervals of each key over all lists, by their first day.

    A list has at most one interval of a key for each day that it covers, which bounds an array.
    """
    span = F.struct("since", "until", "list_name", "verdict")
    return intervals(entries).groupBy("key").agg(F.array_sort(F.collect_list(span)).alias("spans"))


def judge(captures: DataFrame, entries: DataFrame, id_col: str = "page_id", url_col: str = "url", day_col: str = "fetched") -> DataFrame:
    """One row per capture: id, host, n_hits, matched (list:key pairs, sorted), blocked.

    A null or relative URL has no host and no hits; a null fetch day meets no interval.  A verdict belongs
    to a URL and a day: captures that repeat an id are each judged by their own, captures that repeat all
    three share theirs.  The as-of join meets each capture and key with one timeline, in which the spans
    in force on the day are looked up, so revisions of a key multiply no rows; a hot host is split by
    adaptive execution, and only hits are grouped.
    """
    own = captures.select(F.col(f"`{id_col}`").alias("id"), F.col(f"`{url_col}`").alias("url"), F.col(f"`{day_col}`").alias("fetched"))
    asked = own.select("url", "fetched", F.explode(keys_of(F.col("url"))).alias("key"))
    in_force = F.filter("spans", lambda x: (F.col("fetched") >= x["since"]) & (x["until"].isNull() | (F.col("fetched") < x["until"])))
    hits = asked.join(timelines(entries), "key").select("url", "fetched", "key", F.explode(in_force).alias("span")).select("url", "fetched", "key", "span.list_name", "span.verdict")
    judged = hits.groupBy(F.col("url").alias("hit_url"), F.col("fetched").alias("hit_day")).agg(
        F.countDistinct("list_name", "key").alias("n_hits"),
        F.array_join(F.array_sort(F.collect_set(F.concat_ws(":", "list_name", "key"))), ",").alias("matched"),
        F.max(F.struct(F.length("key").alias("n"), (F.col("verdict") == "block").alias("block")))["block"].alias("blocked"),
    )
    return own.join(judged, (F.col("url") == F.col("hit_url")) & (F.col("fetched") == F.col("hit_day")), "left").select(
        F.col("id").alias(id_col), host_of(F.col("url")).alias("host"), F.coalesce("n_hits", F.lit(0).cast("long")).alias("n_hits"),
        F.coalesce("matched", F.lit("")).alias("matched"), F.coalesce("blocked", F.lit(False)).alias("blocked"),
    )


# The list that the query applies (list, key, verdict, event, day).
DEFAULT_LIST = [
    ("ads", "cheap-pills.example.com", "block", "add", "2024-01-01"),
    ("ads", "tionsh.example.net", "block", "add", "2024-02-01"),
    ("ads", "tionsh.example.net", "block", "remove", "2024-06-01"),
    ("ads", "tionsh.example.net", "block", "add", "2024-09-01"),
    ("adult", "thther.example.org", "block", "add", "2024-03-15"),
    ("adult", "m.ththth.example.net", "block", "add", "2024-01-10"),
    ("adult", "m.ththth.example.net", "block", "remove", "2024-11-01"),
    ("regional", "example.org", "block", "add", "2024-07-01"),
    ("regional", "example.org", "block", "remove", "2024-08-01"),
    ("regional", "blog.tionsh.example.net/de", "block", "add", "2024-01-01"),
    ("trusted", "thther.example.org/en", "allow", "add", "2024-04-01"),
    ("trusted", "blog.tionsh.example.net/en", "allow", "add", "2024-02-15"),
    ("trusted", "blog.tionsh.example.net/en", "allow", "remove", "2024-10-01"),
]


def default_entries(spark: SparkSession) -> DataFrame:
    rows = ", ".join(str(r) for r in DEFAULT_LIST)
    return spark.sql(f"SELECT list_name, key, verdict, event, CAST(day AS DATE) AS day FROM VALUES {rows} AS t(list_name, key, verdict, event, day)")


def op6_url_filter(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All pages, taken as fetched on day ``page_id mod 366`` of 2024 (the table has no fetch time)."""
    pages = spark.read.parquet(f"{sf_dir}/pages.parquet").select("page_id", "url", F.date_add(F.lit("2024-01-01").cast("date"), F.pmod("page_id", F.lit(366)).cast("int")).alias("fetched"))
    return judge(pages, default_entries(spark))


_ROWS = ", ".join(f"('{a}', '{b}', '{c}', '{d}', DATE '{e}')" for a, b, c, d, e in DEFAULT_LIST)
_URL = URL.replace("\\s", "[ \\t]")
ORACLE = rf"""
WITH e AS (SELECT * FROM (VALUES {_ROWS}) AS t(list_name, key, verdict, event, day)),
iv AS (SELECT *, lead(day) OVER (PARTITION BY list_name, key ORDER BY day, event = 'add', verdict) AS until FROM e),
p AS (SELECT page_id, DATE '2024-01-01' + CAST(page_id % 366 AS INTEGER) AS fetched, rtrim(lower(regexp_extract(coalesce(url, ''), '{_URL}', 1)), '.') AS host,
      [x FOR x IN string_split(regexp_extract(coalesce(url, ''), '{_URL}', 2), '/') IF x <> ''] AS parts FROM pages),
q AS (SELECT *, string_split(host, '.') AS labels FROM p),
k AS (SELECT page_id, fetched, unnest(list_distinct(list_concat(
        [array_to_string(labels[i:], '.') FOR i IN generate_series(1, greatest(len(labels) - 1, 1))],
        [host || '/' || array_to_string(parts[1:i], '/') FOR i IN generate_series(1, len(parts))]))) AS key FROM q WHERE host <> ''),
h AS (SELECT k.page_id, list_name, k.key, verdict FROM k JOIN iv ON k.key = iv.key AND event = 'add' AND fetched >= day AND (until IS NULL OR fetched < until)),
j AS (SELECT page_id, count(DISTINCT (list_name, key)) AS n_hits, string_agg(DISTINCT list_name || ':' || key, ',' ORDER BY list_name || ':' || key) AS matched,
      arg_max(verdict = 'block', length(key) * 2 + CAST(verdict = 'block' AS INTEGER)) AS blocked FROM h GROUP BY 1)
SELECT page_id, host, coalesce(n_hits, 0) AS n_hits, coalesce(matched, '') AS matched, coalesce(blocked, false) AS blocked FROM p LEFT JOIN j USING (page_id)
"""
