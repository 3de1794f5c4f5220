"""URL filtering with lists that change: each capture is judged by the entries of its time.

Dated entries (add or remove a pattern on a list) become validity intervals: an addition holds until
the next entry for the same list and pattern.  On one day a removal follows an addition.  A capture
is looked up by every pattern that could name it: its host, each parent domain, and each of these
with the first folder of its path.  The join is on equal patterns with the time inside the interval,
so nothing is compared with all entries; the patterns of a capture are as many as its host has parts.

Only the distinct patterns of captures are matched where hosts are hot: captures of one host and day
are one row until the answer is joined back, so a host with a third of all captures is as many rows
as it has days and folders.

Odd input: a null or unreadable URL, or a null time, matches nothing; repeated rows are each answered;
entries without pattern or date are no entries; an empty table gives an empty result.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

HOST = r"^[A-Za-z][A-Za-z0-9+.-]*://(?:[^/?#@]*@)?([^/:?#]+)"
FOLDER = r"^[A-Za-z][A-Za-z0-9+.-]*://[^/?#]+(/[^/?#]+)"


def host(url):
    found = F.rtrim(F.lower(F.regexp_extract(url, HOST, 1)), F.lit("."))
    return F.when(found != "", found)


def folder(url):
    return F.lower(F.regexp_extract(url, FOLDER, 1))


def intervals(entries: DataFrame) -> DataFrame:
    """list, pattern, valid_from, valid_to (null: still valid) from list, pattern, day, action."""
    own = W.partitionBy("list", "pattern").orderBy("day", "action")
    known = entries.where("pattern is not null and day is not null").select("list", "pattern", "day", "action").distinct()
    return known.withColumn("valid_to", F.lead("day").over(own)).where("action = 'add'").where("valid_to is null or valid_to > day").select("list", "pattern", F.col("day").alias("valid_from"), "valid_to")


def patterns(host, folder):
    """Host and parent domains, each with and without the first folder; a bare top level is no pattern."""
    parts = F.split(host, r"\.")
    names = F.transform(F.sequence(F.lit(1), F.greatest(F.size(parts) - 1, F.lit(1))), lambda i: F.array_join(F.slice(parts, i, F.size(parts)), "."))
    return F.when(folder != "", F.concat(names, F.transform(names, lambda n: F.concat(n, folder)))).otherwise(names)


def _with_matches(captures: DataFrame, entries: DataFrame, url: str, at: str) -> DataFrame:
    """The captures as ``row``, with ``host``, ``fetched`` and ``matches`` (null where nothing matches)."""
    seen = captures.select(F.struct("*").alias("row"), host(F.col(url)).alias("host"), folder(F.col(url)).alias("folder"), F.col(at).cast("date").alias("fetched"))
    distinct = seen.where("host is not null and fetched is not null").select("host", "folder", "fetched").distinct()
    asked = distinct.select("host", "folder", "fetched", F.explode(patterns(F.col("host"), F.col("folder"))).alias("pattern"))
    valid = intervals(entries)
    active = asked.join(valid, "pattern").where("fetched >= valid_from and (valid_to is null or fetched < valid_to)")
    found = active.groupBy("host", "folder", "fetched").agg(F.array_sort(F.collect_set(F.concat_ws(":", "list", "pattern"))).alias("matches"))
    return seen.join(found, ["host", "folder", "fetched"], "left")


def filter_captures(captures: DataFrame, entries: DataFrame, id: str = "page_id", url: str = "url", at: str = "fetched") -> DataFrame:
    """A row for each capture: id, host, fetched, blocked, n_matches, matches (list:pattern, sorted)."""
    out = _with_matches(captures.select(id, url, at), entries, url, at)
    n = F.coalesce(F.size("matches"), F.lit(0))
    return out.select(F.col("row").getField(id).alias(id), "host", "fetched", (n > 0).alias("blocked"), n.cast("long").alias("n_matches"), F.coalesce(F.array_join("matches", ","), F.lit("")).alias("matches"))


def keep_allowed(captures: DataFrame, entries: DataFrame, url: str = "url", at: str = "fetched") -> DataFrame:
    """The captures that no entry of their time blocks; columns as they were.  Each row is judged on its own,
    so of one page some captures may stay and others go."""
    return _with_matches(captures, entries, url, at).where("matches is null").select("row.*")


# --- the given tables have neither fetch times nor lists: both follow from pages by these rules ---


def captures_of(pages: DataFrame) -> DataFrame:
    """page_id, url and a day of the year 2024 that depends on the id."""
    day = F.pmod(F.col("page_id") * F.lit(37), F.lit(366)).cast("int")
    return pages.select("page_id", "url", F.date_add(F.lit("2024-01-01").cast("date"), day).alias("fetched"))


def entries_of(pages: DataFrame) -> DataFrame:
    """A dated list over the hosts, domains and host folders of pages, chosen by digest."""
    named = pages.select(host(F.col("url")).alias("host"), folder(F.col("url")).alias("folder")).where("host is not null").distinct()
    names = named.select(F.explode(F.array("host", F.regexp_extract("host", r"([^.]+\.[^.]+\.[^.]+)$", 1), F.concat("host", "folder"))).alias("pattern")).where("pattern <> ''").distinct()
    code = F.conv(F.substring(F.md5("pattern"), 1, 6), 16, 10).cast("long")
    coded = names.withColumn("code", code).where("code % 3 = 0")
    name = F.when(F.col("code") % 2 == 0, "spam").otherwise("adult")
    first = F.date_add(F.lit("2024-01-01").cast("date"), (F.col("code") % 300).cast("int"))
    made = F.array(
        F.struct(first.alias("day"), F.lit("add").alias("action"), F.lit(True).alias("made")),
        F.struct(F.date_add(first, (F.col("code") % 90).cast("int")).alias("day"), F.lit("remove").alias("action"), (F.col("code") % 5 < 3).alias("made")),
        F.struct(F.date_add(first, (F.col("code") % 70 + 60).cast("int")).alias("day"), F.lit("add").alias("action"), (F.col("code") % 7 < 3).alias("made")),
    )
    return coded.select(name.alias("list"), "pattern", F.inline(made)).where("made").select("list", "pattern", "day", "action")


def op3(pages: DataFrame) -> DataFrame:
    return filter_captures(captures_of(pages), entries_of(pages))


SQL = r"""
with seen as (
  select page_id, date '2024-01-01' + cast((page_id * 37) % 366 as integer) as fetched,
         nullif(rtrim(lower(regexp_extract(url, '^[A-Za-z][A-Za-z0-9+.-]*://(?:[^/?#@]*@)?([^/:?#]+)', 1)), '.'), '') as host,
         lower(regexp_extract(url, '^[A-Za-z][A-Za-z0-9+.-]*://[^/?#]+(/[^/?#]+)', 1)) as folder
  from pages),
names as (
  select distinct unnest([host, regexp_extract(host, '([^.]+\.[^.]+\.[^.]+)$', 1), host || folder]) as pattern from seen where host is not null),
coded as (
  select pattern, cast('0x' || substr(md5(pattern), 1, 6) as bigint) as code from names where pattern <> ''),
entries as (
  select case when code % 2 = 0 then 'spam' else 'adult' end as list, pattern, code, date '2024-01-01' + cast(code % 300 as integer) as first_day
  from coded where code % 3 = 0),
dated as (
  select list, pattern, first_day as day, 'add' as action from entries
  union select list, pattern, first_day + cast(code % 90 as integer), 'remove' from entries where code % 5 < 3
  union select list, pattern, first_day + cast(code % 70 + 60 as integer), 'add' from entries where code % 7 < 3),
spans as (
  select *, lead(day) over (partition by list, pattern order by day, action) as until from dated),
hits as (
  select s.page_id, string_agg(distinct v.list || ':' || v.pattern, ',' order by v.list || ':' || v.pattern) as matches, count(distinct v.list || ':' || v.pattern) as n
  from seen s join spans v
    on v.action = 'add' and s.fetched >= v.day and (v.until is null or s.fetched < v.until)
   and (v.pattern = s.host or s.host like '%.' || v.pattern
        or (s.folder <> '' and (v.pattern = s.host || s.folder or s.host || s.folder like '%.' || v.pattern)))
  group by s.page_id)
select s.page_id, s.host, s.fetched, coalesce(h.n, 0) > 0 as blocked, coalesce(h.n, 0) as n_matches, coalesce(h.matches, '') as matches
from seen s left join hits h using (page_id)
"""
