"""The dated URL list and the capture times that the page query uses: the given tables have neither.

A page's capture time is 2024-01-01 plus (page_id * 37) mod 360 days and page_id mod 24 hours. The list below names
hosts of the given pages; its entries come, change and are lifted over the year.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: Fixed values: (entry_id, scope, value, action, listed_on).
ENTRIES = [
    (1, "domain", "example.net", "block", "2024-03-01"),
    (2, "domain", "example.net", "lift", "2024-04-15"),
    (3, "host", "tionsh.example.net", "allow", "2024-02-01"),
    (4, "host", "tionsh.example.net", "block", "2024-06-10"),
    (5, "host", "tionsh.example.net", "allow", "2024-08-20"),
    (6, "prefix", "tionsh.example.net/fr", "block", "2024-01-15"),
    (7, "prefix", "tionsh.example.net/fr", "lift", "2024-09-01"),
    (8, "domain", "casino-win.example.com", "block", "2024-01-01"),
    (9, "host", "m.casino-win.example.com", "block", "2024-01-01"),
    (10, "domain", "tionble.example.com", "block", "2024-05-05"),
    (11, "host", "blog.tionble.example.com", "allow", "2024-07-01"),
    (12, "prefix", "blog.tionble.example.com/de", "block", "2024-07-01"),
    (13, "domain", "example.org", "block", "2024-11-01"),
    (14, "domain", "example.org", "allow", "2024-11-15"),
    (15, "domain", "example.org", "block", "2024-12-01"),
    (16, "host", "ththon.example.com", "block", "2024-02-29"),
    (17, "host", "ththon.example.com", "lift", "2024-02-29"),
    (18, "url", "ththan.example.com/en/7944", "block", "2024-01-01"),
    (19, "domain", "com", "allow", "2024-10-01"),
]


def entries(spark: SparkSession) -> DataFrame:
    return spark.createDataFrame(ENTRIES, "entry_id long, scope string, value string, action string, day string").select("entry_id", "scope", "value", "action", F.to_timestamp("day").alias("listed_on"))


def fetched_at(page_id: str) -> Column:
    days, hours = F.pmod(F.col(page_id) * 37, F.lit(360)), F.pmod(F.col(page_id), F.lit(24))
    return (F.to_timestamp(F.lit("2024-01-01")) + F.make_dt_interval(days.cast("int"), hours.cast("int"))).cast("timestamp")


def oracle() -> str:
    rows = ", ".join(f"({i}, '{s}', '{v}', '{a}', timestamp '{d}')" for i, s, v, a, d in ENTRIES)
    return f"""
with list(entry_id, scope, value, action, ts) as (values {rows}),
day as (select *, row_number() over (partition by scope, value, ts order by entry_id desc) as r from list),
iv as (select scope, value, action, entry_id, ts as valid_from, lead(ts) over (partition by scope, value order by ts) as valid_to from day where r = 1),
c as (
  select page_id, ts, path, case when length(host) <= 253 then host end as host from (
  select page_id, timestamp '2024-01-01' + to_days(cast((page_id * 37) % 360 as integer)) + to_hours(cast(page_id % 24 as integer)) as ts,
    nullif(regexp_extract(lower(trim(url)), '^https?://(?:[^/?#@]*@)?([^/?#:@]+)', 1), '') as host,
    regexp_extract(lower(trim(url)), '^https?://[^/?#]+([^?#]*)', 1) as path
  from pages)),
hit as (
  select c.page_id, iv.entry_id, iv.action,
    row_number() over (partition by c.page_id order by case iv.scope when 'url' then 4 when 'prefix' then 3 when 'host' then 2 else 1 end desc, length(iv.value) desc) as r
  from c join iv on c.ts >= iv.valid_from and (iv.valid_to is null or c.ts < iv.valid_to) and iv.action <> 'lift' and (
    (iv.scope = 'url' and iv.value = c.host || c.path) or
    (iv.scope = 'prefix' and iv.value = c.host || regexp_extract(c.path, '^(/[^/]+)', 1)) or
    (iv.scope = 'host' and iv.value = c.host) or
    (iv.scope = 'domain' and (iv.value = c.host or ends_with(c.host, '.' || iv.value)))))
select c.page_id, c.host, c.ts as fetched_at, hit.entry_id, hit.action, coalesce(hit.action, '') <> 'block' as kept
from c left join hit on hit.page_id = c.page_id and hit.r = 1
"""
