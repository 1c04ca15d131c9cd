"""URL filtering by dated list entries: an as-of join of captures with the entries active at fetch time.

DataFrame functions only. List entries (domain, listed_at, action, category) become validity intervals that
end where the next entry of the domain begins. Intervals are cut at months, so that the join is on equal
domain and month. Domain and month that very many captures ask for are dropped before the join if no entry
is for them, such as those of a whole top-level domain, and dealt over several tasks if one is. The most specific
domain that has an active entry decides: `block` drops the capture, `allow` keeps it.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

#: Seconds of a partition of time in the join.
SLOT = 30 * 86_400


def host_of(url: str = "url"):
    """Host of a URL in lower case, without user, port and final dot; null if there is none."""
    host = F.regexp_extract(F.col(url), r"^(?:[A-Za-z][A-Za-z0-9+.\-]*:)?//(?:[^/?#@]*@)?([^/?#:]+)", 1)
    return F.nullif(F.regexp_replace(F.lower(host), r"\.$", ""), F.lit(""))


def intervals(entries: DataFrame) -> DataFrame:
    """domain, valid_from, valid_to (exclusive; null: open), action, category from dated entries.

    An entry is replaced by the next of its domain; of entries of one instant, the last in order of action
    and category holds and the others are empty intervals, which are dropped. Rows without domain or date
    are dropped, as they state nothing.
    """
    e = entries.select(F.lower("domain").alias("domain"), F.col("listed_at").cast("long").alias("valid_from"), "action", "category").where("domain is not null and valid_from is not null").distinct()
    order = Window.partitionBy("domain").orderBy("valid_from", "action", "category")
    return e.withColumn("valid_to", F.lead("valid_from").over(order)).where("valid_to is null or valid_to > valid_from")


def crowded_keys(asked: DataFrame, cut: DataFrame, rows_each: int, most: int = 10_000) -> DataFrame:
    """domain, slot, salts, listed: keys with more than `rows_each` rows of asked, and into how many parts to deal them.

    Counts are summed before they are shuffled. A key counts as crowded from a share of 1 / most of all rows on at the
    least, so there are never more than `most` of them, and they may be broadcast.
    """
    counts = asked.groupBy("domain", "slot").agg(F.count("*").alias("n"))
    each = F.greatest(F.lit(rows_each), F.ceil(F.col("total") / most))
    found = counts.crossJoin(F.broadcast(counts.agg(F.sum("n").alias("total")))).where(F.col("n") > each)
    listed = cut.select("domain", "slot", F.lit(True).alias("listed")).distinct()
    return found.select("domain", "slot", F.ceil(F.col("n") / each).alias("salts")).join(listed, ["domain", "slot"], "left")


def filter_captures(captures: DataFrame, entries: DataFrame, rows_each: int = 10_000) -> DataFrame:
    """Columns of captures (page_id, url, fetched_at in seconds) with host, rule_domain, rule_action, rule_category, rule_from, allowed.

    Captures without a host or a time match nothing and are allowed, as are those that no active entry covers.
    Repeated captures each get a row. Other columns are left out. An empty list allows everything, and an empty table
    gives no rows.
    """
    own = captures.select("page_id", "url", F.col("fetched_at").cast("long").alias("fetched_at"), host_of().alias("host"))
    lists = intervals(entries).withColumn("slot_lo", F.floor(F.col("valid_from") / SLOT))
    last = own.agg(F.max(F.floor(F.col("fetched_at") / SLOT)).alias("last_slot"))
    cut = lists.crossJoin(F.broadcast(last))  # one row
    hi = F.least(F.col("last_slot"), F.coalesce(F.floor((F.col("valid_to") - 1) / SLOT), F.col("last_slot")))
    cut = cut.withColumn("hi", hi).where("slot_lo <= hi").withColumn("slot", F.explode(F.sequence("slot_lo", "hi")))
    cut = cut.select("domain", "slot", "valid_from", "valid_to", "action", "category")
    # distinct (host, second) before suffixes are spread: copies of a capture are decided once
    asked = own.where("host is not null and fetched_at is not null").select("host", "fetched_at").distinct()
    asked = asked.withColumn("parts", F.split("host", r"\.")).withColumn("k", F.explode(F.expr("sequence(1, size(parts))")))
    asked = asked.select("host", "fetched_at", F.floor(F.col("fetched_at") / SLOT).alias("slot"), F.expr("array_join(slice(parts, k, size(parts)), '.')").alias("domain"))
    crowded = F.broadcast(crowded_keys(asked, cut, rows_each))
    part = F.when(F.col("salts").isNull(), 0).otherwise(F.pmod(F.xxhash64("host", "fetched_at"), F.col("salts")))
    asked = asked.join(crowded, ["domain", "slot"], "left").where("salts is null or listed").withColumn("salt", part.cast("long"))
    cut = cut.join(crowded, ["domain", "slot"], "left").withColumn("salt", F.explode(F.expr("sequence(0L, coalesce(salts, 1L) - 1)")))
    hit = asked.join(cut, ["domain", "slot", "salt"]).where("valid_from <= fetched_at and (valid_to is null or fetched_at < valid_to)")
    best = hit.groupBy("host", "fetched_at").agg(F.max(F.struct(F.length("domain").alias("n"), "domain", "action", "category", "valid_from")).alias("r"))
    # captures that can't match get a key of their own (no host holds a question mark), so that they don't meet in one task
    whole = F.col("host").isNotNull() & F.col("fetched_at").isNotNull()
    own = own.withColumn("__host", F.when(whole, F.col("host")).otherwise(F.concat(F.lit("?"), F.xxhash64("page_id", "url").cast("string"))))
    own = own.withColumn("__at", F.coalesce("fetched_at", F.lit(0)))
    out = own.join(best.select(F.col("host").alias("__host"), F.col("fetched_at").alias("__at"), "r"), ["__host", "__at"], "left")
    rule = {"rule_domain": "domain", "rule_action": "action", "rule_category": "category", "rule_from": "valid_from"}
    found = [F.col(f"r.{c}").alias(name) for name, c in rule.items()]
    return out.select("page_id", "url", "host", "fetched_at", *found, F.coalesce(F.col("r.action") != "block", F.lit(True)).alias("allowed"))


def dated_captures(pages: DataFrame) -> DataFrame:
    """Captures for the given pages, which carry no fetch time: a time within 2024 from a hash of the id."""
    h = F.conv(F.substring(F.md5(F.concat(F.lit("fetch:"), F.coalesce(F.col("page_id").cast("string"), F.lit(""))).cast("binary")), 1, 8), 16, 10).cast("long")
    return pages.select("page_id", "url", (F.lit(1704067200) + F.pmod(h, F.lit(366 * 86_400))).alias("fetched_at"))


def dated_entries(pages: DataFrame) -> DataFrame:
    """A dated list for the hosts of the given pages, which come without one, from hashes of host and entry number.

    Each host has up to three entries for itself and each parent of two labels up to two, dated 2023 to 2024.
    """
    hosts = pages.select(host_of().alias("host")).where("host is not null").distinct()
    parents = hosts.select(F.expr("array_join(slice(split(host, '\\\\.'), -2, 2), '.')").alias("domain")).where("size(split(domain, '\\\\.')) = 2").distinct()
    own = hosts.select(F.col("host").alias("domain"), F.lit(3).alias("most")).unionByName(parents.join(hosts, F.col("domain") == F.col("host"), "left_anti").withColumn("most", F.lit(2)))
    own = own.withColumn("i", F.explode(F.sequence(F.lit(0), F.col("most") - 1)))
    digest = F.md5(F.concat(F.lit("list:"), "domain", F.lit(":"), F.col("i").cast("string")).cast("binary"))
    own = own.withColumn("h", F.conv(F.substring(digest, 1, 8), 16, 10).cast("long"))
    own = own.where("h % 2 = 0")
    listed = F.lit(1672531200) + F.pmod(F.floor(F.col("h") / 2), F.lit(731 * 86_400))
    action = F.when(F.pmod(F.floor(F.col("h") / 16), F.lit(3)) == 0, "allow").otherwise("block")
    category = F.element_at(F.array(*map(F.lit, ("adult", "malware", "spam"))), (F.pmod(F.floor(F.col("h") / 64), F.lit(3)) + 1).cast("int"))
    return own.select("domain", listed.alias("listed_at"), action.alias("action"), category.alias("category"))


ORACLE = r"""
with p as (select page_id, url, nullif(regexp_replace(lower(regexp_extract(url, '^(?:[A-Za-z][A-Za-z0-9+.\-]*:)?//(?:[^/?#@]*@)?([^/?#:]+)', 1)), '\.$', ''), '') as host,
           1704067200 + ('0x' || substr(md5('fetch:' || coalesce(page_id::varchar, '')), 1, 8))::bigint % (366 * 86400) as fetched_at from pages),
hosts as (select distinct host from p where host is not null),
parents as (select distinct split_part(host, '.', -2) || '.' || split_part(host, '.', -1) as domain from hosts where len(string_split(host, '.')) >= 2),
d as (select host as domain, 3 as most from hosts union all select domain, 2 from parents where domain not in (select host from hosts)),
h as (select domain, ('0x' || substr(md5('list:' || domain || ':' || i::varchar), 1, 8))::bigint as h from (select domain, unnest(range(most)) as i from d)),
e as (select distinct domain, 1672531200 + (h // 2) % (731 * 86400) as listed_at, case when (h // 16) % 3 = 0 then 'allow' else 'block' end as action, ['adult', 'malware', 'spam'][(h // 64) % 3 + 1] as category from h where h % 2 = 0),
v as (select *, lead(listed_at) over (partition by domain order by listed_at, action, category) as valid_to from e),
m as (select p.page_id, p.url, p.host, p.fetched_at, v.domain, v.action, v.category, v.listed_at, row_number() over (partition by p.page_id, p.url order by length(v.domain) desc nulls last) as k
      from p left join v on (p.host = v.domain or p.host like '%.' || v.domain) and v.listed_at <= p.fetched_at and (v.valid_to is null or p.fetched_at < v.valid_to))
select page_id, url, host, fetched_at, domain as rule_domain, action as rule_action, category as rule_category, listed_at as rule_from, coalesce(action <> 'block', true) as allowed from m where k = 1
"""
