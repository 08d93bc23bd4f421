"""URL filter: a blocked Bloom filter of listed canonical URLs, then an exact join.

Everything is DataFrame expressions. The filter has 64-bit blocks: a URL's hash picks one block and four bits
in it. Only rows whose block holds all four bits go on to the exact hash join with the list, which removes the
false positives; all others are passed without a shuffle while the filter is small enough to broadcast.

Defined results: a null url, or one without `://`, has an empty host and path and no canonical form; no rule and
no list entry can fit it, so it is allowed. Repeated rows are judged each. Columns of the input are not read except
`page_id` and `url`.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

UPPER, LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"
#: The rules (host and path prefix, verdict).
RULES = (("net/", "block"), ("example.net/en/", "allow"), ("example.com/de/", "block"), ("org/fr/", "allow"))
#: Blocks of the filter that may be broadcast (16 bytes each with their number: 16 MB); a larger one is joined by shuffle.
BROADCAST_BLOCKS = 1 << 20
URLS_A_BLOCK, BITS_A_URL = 4, 4


def ascii_lower(c: Column) -> Column:
    return F.translate(c, UPPER, LOWER)


def host_and_path(url: Column) -> tuple[Column, Column]:
    """Host: after the first `://` to `/`, `?`, `#` or the end, A-Z lower-cased. Path: then to `?`, `#` or the end."""
    found = F.coalesce(F.instr(url, "://"), F.lit(0))
    rest = F.when(found > 0, F.substr(url, found + 3)).otherwise(F.lit(""))
    host = F.regexp_extract(rest, r"^[^/?#]*", 0)
    path = F.regexp_extract(rest, r"^[^/?#]*(/[^?#]*)", 1)
    return ascii_lower(host), path


def canonical(url: Column) -> Column:
    """Scheme dropped, host lower-cased without www., m. and :80/:443, path without closing slashes, query without
    utm_ parts, no fragment. Null where there is no `://`."""
    host, path = host_and_path(url)
    host = F.regexp_replace(F.regexp_replace(host, r":(80|443)$", ""), r"^(www\.|m\.)+", "")
    query = F.regexp_extract(url, r"^[^?#]*\?([^#]*)", 1)
    query = F.regexp_replace(F.regexp_replace(query, r"(^|&)utm_[^&]*", ""), r"^&", "")
    full = F.concat(host, F.regexp_replace(path, r"/+$", ""), F.when(query == "", "").otherwise(F.concat(F.lit("?"), query)))
    return F.when(F.instr(url, "://") > 0, full)


def rule_of(host: Column, path: Column, rules=RULES) -> tuple[Column, Column]:
    """The longest rule that fits, and its verdict; nulls where none fits. The rules are a short literal list."""
    which, verdict = F.lit(None).cast("string"), F.lit(None).cast("string")
    for rule, says in sorted(rules, key=lambda r: len(r[0])):
        rule_host, _, tail = rule.partition("/")
        fits = ((host == rule_host) | host.endswith("." + rule_host)) & path.startswith("/" + tail)
        which, verdict = F.when(fits, rule).otherwise(which), F.when(fits, says).otherwise(verdict)
    return which, verdict


def _address(key: Column, blocks: int) -> tuple[Column, Column]:
    """Block number, and the mask of a key's bits."""
    mask = F.lit(0).cast("long")
    bits = F.xxhash64(key, F.lit("bits"))
    for k in range(BITS_A_URL):
        one = F.expr("1L")
        mask = mask.bitwiseOR(F.call_function("shiftleft", one, F.shiftright(bits, 8 * k).bitwiseAND(63).cast("int")))
    return F.pmod(F.xxhash64(key), F.lit(blocks)).cast("long"), mask


def bloom(listed: DataFrame, n_listed: int) -> tuple[DataFrame, int]:
    """(block, mask) rows of the blocked filter over `listed.canon`, and its number of blocks."""
    blocks = max(64, n_listed // URLS_A_BLOCK + 1)
    block, mask = _address(F.col("canon"), blocks)
    return listed.select(block.alias("block"), mask.alias("mask")).groupBy("block").agg(F.bit_or("mask").alias("mask")), blocks


def url_verdicts(pages: DataFrame, listed: DataFrame, rules=RULES, broadcast_blocks: int = BROADCAST_BLOCKS) -> DataFrame:
    """Judge every url. `listed` has a column canon of canonical URLs to block; nulls in it are ignored.

    Returns page_id, host, path, rule, verdict, listed (in the list for certain), possible (the Bloom filter's answer).
    """
    listed = listed.select("canon").where("canon is not null").distinct()
    n = listed.count()
    table, blocks = bloom(listed, n)
    table = F.broadcast(table) if blocks <= broadcast_blocks else table
    host, path = host_and_path(F.col("url"))
    rows = pages.select("page_id", host.alias("host"), path.alias("path"), canonical(F.col("url")).alias("canon"))
    block, mask = _address(F.col("canon"), blocks)
    rows = rows.withColumns({"block": block, "bits": mask}).join(table, "block", "left")
    rows = rows.withColumn("possible", F.coalesce(F.col("mask").bitwiseAND(F.col("bits")) == F.col("bits"), F.lit(False)) & F.col("canon").isNotNull())
    keep = ["page_id", "host", "path", "canon", "possible"]
    sure = rows.where("possible").select(keep).join(listed.withColumn("listed", F.lit(True)), "canon", "left").withColumn("listed", F.coalesce("listed", F.lit(False)))
    rest = rows.where("not possible").select(keep).withColumn("listed", F.lit(False))
    which, says = rule_of(F.col("host"), F.col("path"), rules)
    method = F.when(F.col("listed"), "block").otherwise("allow")
    return sure.unionByName(rest).select("page_id", "host", "path", which.alias("rule"), F.coalesce(says, method).alias("verdict"), "listed", "possible")


def tracker_list(pages: DataFrame) -> DataFrame:
    """The stand-in for an outside list: canonical URLs of the table's hosts that have a tracker's label."""
    host, _ = host_and_path(F.col("url"))
    return pages.where(host.rlike(TRACKER)).select(canonical(F.col("url")).alias("canon"))


#: A host label that starts with ad(s)-, track or pixel.
TRACKER = r"(^|\.)(ads?-|track|pixel)"

ORACLE = r"""
with a as (select page_id, url, case when strpos(url, '://') > 0 then substr(url, strpos(url, '://') + 3) else '' end as rest from pages),
b as (select page_id, url,
  translate(regexp_extract(rest, '^[^/?#]*', 0), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') as host,
  regexp_extract(rest, '^[^/?#]*(/[^?#]*)', 1) as path,
  regexp_replace(regexp_replace(regexp_extract(url, '^[^?#]*\?([^#]*)', 1), '(^|&)utm_[^&]*', '', 'g'), '^&', '') as query from a),
c as (select page_id, host, path, case when strpos(url, '://') > 0 then
  regexp_replace(regexp_replace(host, ':(80|443)$', ''), '^(www\.|m\.)+', '') || regexp_replace(path, '/+$', '') || case when query = '' then '' else '?' || query end end as canon from b),
listed as (select distinct canon from c where regexp_matches(host, '(^|\.)(ads?-|track|pixel)') and canon is not null),
d as (select c.page_id, c.host, c.path,
  case when (host = 'example.net' or ends_with(host, '.example.net')) and starts_with(path, '/en/') then 'example.net/en/'
       when (host = 'example.com' or ends_with(host, '.example.com')) and starts_with(path, '/de/') then 'example.com/de/'
       when (host = 'org' or ends_with(host, '.org')) and starts_with(path, '/fr/') then 'org/fr/'
       when (host = 'net' or ends_with(host, '.net')) and starts_with(path, '/') then 'net/' end as rule,
  listed.canon is not null as hit from c left join listed on c.canon = listed.canon)
select page_id, host, path, rule, case when rule in ('net/', 'example.com/de/') then 'block' when rule is not null then 'allow' when hit then 'block' else 'allow' end as verdict from d
"""
