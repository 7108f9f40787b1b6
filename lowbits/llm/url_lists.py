"""URL filters: temporal list join (operator 4), DataFrame functions only.

A list feed has dated entries (kind, key, action add or remove, day, category).  Entries of one (kind, key, category)
become validity intervals [from, to): an add opens one unless one is open, a remove closes it; on one day removes
come after adds.  A capture is tested against the entries in force on its fetch day, by exact host, by every parent
domain, and by host plus first path segment.

The intervals of a key are folded to one row, so the as-of join is an equi-join on (kind, key) that returns at most
one row per site (host, first segment, fetch day) and key.  A list whose rows are within ``BROADCAST_ROWS`` is broadcast (size checked by a count);
beyond that both sides are spread over salts, so one host with a third of all captures meets many tasks.  No made-up row numbers are joined on, so a recomputed
partition gives the same rows.

Edge cases: null or unparsable URLs have an empty host and match nothing; a null fetch day matches nothing; entries with a
null key, kind or day are ignored, a null category is "listed"; repeated entries and rows change nothing; an empty list
blocks nothing; an empty table gives an empty table.  Extra columns are ignored.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

BROADCAST_ROWS, SALTS = 100_000, 16
HOST = r"^[A-Za-z][A-Za-z0-9+.-]*://([^/?#:]+)"
SEGMENT = r"^[A-Za-z][A-Za-z0-9+.-]*://[^/?#]+/([^/?#]+)"


def intervals(entries: DataFrame) -> DataFrame:
    """kind, key, category, from_day, to_day (null: still open), one row per time an entry was in force."""
    e = entries.where("kind is not null and key is not null and day is not null and action in ('add', 'remove')")
    e = e.select("kind", F.lower("key").alias("key"), F.coalesce("category", F.lit("listed")).alias("category"), F.col("day").cast("date").alias("day"), (F.col("action") == "add").cast("int").alias("open")).distinct()
    w = Window.partitionBy("kind", "key", "category").orderBy("day", F.col("open").desc())
    change = e.withColumn("was", F.coalesce(F.lag("open").over(w), F.lit(0))).where("open <> was")
    spans = change.withColumn("to_day", F.lead("day").over(w)).where("open = 1 and (to_day is null or to_day > day)")
    return spans.select("kind", "key", "category", F.col("day").alias("from_day"), "to_day")


def capture_keys(captures: DataFrame, url_col: str = "url") -> DataFrame:
    """captures with host, segment and keys (array of kind, key), which follow from host and segment."""
    host = F.lower(F.coalesce(F.regexp_extract(url_col, HOST, 1), F.lit("")))
    segment = F.coalesce(F.regexp_extract(url_col, SEGMENT, 1), F.lit(""))
    d = captures.withColumn("host", host).withColumn("segment", segment).withColumn("labels", F.split("host", r"\."))
    keys = F.expr(
        """case when host = '' then array() else concat(
            array(named_struct('kind', 'host', 'key', host)),
            transform(sequence(1, greatest(size(labels) - 1, 1)), i -> named_struct('kind', 'domain', 'key', array_join(slice(labels, i, size(labels)), '.'))),
            case when segment = '' then array() else array(named_struct('kind', 'prefix', 'key', concat(host, '/', segment))) end) end"""
    )
    return d.withColumn("keys", keys).drop("labels")


def evaluate(captures: DataFrame, entries: DataFrame, id_col: str = "page_id", url_col: str = "url", day_col: str = "fetched", broadcast_rows: int = BROADCAST_ROWS) -> DataFrame:
    """id, host, fetched, blocked, n_rules, rules (kind:key:category, sorted), listed_since; one row per row of captures."""
    spans = intervals(entries).groupBy("kind", "key").agg(F.collect_list(F.struct("from_day", "to_day", "category")).alias("spans"))  # one key's history
    rows = capture_keys(captures.select(F.col(id_col).alias("id"), F.col(url_col).alias("url"), F.col(day_col).cast("date").alias("fetched")), "url").drop("url")
    # a verdict follows from host, segment and day: each of these is tested once, however many captures share it
    site = ["host", "segment", "fetched"]
    tests = rows.where("fetched is not null").select(*site, "keys").distinct().select(*site, F.explode("keys").alias("k")).select(*site, "k.kind", "k.key")
    if spans.limit(broadcast_rows + 1).count() <= broadcast_rows:
        met = tests.join(F.broadcast(spans), ["kind", "key"])
    else:
        salted = spans.withColumn("salt", F.explode(F.sequence(F.lit(0), F.lit(SALTS - 1))))
        met = tests.withColumn("salt", F.pmod(F.xxhash64(*site), F.lit(SALTS)).cast("int")).join(salted, ["kind", "key", "salt"])
    held = met.select(*site, "kind", "key", F.filter("spans", lambda x: (x["from_day"] <= F.col("fetched")) & (x["to_day"].isNull() | (F.col("fetched") < x["to_day"]))).alias("held"))
    rules = held.where("size(held) > 0").groupBy(*site).agg(
        F.array_sort(F.flatten(F.collect_list(F.transform("held", lambda x: F.concat_ws(":", "kind", "key", x["category"]))))).alias("rules"),
        F.min(F.array_min(F.transform("held", lambda x: x["from_day"]))).alias("listed_since"),
    )  # at most the keys of one URL
    out = rows.drop("keys").join(rules, site, "left")
    return out.select(F.col("id").alias(id_col), "host", "fetched", F.col("rules").isNotNull().alias("blocked"), F.coalesce(F.size("rules"), F.lit(0)).cast("long").alias("n_rules"), F.coalesce(F.array_join("rules", ","), F.lit("")).alias("rules"), F.col("listed_since"))


def _number(text: str) -> str:
    return f"cast(conv(substr(md5({text}), 1, 7), 16, 10) as bigint)"


def dated_captures(pages: DataFrame) -> DataFrame:
    """page_id, url and a fetch day made from the id, as the given pages carry none."""
    day = f"date_add(date'2024-01-01', cast({_number("concat('fetch:', cast(page_id as string))")} % 366 as int))"
    return pages.select("page_id", "url", F.expr(day).alias("fetched"))


def derived_feed(pages: DataFrame) -> DataFrame:
    """A list feed made by rule from the hosts and first path segments that occur: dated adds, removes and second adds."""
    keyed = capture_keys(pages.select("url").where("url is not null"))
    keys = keyed.select(F.explode("keys").alias("k")).select("k.kind", "k.key").distinct()
    seeded = keys.withColumn("m", F.expr(_number("concat(kind, ':', key)"))).where("m % 3 = 0")
    start = "date_add(date'2024-01-01', cast(m % 366 as int))"
    return seeded.select(
        "kind",
        "key",
        F.when(F.col("m") % 2 == 0, "adult").otherwise("malware").alias("category"),
        F.explode(
            F.expr(
                f"""filter(array(
                    named_struct('day', {start}, 'action', 'add', 'use', true),
                    named_struct('day', date_add({start}, 20 + cast(m % 60 as int)), 'action', 'remove', 'use', m % 4 <> 1),
                    named_struct('day', date_add({start}, 120), 'action', 'add', 'use', m % 5 = 0)), x -> x.use)"""
            )
        ).alias("e"),
    ).select("kind", "key", "category", "e.day", "e.action")
