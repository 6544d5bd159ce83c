"""URL filters by a temporal list join. Native: DataFrame functions alone.

A list is a log of dated entries (domain, list, action add or remove, day). Each entry is valid from its day to the next
entry of the same (domain, list); open ends stay valid. Every suffix of a capture's host asks for its day: an as-of join
gives each (domain, day) that is asked for the last entry of either list that began no later, by one pass over both in the
order of days, and the entry counts if it still holds. So a domain's history meets the days once each, whatever number of
hosts and captures ask. The longest listed suffix decides, and at equal length ``allow`` wins over ``block``; lists of other
names aren't read.

Edge cases: a null or hostless URL gives host null and verdict ``invalid``; hosts are lower-cased and lose a dot at the end; a
URL may begin with its two slashes; an address of numbers or in brackets has no parent domains; an unlisted host or a day before the first
entry gives ``keep``; entries of one day count in the order remove, add; repeated captures keep their rows; empty lists or
tables work; columns other than the named ones are not read.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from rgsketch.llm.common import materialize, maybe_broadcast

HOST = r"^(?:[A-Za-z][A-Za-z0-9+.-]*:)?//(?:[^/?#@]*@)?(\[[0-9A-Fa-f:.]+\]|[^/?#:@]+)"
ADDRESS = r"^(?:\[.*|[0-9]{1,3}(?:\.[0-9]{1,3}){3})$"
LISTS = ("block", "allow")


def intervals(entries: DataFrame) -> DataFrame:
    """(domain, list, valid_from, valid_to) of the entries in force; valid_to is the first day no longer held, or null."""
    log = Window.partitionBy("domain", "list").orderBy("day", F.col("action") == "add")
    held = entries.withColumn("valid_to", F.lead("day").over(log)).where("action = 'add'").withColumnRenamed("day", "valid_from")
    return held.where("valid_to IS NULL OR valid_to > valid_from").select("domain", "list", "valid_from", "valid_to").distinct()


def host_of(url: F.Column) -> F.Column:
    host = F.regexp_replace(F.lower(F.regexp_extract(url, HOST, 1)), r"\.+$", "")
    return F.when(host != "", host)


def suffixes(host: F.Column) -> F.Column:
    """The host and each parent domain of two labels or more (a single label stands for itself)."""
    labels = F.split(host, r"\.")
    n = F.size(labels)
    last = F.when(host.rlike(ADDRESS), 1).otherwise(F.greatest(F.lit(1), n - 1))
    return F.transform(F.sequence(F.lit(1), last), lambda i: F.array_join(F.slice(labels, i, n), "."))


def in_force(asked: DataFrame, held: DataFrame) -> DataFrame:
    """(domain, day, list, valid_from, valid_to) of the asked (domain, day) on which an interval holds, ``allow`` first. An
    as-of join: entries and days in one order, the last entry of each list carried on to the days after it."""
    known = asked.select("domain").distinct()
    entry = F.struct("list", "valid_from", "valid_to")
    both = held.where(F.col("list").isin(*LISTS)).join(known, "domain", "left_semi").select("domain", F.col("valid_from").alias("day"), F.lit(0).alias("asks"), entry.alias("e"))
    both = both.unionByName(asked.select("domain", "day", F.lit(1).alias("asks")), allowMissingColumns=True)
    run = Window.partitionBy("domain").orderBy("day", "asks").rowsBetween(Window.unboundedPreceding, 0)
    last = {name: F.last(F.when(F.col("e.list") == name, F.col("e")), ignorenulls=True).over(run) for name in LISTS}
    rows = both.withColumns(last).where("asks = 1 AND day IS NOT NULL")
    holds = lambda e: F.when(F.col(e).isNotNull() & (F.col(f"{e}.valid_to").isNull() | (F.col("day") < F.col(f"{e}.valid_to"))), F.col(e))
    return rows.select("domain", "day", F.coalesce(holds("allow"), holds("block")).alias("hit")).where("hit IS NOT NULL").select("domain", "day", "hit.*")


def classify(captures: DataFrame, entries: DataFrame, id_col: str = "page_id", url_col: str = "url", day_col: str = "day") -> DataFrame:
    """page_id, host, day, verdict (block, keep, allow, invalid), domain, valid_from, valid_to; a row for every capture.

    What is in force on the days asked for is broadcast when its counted rows are few; past that the joins shuffle.
    """
    caps = captures.select(F.col(id_col).alias("page_id"), host_of(F.col(url_col)).alias("host"), F.col(day_col).alias("day"))
    hosts = caps.where("host IS NOT NULL").select("host", "day").distinct()  # verdicts hang on host and day alone
    parts = hosts.withColumn("domain", F.explode(suffixes(F.col("host"))))
    force = materialize(in_force(parts.select("domain", "day").distinct(), intervals(entries)))
    hits = parts.join(maybe_broadcast(force, force.count()), ["domain", "day"])
    best = F.max(F.struct(F.length("domain").alias("n"), "domain", "list", "valid_from", "valid_to"))
    found = hits.groupBy("host", "day").agg(best.alias("hit"))
    verdict = F.when(F.col("host").isNull(), "invalid").otherwise(F.coalesce("hit.list", F.lit("keep")))
    return caps.join(found, ["host", "day"], "left").select("page_id", "host", "day", verdict.alias("verdict"), "hit.domain", "hit.valid_from", "hit.valid_to")


def _draw(col: F.Column, salt: str, n: int) -> F.Column:
    return F.pmod(F.conv(F.substring(F.md5(F.concat(F.lit(salt), col).cast("binary")), 1, 7), 16, 10).cast("long"), F.lit(n)).cast("int")


def sample_entries(pages: DataFrame, start: str = "2024-01-01") -> DataFrame:
    """A dated list made by rule, as the tables hold none: of the pages' hosts and their parents, two of five are blocked
    from a drawn day on, half of those are freed after a drawn span, and one of eleven is allowed from a drawn day on."""
    names = pages.select(host_of(F.col("url")).alias("h")).where("h IS NOT NULL").distinct().select(F.explode(suffixes(F.col("h"))).alias("domain")).distinct()
    day = F.date_add(F.lit(start).cast("date"), _draw(F.col("domain"), "day:", 300))
    block = names.where(_draw(F.col("domain"), "block:", 5) < 2)
    parts = [
        block.select("domain", F.lit("block").alias("list"), F.lit("add").alias("action"), day.alias("day")),
        block.where(_draw(F.col("domain"), "free:", 2) == 0).select("domain", F.lit("block").alias("list"), F.lit("remove").alias("action"), F.date_add(day, _draw(F.col("domain"), "span:", 60) + 1).alias("day")),
        names.where(_draw(F.col("domain"), "allow:", 11) == 0).select("domain", F.lit("allow").alias("list"), F.lit("add").alias("action"), day.alias("day")),
    ]
    return parts[0].unionByName(parts[1]).unionByName(parts[2])


def query(spark, sf_dir: str) -> DataFrame:
    """Every page, fetched on a day of 2024 that its id draws, against the list made by rule."""
    pages = spark.read.parquet(f"{sf_dir}/pages.parquet").select("page_id", "url")
    captures = pages.withColumn("day", F.date_add(F.lit("2024-01-01").cast("date"), F.pmod("page_id", F.lit(366)).cast("int")))
    return classify(captures, sample_entries(pages))


ORACLE = r"""
WITH caps AS (
  SELECT page_id, nullif(regexp_replace(lower(regexp_extract(url, '^(?:[A-Za-z][A-Za-z0-9+.-]*:)?//(?:[^/?#@]*@)?(\[[0-9A-Fa-f:.]+\]|[^/?#:@]+)', 1)), '\.+$', ''), '') AS host, (DATE '2024-01-01' + (page_id % 366)::INT)::DATE AS day FROM pages),
parts AS (
  SELECT host, unnest(list_transform(range(1, CASE WHEN regexp_matches(host, '^(?:\[.*|[0-9]{1,3}(?:\.[0-9]{1,3}){3})$') THEN 2 ELSE greatest(1, len(string_split(host, '.')) - 1) + 1 END), lambda i: array_to_string(string_split(host, '.')[i:], '.'))) AS domain
  FROM (SELECT DISTINCT host FROM caps WHERE host IS NOT NULL)),
names AS (SELECT DISTINCT domain FROM parts),
drawn AS (
  SELECT domain, (DATE '2024-01-01' + (('0x' || substr(md5('day:' || domain), 1, 7))::BIGINT % 300)::INT)::DATE AS day, ('0x' || substr(md5('block:' || domain), 1, 7))::BIGINT % 5 AS b,
         ('0x' || substr(md5('free:' || domain), 1, 7))::BIGINT % 2 AS f, (('0x' || substr(md5('span:' || domain), 1, 7))::BIGINT % 60 + 1)::INT AS span, ('0x' || substr(md5('allow:' || domain), 1, 7))::BIGINT % 11 AS a
  FROM names),
held AS (
  SELECT domain, 'block' AS list, day AS valid_from, CASE WHEN f = 0 THEN (day + span)::DATE END AS valid_to FROM drawn WHERE b < 2
  UNION ALL SELECT domain, 'allow', day, NULL::DATE FROM drawn WHERE a = 0),
hits AS (
  SELECT c.host, c.day, h.*, row_number() OVER (PARTITION BY c.host, c.day ORDER BY length(h.domain) DESC, h.list = 'allow' DESC) AS k
  FROM (SELECT DISTINCT host, day FROM caps) c JOIN parts p ON p.host = c.host JOIN held h ON h.domain = p.domain AND h.valid_from <= c.day AND (h.valid_to IS NULL OR c.day < h.valid_to))
SELECT c.page_id, c.host, c.day, CASE WHEN c.host IS NULL THEN 'invalid' ELSE coalesce(h.list, 'keep') END AS verdict, h.domain, h.valid_from, h.valid_to
FROM caps c LEFT JOIN hits h ON h.host = c.host AND h.day = c.day AND h.k = 1
"""
