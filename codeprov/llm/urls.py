"""URL filters by a temporal list join.

Lists of hosts and of path prefixes change over time: dated entries (added, removed) become validity
intervals [from, to). A capture of a URL is asked under its host, every parent domain and every path
prefix that an entry could have, and joined as of its fetch time with the entries active then. Captures
of one URL at one time are looked up once, however often they occur.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

#: Intervals are broadcast up to this number of rows; beyond it they are joined by a shuffle.
MOST_BROADCAST = 200_000


def host(url) -> F.Column:
    """Lower-case host without user and port; empty where there is none."""
    return F.regexp_extract(F.lower(url), r"^[a-z][a-z0-9+.-]*://(?:[^/?#@]*@)?([^/?#:@]*)", 1)


def path(url) -> F.Column:
    """Path as written, with its leading slash."""
    return F.regexp_extract(url, r"^[A-Za-z][A-Za-z0-9+.-]*://[^/?#]*(/[^?#]*)", 1)


def intervals(entries: DataFrame) -> DataFrame:
    """``entry, valid_from, valid_to`` (null: still active) of dated entries ``entry, action, at``.

    ``action`` is add or remove; anything else, and rows with nulls, are left out. An addition while the entry
    is active, and a removal while it is not, change nothing. Of both at one time the removal counts.
    """
    clean = entries.where("entry IS NOT NULL AND at IS NOT NULL AND action IN ('add', 'remove')")
    once = clean.groupBy("entry", "at").agg(F.min(F.col("action") == "add").alias("on"))
    by = Window.partitionBy("entry").orderBy("at")
    turned = once.withColumn("was", F.coalesce(F.lag("on").over(by), F.lit(False))).where("on <> was")
    return turned.withColumn("to", F.lead("at").over(by)).where("on").select("entry", F.col("at").alias("valid_from"), F.col("to").alias("valid_to"))


def keys(url, depth: int) -> F.Column:
    """What a URL may be listed as: its host, each parent domain, host and the first 1 to ``depth`` path segments."""
    h = host(url)
    labels = F.split(h, r"\.")
    domains = F.transform(F.sequence(F.lit(1), F.size(labels)), lambda i: F.array_join(F.slice(labels, i, F.size(labels)), "."))
    if depth < 1:
        return F.when(h != "", domains)
    segments = F.slice(F.filter(F.split(path(url), "/"), lambda s: s != ""), 1, depth)
    n = F.least(F.size(segments), F.lit(depth))
    paths = F.when(n > 0, F.transform(F.sequence(F.lit(1), F.greatest(n, F.lit(1))), lambda i: F.concat(h, F.lit("/"), F.array_join(F.slice(segments, F.lit(1), i), "/")))).otherwise(F.array().cast("array<string>"))
    return F.when(h != "", F.concat(domains, paths))


def evaluate(captures: DataFrame, entries: DataFrame, url: str = "url", at: str = "fetched_at", most_broadcast: int = MOST_BROADCAST) -> DataFrame:
    """``captures`` with host, n_active (entries active at the fetch time), entry (the longest of them, the last in order on ties) and blocked.

    A null or hostless URL and a null time are never blocked. An entry that starts at the fetch time counts,
    one that ends then does not. Repeated captures each keep their row. Empty tables are fine on either side.
    """
    valid = intervals(entries)
    size = valid.agg(F.count("*").alias("n"), F.max(F.size(F.split("entry", "/"))).alias("d")).first()
    depth = max(0, (size["d"] or 1) - 1)
    asked = captures.select(F.col(url).alias("_u"), F.col(at).alias("_t")).where("_u IS NOT NULL AND _t IS NOT NULL").distinct()
    asked = asked.select("_u", "_t", F.explode(F.array_distinct(keys(F.col("_u"), depth))).alias("_k"))
    valid = F.broadcast(valid) if size["n"] <= most_broadcast else valid
    found = asked.join(valid, (F.col("_k") == F.col("entry")) & (F.col("valid_from") <= F.col("_t")) & (F.col("valid_to").isNull() | (F.col("_t") < F.col("valid_to"))))
    found = found.groupBy("_u", "_t").agg(F.count("*").alias("n_active"), F.max(F.struct(F.length("entry"), "entry")).alias("_e")).select("_u", "_t", "n_active", F.col("_e.entry").alias("entry"))
    own = captures.drop("host", "n_active", "entry", "blocked", "_u", "_t")
    out = own.join(found, (own[url] == found["_u"]) & (own[at] == found["_t"]), "left").drop("_u", "_t")
    return out.withColumns({"host": F.coalesce(host(F.col(url)), F.lit("")), "n_active": F.coalesce("n_active", F.lit(0).cast("long")), "blocked": F.col("entry").isNotNull()})


def example_entries(pages: DataFrame) -> DataFrame:
    """A dated list made from the hosts and first path segments of ``pages`` by the md5 of their names.

    Of three names one is added in 2024; of these every second is removed 60 days later; of these every
    second is added again after another 60 days.
    """
    h = host(F.col("url"))
    first = F.regexp_extract("url", r"^[A-Za-z][A-Za-z0-9+.-]*://[^/?#]*/([^/?#]+)", 1)
    names = pages.where("url IS NOT NULL").select(F.explode(F.array(h, F.concat(h, F.lit("/"), first))).alias("entry")).where("entry NOT LIKE '%/' AND entry <> ''").distinct()
    names = names.withColumn("m", F.conv(F.substring(F.md5(F.col("entry").cast("binary")), 1, 4), 16, 10).cast("int")).where("m % 3 = 0")
    day = lambda d: F.expr(f"timestamp_ntz'2024-01-01 00:00:00' + make_dt_interval(m % 200 + {d})")
    rows = [("add", 0, 1), ("remove", 60, 6), ("add", 120, 12)]
    out = names.select("entry", "m", F.inline(F.array(*(F.struct(F.lit(a).alias("action"), day(d).alias("at"), F.lit(k).alias("k")) for a, d, k in rows))))
    return out.where("m % k = 0").select("entry", "action", "at")


def example_captures(pages: DataFrame) -> DataFrame:
    """``pages`` with a fetch time on some day of 2024, by the page's number."""
    return pages.select("page_id", "url", F.expr("timestamp_ntz'2024-01-01 00:00:00' + make_dt_interval(CAST(page_id * 37 % 366 AS INT))").alias("fetched_at"))


SQL = r"""
WITH p AS (SELECT page_id, url, TIMESTAMP '2024-01-01' + INTERVAL 1 DAY * CAST(page_id * 37 % 366 AS INT) AS t,
    regexp_extract(lower(url), '^[a-z][a-z0-9+.-]*://(?:[^/?#@]*@)?([^/?#:@]*)', 1) AS h,
    regexp_extract(url, '^[A-Za-z][A-Za-z0-9+.-]*://[^/?#]*/([^/?#]+)', 1) AS s FROM pages),
names AS (SELECT DISTINCT e AS entry, ('0x' || substr(md5(e), 1, 4))::INT AS m FROM (SELECT unnest([h, h || '/' || s]) AS e FROM p) WHERE e NOT LIKE '%/' AND e <> ''),
listed AS (SELECT entry, TIMESTAMP '2024-01-01' + INTERVAL 1 DAY * (m % 200) AS f,
    CASE WHEN m % 6 = 0 THEN TIMESTAMP '2024-01-01' + INTERVAL 1 DAY * (m % 200 + 60) END AS u FROM names WHERE m % 3 = 0
  UNION ALL SELECT entry, TIMESTAMP '2024-01-01' + INTERVAL 1 DAY * (m % 200 + 120), NULL FROM names WHERE m % 12 = 0),
labels AS (SELECT DISTINCT h, string_split(h, '.') AS l FROM p WHERE h <> ''),
asked AS (SELECT h, array_to_string(l[i:], '.') AS k FROM labels, LATERAL (SELECT unnest(range(1, len(l) + 1)) AS i)),
pairs AS (SELECT page_id, url, t, k FROM p JOIN asked USING (h) UNION SELECT page_id, url, t, h || '/' || s FROM p WHERE h <> '' AND s <> ''),
hits AS (SELECT page_id, url, count(*) AS n, arg_max(entry, (length(entry), entry)) AS entry FROM pairs JOIN listed ON k = entry AND f <= t AND (u IS NULL OR t < u) GROUP BY ALL)
SELECT p.page_id, p.url, p.h AS host, strftime(p.t, '%Y-%m-%d') AS fetched_on, coalesce(hits.n, 0)::BIGINT AS n_active, hits.entry, hits.entry IS NOT NULL AS blocked
FROM p LEFT JOIN hits ON p.page_id = hits.page_id AND p.url = hits.url
"""
