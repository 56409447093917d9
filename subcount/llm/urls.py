"""URL filters over time: dated list entries become validity intervals, captures are judged as of their fetch.

A list is a table of events (pattern, day, action add or remove, list). Patterns are a host, a parent
domain or a host with its first path part. intervals() turns each pattern's events into [from, until). A
capture is checked against every pattern it could match, by equality on the pattern and its day within the
interval; intervals of one pattern and list never overlap, so there is one match at most for each.

The verdict depends only on (host, first path part, day), so captures are reduced to distinct triples
before anything is shuffled on a host: a hot host counts once a day and path part. Every host asks for its top-level
domain, so a pattern that more than a thousandth of the questions ask for (there are a thousand at most) is salted:
its questions are dealt to SALTS parts and its intervals copied to each. DataFrame functions only.

Defined cases: null or unparsable urls match nothing; of events of one pattern and day `remove` holds;
repeated events and captures change nothing and captures keep their number; without entries nothing is
blocked; a null fetch day matches nothing; further columns are kept unless a result column has their name.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

FOREVER = 1 << 40
_URL = r"^[A-Za-z][A-Za-z0-9+.-]*://(?:[^/?#@]*@)?([^/:?#]+)(?::[0-9]*)?(?:/([^/?#]*))?"
RESULTS = ("host", "part", "n_matches", "matched", "blocked")
HOT, SALTS = 1000, 64  # a hot pattern takes more than 1 / HOT of the questions


def intervals(events: DataFrame) -> DataFrame:
    """pattern, list, from_day, until_day of the times at which entries hold."""
    e = events.where("pattern is not null and day is not null").groupBy("pattern", "list", "day").agg(F.min(F.when(F.col("action") == "add", 1).otherwise(0)).alias("on"))
    until = F.lead("day", 1, FOREVER).over(Window.partitionBy("pattern", "list").orderBy("day"))
    return e.select("pattern", "list", "on", F.col("day").alias("from_day"), until.alias("until_day")).where("on = 1").drop("on")


def located(captures: DataFrame, url: str = "url") -> DataFrame:
    host = F.nullif(F.lower(F.regexp_extract(F.col(url), _URL, 1)), F.lit(""))
    part = F.nullif(F.regexp_extract(F.col(url), _URL, 2), F.lit(""))
    kept = [F.col(f"`{c}`") for c in captures.columns if c not in RESULTS]
    return captures.select(*kept, host.alias("host"), part.alias("part"))


def judge(captures: DataFrame, events: DataFrame, url: str = "url", day: str = "fetch_day") -> DataFrame:
    """The captures with host, part, n_matches, matched (patterns, sorted) and blocked."""
    seen = located(captures, url)
    spots = seen.select("host", "part", F.col(day).alias("at")).where("host is not null and at is not null").distinct()
    labels = F.split("host", r"\.")
    levels = F.transform(F.sequence(F.lit(1), F.size(labels)), lambda i: F.array_join(F.slice(labels, i, F.size(labels)), "."))
    keys = F.array_compact(F.array_append(levels, F.concat("host", F.lit("/"), "part")))
    asked = spots.select("host", "part", "at", F.explode(F.array_distinct(keys)).alias("pattern"))
    weight = asked.groupBy("pattern").agg(F.count("*").alias("n"))
    hot = weight.join(F.broadcast(weight.agg(F.sum("n").alias("all")))).where(F.col("n") * HOT > F.col("all"))
    hot = F.broadcast(hot.select("pattern", F.lit(True).alias("hot")))
    deal = F.pmod(F.xxhash64("host", "part", "at"), F.lit(SALTS)).cast("int")
    asked = asked.join(hot, "pattern", "left").withColumn("salt", F.when(F.col("hot"), deal).otherwise(0))
    copies = F.explode(F.sequence(F.lit(0), F.when(F.col("hot"), SALTS - 1).otherwise(0)))
    held = intervals(events).join(hot, "pattern", "left").withColumn("salt", copies)
    hits = asked.join(held, ["pattern", "salt"]).where("at >= from_day and at < until_day")
    found = hits.groupBy("host", "part", "at").agg(
        F.count("*").alias("n_matches"), F.array_join(F.array_sort(F.collect_set("pattern")), " ").alias("matched")
    )
    c, v = seen.alias("c"), found.alias("v")
    same = (F.col("c.host") == F.col("v.host")) & F.col("c.part").eqNullSafe(F.col("v.part")) & (F.col(f"c.`{day}`") == F.col("v.at"))
    return c.join(v, same, "left").select(
        *[F.col(f"c.`{x}`").alias(x) for x in seen.columns],
        F.coalesce("v.n_matches", F.lit(0)).cast("long").alias("n_matches"),
        F.coalesce("v.matched", F.lit("")).alias("matched"),
        F.col("v.n_matches").isNotNull().alias("blocked"),
    )


def example_list(hosts: DataFrame) -> DataFrame:
    """Dated entries for the hosts of a table, from their hashes: adds, removals and returns on three levels."""
    base = hosts.select("host", "part").where("host is not null").distinct()
    alone = base.select("host").distinct()
    parent = F.regexp_replace("host", r"^[^.]*\.", "")
    up = alone.select(parent.alias("host")).distinct()

    def some(df, pattern, k, of, name):
        n = F.conv(F.substring(F.md5(pattern.cast("binary")), 1, 7), 16, 10).cast("long")
        dated = [("add", n % 200, F.lit(True)), ("remove", n % 200 + 60, n % 7 < 4), ("add", n % 200 + 120, n % 5 == 0)]
        picked = df.where(n % of < k)
        out = picked.select(
            pattern.alias("pattern"),
            F.lit(name).alias("list"),
            F.explode(F.array_compact(F.array(*[F.when(c, F.struct(d.alias("day"), F.lit(a).alias("action"))) for a, d, c in dated]))).alias("e"),
        )
        return out.select("pattern", "list", F.col("e.day").alias("day"), F.col("e.action").alias("action"))

    return (
        some(alone, F.col("host"), 1, 3, "hosts")
        .unionByName(some(up, F.col("host"), 1, 2, "domains"))
        .unionByName(some(base.where("part is not null"), F.concat("host", F.lit("/"), "part"), 1, 4, "paths"))
    )
