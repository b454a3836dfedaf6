"""URL filter rules as a sort-merge range join over reversed-host keys, in DataFrame operations only.

A host's canonical key is its labels in reverse, each closed by a dot: ``a.b.net`` -> ``net.b.a.``. A rule host then
covers the keys that start with its own key, which is one interval of the sorted keys, and two such intervals nest
or are disjoint. Urls and rule starts are sorted together. The sweep keeps for each row the stack of the rule that
started last (that rule and those around it); rules already closed are popped by comparing keys. Sorting is by range
partitions with the page id as tie-break, so a hot host spreads over tasks; each partition takes over the stack that
is open where it begins, one row per partition.

The stack of a rule start holds the rules on its chain of parent hosts. Rules are configuration: their number and the
rules of one chain must fit a task. Nothing of the pages is ever gathered.

Null url or no ``://``: host and path are empty, no rule fits. Rows with null or repeated ids are judged each.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from seqvault.operators.prefix import PART, place_by_range

UPPER, LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"
#: host up to / ? # after the first ://, then the path up to ? or #
SPLIT = r"(?s)^.*?://([^/?#]*)([^?#]*)"
#: Fixed values of the query: verdict, host, path.
RULES = [("block", "net", "/"), ("allow", "example.net", "/en/"), ("block", "example.com", "/de/"), ("allow", "org", "/fr/")]
DEFAULT = "allow"


def host_key(host: Column) -> Column:
    """Reversed labels, each closed by a dot; the empty host has the empty key."""
    return F.when(host == "", F.lit("")).otherwise(F.concat(F.array_join(F.reverse(F.split(host, r"\.")), "."), F.lit(".")))


def split_url(url: Column) -> tuple[Column, Column]:
    """Lower-cased host and path; empty where there is no ``://``."""
    text = F.coalesce(url, F.lit(""))
    return F.translate(F.regexp_extract(text, SPLIT, 1), UPPER, LOWER), F.regexp_extract(text, SPLIT, 2)


def rule_table(spark: SparkSession, rules: list[tuple[str, str, str]]) -> DataFrame:
    """Rules as rows: verdict, rule, rule_path, rule_key."""
    frame = spark.createDataFrame(rules, "verdict string, rule_host string, rule_path string")
    return frame.select("verdict", F.concat("rule_host", "rule_path").alias("rule"), "rule_path", host_key(F.translate("rule_host", UPPER, LOWER)).alias("rule_key"))


def rule_starts(rules: DataFrame) -> DataFrame:
    """One row per rule host: its key and its stack (its own rules and those of its parent hosts)."""
    hosts = rules.select(F.col("rule_key").alias("key")).distinct()
    labels = F.split(F.col("key"), r"\.")
    chain = F.transform(F.sequence(F.lit(1), F.size(labels) - 1), lambda n: F.concat(F.array_join(F.slice(labels, F.lit(1), n), "."), F.lit(".")))
    entry = F.struct(F.length("rule").alias("size"), "rule", "verdict", "rule_path", "rule_key")
    return hosts.select("key", F.explode(chain).alias("rule_key")).join(rules, "rule_key").groupBy("key").agg(F.sort_array(F.collect_list(entry)).alias("stack"))


def judge(pages: DataFrame, rules: DataFrame, default: str = DEFAULT, id_col: str = "page_id", url_col: str = "url") -> DataFrame:
    """page_id, host, path, rule (the longest that fits, ties by its text, or null) and verdict of every row."""
    host, path = split_url(F.col(url_col))
    urls = pages.select(F.col(id_col).alias("_id"), host.alias("_host"), path.alias("_path"))
    starts = rule_starts(rules)
    stack_type = starts.schema["stack"].dataType
    rows = urls.select(host_key(F.col("_host")).alias("key"), F.lit(1).alias("kind"), "_id", "_host", "_path", F.lit(None).cast(stack_type).alias("stack"))
    opens = starts.select("key", F.lit(0).alias("kind"), F.lit(None).cast(urls.schema["_id"].dataType).alias("_id"), F.lit(None).cast("string").alias("_host"), F.lit(None).cast("string").alias("_path"), "stack")
    placed = place_by_range(rows.unionByName(opens), ["key", "kind", "_id"], "urls")

    sweep = Window.partitionBy(PART).orderBy("key", "kind").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    last = placed.groupBy(PART).agg(F.max_by(F.when(F.col("kind") == 0, F.col("stack")), F.when(F.col("kind") == 0, F.col("key"))).alias("stack"))
    earlier = Window.orderBy(PART).rowsBetween(Window.unboundedPreceding, -1)
    carried = last.select(PART, F.last("stack", ignorenulls=True).over(earlier).alias("_carried"))
    swept = (
        placed.withColumn("_open", F.last("stack", ignorenulls=True).over(sweep))
        .join(carried, PART)
        .filter("kind = 1")
        .withColumn("_open", F.coalesce("_open", "_carried"))
    )
    fits = F.filter("_open", lambda r: F.col("key").startswith(r["rule_key"]) & F.col("_path").startswith(r["rule_path"]))
    return swept.withColumn("_best", F.array_max(fits)).select(
        F.col("_id").alias(id_col),
        F.col("_host").alias("host"),
        F.col("_path").alias("path"),
        F.col("_best.rule").alias("rule"),
        F.coalesce(F.col("_best.verdict"), F.lit(default)).alias("verdict"),
    )


JUDGE_SQL = """
WITH cut AS (
  SELECT page_id, coalesce(url, '') AS u, strpos(coalesce(url, ''), '://') AS mark FROM pages
), parts AS (
  SELECT page_id,
    CASE WHEN mark = 0 THEN '' ELSE regexp_extract(substr(u, mark + 3), '^[^/?#]*') END AS raw,
    CASE WHEN mark = 0 THEN '' ELSE regexp_extract(substr(u, mark + 3), '^[^/?#]*([^?#]*)', 1) END AS path
  FROM cut
), named AS (
  SELECT page_id, translate(raw, 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') AS host, path FROM parts
), rules(verdict, rhost, rpath) AS (
  VALUES ('block', 'net', '/'), ('allow', 'example.net', '/en/'), ('block', 'example.com', '/de/'), ('allow', 'org', '/fr/')
), best AS (
  SELECT n.page_id, n.host, n.path, r.rhost || r.rpath AS rule, r.verdict,
    row_number() OVER (PARTITION BY n.page_id ORDER BY length(r.rhost || r.rpath) DESC NULLS LAST) AS k
  FROM named n LEFT JOIN rules r
    ON (n.host = r.rhost OR ends_with(n.host, '.' || r.rhost)) AND starts_with(n.path, r.rpath)
)
SELECT page_id, host, path, rule, coalesce(verdict, 'allow') AS verdict FROM best WHERE k = 1
"""
