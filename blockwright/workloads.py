"""The experiments' record sets and labelled pairs, from the given tables."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .functions.scratch import cut
from .model import Attribute, BlockingSpec


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


# D: documents -------------------------------------------------------------------

DOC_SPEC = BlockingSpec(
    "doc_id",
    (
        Attribute("lang", "code", "lang"),
        Attribute("line1", "text", "substring_index(text, '\\n', 1)", "split_part(text, chr(10), 1)"),
        Attribute("n_chars", "int", "n_chars"),
        Attribute("source", "code", "source"),
        Attribute("text", "token_text", "text"),
    ),
)


def doc_pairs(docs: DataFrame, threshold: float = 0.5, k: int = 5) -> DataFrame:
    """(l_id, r_id, jaccard, exact): documents whose sets of k-word runs have a Jaccard similarity of at least `threshold`.

    Equal words are one node, whose documents are all pairs. Two nodes as similar as that
    share a run among the rarest of either, n - ceil(threshold n) + 1 of n, when all runs are
    ordered by how many nodes hold them; so candidates share such a run and none is lost.
    Runs of one node alone come first in that order and add to no overlap, so they are only counted.
    """
    text = F.lower(F.trim(F.regexp_replace("text", r"\s+", " ")))
    members = docs.where("text IS NOT NULL").select("doc_id", F.xxhash64("text").alias("t"), F.xxhash64(text).alias("node"))
    words = docs.where("text IS NOT NULL").select(text.alias("text")).select("text", F.xxhash64("text").alias("node")).dropDuplicates(["node"]).select("node", F.split("text", " ").alias("w"))
    runs = F.when(F.size("w") < k, F.array(F.array_join("w", " "))).otherwise(F.array_distinct(F.transform(F.sequence(F.lit(1), F.size("w") - k + 1), lambda i: F.array_join(F.slice("w", i, k), " "))))
    sets = words.select("node", F.transform(runs, lambda r: F.xxhash64(r)).alias("s"))
    # explode would have Spark infer a filter on the set's size and compute the set once more below it
    inv = sets.select("node", F.size("s").alias("n"), F.explode_outer("s").alias("x"))
    held = inv.withColumn("df", F.count("*").over(Window.partitionBy("x"))).where("df > 1")
    shared = cut(held.groupBy("node", "n").agg(F.array_sort(F.collect_list(F.struct("df", "x"))).alias("o")).select("node", "n", F.col("o.x").alias("s")), "shared")
    # a little below the threshold, as the similarity is rounded before it is compared
    least = threshold - 1e-6
    more = (F.col("n") - F.ceil(F.col("n") * F.lit(least)) + 1 - (F.col("n") - F.size("s"))).cast("int")
    first = cut(shared.withColumn("more", more).where("more > 0").select("node", "n", F.explode_outer(F.slice("s", F.lit(1), F.col("more"))).alias("x")), "first")
    a, b = (first.select("x", F.col("node").alias(f"{p}_node"), F.col("n").alias(f"{p}n")) for p in "lr")
    cand = a.join(b, "x").where("l_node < r_node").where((F.col("ln") >= F.col("rn") * F.lit(least)) & (F.col("rn") >= F.col("ln") * F.lit(least))).select("l_node", "r_node").distinct()
    l, r = (shared.select(F.col("node").alias(f"{p}_node"), F.col("n").alias(f"{p}n"), F.col("s").alias(f"{p}s")) for p in "lr")
    both = F.size(F.array_intersect("ls", "rs"))
    j = F.round(both / (F.col("ln") + F.col("rn") - both), 6)
    near = cand.join(l, "l_node").join(r, "r_node").select("l_node", "r_node", j.alias("jaccard")).where(F.col("jaccard") >= threshold)
    near = cut(near, "near")
    near = near.unionByName(near.select(F.col("r_node").alias("l_node"), F.col("l_node").alias("r_node"), "jaccard"))
    l, r = (members.select(F.col("node").alias(f"{p}_node"), F.col("doc_id").alias(f"{p}_id"), F.col("t").alias(f"{p}t")) for p in "lr")
    same = l.join(r, F.col("l_node") == F.col("r_node")).where("l_id < r_id").withColumn("jaccard", F.lit(1.0))
    other = near.join(l, "l_node").join(r, "r_node").where("l_id < r_id")
    return same.select("l_id", "r_id", "jaccard", "lt", "rt").unionByName(other.select("l_id", "r_id", "jaccard", "lt", "rt")).select("l_id", "r_id", "jaccard", (F.col("lt") == F.col("rt")).alias("exact"))


DOC_PAIRS_SQL = r"""
WITH w AS (SELECT doc_id, text, string_split(lower(trim(regexp_replace(text, '\s+', ' ', 'g'))), ' ') AS w FROM documents),
t AS (SELECT doc_id, unnest(w) AS t, generate_subscripts(w, 1) AS p FROM w),
g AS (SELECT doc_id, t || ' ' || lead(t, 1) OVER d || ' ' || lead(t, 2) OVER d || ' ' || lead(t, 3) OVER d || ' ' || lead(t, 4) OVER d AS x FROM t WINDOW d AS (PARTITION BY doc_id ORDER BY p)),
i AS (SELECT DISTINCT doc_id, x FROM g WHERE x IS NOT NULL UNION ALL SELECT doc_id, array_to_string(w, ' ') FROM w WHERE len(w) < 5),
n AS (SELECT doc_id, count(*) AS n FROM i GROUP BY 1),
c AS (SELECT a.doc_id AS l_id, b.doc_id AS r_id, count(*) AS both_ FROM i a JOIN i b USING (x) WHERE a.doc_id < b.doc_id GROUP BY 1, 2),
j AS (SELECT l_id, r_id, round(both_ / (nl.n + nr.n - both_), 6) AS jaccard, l.text = r.text AS exact FROM c JOIN w l ON l.doc_id = l_id JOIN w r ON r.doc_id = r_id JOIN n nl ON nl.doc_id = l_id JOIN n nr ON nr.doc_id = r_id)
SELECT l_id, r_id, jaccard, exact FROM j WHERE jaccard >= 0.5
"""

# P: part feeds ------------------------------------------------------------------

PART_FEEDS_SQL = """
SELECT 2 * p_partkey AS rec_id, p_partkey AS ent, 'A' AS feed, p_name, p_brand, p_type, p_size, p_retailprice FROM part
UNION ALL
SELECT 2 * p_partkey + 1, p_partkey, 'B',
  CASE WHEN p_partkey % 10 = 0 THEN NULL WHEN p_partkey % 10 = 4 THEN replace(p_name, 'e', '') ELSE p_name END,
  CASE WHEN p_partkey % 7 = 0 THEN NULL ELSE p_brand END,
  CASE WHEN p_partkey % 13 = 0 THEN NULL ELSE p_type END,
  CASE WHEN p_partkey % 9 = 0 THEN p_size + 1 ELSE p_size END,
  CASE WHEN p_partkey % 11 = 0 THEN NULL ELSE p_retailprice END
FROM part WHERE p_partkey % 2 = 0
"""

PART_SPEC = BlockingSpec(
    "rec_id",
    (Attribute("brand", "text", "p_brand"), Attribute("name", "token_text", "p_name"), Attribute("price", "float", "p_retailprice"), Attribute("size", "int", "p_size"), Attribute("type", "token_text", "p_type")),
)


def part_feeds(spark: SparkSession, sf_dir: str) -> DataFrame:
    return spark.sql(PART_FEEDS_SQL.replace("FROM part", "FROM {part}"), part=table(spark, sf_dir, "part"))


def ent_pairs(feeds: DataFrame) -> DataFrame:
    """All pairs of records of one entity."""
    a, b = (feeds.select("ent", F.col("rec_id").alias(x)) for x in ("l_id", "r_id"))
    return a.join(b, "ent").where("l_id < r_id").select("l_id", "r_id")


# C: customer feeds --------------------------------------------------------------

_CUSTOMER = "FROM customer JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey"
CUSTOMER_FEEDS_SQL = f"""
WITH c AS (SELECT c_custkey AS k, c_name AS name, c_mktsegment AS street, n_name AS city, r_name AS state, CAST(floor(c_acctbal) AS BIGINT) AS zip {_CUSTOMER})
SELECT 3 * k AS rec_id, k AS ent, 'A' AS feed, name, street, city, state, zip FROM c
UNION ALL SELECT 3 * k + 1, k, 'B', CASE WHEN k % 11 = 0 THEN NULL WHEN k % 4 = 1 THEN replace(name, '#', '') ELSE name END,
  CASE WHEN k % 7 = 0 THEN NULL ELSE street END, city, CASE WHEN k % 13 = 0 THEN NULL ELSE state END, CASE WHEN k % 5 = 0 THEN zip + 1 ELSE zip END FROM c
UNION ALL SELECT 3 * k + 2, k, 'C', CASE WHEN k % 9 = 0 THEN NULL WHEN k % 4 = 2 THEN left(name, length(name) - 1) ELSE 'Cust ' || right(name, 6) END,
  street, CASE WHEN k % 6 = 0 THEN NULL ELSE city END, state, CASE WHEN k % 8 = 0 THEN NULL ELSE zip END FROM c
"""

CUSTOMER_SPEC = BlockingSpec(
    "rec_id",
    (Attribute("city", "text", "city"), Attribute("name", "token_text", "name"), Attribute("state", "text", "state"), Attribute("street", "text", "street"), Attribute("zip", "int", "zip")),
)


def customer_feeds(spark: SparkSession, sf_dir: str) -> DataFrame:
    sql = CUSTOMER_FEEDS_SQL
    for t in ("customer", "nation", "region"):
        sql = sql.replace(f"FROM {t} ", f"FROM {{{t}}} ").replace(f"JOIN {t} ", f"JOIN {{{t}}} ")
    return spark.sql(sql, **{t: table(spark, sf_dir, t) for t in ("customer", "nation", "region")})


# O: orders, W: pages, B: benchmark ------------------------------------------------

ORDER_SPEC = BlockingSpec("o_orderkey", (Attribute("day", "date", "CAST(o_orderdate AS DATE)"), Attribute("customer", "int", "o_custkey")))


def order_pairs(orders: DataFrame, days: int = 3) -> DataFrame:
    """Orders of one customer at most `days` apart."""
    a, b = (orders.select("o_custkey", F.col("o_orderkey").alias(f"{p}_id"), F.to_date("o_orderdate").alias(f"{p}d")) for p in "lr")
    return a.join(b, "o_custkey").where("l_id < r_id").where(F.abs(F.datediff("ld", "rd")) <= days).select("l_id", "r_id")


ORDER_PAIRS_SQL = """
SELECT a.o_orderkey AS l_id, b.o_orderkey AS r_id FROM orders a JOIN orders b ON a.o_custkey = b.o_custkey AND a.o_orderkey < b.o_orderkey
WHERE abs(date_diff('day', CAST(a.o_orderdate AS DATE), CAST(b.o_orderdate AS DATE))) <= 3
"""


def page_records(pages: DataFrame) -> DataFrame:
    """page_id, host, path, path_lang, title and visible text of raw pages."""
    body = F.regexp_replace("html", r"(?is)<(script|style)[^>]*>.*?</(script|style)>", " ")
    text = F.trim(F.regexp_replace(F.regexp_replace(body, r"(?s)<[^>]+>", " "), r"\s+", " "))
    path = F.regexp_extract("url", r"^[a-z]+://[^/]+(/[^?#]*)", 1)
    return pages.select("page_id", F.regexp_extract("url", r"^[a-z]+://([^/?#]+)", 1).alias("host"), path.alias("path"), F.regexp_extract(path, r"^/([a-z]{2})/", 1).alias("path_lang"), F.regexp_extract("html", r"(?is)<title>(.*?)</title>", 1).alias("title"), F.length("html").alias("n_html"), text.alias("body_text"))


PAGE_RECORDS_SQL = r"""
SELECT page_id, regexp_extract(url, '^[a-z]+://([^/?#]+)', 1) AS host, regexp_extract(url, '^[a-z]+://[^/]+(/[^?#]*)', 1) AS path,
  regexp_extract(regexp_extract(url, '^[a-z]+://[^/]+(/[^?#]*)', 1), '^/([a-z]{2})/', 1) AS path_lang, regexp_extract(html, '(?is)<title>(.*?)</title>', 1) AS title,
  CAST(length(html) AS INTEGER) AS n_html, trim(regexp_replace(regexp_replace(regexp_replace(html, '(?is)<(script|style)[^>]*>.*?</(script|style)>', ' ', 'g'), '(?s)<[^>]+>', ' ', 'g'), '\s+', ' ', 'g')) AS body_text
FROM pages
"""


def benchmark_links(benchmark: DataFrame, docs: DataFrame, n: int = 8) -> DataFrame:
    """(item_id, doc_id): any run of `n` words of the item, or the whole of a shorter item, stands in the document.

    Both sides are cut into runs, so that linking is an equi-join on a run and not a search of
    every text for every item. Documents are cut into runs of fewer words only where items have as few.
    """
    words = F.split(F.trim(F.regexp_replace("text", r"\s+", " ")), " ")

    def runs(size):
        return F.transform(F.sequence(F.lit(1), F.size("w") - size + 1), lambda i: F.array_join(F.slice("w", i, size), " "))

    items = benchmark.select("item_id", words.alias("w")).where("w[0] != ''")
    probe = items.select("item_id", F.explode_outer(F.when(F.size("w") < n, F.array(F.array_join("w", " "))).otherwise(runs(n))).alias("run")).distinct()
    lengths = sorted(r[0] for r in items.select(F.least(F.size("w"), F.lit(n))).distinct().collect())
    held = docs.select("doc_id", words.alias("w"))
    cuts = [F.when(F.size("w") >= k, runs(k)).otherwise(F.array().cast("array<string>")) for k in lengths]
    found = held.select("doc_id", F.explode_outer(F.flatten(F.array(*cuts)) if cuts else F.array().cast("array<string>")).alias("run"))
    return found.join(probe, "run").select("item_id", "doc_id").distinct()


BENCHMARK_LINKS_SQL = r"""
WITH i AS (SELECT item_id, string_split_regex(trim(regexp_replace(text, '\s+', ' ', 'g')), ' ') AS w FROM benchmark),
p AS (SELECT DISTINCT item_id, unnest(CASE WHEN len(w) < 8 THEN [array_to_string(w, ' ')] ELSE list_transform(range(1, len(w) - 6), lambda k: array_to_string(list_slice(w, k, k + 7), ' ')) END) AS run FROM i WHERE w[1] <> ''),
d AS (SELECT doc_id, string_split_regex(trim(regexp_replace(text, '\s+', ' ', 'g')), ' ') AS w FROM documents),
n AS (SELECT DISTINCT least(len(w), 8) AS n FROM i WHERE w[1] <> ''),
r AS (SELECT doc_id, unnest(list_transform(range(1, len(w) - n + 2), lambda k: array_to_string(list_slice(w, k, k + n - 1), ' '))) AS run FROM d JOIN n ON len(w) >= n)
SELECT DISTINCT item_id, doc_id FROM r JOIN p USING (run)
"""


def flagship(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Learn a block tree on documents, assign all, count each block."""
    from .functions.hashes import default_library
    from .model import BlockingConfig
    from .operators import assign, learn, sizes

    docs = table(spark, sf_dir, "documents")
    f = sizes.features(docs, DOC_SPEC, doc_pairs(docs), default_library(DOC_SPEC), cap=20)
    tree = learn.learn_block_tree(f, BlockingConfig(max_block_size=20, scorer="expected"))
    return sizes.block_sizes(assign.assign_blocks(docs, tree, DOC_SPEC)).orderBy(F.desc("n"), "block_key")
