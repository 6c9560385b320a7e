"""URL verdicts: rules first, else trust and distrust propagated over the link graph of hosts."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import LOWER, UPPER, Workspace, table

RULES = (("block", "net", "/"), ("allow", "example.net", "/en/"), ("block", "example.com", "/de/"), ("allow", "org", "/fr/"))
#: Rules up to this many are sent to every task; more are joined by a shuffle.
SENT_RULES = 50_000
#: Share of rank that follows links, rounds of the walk, and rounds between two saved tables.
DAMPING, ROUNDS, SAVE_EVERY = 0.85, 12, 4
#: A host is blocked when distrust has more than this share of its trust and distrust.
BLOCK_SHARE = 0.5


def host_and_path(url: Column) -> tuple[Column, Column]:
    """The host, A-Z lower-cased, and the path of a url; both empty without ``://`` or for a null url."""
    at = F.instr(url, "://")
    rest = F.when(at > 0, url.substr(at + F.lit(3), F.length(url))).otherwise(F.lit(""))
    rest = F.coalesce(rest, F.lit(""))
    host = F.translate(F.regexp_extract(rest, "^[^/?#]*", 0), UPPER, LOWER)
    return host, F.regexp_extract(rest, "^[^/?#]*([^?#]*)", 1)


def apply_rules(pages: DataFrame, rules: tuple[tuple[str, str, str], ...] = RULES) -> DataFrame:
    """Adds rule and rule_verdict to rows with host and path; both null where no rule fits.

    Only the last labels of a host, as many as some rule has, are looked up: a lookup for each count of labels.
    The longest fitting rule wins; of equally long ones the first by text.
    """
    counts = sorted({h.count(".") + 1 for _, h, _ in rules})
    spark = pages.sparkSession
    known = spark.createDataFrame([(h.translate(str.maketrans(UPPER, LOWER)), p, v) for v, h, p in rules], "rule_host string, rule_path string, rule_verdict string")
    known = known.groupBy("rule_host").agg(F.collect_list(F.struct("rule_path", "rule_verdict")).alias("of_host"))
    out, fitting = pages, F.array().cast("array<struct<n:int,rule:string,rule_verdict:string>>")
    parts = F.split("host", "[.]")
    for k in counts:
        end = F.when(F.size(parts) >= k, F.array_join(F.slice(parts, -k, k), "."))
        mine = known.select(F.col("rule_host").alias(f"__host{k}"), F.col("of_host").alias(f"__of{k}"))
        out = out.withColumn(f"__host{k}", end).join(F.broadcast(mine) if len(rules) <= SENT_RULES else mine, f"__host{k}", "left")
        fits = F.filter(F.coalesce(f"__of{k}", F.array().cast("array<struct<rule_path:string,rule_verdict:string>>")), lambda r: F.col("path").startswith(r["rule_path"]))
        end_host = F.col(f"__host{k}")
        named = lambda r: F.struct((F.length(end_host) + F.length(r["rule_path"])).cast("int").alias("n"), F.concat(end_host, r["rule_path"]).alias("rule"), r["rule_verdict"].alias("rule_verdict"))  # noqa: B023, E731  used at once
        fitting = F.concat(fitting, F.transform(fits, named))
    # Longest first; among these the first by text.
    best = F.reduce(fitting, F.lit(None).cast("struct<n:int,rule:string,rule_verdict:string>"), lambda a, x: F.when(a.isNull() | (x["n"] > a["n"]) | ((x["n"] == a["n"]) & (x["rule"] < a["rule"])), x).otherwise(a))
    out = out.withColumn("__best", best)
    return out.select(*pages.columns, F.col("__best.rule").alias("rule"), F.col("__best.rule_verdict").alias("rule_verdict"))


def host_edges(pages: DataFrame) -> DataFrame:
    """(a, b, n): links from host a to another host b, and between a host and its parent domain (n = 1).

    ``pages``: host, html. Links are absolute or begin with two slashes. Counts are combined before the shuffle.
    """
    found = F.regexp_extract_all(F.coalesce("html", F.lit("")), F.lit("(?i)href\\s*=\\s*[\"']?(?:https?:)?//([^/\"'?#\\s<>]+)"), F.lit(1))
    links = pages.select(F.col("host").alias("a"), F.explode(found).alias("b")).select("a", F.translate("b", UPPER, LOWER).alias("b"))
    links = links.where("a <> b and a <> '' and b <> ''").groupBy("a", "b").agg(F.count(F.lit(1)).cast("double").alias("n"))
    hosts = pages.select("host").where("host <> ''").distinct().select(F.col("host").alias("a"), F.split("host", "[.]").alias("parts"))
    above = hosts.where(F.size("parts") > 2).select("a", F.array_join(F.slice("parts", 2, 1 << 20), ".").alias("b"))
    domain = above.select("a", "b", F.lit(1.0).alias("n")).unionByName(above.select(F.col("b").alias("a"), F.col("a").alias("b"), F.lit(1.0).alias("n")))
    return links.unionByName(domain).groupBy("a", "b").agg(F.sum("n").alias("n"))


def propagate(seeds: DataFrame, edges: DataFrame, ws: Workspace, damping: float = DAMPING, rounds: int = ROUNDS) -> DataFrame:
    """host, trust, distrust: personalised PageRank of the seeds, and of the seeds over reversed edges.

    ``seeds``: host, trust, distrust (each sums to 1 or 0). Trust follows links; distrust goes back from a host to
    those that link to it. A walk that reaches a host without links ends there. One join and one combined sum a round.
    """
    out_n = edges.groupBy(F.col("a").alias("from")).agg(F.sum("n").alias("of"))
    in_n = edges.groupBy(F.col("b").alias("from")).agg(F.sum("n").alias("of"))
    along = edges.select(F.col("a").alias("from"), F.col("b").alias("to"), "n").join(out_n, "from").select("from", "to", (F.col("n") / F.col("of")).alias("wt"), F.lit(0.0).alias("wd"))
    back = edges.select(F.col("b").alias("from"), F.col("a").alias("to"), "n").join(in_n, "from").select("from", "to", F.lit(0.0).alias("wt"), (F.col("n") / F.col("of")).alias("wd"))
    steps = ws.save(along.unionByName(back).groupBy("from", "to").agg(F.sum("wt").alias("wt"), F.sum("wd").alias("wd")), "steps")
    ranks = seeds
    for k in range(1, rounds + 1):
        moved = steps.join(ranks.withColumnRenamed("host", "from"), "from").groupBy(F.col("to").alias("host")).agg(F.sum(F.col("wt") * F.col("trust")).alias("t"), F.sum(F.col("wd") * F.col("distrust")).alias("d"))
        part = lambda own, got: ((1 - damping) * F.coalesce(own, F.lit(0.0)) + damping * F.coalesce(got, F.lit(0.0)))
        ranks = seeds.join(moved, "host", "full").select("host", part("trust", "t").alias("trust"), part("distrust", "d").alias("distrust"))
        if k % SAVE_EVERY == 0:
            ranks = ws.save(ranks, f"ranks{k}")
    return ranks


def judge(pages: DataFrame, rules: tuple[tuple[str, str, str], ...] = RULES) -> DataFrame:
    """Per row of ``pages`` (page_id, url, html): page_id, host, path, rule, verdict, host_trust, host_distrust.

    Seeds: a host of whose pages over half are allowed (blocked) by rules is trusted (blocked). Without a rule the
    host's share of distrust decides; hosts that neither rank reaches, and urls without a host, are allowed. Nulls
    count as empty; repeated rows are judged alike; an empty table gives no rows.
    """
    ws = Workspace(pages.sparkSession, "urls")
    host, path = host_and_path(F.col("url"))
    named = pages.select(F.col("page_id").cast("long").alias("page_id"), host.alias("host"), path.alias("path"))
    ruled = ws.save(apply_rules(named, rules), "ruled")
    edges = ws.save(host_edges(pages.select(host.alias("host"), F.col("html"))), "edges")
    counted = ruled.where("host <> ''").groupBy("host").agg(F.count(F.lit(1)).alias("n"), F.count_if(F.col("rule_verdict") == "allow").alias("allowed"), F.count_if(F.col("rule_verdict") == "block").alias("blocked"))
    marked = ws.save(counted.select("host", (2 * F.col("allowed") > F.col("n")).cast("double").alias("t"), (2 * F.col("blocked") > F.col("n")).cast("double").alias("d")), "seeds")
    total = marked.agg(F.greatest(F.sum("t"), F.lit(1.0)).alias("t"), F.greatest(F.sum("d"), F.lit(1.0)).alias("d")).first()
    seeds = marked.select("host", (F.col("t") / F.lit(float(total["t"] or 1))).alias("trust"), (F.col("d") / F.lit(float(total["d"] or 1))).alias("distrust"))
    ranks = propagate(seeds, edges, ws)
    # Compared at a fixed precision, so that the order of sums cannot turn a verdict.
    share = F.round(F.col("distrust") / (F.col("trust") + F.col("distrust")), 9)
    hosts = ranks.where("host <> '' and trust + distrust > 0").select("host", "trust", "distrust", (share > BLOCK_SHARE).alias("bad"))
    out = ruled.join(hosts, "host", "left")
    verdict = F.coalesce("rule_verdict", F.when(F.col("bad"), "block").otherwise("allow"))
    return out.select("page_id", "host", "path", "rule", verdict.alias("verdict"), F.coalesce("trust", F.lit(0.0)).alias("host_trust"), F.coalesce("distrust", F.lit(0.0)).alias("host_distrust"))


def op7_url_filter(spark: SparkSession, sf_dir: str) -> DataFrame:
    """judge() of all ``pages`` by the fixed rules."""
    return judge(table(spark, sf_dir, "pages")).select("page_id", "host", "path", "rule", "verdict")


def _oracle() -> str:
    """The same verdicts in DuckDB's SQL: one step of the walk is one common table expression."""
    low = lambda x: f"translate({x}, '{UPPER}', '{LOWER}')"
    rules = ", ".join(f"('{v}', '{h}', '{p}')" for v, h, p in RULES)
    fits = "FROM rules WHERE (host = rh OR ends_with(host, '.' || rh)) AND starts_with(path, rp)"
    steps = "".join(
        f""", r{k} AS MATERIALIZED (SELECT s.host, {1 - DAMPING!r} * s.t + {DAMPING!r} * coalesce(m.t, 0) AS t, {1 - DAMPING!r} * s.d + {DAMPING!r} * coalesce(m.d, 0) AS d
FROM nodes s LEFT JOIN (SELECT x.b AS host, sum(x.wt * r.t) AS t, sum(x.wd * r.d) AS d FROM moves x JOIN r{k - 1} r ON x.a = r.host GROUP BY x.b) m ON s.host = m.host)"""
        for k in range(1, ROUNDS + 1)
    )
    return f"""
WITH cut AS (SELECT page_id, coalesce(html, '') AS html, coalesce(CASE WHEN instr(url, '://') > 0 THEN substr(url, instr(url, '://') + 3) END, '') AS rest FROM pages),
named AS (SELECT page_id, html, {low("regexp_extract(rest, '^[^/?#]*')")} AS host, regexp_extract(rest, '^[^/?#]*([^?#]*)', 1) AS path FROM cut),
rules(v, rh, rp) AS (VALUES {rules}),
ruled AS MATERIALIZED (SELECT page_id, html, host, path, (SELECT arg_max(rh || rp, length(rh || rp)) {fits}) AS rule, (SELECT arg_max(v, length(rh || rp)) {fits}) AS rv FROM named),
links AS (SELECT a, {low("b")} AS b FROM (SELECT host AS a, unnest(regexp_extract_all(html, '(?i)href\\s*=\\s*["'']?(?:https?:)?//([^/"''?#\\s<>]+)', 1)) AS b FROM ruled) x),
above AS (SELECT host AS a, array_to_string(string_split(host, '.')[2:], '.') AS b FROM (SELECT DISTINCT host FROM ruled WHERE len(string_split(host, '.')) > 2) x),
edges AS MATERIALIZED (SELECT a, b, sum(n) AS n FROM (SELECT a, b, 1.0::DOUBLE AS n FROM links WHERE a <> b AND a <> '' AND b <> '' UNION ALL SELECT a, b, 1.0 FROM above UNION ALL SELECT b, a, 1.0 FROM above) x GROUP BY a, b),
moves AS MATERIALIZED (
  SELECT a, b, sum(wt) AS wt, sum(wd) AS wd FROM (
    SELECT a, b, n / sum(n) OVER (PARTITION BY a) AS wt, 0.0::DOUBLE AS wd FROM edges UNION ALL SELECT b, a, 0.0, n / sum(n) OVER (PARTITION BY b) FROM edges) x GROUP BY a, b),
marked AS (SELECT host, (2 * count(*) FILTER (rv = 'allow') > count(*))::INT::DOUBLE AS t, (2 * count(*) FILTER (rv = 'block') > count(*))::INT::DOUBLE AS d FROM ruled WHERE host <> '' GROUP BY host),
nodes AS MATERIALIZED (SELECT host, coalesce(t, 0) / (SELECT greatest(sum(t), 1) FROM marked) AS t, coalesce(d, 0) / (SELECT greatest(sum(d), 1) FROM marked) AS d FROM (SELECT host FROM marked UNION SELECT b FROM edges) x LEFT JOIN marked USING (host)),
r0 AS (SELECT * FROM nodes){steps}
SELECT page_id, p.host, path, rule, coalesce(rv, CASE WHEN r.t + r.d > 0 AND round(r.d / (r.t + r.d), 9) > {BLOCK_SHARE} THEN 'block' ELSE 'allow' END) AS verdict
FROM ruled p LEFT JOIN r{ROUNDS} r ON p.host = r.host
"""


OP7_SQL = _oracle()
