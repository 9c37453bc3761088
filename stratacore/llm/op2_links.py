"""URL filter: rules, then trust and distrust propagated over the host graph. DataFrame functions only.

Hosts that rules allow or block are seeds, weighted by their pages. Trust is a personalised PageRank from the allowed
pages along links; distrust is one from the blocked pages against the links (who links to a blocked host is
distrusted). A page without a rule is blocked when distrust makes up at least BLOCK_SHARE of its host's score.

Contributions are fractions of a UNIT per seed page and vanish at no degree. They are summed exactly, as whole numbers
by binary magnitude (see `_summed`), so sums do not depend on their order and a recomputed task gives the same
verdicts. Edges are host pairs with link counts, combined before any shuffle. The state
is checkpointed each round.

Edge cases: null url or one without `://` has empty host and path, no rule, and is judged by the empty host's score;
null html has no links; links inside a host are no edges; repeated rows are judged alike and count as pages; hosts
without any score are allowed; empty table: empty result; other columns are ignored.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import LOWER, UPPER, shared_dir

#: Fixed values: (verdict, host, path) of the rules.
RULES = (("allow", "org", "/"), ("block", "example.org", "/es/"), ("block", "example.org", "/en/1"), ("allow", "com", "/fr/"), ("block", "com", "/de/"))
DAMPING, ROUNDS, UNIT, BLOCK_SHARE = 0.85, 8, 1_000_000, 0.75
LINK = r"""(?i)href\s*=\s*["']?(?:https?:)?//([^/?#"'\s>]+)"""


def split_url(pages: DataFrame, url_column: str = "url") -> DataFrame:
    """pages with host and path (replacing columns of these names)."""
    url = F.col(url_column)
    at = F.coalesce(F.locate("://", url), F.lit(0))
    rest = F.when(at > 0, F.expr(f"substring(`{url_column}`, locate('://', `{url_column}`) + 3)")).otherwise("")
    pages = pages.withColumn("_rest", rest)
    host = F.translate(F.regexp_extract("_rest", r"^[^/?#]*", 0), UPPER, LOWER)
    return pages.withColumns({"host": host, "path": F.regexp_extract("_rest", r"^[^/?#]*([^?#]*)", 1)}).drop("_rest")


def _fits(host: str, path: str) -> Column:
    return ((F.col("host") == host) | F.endswith(F.col("host"), F.lit("." + host))) & F.startswith(F.col("path"), F.lit(path))


def with_rule(pages: DataFrame, rules=RULES) -> DataFrame:
    """Columns rule and rule_verdict from the longest rule that fits, null where none does."""
    rule = verdict = F.lit(None).cast("string")
    for v, host, path in sorted(rules, key=lambda r: (len(r[1] + r[2]), r)):  # the longest is asked first
        rule, verdict = F.when(_fits(host, path), host + path).otherwise(rule), F.when(_fits(host, path), v).otherwise(verdict)
    return pages.withColumns({"rule": rule, "rule_verdict": verdict})


def host_edges(pages: DataFrame, html_column: str = "html") -> DataFrame:
    """(src, dst, n): links between different hosts."""
    links = pages.select(F.col("host").alias("src"), F.explode(F.regexp_extract_all(html_column, F.lit(LINK), F.lit(1))).alias("dst"))
    links = links.select("src", F.translate("dst", UPPER, LOWER).alias("dst")).where("src != dst and src != ''")
    return links.groupBy("src", "dst").agg(F.count(F.lit(1)).alias("n"))


#: Contributions of one magnitude lie within a factor of 2^SPAN and are rounded down to PLACES binary places of its lower end.
SPAN, PLACES = 16, 40


def _summed(parts: DataFrame, *columns: str) -> DataFrame:
    """Sums by host of non-negative doubles, the same in any order: whole numbers are added within a magnitude, then the few magnitudes in order."""
    each = parts.select("host", F.explode(F.array(*[F.struct(F.lit(k).alias("k"), F.col(c).alias("v")) for k, c in enumerate(columns)])).alias("p")).select("host", "p.*").where("v > 0")
    each = each.withColumn("e", F.floor(F.log2("v") / SPAN).cast("int"))
    whole = F.floor(F.col("v") * F.pow(F.lit(2.0), PLACES - SPAN * F.col("e"))).cast("decimal(20,0)")
    each = each.groupBy("host", "k", "e").agg(F.sum(whole).alias("m"))
    value = lambda x: x["m"].cast("double") * F.pow(F.lit(2.0), SPAN * x["e"] - PLACES)
    total = lambda k: F.aggregate(F.sort_array(F.collect_list(F.when(F.col("k") == k, F.struct("e", "m")))), F.lit(0.0), lambda s, x: s + value(x))
    return each.groupBy("host").agg(*[total(k).alias(c) for k, c in enumerate(columns)])


def host_scores(seeds: DataFrame, edges: DataFrame, rounds: int = ROUNDS, damping: float = DAMPING) -> DataFrame:
    """(host, trust, distrust) from (host, allowed, blocked) page counts and (src, dst, n) edges."""
    shared_dir(seeds.sparkSession)
    start = seeds.select("host", F.floor(F.col("allowed") * UNIT * (1 - damping)).cast("double").alias("trust"), F.floor(F.col("blocked") * UNIT * (1 - damping)).cast("double").alias("distrust")).checkpoint()
    edges = edges.checkpoint()
    if edges.isEmpty():
        return start
    out = edges.groupBy(F.col("src").alias("at")).agg(F.sum("n").alias("total"))
    back = edges.groupBy(F.col("dst").alias("at")).agg(F.sum("n").alias("total"))
    step = lambda kind, tot, a, b: edges.join(tot, edges[a] == tot["at"]).select(F.col(a).alias("at"), F.col(b).alias("to"), F.lit(kind).alias("forward"), (damping * (F.col("n") / F.col("total"))).alias("share"))
    steps = step(True, out, "src", "dst").unionByName(step(False, back, "dst", "src")).checkpoint()
    state = start
    for _ in range(rounds):
        moved = steps.join(state, steps["at"] == state["host"])
        flow = lambda c, forward: F.when(F.col("forward") == forward, F.col(c) * F.col("share")).otherwise(0.0).alias(c)
        moved = moved.select(F.col("to").alias("host"), flow("trust", True), flow("distrust", False))
        state = _summed(start.unionByName(moved), "trust", "distrust").checkpoint()
    return state


def judged_pages(pages: DataFrame, rules=RULES, id_column: str = "page_id", url_column: str = "url", html_column: str = "html") -> DataFrame:
    """(page_id, host, path, rule, verdict, trust, distrust) for every row."""
    rows = with_rule(split_url(pages.select(F.col(id_column).alias("page_id"), F.col(url_column).alias("url"), F.col(html_column).alias("html"))), rules)
    count = lambda v: F.count(F.when(F.col("rule_verdict") == v, 1))
    seeds = rows.groupBy("host").agg(count("allow").alias("allowed"), count("block").alias("blocked")).where("allowed + blocked > 0")
    scores = host_scores(seeds, host_edges(rows))
    both = rows.drop("html", "url").join(scores, "host", "left").fillna(0, ["trust", "distrust"])
    bad = (F.col("distrust") > 0) & (F.col("distrust") >= BLOCK_SHARE * (F.col("trust") + F.col("distrust")))
    return both.select("page_id", "host", "path", "rule", F.coalesce("rule_verdict", F.when(bad, "block").otherwise("allow")).alias("verdict"), "trust", "distrust")
