"""URL verdicts from host rules and a tree of path templates.

Rules decide where one fits (the longest wins) and label the pages they fit.
For the rest, every host has a tree of path segments, in which digits are
wildcards from the start.  Level by level, a branching with many distinct
segments for its size becomes one wildcard, and labelled siblings on one side
(mostly blocked, or mostly not) whose share of blocked pages does not differ
from that side's pooled share merge; others stay literal.

A page's path with its wildcards is its template.  The purity of a template on
a host is the share of blocked pages among the labelled ones of its merged
branch, smoothed towards the share of the same template over all hosts, which
itself is smoothed towards a half; a template that few hosts have labels for
counts a half there.  A template is rejected where the lower confidence bound
of its purity is high, so a path that rules have condemned wherever they reach
is condemned on hosts that no rule knows, unless pages of that host say otherwise.

Counting happens once, by (host, segments); the levels work on those counts.
Built-in expressions only.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .workspace import Workspace

#: The rules, as (host, path, action).
RULES = [("net", "/", "block"), ("example.net", "/en/", "allow"), ("example.com", "/de/", "block"), ("org", "/fr/", "allow")]

MANY, MANY_PERCENT = 20, 30  # distinct segments, and their share of the pages, that make a wildcard
ENOUGH = 5  # labels with which a branch can be told from others
CHI2 = 3.84  # 95 percent, one degree of freedom
PRIOR = 4  # pseudo-labels, half of them blocked, behind a template's share over all hosts
STRENGTH = 4  # pseudo-labels, at that share, behind a template on one host
FEW_HOSTS = 3  # hosts with labels from which on the share over all hosts says anything
LEAST_PURITY = 0.75  # lower bound (one standard error) of a rejected template
LITERAL_RULES = 200
BROADCAST_ROWS = 500_000


def url_parts(url) -> tuple[F.Column, F.Column]:
    """(host, path): both empty for null or without "://"."""
    at = F.instr(url, "://")
    rest = F.when(at > 0, F.substring(url, at + 3, F.length(url))).otherwise("")
    host = F.regexp_extract(rest, r"^[^/?#]*", 0)
    path = F.regexp_extract(rest, r"^[^/?#]*([^?#]*)", 1)
    upper = "ABCDEFGHIJKLMNOPQRSTUVWXYZ"
    return F.coalesce(F.translate(host, upper, upper.lower()), F.lit("")), F.coalesce(path, F.lit(""))


def with_rules(pages: DataFrame, rules: list[tuple[str, str, str]]) -> DataFrame:
    """Adds ``rule`` (host and path as one string) and ``action``, null where no rule fits.

    Few rules are tried in place; more of them meet the suffixes of the host in a join.
    """
    if len(rules) <= LITERAL_RULES:
        ordered = sorted(rules, key=lambda r: (-len(r[0] + r[1]), r[0] + r[1], r[2]))
        fits = None
        name, action = F, F
        for host, path, what in ordered:
            hit = ((F.col("host") == host) | F.col("host").endswith("." + host)) & F.col("path").startswith(path)
            name, action = name.when(hit, host + path), action.when(hit, what)
            fits = hit
        return pages.withColumns({"rule": name if fits is not None else F.lit(None).cast("string"), "action": action if fits is not None else F.lit(None).cast("string")})
    table = pages.sparkSession.createDataFrame(rules, "rhost string, rpath string, raction string").dropDuplicates(["rhost", "rpath"])
    labels = F.split("host", r"\.")
    suffixes = F.transform(F.sequence(F.lit(1), F.size(labels)), lambda i: F.array_join(F.slice(labels, i, F.size(labels)), "."))
    keyed = pages.withColumn("key", F.struct("host", "path"))
    pairs = keyed.select("host", "path").distinct().withColumn("rhost", F.explode(suffixes)).join(table, "rhost").filter(F.col("path").startswith(F.col("rpath")))
    best = pairs.groupBy("host", "path").agg(F.max_by(F.struct(F.concat("rhost", "rpath").alias("rule"), F.col("raction").alias("action")), F.struct(F.length(F.concat("rhost", "rpath")), F.concat("rhost", "rpath"))).alias("best"))
    return pages.join(best, ["host", "path"], "left").select(*pages.columns, "best.rule", "best.action")


def _segments(path) -> F.Column:
    """Segments with digits as wildcards; slashes at the end make none."""
    return F.split(F.regexp_replace(F.regexp_replace(F.substring(path, 2, 1 << 30), "/+$", ""), r"[0-9]+", "{n}"), "/")


def _literal(seg) -> F.Column:
    return F.replace(seg, F.lit("*"), F.lit("%2A"))


def _branches(node: DataFrame) -> DataFrame:
    """(host, up, seg, name, branch): each child's name in the template, and the merged branch it is of.

    ``node`` has a row per child with n, l and b; an empty segment past the end of a path is a child too.
    """
    told = F.col("l") >= ENOUGH
    node = node.withColumn("side", F.when(~told, "open").when(2 * F.col("b") >= F.col("l"), "blocked").otherwise("allowed"))
    sides = node.groupBy("host", "up", "side").agg(F.count("*").alias("kinds"), F.sum("n").alias("all"), F.sum("l").alias("pl"), F.sum("b").alias("pb"))
    whole = sides.groupBy("host", "up").agg(F.sum("kinds").alias("kinds"), F.sum("all").alias("all"))
    many = whole.select("host", "up", ((F.col("kinds") >= MANY) & (100 * F.col("kinds") > MANY_PERCENT * F.col("all"))).alias("many"))
    both = node.join(sides.select("host", "up", "side", "pl", "pb"), ["host", "up", "side"]).join(many, ["host", "up"])
    # |b - l p| within the limit, times the pooled labels so that it stays in whole numbers
    gap = F.col("b") * F.col("pl") - F.col("l") * F.col("pb")
    alike = (F.col("side") != "open") & (gap.cast("double") * gap <= F.lit(CHI2) * F.col("l") * F.col("pb") * (F.col("pl") - F.col("pb")))
    branch = F.when(F.col("many"), "*").when(alike, F.concat(F.lit("~"), F.col("side"))).otherwise(F.concat(F.lit("="), F.col("seg")))
    return both.select("host", "up", "seg", F.when(F.col("many"), "*").otherwise(_literal("seg")).alias("name"), branch.alias("branch"))


def path_templates(pages: DataFrame, work: Workspace) -> DataFrame:
    """(host, parts, template, purity, rejected) per distinct run of segments.

    ``pages`` has host, parts and action.  The tree goes down until no path has
    a further segment to share; a run whose node nobody else reaches keeps its
    other segments as they are, and a run that has ended counts as a child of
    its parent on the level where others go on.
    """
    tree = pages.groupBy("host", "parts").agg(F.count("*").alias("n"), F.count("action").alias("labelled"), F.sum(F.when(F.col("action") == "block", 1).otherwise(0)).cast("long").alias("blocked"))
    tree = work.save(tree.withColumns({"shape": F.lit(""), "up": F.lit("")}), "segments")
    deepest = tree.agg(F.max(F.size("parts"))).first()[0] or 0
    done, i = tree.filter("false"), 0
    while i < deepest and not tree.isEmpty():
        here = tree.withColumn("seg", F.coalesce(F.get("parts", F.lit(i)), F.lit("")))
        node = here.groupBy("host", "up", "seg").agg(F.sum("n").alias("n"), F.sum("labelled").alias("l"), F.sum("blocked").alias("b"))
        named = here.join(_branches(node), ["host", "up", "seg"])
        # a name of fixed length for the branch, however deep it lies
        below = F.sha2(F.concat_ws("/", "up", "branch").cast("binary"), 256)
        saved, i = work.save(named.select("host", "parts", "n", "labelled", "blocked", F.concat_ws("/", "shape", "name").alias("shape"), below.alias("up")), f"level{i + 1}"), i + 1
        on = saved.groupBy("host", "up").agg(F.max(F.size("parts")).alias("longest"), F.count("*").alias("runs"))
        both = saved.join(on, ["host", "up"])
        further = (F.col("longest") > i) & (F.col("runs") > 1)
        rest = F.transform(F.slice("parts", i + 1, F.greatest(F.size("parts") - i, F.lit(0))), _literal)
        over = both.filter(~further).drop("longest", "runs").withColumn("shape", F.array_join(F.concat(F.array("shape"), rest), "/"))
        tree = work.save(both.filter(further).drop("longest", "runs"), f"open{i}")
        done = done.unionByName(over)
    template = F.regexp_replace("shape", "/+$", "")
    done = work.save(done.withColumn("template", F.when(template == "", "/").otherwise(template)).drop("shape"), "templates")
    own = done.groupBy("host", "up").agg(F.sum("labelled").alias("tl"), F.sum("blocked").alias("tb"))
    by_host = done.filter("labelled > 0").groupBy("template", "host").agg(F.sum("labelled").alias("pl"), F.sum("blocked").alias("pb"))
    pool = by_host.groupBy("template").agg(F.sum("pl").alias("pl"), F.sum("pb").alias("pb"), F.count("*").alias("hosts")).filter(F.col("hosts") >= FEW_HOSTS)
    share = F.coalesce((F.col("pb") + PRIOR / 2) / (F.col("pl") + float(PRIOR)), F.lit(0.5))
    weight = F.col("tl") + float(STRENGTH)
    judged = done.join(own, ["host", "up"]).join(pool, "template", "left").withColumn("purity", (F.col("tb") + STRENGTH * share) / weight)
    lower = F.col("purity") - F.sqrt(F.col("purity") * (1.0 - F.col("purity")) / weight)
    return judged.select("host", "parts", "template", F.round("purity", 6).alias("purity"), (lower >= LEAST_PURITY).alias("rejected"))


def url_verdicts(pages: DataFrame, rules: list[tuple[str, str, str]] = RULES, id_col: str = "page_id", url_col: str = "url") -> DataFrame:
    """Per row: (page_id, host, path, rule, verdict, template, purity).

    Null urls, and those without "://", have empty parts, no rule, and share
    one template of the empty host.  Null and repeated ids keep their rows;
    other columns are ignored; an empty table gives no rows.
    """
    work = Workspace(pages.sparkSession, "urls")
    host, path = url_parts(F.col(url_col))
    rows = with_rules(pages.select(F.col(id_col).alias("page_id"), host.alias("host"), path.alias("path")), rules)
    rows = rows.withColumn("parts", _segments(F.col("path")))
    judged = work.save(path_templates(rows, work), "judged")
    few = judged.count() <= BROADCAST_ROWS
    out = rows.join(F.broadcast(judged) if few else judged, ["host", "parts"])
    return out.select("page_id", "host", "path", "rule", F.coalesce("action", F.when(F.col("rejected"), "block"), F.lit("allow")).alias("verdict"), "template", "purity")


def op9_url_templates(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Verdicts for the urls of all ``pages``."""
    return url_verdicts(spark.read.parquet(f"{sf_dir}/pages.parquet"))


def _sql_case(rules, of) -> str:
    ordered = sorted(rules, key=lambda r: (-len(r[0] + r[1]), r[0] + r[1], r[2]))
    return "CASE " + " ".join(f"WHEN (host = '{h}' OR ends_with(host, '.{h}')) AND starts_with(path, '{p}') THEN '{of((h, p, a))}'" for h, p, a in ordered) + " END"


TWIN_LEVELS = 4  # the twin looks at this many segments; those of the given pages are fewer


def _twin() -> str:
    """The same verdicts by windows over paths of a fixed depth, one row a page."""
    steps = []
    for i in range(1, TWIN_LEVELS + 1):
        steps.append(f"""
k{i} AS (SELECT *, coalesce(seg[{i}], '') AS s, count(action) OVER c AS l, count(*) FILTER (WHERE action = 'block') OVER c AS b FROM k{i - 1} WINDOW c AS (PARTITION BY host, node, coalesce(seg[{i}], ''))),
m{i} AS (SELECT *, CASE WHEN l < {ENOUGH} THEN 0 WHEN 2 * b >= l THEN 1 ELSE 2 END AS side,
         count(DISTINCT s) OVER (PARTITION BY host, node) AS kinds, count(*) OVER (PARTITION BY host, node) AS pages FROM k{i}),
j{i} AS (SELECT *, count(action) OVER o AS pl, count(*) FILTER (WHERE action = 'block') OVER o AS pb FROM m{i} WINDOW o AS (PARTITION BY host, node, side)),
k{i} AS MATERIALIZED (SELECT page_id, host, path, rule, action, seg, CASE WHEN wild THEN shape || '/*' ELSE shape || '/' || replace(s, '*', '%2A') END AS shape,
         list_append(node, CASE WHEN wild THEN '*' WHEN side > 0 AND CAST(b * pl - l * pb AS DOUBLE) * (b * pl - l * pb) <= {CHI2} * l * pb * (pl - pb) THEN '~' || side ELSE '=' || s END) AS node
         FROM (SELECT *, kinds >= {MANY} AND 100 * kinds > {MANY_PERCENT} * pages AS wild FROM j{i}))""".replace(f"k{i} AS (SELECT *,", f"e{i} AS (SELECT *,").replace(f"FROM k{i})", f"FROM e{i})"))
    return ",".join(steps)


OP9_SQL = f"""
WITH u AS (SELECT page_id, CASE WHEN instr(url, '://') > 0 THEN substr(url, instr(url, '://') + 3) ELSE '' END AS rest FROM pages),
hp AS (SELECT page_id, translate(regexp_extract(rest, '^[^/?#]*', 0), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') AS host, regexp_extract(rest, '^[^/?#]*([^?#]*)', 1) AS path FROM u),
k0 AS (SELECT *, {_sql_case(RULES, lambda r: r[0] + r[1])} AS rule, {_sql_case(RULES, lambda r: r[2])} AS action,
  string_split(regexp_replace(regexp_replace(substr(path, 2), '/+$', ''), '[0-9]+', '{{n}}', 'g'), '/') AS seg, '' AS shape, []::VARCHAR[] AS node FROM hp),
{_twin()},
t AS (SELECT *, CASE WHEN regexp_replace(shape, '/+$', '') = '' THEN '/' ELSE regexp_replace(shape, '/+$', '') END AS template,
  count(action) OVER (PARTITION BY host, node) AS tl, count(*) FILTER (WHERE action = 'block') OVER (PARTITION BY host, node) AS tb FROM k{TWIN_LEVELS}),
pool AS (SELECT template, (count(*) FILTER (WHERE action = 'block') + {PRIOR / 2}) / (count(*) + {PRIOR}.0::DOUBLE) AS share FROM t WHERE action IS NOT NULL GROUP BY template HAVING count(DISTINCT host) >= {FEW_HOSTS}),
p AS (SELECT t.*, (tb + {STRENGTH} * coalesce(share, 0.5::DOUBLE)) / (tl + {STRENGTH}.0::DOUBLE) AS purity FROM t LEFT JOIN pool USING (template))
SELECT page_id, host, path, rule, coalesce(action, CASE WHEN purity - sqrt(purity * (1 - purity) / (tl + {STRENGTH}.0::DOUBLE)) >= {LEAST_PURITY} THEN 'block' ELSE 'allow' END) AS verdict,
  template, round(purity, 6) AS purity FROM p
"""
