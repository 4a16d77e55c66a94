"""URL verdicts: longest host-and-path rule first, link-graph propagation for the rest. DataFrame functions only.

Trust starts at hosts with pages that a rule allows, distrust at hosts with pages that a rule blocks, each in proportion to the
share of these pages. Trust follows links from host to host (personalised PageRank); distrust follows them backwards, since
who links to a bad host is suspect. Each link counts by its frequency; links inside a host count for nothing. A
host is blocked when its distrust is above ``ratio`` times its trust, and a page without a rule gets its host's verdict.

Rules are literals of the caller and become one expression, so judging by rule needs no join. Link counts and seeds are added
up before they are shuffled; page bodies are read once for links and never shuffled. Each round is one join and one
aggregation over the host graph, kept as a table in the shared folder, which cuts the lineage. Rounds go on until no host was newly
reached and no mass changed by more than ``tolerance`` of itself, so hosts at any distance from a seed are judged. The SQL twin
writes out ``ROUNDS`` rounds and is equal only where these are enough, as on tables whose links stay inside their hosts.

Behaviour at the edges: a null url, or one without ``://``, has an empty host and path, fits no rule and is allowed; null html
has no links; page ids may repeat or be null, each row is judged; links of pages without host are ignored; an
empty table gives no rows; other columns are ignored.
"""

from __future__ import annotations

from dataclasses import dataclass
from itertools import count

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import discard, materialize

UPPER, LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"
LINK = r"""(?i)href\s*=\s*["']?(https?:)?//([^/?#"'\s>]+)"""
DAMPING, ROUNDS, RATIO = 0.85, 10, 1.0  # ROUNDS is that of the SQL twin alone
TOLERANCE = 1e-9


@dataclass(frozen=True)
class Rule:
    verdict: str
    text: str  # host, then the path from the first slash on

    @property
    def host(self) -> str:
        return self.text.partition("/")[0]

    @property
    def path(self) -> str:
        return "/" + self.text.partition("/")[2]


DEFAULT_RULES = (
    Rule("allow", "com/"),
    Rule("block", "example.com/en/"),
    Rule("allow", "www.example.com/en/"),
    Rule("block", "net/es/"),
    Rule("block", "net/fr/"),
)


def parts(pages: DataFrame) -> DataFrame:
    """page_id, url, html with host and path."""
    cols = [pages["page_id"].cast("long").alias("page_id"), pages["url"].cast("string").alias("url"), pages["html"].cast("string").alias("html")]
    rest = F.when(F.instr("url", "://") > 0, F.expr("substring(url, instr(url, '://') + 3)")).otherwise("")
    return (
        pages.select(cols)
        .withColumn("rest", F.coalesce(rest, F.lit("")))
        .withColumn("host", F.translate(F.regexp_extract("rest", r"^([^/?#]*)", 1), UPPER, LOWER))
        .withColumn("path", F.regexp_extract("rest", r"^[^/?#]*([^?#]*)", 1))
        .drop("rest")
    )


def rule_columns(host: Column, path: Column, rules=DEFAULT_RULES) -> tuple[Column, Column]:
    """The longest rule that fits, and its verdict; null where none does."""
    rule, verdict = F.lit(None).cast("string"), F.lit(None).cast("string")
    for r in sorted(rules, key=lambda r: (len(r.text), r.text)):  # the longest is asked first
        fits = ((host == r.host) | host.endswith("." + r.host)) & path.startswith(r.path)
        rule, verdict = F.when(fits, r.text).otherwise(rule), F.when(fits, r.verdict).otherwise(verdict)
    return rule, verdict


def host_links(judged: DataFrame) -> DataFrame:
    """(src, dst, n) of links between different hosts."""
    targets = F.regexp_extract_all("html", F.lit(LINK), 2)
    return (
        judged.where((F.col("host") != "") & F.col("html").isNotNull())
        .select(F.col("host").alias("src"), F.explode(targets).alias("dst"))
        .withColumn("dst", F.translate("dst", UPPER, LOWER))
        .where(F.col("src") != F.col("dst"))
        .groupBy("src", "dst")
        .agg(F.count("*").alias("n"))
    )


def propagate(links: DataFrame, seeds: DataFrame, damping: float = DAMPING, rounds: int | None = None, tolerance: float = TOLERANCE) -> DataFrame:
    """(kind, host, mass): personalised PageRank of each kind of ``seeds`` (kind, host, seed) over ``links`` (kind, src, dst, n).

    Every change is measured against the host's own mass, as far hosts have little. ``rounds`` is a cap for callers that want one.
    """
    total = seeds.groupBy("kind").agg(F.sum("seed").alias("all_seed"))
    start = seeds.join(F.broadcast(total), "kind").select("kind", "host", (F.col("seed") / F.col("all_seed")).alias("seed"))
    out = links.groupBy("kind", "src").agg(F.sum("n").alias("out_n"))
    step = materialize(links.join(out, ["kind", "src"]).select("kind", "src", "dst", (F.col("n") / F.col("out_n")).alias("w")), "linkshares")
    start = materialize(start, "seeds")
    base = start.select("kind", "host", (F.col("seed") * (1 - damping)).alias("mass"))
    mass, before = base, None
    if step.isEmpty():
        return base
    for _ in count() if rounds is None else range(rounds):
        moved = mass.join(step, (mass["kind"] == step["kind"]) & (mass["host"] == step["src"])).select(step["kind"], step["dst"].alias("host"), (mass["mass"] * step["w"] * damping).alias("mass"))
        after = materialize(base.unionByName(moved).groupBy("kind", "host").agg(F.sum("mass").alias("mass")), "mass")
        old = mass.select("kind", "host", F.col("mass").alias("old"))
        change = after.join(old, ["kind", "host"], "left").agg(F.max(F.when(F.col("mass") > 0, F.abs(F.col("mass") - F.coalesce("old", F.lit(0.0))) / F.col("mass")).otherwise(0.0))).first()[0] or 0.0
        discard(before)
        mass = before = after
        if change <= tolerance:
            break
    return mass


def judge(pages: DataFrame, rules=DEFAULT_RULES, damping: float = DAMPING, rounds: int | None = None, ratio: float = RATIO) -> DataFrame:
    """page_id, host, path, rule, verdict, and the host's trust and distrust."""
    judged = parts(pages)
    rule, verdict = rule_columns(F.col("host"), F.col("path"), rules)
    judged = judged.withColumn("rule", rule).withColumn("by_rule", verdict)
    seeds = (
        judged.where((F.col("host") != "") & F.col("by_rule").isNotNull())
        .groupBy(F.when(F.col("by_rule") == "allow", "trust").otherwise("distrust").alias("kind"), "host")
        .agg(F.count("*").cast("double").alias("seed"))
    )
    links = materialize(host_links(judged), "hostlinks")
    both = links.select(F.lit("trust").alias("kind"), "src", "dst", "n").unionByName(links.select(F.lit("distrust").alias("kind"), F.col("dst").alias("src"), F.col("src").alias("dst"), "n"))
    mass = propagate(both, seeds, damping, rounds)
    hosts = mass.groupBy("host").agg(
        F.sum(F.when(F.col("kind") == "trust", F.col("mass")).otherwise(0.0)).alias("trust"), F.sum(F.when(F.col("kind") == "distrust", F.col("mass")).otherwise(0.0)).alias("distrust")
    )
    rows = judged.select("page_id", "host", "path", "rule", "by_rule")
    trust, distrust = F.coalesce("trust", F.lit(0.0)), F.coalesce("distrust", F.lit(0.0))
    by_graph = F.when(distrust > trust * ratio, "block").otherwise("allow")
    return rows.join(hosts, "host", "left").select("page_id", rows["host"], "path", "rule", F.coalesce("by_rule", by_graph).alias("verdict"))


def oracle(rules=DEFAULT_RULES, damping: float = DAMPING, rounds: int = ROUNDS, ratio: float = RATIO) -> str:
    """The same result as SQL for DuckDB, with the rounds written out."""
    fits = [(r, f"(host = '{r.host}' or ends_with(host, '.{r.host}')) and starts_with(path, '{r.path}')") for r in sorted(rules, key=lambda r: (-len(r.text), r.text))]
    case = lambda value: "case " + " ".join(f"when {f} then '{value(r)}'" for r, f in fits) + " end"
    link = LINK.replace("'", "''")
    chain = "\n".join(
        f"m{i + 1} as materialized (select kind, host, sum(mass) as mass from (select * from m0 union all select s.kind, s.dst, m.mass * s.w * {damping} from m{i} m join step s on m.kind = s.kind and m.host = s.src) group by all),"
        for i in range(rounds)
    )
    return f"""
with p as (select page_id, url, html, case when instr(url, '://') > 0 then substring(url, instr(url, '://') + 3) else '' end as rest from pages),
q as (select page_id, html, translate(regexp_extract(rest, '^([^/?#]*)', 1), '{UPPER}', '{LOWER}') as host, regexp_extract(rest, '^[^/?#]*([^?#]*)', 1) as path from p),
j as materialized (select *, {case(lambda r: r.text)} as rule, {case(lambda r: r.verdict)} as by_rule from q),
e as (select host as src, translate(unnest(regexp_extract_all(html, '{link}', 2)), '{UPPER}', '{LOWER}') as dst from j where host <> ''),
l as (select src, dst, count(*) as n from e where src <> dst group by all),
k as (select 'trust' as kind, src, dst, n from l union all select 'distrust', dst, src, n from l),
step as materialized (select kind, src, dst, n / sum(n) over (partition by kind, src) as w from k),
s as (select case when by_rule = 'allow' then 'trust' else 'distrust' end as kind, host, count(*)::double as seed from j where host <> '' and by_rule is not null group by all),
m0 as materialized (select kind, host, seed / sum(seed) over (partition by kind) * (1 - {damping}) as mass from s),
{chain}
h as (select host, sum(case when kind = 'trust' then mass else 0 end) as trust, sum(case when kind = 'distrust' then mass else 0 end) as distrust from m{rounds} group by 1)
select j.page_id, j.host, j.path, j.rule, coalesce(j.by_rule, case when coalesce(h.distrust, 0) > coalesce(h.trust, 0) * {ratio} then 'block' else 'allow' end) as verdict
from j left join h on j.host = h.host
"""
