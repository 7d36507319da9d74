"""Hierarchical token budgets and seeded epoch prefixes, built-in functions only."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from shardgraph.llm.common import Workspace

#: Weights of the query's tree, integers so that every engine gets the same quotients. Names that are not listed weigh OTHER.
DOMAIN_WEIGHTS = {"d0": 50, "d1": 30, "d2": 20}
LANG_WEIGHTS = {"en": 55, "de": 20, "fr": 15, "es": 10}
SOURCE_WEIGHTS: dict[str, int] = {}
OTHER = 10
BUCKET_DIGITS = 3
LEVELS = ("domain", "lang", "source")


def n_tokens(text: Column) -> Column:
    """Tokens of a text: blanks plus one; none for null or empty."""
    return F.when(F.coalesce(F.length(text), F.lit(0)) == 0, 0).otherwise(F.length(text) - F.length(F.replace(text, F.lit(" "))) + 1).cast("bigint")


def domain_of(source: Column) -> Column:
    """Domain of a source: its trailing number modulo 3, ``d0`` without a number."""
    return F.concat(F.lit("d"), (F.coalesce(F.regexp_extract(source, r"(\d{1,9})$", 1).try_cast("int"), F.lit(0)) % 3).cast("string"))


def _weight(name: Column, weights: dict[str, int]) -> Column:
    out = F.lit(OTHER)
    for k, w in weights.items():
        out = F.when(name == k, w).otherwise(out)
    return out.cast("double")


def _fill(nodes: DataFrame, parent: list[str], node: str) -> DataFrame:
    """Water-filling of each parent's ``budget`` over its children's ``cap`` by ``weight``.

    In the order of cap/weight a child is full as long as its cap is under its share of what is
    left; the first that is not sets the level for all others. Shortages therefore go to siblings
    first, and reach an ancestor's other children only through this subtree's own cap.
    """
    order = [F.col("cap") / F.col("weight"), F.col(node)]
    w = Window.partitionBy(*parent).orderBy(*order)
    before = F.coalesce(F.sum("cap").over(w.rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    rest = F.sum("weight").over(w.rowsBetween(0, Window.unboundedFollowing))
    lam = (F.col("budget") - before) / rest
    level = F.max(F.when(F.col("cap") / F.col("weight") > F.col("lam"), F.col("lam"))).over(Window.partitionBy(*parent))
    return (
        nodes.withColumn("lam", lam)
        .withColumn("level", level)
        .withColumn("got", F.when(F.col("level").isNull() | (F.col("cap") / F.col("weight") <= F.col("lam")), F.col("cap").cast("double")).otherwise(F.col("weight") * F.col("level")))
        .drop("lam", "level", "budget", "weight")
    )


def leaf_budgets(leaves: DataFrame, total: Column, weights: dict[str, dict[str, int]], max_epochs: int) -> DataFrame:
    """Budget of each leaf (domain, lang, source, avail); one row per leaf, so all windows are small."""
    caps = leaves.withColumn("cap", F.col("avail") * max_epochs)
    d = caps.groupBy("domain").agg(F.sum("cap").alias("cap"))
    d = d.withColumn("weight", _weight(F.col("domain"), weights["domain"]))
    d = d.crossJoin(F.broadcast(caps.agg(F.least(F.sum("cap").cast("double"), F.floor(F.sum("avail") * total).cast("double")).alias("budget"))))
    d = _fill(d.withColumn("root", F.lit(0)), ["root"], "domain").select("domain", F.col("got").alias("budget"))
    lang = caps.groupBy("domain", "lang").agg(F.sum("cap").alias("cap")).withColumn("weight", _weight(F.col("lang"), weights["lang"])).join(d, "domain")
    lang = _fill(lang, ["domain"], "lang").select("domain", "lang", F.col("got").alias("budget"))
    src = caps.withColumn("weight", _weight(F.col("source"), weights["source"])).join(lang, ["domain", "lang"])
    return _fill(src, ["domain", "lang"], "source").withColumn("tokens", F.floor("got").cast("bigint")).drop("got", "cap")


def mix(
    docs: DataFrame,
    budget_share: float = 1.0,
    max_epochs: int = 2,
    seed: int = 7,
    weights: dict[str, dict[str, int]] | None = None,
    id_col: str = "doc_id",
) -> DataFrame:
    """Rows (doc_id, domain, lang, source, epoch, n_tokens) of the mixture.

    The budget is ``budget_share`` of all tokens. Leaf budgets come from the tree by ``_fill``; a
    leaf may repeat up to ``max_epochs`` times. Every epoch orders a leaf by a seeded hash of the
    id; full epochs take all of it, the last takes the prefix whose running tokens fit. The prefix
    needs no sort of a whole leaf: the hash's leading digits deal each leaf into 4,096 buckets
    whose sums, a small table, tell which bucket holds the cut, and only that bucket's rows are
    windowed. A source with a third of all rows is one leaf of 4,096 even buckets.

    Null lang and source are nodes named ``?``; a null id hashes as ``?``; empty texts have no
    tokens and are taken while their bucket is; repeated rows count each; an empty table gives none.
    """
    weights = weights or {"domain": DOMAIN_WEIGHTS, "lang": LANG_WEIGHTS, "source": SOURCE_WEIGHTS}
    ws = Workspace(docs.sparkSession, "mix")
    src = F.coalesce(F.col("source"), F.lit("?"))
    rows = ws.write(
        docs.select(
            F.col(id_col).alias("doc_id"), domain_of(src).alias("domain"), F.coalesce("lang", F.lit("?")).alias("lang"), src.alias("source"), n_tokens(F.col("text")).alias("n_tokens")
        ),
        "rows",
    )
    leaves = rows.groupBy(*LEVELS).agg(F.sum("n_tokens").alias("avail"))
    plan = leaf_budgets(leaves, F.lit(budget_share), weights, max_epochs)
    plan = plan.withColumn("whole", F.when(F.col("avail") > 0, F.least(F.floor(F.col("tokens") / F.col("avail")), F.lit(max_epochs))).otherwise(max_epochs).cast("int"))
    plan = ws.write(plan.withColumn("left", F.col("tokens") - F.col("whole") * F.col("avail")).coalesce(1), "plan")
    few = plan.count() <= 100_000
    dealt = rows.join(F.broadcast(plan) if few else plan, list(LEVELS))
    last = dealt.where("left > 0").withColumn("h", F.md5(F.concat_ws("-", F.lit(str(seed)), (F.col("whole") + 1).cast("string"), F.coalesce(F.col("doc_id").cast("string"), F.lit("?")))))
    last = last.withColumn("bucket", F.substring("h", 1, BUCKET_DIGITS))
    sums = last.groupBy(*LEVELS, "bucket", "left").agg(F.sum("n_tokens").alias("s"))
    upto = F.sum("s").over(Window.partitionBy(*LEVELS).orderBy("bucket"))
    cuts = sums.withColumn("upto", upto).withColumn("before", F.col("upto") - F.col("s")).where("before < left").select(*LEVELS, "bucket", "upto", "before")
    inside = last.join(cuts, [*LEVELS, "bucket"])
    cols = ["doc_id", *LEVELS, "n_tokens"]
    run = F.sum("n_tokens").over(Window.partitionBy(*LEVELS, "bucket").orderBy("h", "doc_id", "n_tokens").rowsBetween(Window.unboundedPreceding, 0))
    part = inside.where("upto <= left").select(*cols, (F.col("whole") + 1).alias("epoch")).unionByName(
        inside.where("upto > left").withColumn("run", run).where("before + run <= left").select(*cols, (F.col("whole") + 1).alias("epoch"))
    )
    full = dealt.where("whole > 0").select(*cols, F.explode(F.sequence(F.lit(1), F.col("whole"))).alias("epoch"))
    return full.unionByName(part).select("doc_id", *LEVELS, F.col("epoch").cast("int").alias("epoch"), "n_tokens")


def in_mix(docs: DataFrame, budget_share: float, seed: int = 7, weights: dict[str, dict[str, int]] | None = None) -> DataFrame:
    """Rows of ``docs`` that one epoch of the mixture takes, all columns kept.

    A leaf's prefix ends at one hash, so a small table of cuts, one per leaf, decides every row
    where it stands; texts are not shuffled. Nulls as in ``mix``; rows that repeat an id go together.
    """
    h = F.md5(F.concat_ws("-", F.lit(str(seed)), F.lit("1"), F.coalesce(F.col("doc_id").cast("string"), F.lit("?"))))
    src = F.coalesce(F.col("source"), F.lit("?"))
    taken = mix(docs, budget_share, 1, seed, weights).where("epoch = 1")
    cuts = Workspace(docs.sparkSession, "cuts").write(taken.groupBy(*LEVELS).agg(F.max(h).alias("cut")).coalesce(1), "cuts")
    few = cuts.count() <= 100_000
    here = docs.select(F.struct(*docs.columns).alias("_row"), domain_of(src).alias("domain"), F.coalesce("lang", F.lit("?")).alias("lang"), src.alias("source"), h.alias("h"))
    return here.join(F.broadcast(cuts) if few else cuts, list(LEVELS)).where("h <= cut").select("_row.*")


def _sql_weight(col: str, weights: dict[str, int]) -> str:
    return "case " + " ".join(f"when {col} = '{k}' then {w}" for k, w in weights.items()) + f" else {OTHER} end" if weights else str(OTHER)


def _sql_fill(name: str, nodes: str, parent: str, node: str) -> str:
    return f"""{name}1 as (select *, (budget - coalesce(sum(cap) over (partition by {parent} order by cap / weight, {node} rows between unbounded preceding and 1 preceding), 0))
    / sum(weight) over (partition by {parent} order by cap / weight, {node} rows between current row and unbounded following) as lam from {nodes}),
  {name} as (select *, case when lev is null or cap / weight <= lam then cap::double else weight * lev end as got
    from (select *, max(case when cap / weight > lam then lam end) over (partition by {parent}) as lev from {name}1))"""


def oracle(share: float = 1.0, epochs: int = 2, seed: int = 7) -> str:
    return f"""
with d0 as (select doc_id, coalesce(source, '?') as source, coalesce(lang, '?') as lang,
    (case when coalesce(length(text), 0) = 0 then 0 else length(text) - length(replace(text, ' ', '')) + 1 end)::bigint as n_tokens from documents),
  r as (select *, 'd' || (coalesce(try_cast(regexp_extract(source, '(\\d{{1,9}})$', 1) as int), 0) % 3)::varchar as domain from d0),
  leaf as (select domain, lang, source, sum(n_tokens)::bigint as avail, (sum(n_tokens) * {epochs})::double as cap from r group by all),
  dn as (select domain, 0 as root, sum(cap) as cap, any_value(({_sql_weight('domain', DOMAIN_WEIGHTS)})::double) as weight,
    any_value((select least(sum(cap), floor(sum(avail) * {share!r}::double)) from leaf)) as budget from leaf group by domain),
  {_sql_fill('dg', 'dn', 'root', 'domain')},
  ln as (select l.domain, l.lang, sum(l.cap) as cap, any_value(({_sql_weight('l.lang', LANG_WEIGHTS)})::double) as weight, any_value(g.got) as budget
    from leaf l join dg g using (domain) group by l.domain, l.lang),
  {_sql_fill('lg', 'ln', 'domain', 'lang')},
  sn as (select l.*, ({_sql_weight('l.source', SOURCE_WEIGHTS)})::double as weight, g.got as budget from leaf l join lg g on l.domain = g.domain and l.lang = g.lang),
  {_sql_fill('sg', 'sn', 'domain, lang', 'source')},
  p as (select domain, lang, source, avail, floor(got)::bigint as tokens,
    (case when avail > 0 then least(floor(got)::bigint // avail, {epochs}) else {epochs} end)::int as whole from sg),
  j as (select r.*, whole, tokens - whole * avail as rest, md5('{seed}-' || (whole + 1)::varchar || '-' || coalesce(doc_id::varchar, '?')) as h from r join p using (domain, lang, source)),
  c as (select *, sum(n_tokens) over (partition by domain, lang, source order by h, doc_id, n_tokens rows unbounded preceding) as run from j where rest > 0)
select doc_id, domain, lang, source, e::int as epoch, n_tokens from j, range(1, whole + 1) t(e) where whole > 0
union all select doc_id, domain, lang, source, (whole + 1)::int, n_tokens from c where run <= rest
"""
