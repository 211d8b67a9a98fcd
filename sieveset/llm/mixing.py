"""Mixing sources to target weights by hierarchical budgeting.

A token budget flows down a tree of domain, language and source. At each node the children share its budget by weight; a
child that has too few tokens takes all it has, and what it lacks goes to its siblings by their weights. Only what all
siblings together cannot take goes back to the ancestors: a node never gets more than its leaves can give. Every leaf then takes a
prefix of its documents, in an order seeded anew for each epoch. DataFrame functions only, integers only.

Defined cases: a null text has 0 tokens; null domain, language or source are leaves of their own; documents without tokens
are never chosen, since no budget is spent on them; an empty table gives an empty result; repeated rows with one doc_id
stand next to each other in the order. Further columns pass through.
"""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .common import materialise, table

SEED = 20
#: Of all available tokens, in thousandths.
BUDGET_SHARE = 800
MAX_EPOCHS = 2
LEVELS = ("domain", "lang", "source")
#: Rows of one leaf and epoch that share a prefix of the seeded order, on average at most.
SLICE_ROWS = 65_536
#: The leaves' budgets are broadcast up to so many leaves.
BROADCAST_LEAVES = 200_000


def whitespace_tokens(text: Column) -> Column:
    """Spaces and line feeds of a text, and one; 0 for an empty or null text."""
    gaps = F.length(text) - F.length(F.translate(text, " \n", ""))
    return F.when(F.coalesce(F.length(text), F.lit(0)) == 0, F.lit(0)).otherwise(gaps + 1).cast("long")


def with_domain(docs: DataFrame) -> DataFrame:
    """The tables name no domain: four domains are made of the sources, by the first digit of their md5."""
    digit = F.ascii(F.substring(F.md5(F.coalesce(F.col("source"), F.lit("")).cast("binary")), 1, 1))
    return docs.withColumn("domain", F.concat(F.lit("d"), (digit % 4).cast("string")))


def _share(nodes: DataFrame, parent: list[str], node: str) -> DataFrame:
    """Children's budgets out of ``_budget`` of their parent.

    Sorted by capacity over weight, the children that are filled to the brim come first; the first that is not fixes the
    level for all after it. Products stay exact as decimals.
    """
    big = lambda c: F.col(c).cast("decimal(38,0)")
    group = Window.partitionBy(*parent)
    order = group.orderBy(F.col("_ratio"), F.col(node).asc_nulls_first())
    before, after = order.rowsBetween(Window.unboundedPreceding, -1), order.rowsBetween(0, Window.unboundedFollowing)
    out = nodes.withColumn("_ratio", F.col("_capacity") / F.col("_weight"))
    out = out.withColumns({"_spent": F.coalesce(F.sum("_capacity").over(before), F.lit(0)), "_left_weight": F.sum("_weight").over(after)})
    out = out.withColumn("_full", big("_capacity") * big("_left_weight") <= (big("_budget") - big("_spent")) * big("_weight"))
    first = F.min(F.when(~F.col("_full"), F.struct("_ratio", F.coalesce(F.col(node), F.lit("")).alias("n"), "_spent", "_left_weight"))).over(group)
    out = out.withColumn("_level", first)
    rest = F.expr("(cast(_budget as decimal(38,0)) - cast(_level._spent as decimal(38,0))) * cast(_weight as decimal(38,0)) div cast(_level._left_weight as decimal(38,0))")
    return out.withColumn("_budget", F.when(F.col("_full"), F.col("_capacity")).otherwise(rest).cast("long")).drop("_ratio", "_spent", "_left_weight", "_full", "_level")


def leaf_budgets(leaves: DataFrame, weights: dict[str, Column], levels: tuple[str, ...], budget_share: int, max_epochs: int) -> DataFrame:
    """Leaves with their budget. ``weights`` has, by level, an integer expression over ``_tokens`` of the node."""
    leaves = leaves.withColumn("_capacity", F.col("_tokens") * max_epochs).where("_tokens > 0")
    total = leaves.agg(F.expr(f"sum(_tokens) * {budget_share} div 1000").alias("_budget"))
    out = None
    for depth, level in enumerate(levels):
        path = list(levels[: depth + 1])
        nodes = leaves.groupBy(*path).agg(F.sum("_tokens").alias("_tokens"), F.sum("_capacity").alias("_capacity"))
        nodes = nodes.withColumn("_weight", weights[level])
        if out is None:
            nodes = nodes.crossJoin(F.broadcast(total)).withColumn("_root", F.lit(0))
            out = _share(nodes, ["_root"], level).drop("_root")
        else:
            above = out.select(*(F.col(p).alias(f"_up_{p}") for p in path[:-1]), "_budget")
            same = [F.col(p).eqNullSafe(F.col(f"_up_{p}")) for p in path[:-1]]
            out = _share(nodes.join(above, same).drop(*(f"_up_{p}" for p in path[:-1])), path[:-1], level)
    return out.select(*levels, F.col("_tokens").alias("leaf_tokens"), F.col("_budget").alias("leaf_budget"))


def standard_weights() -> dict[str, Column]:
    """Domains: root of their tokens. Languages: their tokens in thousands. Sources: all alike."""
    return {
        "domain": F.greatest(F.lit(1), F.floor(F.sqrt(F.col("_tokens").cast("double"))).cast("long")),
        "lang": F.expr("greatest(1, _tokens div 1000)"),
        "source": F.lit(1).cast("long"),
    }


def mix(docs: DataFrame, levels: tuple[str, ...] = LEVELS, weights: dict[str, Column] | None = None, budget_share: int = BUDGET_SHARE, max_epochs: int = MAX_EPOCHS, seed: int = SEED, text: str = "text", id_col: str = "doc_id", counted: str | None = None) -> DataFrame:
    """The chosen documents, once for each epoch that takes them, with epoch, tokens, leaf_tokens, leaf_budget, taken_before (-1 where a whole epoch is taken).

    A leaf may hold any share of the rows. Its order is cut into slices by the leading digits of the seeded hash;
    running sums are taken inside slices and over the slices' sums, so no task gets a whole leaf. ``counted`` names a column of
    ``docs`` with tokens that are counted already; without it texts are counted in each of the four passes.
    """
    weights = weights or standard_weights()
    made = ("epoch", "tokens", "leaf_tokens", "leaf_budget", "taken_before")
    keep = [c for c in docs.columns if c.lower() not in made]
    rows = docs.select(*keep, (F.col(counted).cast("long") if counted else whitespace_tokens(F.col(text))).alias("tokens"))
    leaves = materialise(rows.groupBy(*levels).agg(F.sum("tokens").alias("_tokens"), F.count("*").alias("_rows")), "mix-leaves")
    digits = max(2, math.ceil(math.log(max(1, (leaves.agg(F.sum("_rows")).first()[0] or 1) / SLICE_ROWS), 16)))
    budgets = materialise(leaf_budgets(leaves.drop("_rows"), weights, levels, budget_share, max_epochs), "mix-budgets")
    wanted = budgets.select(*(F.col(p).alias(f"_b_{p}") for p in levels), "leaf_tokens", "leaf_budget", F.expr("cast(leaf_budget div leaf_tokens as int)").alias("_epochs"), (F.col("leaf_budget") % F.col("leaf_tokens")).alias("_rest"))
    if budgets.count() <= BROADCAST_LEAVES:
        wanted = F.broadcast(wanted)
    same = lambda mark, names: [F.col(p).eqNullSafe(F.col(f"{mark}{p}")) for p in names]
    tagged = rows.where("tokens > 0").join(wanted, same("_b_", levels)).drop(*(f"_b_{p}" for p in levels))
    whole = tagged.where("_epochs > 0").withColumn("epoch", F.explode(F.sequence(F.lit(0), F.col("_epochs") - 1))).withColumn("taken_before", F.lit(-1).cast("long"))

    part = tagged.where("_rest > 0").withColumn("epoch", F.col("_epochs"))
    part = part.withColumn("_key", F.md5(F.concat_ws(":", F.lit(str(seed)), F.col("epoch").cast("string"), F.coalesce(F.col(id_col).cast("string"), F.lit(""))).cast("binary")))
    part = part.withColumn("_slice", F.substring("_key", 1, digits))
    place = (*levels, "_slice")
    sums = part.groupBy(*place).agg(F.sum("tokens").alias("_sum"))
    run = Window.partitionBy(*levels).orderBy("_slice").rowsBetween(Window.unboundedPreceding, -1)
    starts = sums.withColumn("_start", F.coalesce(F.sum("_sum").over(run), F.lit(0))).select(*(F.col(p).alias(f"_s_{p}") for p in place), "_start")
    # only slices that begin before the leaf's rest is spent are put in order
    begun = part.join(starts, same("_s_", place)).where("_start < _rest").drop(*(f"_s_{p}" for p in place))
    within = Window.partitionBy(*place).orderBy("_key", "tokens").rowsBetween(Window.unboundedPreceding, -1)
    prefix = begun.withColumn("taken_before", F.col("_start") + F.coalesce(F.sum("tokens").over(within), F.lit(0))).where("taken_before + tokens <= _rest")
    return whole.select(*keep, *made).unionByName(prefix.select(*keep, *made))


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = with_domain(table(spark, sf_dir, "documents").select("doc_id", "lang", "source", "text"))
    light = materialise(docs.select("doc_id", *LEVELS, whitespace_tokens(F.col("text")).alias("tokens")), "mix-counted")  # texts are read once
    return mix(light, counted="tokens").select("doc_id", *LEVELS, "epoch", "tokens", "leaf_tokens", "leaf_budget", "taken_before")


def _share_sql(name: str, source: str, parent: list[str], node: str, path: list[str]) -> str:
    over = f"partition by {', '.join(parent)}" if parent else ""
    cols = ", ".join(path)
    return f"""
{name}_a as (select *, capacity / weight as ratio from {source}),
{name}_b as (select *,
    coalesce(sum(capacity) over ({over} order by ratio, {node} nulls first rows between unbounded preceding and 1 preceding), 0)::hugeint as spent,
    sum(weight) over ({over} order by ratio, {node} nulls first rows between current row and unbounded following)::hugeint as left_weight from {name}_a),
{name}_c as (select *, capacity::hugeint * left_weight <= (budget - spent) * weight as brim from {name}_b),
{name}_d as (select *,
    first_value(spent) over ({over} order by brim, ratio, {node} nulls first) as level_spent,
    first_value(left_weight) over ({over} order by brim, ratio, {node} nulls first) as level_weight from {name}_c),
{name} as (select {cols}, tokens, case when brim then capacity else ((budget - level_spent) * weight) // level_weight end::bigint as budget from {name}_d)"""


def oracle() -> str:
    weight = {"domain": "greatest(1, floor(sqrt(sum(tokens)::double))::bigint)", "lang": "greatest(1, sum(tokens) // 1000)::bigint", "source": "1::bigint"}
    parts, above = [], ""
    for depth, level in enumerate(LEVELS):
        path = list(LEVELS[: depth + 1])
        cols = ", ".join(path)
        parts.append(f"n{depth} as (select {cols}, sum(tokens)::bigint as tokens, (sum(tokens) * {MAX_EPOCHS})::bigint as capacity, {weight[level]} as weight from leaves group by {cols})")
        if depth:
            on = " and ".join(f"n.{p} is not distinct from u.{p}" for p in path[:-1])
            parts.append(f"m{depth} as (select n.*, u.budget::hugeint as budget from n{depth} n join {above} u on {on})")
        else:
            parts.append(f"m0 as (select n0.*, (select sum(tokens) * {BUDGET_SHARE} // 1000 from leaves)::hugeint as budget from n0)")
        parts.append(_share_sql(f"s{depth}", f"m{depth}", path[:-1], level, path))
        above = f"s{depth}"
    on = " and ".join(f"r.{p} is not distinct from b.{p}" for p in LEVELS)
    return f"""
with rows as (
  select doc_id, 'd' || (ascii(substr(md5(coalesce(source, '')), 1, 1)) % 4) as domain, lang, source,
         case when coalesce(length(text), 0) = 0 then 0 else length(text) - length(replace(replace(text, ' ', ''), chr(10), '')) + 1 end::bigint as tokens from documents),
leaves as (select {', '.join(LEVELS)}, sum(tokens) as tokens from rows group by all having sum(tokens) > 0),
{','.join(parts)},
tagged as (select r.*, b.tokens as leaf_tokens, b.budget as leaf_budget, (b.budget // b.tokens)::int as epochs, b.budget % b.tokens as rest
           from rows r join {above} b on {on} where r.tokens > 0),
ordered as (select *, coalesce(sum(tokens) over (partition by {', '.join(LEVELS)} order by md5('{SEED}:' || epochs || ':' || doc_id), tokens
            rows between unbounded preceding and 1 preceding), 0)::bigint as taken_before from tagged where rest > 0)
select doc_id, {', '.join(LEVELS)}, unnest(range(epochs))::int as epoch, tokens, leaf_tokens, leaf_budget, (-1)::bigint as taken_before from tagged
union all
select doc_id, {', '.join(LEVELS)}, epochs as epoch, tokens, leaf_tokens, leaf_budget, taken_before from ordered where taken_before + tokens <= rest"""
