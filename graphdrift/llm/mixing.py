"""Mixing sources to target weights, with DataFrame functions only.

A tree domain -> language -> source carries weights on its edges. A budget of
tokens flows down from the root: at every node it is divided among the children
in proportion to their weights, no child getting more than its subtree can supply
(its tokens times the epochs allowed). What a full child leaves over goes to its
siblings; because a node never gets more than its own subtree holds, only what
all siblings together can't take moves up to the node's own siblings. Each leaf
then fills its budget with a prefix of a seeded order: epoch 0 in one random
order, epoch 1 in another, and so on.

The prefix is found without sorting a leaf in one task: the seeded order is cut
into fine buckets, whole buckets are summed, and only the one bucket in which the
budget ends is ordered row by row.

Defined results: null domain, language and source are values of their own; null
text counts no tokens and is selected while its leaf has budget left at its
place; repeated rows each count; rows without tokens are ordered like others; an
empty table gives an empty result; other columns pass through, one with an added
column's name as ``input_<name>``.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from graphdrift.llm import common

LEVELS = ["mix_domain", "mix_lang", "mix_source"]


def default_tokens() -> Column:
    """About four bytes of text make a token."""
    return F.expr("(octet_length(coalesce(text, '')) + 3) div 4").cast("long")


def default_domain() -> Column:
    """Sources numbered alike modulo four form a domain."""
    n = F.coalesce(F.regexp_extract(F.coalesce(F.col("source"), F.lit("")), "([0-9]+)$", 1), F.lit(""))
    return F.concat(F.lit("domain"), F.when(n == "", F.lit("0")).otherwise(F.pmod(n.cast("long"), F.lit(4)).cast("string")))


#: Weights of the default recipe; a node that isn't named has weight 1.
DOMAIN_WEIGHTS = {"domain0": 4, "domain1": 3, "domain2": 2, "domain3": 1}
LANG_WEIGHTS = {"en": 5, "de": 2, "fr": 2, "es": 2}


def weight_of(column: Column, weights: dict[str, int]) -> Column:
    out = F.lit(1)
    for k, v in weights.items():
        out = F.when(column == k, F.lit(v)).otherwise(out)
    return out.cast("long")


def poured(children: DataFrame, parent: list[str]) -> DataFrame:
    """Divide each parent's ``budget`` among its children by ``w`` under their ``cap``.

    The children that fill up are those with the least cap / w; in that order one
    running sum tells at which child the level of the rest stands. One window over
    siblings, so the cost follows the size of the tree and not of the corpus.
    """
    order = Window.partitionBy(*parent).orderBy(F.col("cap") / F.col("w"), *LEVELS[: len(parent) + 1] if parent != ["root"] else ["mix_domain"])
    before = F.coalesce(F.sum("cap").over(order.rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    rest = F.sum("w").over(order.rowsBetween(0, Window.unboundedFollowing))
    level = (F.col("budget") - F.col("cap_before")) / F.col("w_rest")
    full = F.col("cap") / F.col("w") <= F.col("level")
    children = children.withColumn("cap_before", before).withColumn("w_rest", rest).withColumn("level", level).withColumn("full", full)
    first = F.min(F.when(~F.col("full"), F.struct(F.col("cap_before"), F.col("level")))).over(Window.partitionBy(*parent))
    share = F.when(F.col("full"), F.col("cap")).otherwise(F.floor(F.col("w") * F.col("open.level")))
    return children.withColumn("open", first).withColumn("share", F.least(F.col("cap"), F.greatest(F.lit(0), share)).cast("long"))


def leaf_budgets(leaves: DataFrame, budget: Column | int, epochs: int, domain_weights: dict | None = None, lang_weights: dict | None = None, source_weights: dict | None = None) -> DataFrame:
    """Budget of every leaf. ``leaves``: LEVELS and ``tokens``."""
    c = leaves.withColumn("cap", F.col("tokens") * F.lit(epochs))
    top = c.groupBy("mix_domain").agg(F.sum("cap").alias("cap")).withColumn("w", weight_of(F.col("mix_domain"), DOMAIN_WEIGHTS if domain_weights is None else domain_weights))
    want = budget if isinstance(budget, Column) else F.lit(budget)
    top = top.withColumn("root", F.lit(0)).withColumn("budget", F.least(want, F.sum("cap").over(Window.partitionBy("root"))))
    top = poured(top, ["root"]).select("mix_domain", F.col("share").alias("budget"))
    mid = c.groupBy("mix_domain", "mix_lang").agg(F.sum("cap").alias("cap")).withColumn("w", weight_of(F.col("mix_lang"), LANG_WEIGHTS if lang_weights is None else lang_weights))
    mid = poured(mid.join(top, "mix_domain"), ["mix_domain"]).select("mix_domain", "mix_lang", F.col("share").alias("budget"))
    low = c.withColumn("w", weight_of(F.col("mix_source"), source_weights or {})).join(mid, ["mix_domain", "mix_lang"])
    return poured(low, ["mix_domain", "mix_lang"]).select(*LEVELS, "tokens", F.col("share").alias("leaf_budget"))


def place(seed: int, epoch: Column) -> Column:
    """A row's place in an epoch's random order (portable: any SQL engine has md5)."""
    return F.md5(F.concat(F.lit(f"{seed}:"), epoch.cast("string"), F.lit(":"), F.coalesce(F.col("doc_id").cast("string"), F.lit(""))).cast("binary"))


def mix(docs: DataFrame, budget_share: float = 0.5, epochs: int = 2, seed: int = 7, tokens: Column | None = None, domain: Column | None = None, domain_weights: dict | None = None, lang_weights: dict | None = None, source_weights: dict | None = None, digits: int = 2, rounds: int = 2, most_broadcast: int = 100_000, keep: list[str] | None = None) -> DataFrame:
    """Rows of ``docs`` chosen for the mixture, once for each epoch that takes them.

    To the columns ``keep`` (all) it adds the LEVELS, ``mix_tokens``, ``mix_epoch`` and ``leaf_budget``. The budget
    is ``budget_share`` of all tokens. The place where a leaf's budget ends is
    found in ``rounds`` rounds of 16^digits buckets, each inside the last. The plan
    (a row a leaf) is broadcast up to ``most_broadcast`` leaves and joined beyond.
    """
    keep = docs.columns if keep is None else keep
    level = [F.coalesce(c, F.lit("(none)")) for c in (default_domain() if domain is None else domain, F.col("lang"), F.col("source"))]
    rows = common.packed(docs, keep, doc_id=F.col("doc_id"), **dict(zip(LEVELS, level)), mix_tokens=default_tokens() if tokens is None else tokens)
    turns = F.explode(F.array(*[F.struct(F.lit(e).alias("mix_epoch"), place(seed, F.lit(e)).alias("mix_place")) for e in range(epochs)]))
    slim = rows.select(*LEVELS, "mix_tokens", turns.alias("e")).select(*LEVELS, "mix_tokens", "e.mix_epoch", "e.mix_place")
    plan = None
    for k in range(1, rounds + 1):
        inside = slim if plan is None else slim.join(_small(plan, most_broadcast), LEVELS).where((F.col("mix_epoch") == F.col("stop.mix_epoch")) & F.startswith("mix_place", F.col("stop.bucket")))
        # leaves x epochs x 16^digits rows at most, summed before the shuffle
        sums = common.cut(inside.groupBy(*LEVELS, "mix_epoch", F.substring("mix_place", 1, digits * k).alias("bucket")).agg(F.sum("mix_tokens").alias("n")))
        if plan is None:
            leaves = sums.where("mix_epoch = 0").groupBy(*LEVELS).agg(F.sum("n").alias("tokens"))
            total = leaves.agg(F.sum("tokens")).first()[0] or 0
            known = common.cut(leaf_budgets(leaves, int(total * budget_share), epochs, domain_weights, lang_weights, source_weights)).withColumn("done", F.lit(0).cast("long"))
        else:
            known = plan.withColumn("done", F.coalesce("stop.done", F.lit(0).cast("long")))
        known = known.select(*LEVELS, "leaf_budget", "done")
        steps = Window.partitionBy(*LEVELS).orderBy("mix_epoch", "bucket")
        upto = sums.join(known, LEVELS).withColumn("upto", F.sum("n").over(steps) + F.col("done"))
        last = upto.where("upto > leaf_budget").groupBy(*LEVELS).agg(F.min(F.struct("mix_epoch", "bucket", (F.col("upto") - F.col("n")).alias("done"))).alias("stop"))
        plan = common.cut(known.join(last, LEVELS, "left").select(*LEVELS, "leaf_budget", "stop"))
    chosen = rows.join(_small(plan, most_broadcast), LEVELS).select("*", turns.alias("e")).withColumn("mix_epoch", F.col("e.mix_epoch")).withColumn("mix_place", F.col("e.mix_place"))
    here = F.struct(F.col("mix_epoch"), F.substring("mix_place", 1, digits * rounds).alias("bucket"))
    stop = F.struct(F.col("stop.mix_epoch").alias("mix_epoch"), F.col("stop.bucket").alias("bucket"))
    whole = chosen.where(F.col("stop").isNull() | (here < stop))
    order = Window.partitionBy(*LEVELS).orderBy("mix_place", "mix_tokens").rowsBetween(Window.unboundedPreceding, 0)
    edge = chosen.where(F.col("stop").isNotNull() & (here == stop)).withColumn("run", F.sum("mix_tokens").over(order) + F.col("stop.done"))
    edge = edge.where("run <= leaf_budget").drop("run")
    added = {c: F.col(c) for c in [*LEVELS, "mix_tokens", "mix_epoch", "leaf_budget"]}
    return common.unpacked(whole, keep, **added).unionAll(common.unpacked(edge, keep, **added))


def _small(plan: DataFrame, most: int) -> DataFrame:
    """A hint to broadcast a plan whose counted rows are within the bound."""
    return F.broadcast(plan) if plan.count() <= most else plan


def mixed_documents(docs: DataFrame) -> DataFrame:
    """The default recipe over whole rows, without the text."""
    slim = docs.select("doc_id", "lang", "source", default_tokens().alias("tokens"))
    return mix(slim, tokens=F.col("tokens"), keep=["doc_id"]).select("doc_id", *[F.col(c) for c in LEVELS], F.col("mix_epoch").cast("int"), F.col("mix_tokens").alias("tokens"), "leaf_budget")


def mix_sql(budget_share: str = "0.5", epochs: int = 2, seed: int = 7) -> str:
    """The default recipe in DuckDB SQL, by whole-leaf running sums."""
    dw = " ".join(f"when '{k}' then {v}" for k, v in DOMAIN_WEIGHTS.items())
    lw = " ".join(f"when '{k}' then {v}" for k, v in LANG_WEIGHTS.items())

    def pour(name: str, source: str, keys: str, parent: str) -> str:
        return f"""
{name}_a as (select *, coalesce(sum(cap) over (partition by {parent} order by cap / w, {keys} rows between unbounded preceding and 1 preceding), 0)::bigint cap_before,
  sum(w) over (partition by {parent} order by cap / w, {keys} rows between current row and unbounded following)::bigint w_rest from {source}),
{name}_b as (select *, (budget - cap_before)::double / w_rest lvl, cap / w <= (budget - cap_before)::double / w_rest is_full from {name}_a),
{name}_c as (select *, min(case when not is_full then cap_before end) over (partition by {parent}) open_before from {name}_b),
{name}_d as (select *, max(case when not is_full and cap_before = open_before then lvl end) over (partition by {parent}) open_level from {name}_c),
{name} as (select *, least(cap, greatest(0, case when is_full then cap else floor(w * open_level)::bigint end))::bigint share from {name}_d)"""

    return f"""
with base as (select doc_id, coalesce(lang, '(none)') mix_lang, coalesce(source, '(none)') mix_source,
  'domain' || case when regexp_extract(coalesce(source, ''), '([0-9]+)$', 1) = '' then '0' else (regexp_extract(source, '([0-9]+)$', 1)::bigint % 4)::varchar end mix_domain,
  ((octet_length(encode(coalesce(text, ''))) + 3) // 4)::bigint mix_tokens from documents),
leaves as (select mix_domain, mix_lang, mix_source, sum(mix_tokens)::bigint cap0, (sum(mix_tokens) * {epochs})::bigint cap from base group by all),
root_budget as (select least(floor(sum(cap0) * {budget_share})::bigint, sum(cap)::bigint) budget from leaves),
t0 as (select mix_domain, 0 root, sum(cap)::bigint cap, case mix_domain {dw} else 1 end::bigint w, (select budget from root_budget) budget from leaves group by mix_domain),
{pour("t", "t0", "mix_domain", "root")},
m0 as (select l.mix_domain, l.mix_lang, sum(l.cap)::bigint cap, case l.mix_lang {lw} else 1 end::bigint w, any_value(t.share) budget from leaves l join t on l.mix_domain = t.mix_domain group by l.mix_domain, l.mix_lang),
{pour("m", "m0", "mix_domain, mix_lang", "mix_domain")},
s0 as (select l.mix_domain, l.mix_lang, l.mix_source, l.cap, 1::bigint w, m.share budget from leaves l join m on l.mix_domain = m.mix_domain and l.mix_lang = m.mix_lang),
{pour("s", "s0", "mix_domain, mix_lang, mix_source", "mix_domain, mix_lang")},
turns as (select b.*, e.mix_epoch::int mix_epoch, md5('{seed}:' || e.mix_epoch || ':' || coalesce(doc_id::varchar, '')) place from base b, (select unnest(range({epochs})) mix_epoch) e),
runs as (select u.*, s.share leaf_budget, sum(u.mix_tokens) over (partition by u.mix_domain, u.mix_lang, u.mix_source order by u.mix_epoch, u.place, u.mix_tokens rows between unbounded preceding and current row) run
  from turns u join s on u.mix_domain = s.mix_domain and u.mix_lang = s.mix_lang and u.mix_source = s.mix_source)
select doc_id, mix_domain, mix_lang, mix_source, mix_epoch, mix_tokens as tokens, leaf_budget from runs where run <= leaf_budget"""
