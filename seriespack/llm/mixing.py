"""Mixing sources to target weights by hierarchical budgeting; DataFrame functions only.

Weights are given for the nodes of a tree (domain, language, source); a node's share among its siblings
is its weight over theirs.  A token budget flows down from the root.  At each node the children get their
shares, but none more than its leaves hold in ``max_epochs`` epochs; what a child can't take is spread
over its siblings by their weights (found in one pass over the siblings in the order of capacity over
weight), and only what a whole subtree can't take was already spread one level up.  All arithmetic is in
whole tokens.

A leaf's budget is a prefix of its token stream: epoch after epoch, each in an order seeded by an MD5 of
seed, epoch and id.  Whole epochs need no order.  Of the last one, tokens are summed by ranges of the MD5
and then within the one range where the budget ends, so no task ever sorts a leaf.  The range count grows
with the table and does not change the result.  Each leaf ends in one cut (MD5, id); documents compare
themselves with it where they lie, so texts are not moved.

Defined cases: null texts and texts without words hold no tokens and are not taken by a budget that ends;
null languages and sources are nodes named ``?``; null ids take the name ``?``; documents with equal ids
share a place in the order; leaves below a node of weight 0 get nothing and hold no capacity; an empty table
gives an empty result; where a column of ``docs`` has the name of one made here, that gets underscores until it
has a name of its own.
"""

from __future__ import annotations

from functools import reduce
from operator import or_

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .store import written
from .text import unused

LEVELS = ("_domain", "_lang", "_source")
SEED = 17
DOMAINS = 4
#: Target weights of the queries: languages as listed, others 1; domains and sources count alike unless weights are given.
LANG_WEIGHTS = {"en": 4, "fr": 2, "de": 2, "es": 2}
MAX_EPOCHS = 2
SHARE = (6, 10)
RANGE_ROWS = 20_000


def tokens(text: str = "text") -> Column:
    """Words parted by ASCII white space."""
    return F.coalesce(F.regexp_count(F.col(text), F.lit(r"[^\x20\x09-\x0D]+")), F.lit(0)).cast("bigint")


def listed(values: dict, key: Column) -> Column:
    """What ``values`` lists for a key; null for others."""
    return F.create_map(*[F.lit(x) for kv in values.items() for x in kv])[key] if values else F.lit(None)


def domain(source: Column, domains: int = DOMAINS, given: dict[str, str] | None = None) -> Column:
    """The domain ``given`` for a source; where none is, one of at most 16 by the first digit of the source's MD5."""
    made = F.concat(F.lit("domain"), (F.conv(F.substring(F.md5(source.cast("binary")), 1, 1), 16, 10).cast("int") % domains).cast("string"))
    return F.coalesce(listed(given, source), made) if given else made


def place(seed: int, epoch: Column, doc_id: Column) -> Column:
    """The seeded order of a document in an epoch."""
    return F.md5(F.concat_ws(":", F.lit(str(seed)), epoch.cast("string"), F.coalesce(doc_id.cast("string"), F.lit("?"))).cast("binary"))


def _share(children: DataFrame, parent: list[str], node: str) -> DataFrame:
    """``_budget`` of each child out of ``_parent_budget``: proportional to ``_weight``, at most ``_capacity``.

    In the order of capacity over weight a child is full if its fair part of what the children before it
    left reaches its capacity; the first that is not full sets the rate for all after it.
    """
    order = Window.partitionBy(*parent).orderBy("_ratio", node)
    before, after = order.rowsBetween(Window.unboundedPreceding, -1), order.rowsBetween(0, Window.unboundedFollowing)
    wide = lambda c: F.col(c).cast("decimal(38,0)")
    out = children.withColumn("_capacity", F.when(F.col("_weight") > 0, F.col("_capacity")).otherwise(F.lit(0)))
    out = out.withColumn("_ratio", F.expr("_capacity * 1000 div greatest(_weight, 1)"))
    out = out.withColumn("_left", F.col("_parent_budget") - F.coalesce(F.sum("_capacity").over(before), F.lit(0))).withColumn("_rest", F.sum("_weight").over(after))
    out = out.withColumn("_full", wide("_capacity") * wide("_rest") <= wide("_left") * wide("_weight"))
    first = F.min(F.when(~F.col("_full"), F.struct(F.col("_ratio"), F.col(node), F.col("_left"), F.col("_rest")))).over(Window.partitionBy(*parent))
    out = out.withColumn("_rate", first)
    part = F.expr("cast(cast(_rate._left as decimal(38,0)) * cast(_weight as decimal(38,0)) div greatest(_rate._rest, 1) as bigint)")
    early = F.col("_rate").isNull() | (F.struct("_ratio", node) < F.struct(F.col("_rate._ratio"), F.col(f"_rate.{node}")))
    budget = F.when(early, F.col("_capacity")).otherwise(F.least(F.col("_capacity"), F.greatest(F.lit(0), part)))
    out = out.withColumn("_floor", budget.cast("bigint")).withColumn("_open", (F.col("_weight") > 0) & (F.col("_floor") < F.col("_capacity")))
    spare = F.col("_parent_budget") - F.sum("_floor").over(Window.partitionBy(*parent))
    turn = F.row_number().over(Window.partitionBy(*parent).orderBy(F.desc("_open"), "_ratio", node))
    out = out.withColumn("_budget", F.col("_floor") + F.when(F.col("_open") & (turn <= spare), 1).otherwise(0))
    return out.drop("_left", "_rest", "_full", "_rate", "_ratio", "_floor", "_open")


def budgets(leaves: DataFrame, total: Column, lang_weights: dict[str, int], max_epochs: int, domain_weights: dict[str, int] | None = None, source_weights: dict[str, int] | None = None) -> DataFrame:
    """``leaves`` (levels, ``_tokens``) with ``_budget``, of a total that is an aggregate of ``_tokens``.

    Weights are by the node's name, 1 for names not listed.  A leaf below any node of weight 0 holds no capacity.
    """
    given = dict(zip(LEVELS, (domain_weights, lang_weights, source_weights), strict=True))
    weights = {level: F.coalesce(listed(given[level], F.col(level)), F.lit(1)).cast("bigint") if given[level] else F.lit(1).cast("bigint") for level in LEVELS}
    barred = reduce(or_, (weights[level] <= 0 for level in LEVELS))
    leaves = leaves.withColumn("_capacity", F.when(barred, F.lit(0)).otherwise(F.col("_tokens") * max_epochs).cast("bigint"))
    nodes = [leaves]
    for depth in (2, 1):
        nodes.insert(0, leaves.groupBy(*LEVELS[:depth]).agg(F.sum("_capacity").alias("_capacity")))
    passed = leaves.agg(total.cast("bigint").alias("_parent_budget"))
    for depth, level in enumerate(nodes):
        keys = list(LEVELS[:depth])
        children = level.withColumn("_weight", weights[LEVELS[depth]])
        children = children.crossJoin(passed) if not keys else children.join(passed, keys)
        shared = _share(children, keys or [F.lit(0)], LEVELS[depth])
        passed = shared.select(*LEVELS[: depth + 1], F.col("_budget").alias("_parent_budget"))
    return shared.select(*LEVELS, "_tokens", "_capacity", "_budget")


def _measured(docs: DataFrame, text: str, domains: dict[str, str] | None) -> DataFrame:
    source = F.coalesce(F.col("source").cast("string"), F.lit("?"))
    return docs.select(F.col("doc_id").alias("_id"), domain(source, given=domains).alias("_domain"), F.coalesce(F.col("lang").cast("string"), F.lit("?")).alias("_lang"), source.alias("_source"), tokens(text).alias("_n"))


def cuts(measured: DataFrame, total: Column, seed: int = SEED, lang_weights: dict[str, int] | None = None, max_epochs: int = MAX_EPOCHS, range_rows: int = RANGE_ROWS, domain_weights: dict[str, int] | None = None, source_weights: dict[str, int] | None = None) -> DataFrame:
    """A row for each leaf: its budget, whole epochs, and where the last epoch's prefix ends.

    ``_epochs`` whole epochs are taken; of the next, documents before (``_cut``, ``_cut_id``), and ``_cut_tokens`` of those there.
    """
    levels = list(LEVELS)
    leaves = measured.groupBy(*levels).agg(F.sum("_n").alias("_tokens"), F.count("*").alias("_rows"))
    planned = budgets(leaves.drop("_rows"), total, LANG_WEIGHTS if lang_weights is None else lang_weights, max_epochs, domain_weights, source_weights)
    planned = planned.withColumn("_epochs", F.expr("coalesce(_budget div nullif(_tokens, 0), 0)")).withColumn("_remainder", F.col("_budget") - F.col("_epochs") * F.col("_tokens"))
    planned = written(planned, "mixing-leaves")
    ranges = measured.agg(F.ceil(F.count("*") / F.lit(range_rows)).alias("_ranges"))
    keyed = measured.where("_n > 0").join(planned.where("_remainder > 0").select(*levels, "_epochs", "_remainder"), levels).withColumn("_place", place(seed, F.col("_epochs"), F.col("_id")))
    keyed = keyed.crossJoin(F.broadcast(ranges)).withColumn("_range", F.expr("cast(conv(substr(_place, 1, 7), 16, 10) as bigint) * _ranges div 268435456"))
    sums = keyed.groupBy(*levels, "_range", "_remainder").agg(F.sum("_n").alias("_sum"))
    so_far = Window.partitionBy(*levels).orderBy("_range").rowsBetween(Window.unboundedPreceding, -1)
    sums = sums.withColumn("_before", F.coalesce(F.sum("_sum").over(so_far), F.lit(0))).where("_before < _remainder and _before + _sum >= _remainder")
    within = keyed.drop("_remainder").join(sums.select(*levels, "_range", "_before", "_remainder"), [*levels, "_range"])
    order = Window.partitionBy(*levels, "_range").orderBy("_place", "_id")
    within = within.groupBy(*levels, "_range", "_place", "_id").agg(F.sum("_n").alias("_n"), F.first("_before").alias("_before"), F.first("_remainder").alias("_remainder"))
    within = within.withColumn("_start", F.col("_before") + F.sum("_n").over(order) - F.col("_n")).where("_start < _remainder and _start + _n >= _remainder")
    ends = within.select(*levels, F.col("_place").alias("_cut"), F.expr("_remainder - _start").alias("_cut_tokens"))
    return written(planned.join(ends, levels, "left"), "mixing-cuts")


def made_names(columns: list[str]) -> dict[str, str]:
    """Names of the columns that are made beside these."""
    return {k: unused(columns, k) for k in (*LEVELS, "_n", "_epochs", "_cut", "_cut_tokens", "_place", "_tokens_more", "_times", "_epoch")}


def taken(docs: DataFrame, share: tuple[int, int] = SHARE, seed: int = SEED, lang_weights: dict[str, int] | None = None, max_epochs: int = MAX_EPOCHS, text: str = "text", domain_weights: dict[str, int] | None = None, source_weights: dict[str, int] | None = None, domains: dict[str, str] | None = None) -> DataFrame:
    """``docs`` with ``_n`` (tokens), ``_epochs`` (whole times taken) and ``_tokens_more`` (of the last, partial epoch).

    ``domains`` maps sources to domains; the weights of each level are by name.
    """
    measured = written(_measured(docs, text, domains), "mixing-tokens")
    total = F.expr(f"coalesce(sum(_tokens), 0) * {share[0]} div {share[1]}")
    leaves = cuts(measured, total, seed, lang_weights, max_epochs, domain_weights=domain_weights, source_weights=source_weights)
    name = made_names(docs.columns)
    c = {k: F.col(v) for k, v in name.items()}
    source = F.coalesce(F.col("source").cast("string"), F.lit("?"))
    placed = docs.withColumns({name["_domain"]: domain(source, given=domains), name["_lang"]: F.coalesce(F.col("lang").cast("string"), F.lit("?")), name["_source"]: source, name["_n"]: tokens(text)})
    leaves = leaves.select(*[F.col(k).alias(name[k]) for k in (*LEVELS, "_epochs", "_cut", "_cut_tokens")])
    known = placed.join(leaves, [name[k] for k in LEVELS], "left").withColumn(name["_place"], place(seed, c["_epochs"], F.col("doc_id")))
    more = F.when(c["_place"] < c["_cut"], c["_n"]).when(c["_place"] == c["_cut"], F.least(c["_n"], c["_cut_tokens"])).otherwise(F.lit(0))
    known = known.withColumn(name["_tokens_more"], F.when(c["_cut"].isNull(), F.lit(0)).otherwise(more).cast("bigint"))
    return known.select(*docs.columns, *[name[k] for k in ("_domain", "_n", "_epochs", "_tokens_more")])


def report(docs: DataFrame, **options) -> DataFrame:
    """Per document: doc_id, its leaf's domain, n_tokens, epochs (whole), tokens_taken (in all)."""
    out = taken(docs.select("doc_id", "text", "lang", "source"), **options)
    return out.select("doc_id", F.col("_domain").alias("domain"), F.col("_n").alias("n_tokens"), F.col("_epochs").alias("epochs"), (F.col("_epochs") * F.col("_n") + F.col("_tokens_more")).alias("tokens_taken"))


def mix(docs: DataFrame, **options) -> DataFrame:
    """Documents of the mixture, with the columns of ``docs``: a row for each epoch that takes any of it, texts whole."""
    out, name = taken(docs, **options), made_names(docs.columns)
    times = F.col(name["_epochs"]) + (F.col(name["_tokens_more"]) > 0).cast("bigint")
    out = out.withColumn(name["_times"], times).where(F.col(name["_times"]) > 0)
    return out.select(*docs.columns, F.explode(F.sequence(F.lit(1).cast("bigint"), F.col(name["_times"]))).alias(name["_epoch"])).select(*docs.columns)
