"""Operator 6: mixing sources to target weights by hierarchical budgets. DataFrame functions only.

The tree is domain, language, source. A token budget is dealt from the root: at each node it is shared among the
children by weight, and what a child cannot take (``max_epochs`` times its tokens) goes to its siblings with room; only
what a whole subtree cannot take reaches the siblings of its parent. Every leaf then takes whole epochs, and of the last
one the prefix, in a seeded order, whose tokens fit the rest.

The prefix is found without moving texts or sorting a leaf: tokens are summed by the first bits of the order keys, which
tells the bits at which the budget ends; the few rows that begin with these are written and summed by the next bits, until
what is left of every leaf is short. The first key that does not fit makes the leaf's cut key, and documents are chosen by
comparing their own key with it. Every step is one aggregation, so a leaf with a third of all rows is no heavier to a task
than another.

Edge cases: a null text has no tokens, null domain, language and source count as ``''``; rows alike in id and text share
a key and are taken or left together; leaves without tokens take nothing; a weight of 0 takes nothing; an empty table
gives an empty result.
"""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import ASCII_SPACE, cut, fresh

LEVELS = ("domain", "lang", "source")


@dataclass(frozen=True)
class MixTargets:
    """Targets of a mix.

    ``weights`` maps a path (``"domain"``, ``"domain/lang"`` or ``"domain/lang/source"``) to its weight among its
    siblings; others weigh ``default_weight``. ``budget`` is in tokens; by default ``budget_share`` of those there are.
    """

    weights: dict[str, float] = field(default_factory=dict)
    default_weight: float = 1.0
    budget: int | None = None
    budget_share: float = 1.0
    max_epochs: int = 4
    seed: int = 20
    step_bits: int = 6
    bucket_rows: int = 512  # rows of a leaf that are ordered at once
    domains: int = 3


TARGETS = MixTargets()


def default_domain(targets: MixTargets = TARGETS) -> Column:
    """The given tables have no domain: sources are dealt into ``domains`` groups by their digest."""
    digest = F.conv(F.substring(F.md5(F.coalesce(F.col("source").cast("string"), F.lit("")).cast("binary")), 1, 6), 16, 10).cast("long")
    return F.concat(F.lit("d"), (digest % targets.domains).cast("string"))


def count_tokens(text: Column) -> Column:
    """Tokens here are the words between ASCII white space."""
    return F.regexp_count(F.coalesce(text, F.lit("")), F.lit(f"[^{ASCII_SPACE}]+")).cast("long")


def order_key(seed: int, epoch: Column, doc_id: Column, text_digest: Column) -> Column:
    """60 bits that order a leaf's documents in an epoch."""
    made = F.md5(F.concat_ws("|", F.lit(str(seed)), epoch.cast("string"), F.coalesce(doc_id.cast("string"), F.lit("")), text_digest).cast("binary"))
    return F.conv(F.substring(made, 1, 15), 16, 10).cast("long")


def _share(nodes: DataFrame, parent: list[str]) -> DataFrame:
    """Adds ``budget``: ``given``, the parent's budget, dealt among the rows with the same ``parent`` by ``weight``.

    Children are filled in the order of capacity per weight. The level at which the rest is shared is known once the
    children that are filled are; a child is filled when its own ratio is below the level that would hold without it.
    """
    order = Window.partitionBy(*parent).orderBy("ratio", *LEVELS[len(parent) : len(parent) + 1])
    before = order.rowsBetween(Window.unboundedPreceding, -1)
    onward = order.rowsBetween(Window.currentRow, Window.unboundedFollowing)
    whole = Window.partitionBy(*parent)
    live = nodes.withColumn("ratio", F.when(F.col("weight") > 0, F.col("capacity") / F.col("weight")).otherwise(F.lit(float("inf"))))
    live = live.withColumn("level", F.when(F.sum("weight").over(onward) > 0, (F.col("given") - F.coalesce(F.sum("capacity").over(before), F.lit(0.0))) / F.sum("weight").over(onward)).otherwise(F.lit(0.0)))
    live = live.withColumn("full", (F.col("weight") > 0) & (F.col("ratio") <= F.col("level")))
    rest = F.col("given") - F.coalesce(F.sum(F.when(F.col("full"), F.col("capacity"))).over(whole), F.lit(0.0))
    open_weight = F.coalesce(F.sum(F.when(~F.col("full"), F.col("weight"))).over(whole), F.lit(0.0))
    live = live.withColumns({"rest": rest, "open_weight": open_weight})
    return live.withColumn("budget", F.when(F.col("full"), F.col("capacity")).when(F.col("open_weight") > 0, F.col("rest") * F.col("weight") / F.col("open_weight")).otherwise(F.lit(0.0))).drop("ratio", "level", "full", "rest", "open_weight")


def allot(leaves: DataFrame, targets: MixTargets = TARGETS) -> DataFrame:
    """``domain, lang, source, tokens, budget, epochs, rest`` from ``domain, lang, source, tokens`` of the leaves.

    The windows see the children of one node; the tables have a row per node.
    """
    weight = lambda path: F.lit(float(targets.default_weight)) if not targets.weights else F.coalesce(F.create_map(*[F.lit(x) for k, v in sorted(targets.weights.items()) for x in (k, float(v))])[path], F.lit(float(targets.default_weight)))
    path = lambda n: F.concat_ws("/", *LEVELS[:n])
    at = [leaves.withColumn("w", weight(path(3)))]
    # what a subtree can take counts only children that weigh something
    at.append(at[0].groupBy("domain", "lang").agg(F.sum(F.when(F.col("w") > 0, F.col("tokens"))).alias("tokens")).withColumn("w", weight(path(2))))
    at.append(at[1].groupBy("domain").agg(F.sum(F.when(F.col("w") > 0, F.col("tokens"))).alias("tokens")).withColumn("w", weight(path(1))))
    capacity = (F.coalesce(F.col("tokens"), F.lit(0)) * targets.max_epochs).cast("double")
    root = at[2].agg(F.sum(F.when(F.col("w") > 0, F.col("tokens"))).alias("can"))
    total = leaves.agg(F.sum("tokens").alias("all"))
    given = root.crossJoin(total).select(F.least((F.lit(float(targets.budget)) if targets.budget is not None else F.col("all") * float(targets.budget_share)), (F.col("can") * targets.max_epochs).cast("double")).alias("given"))
    nodes = at[2].withColumnRenamed("w", "weight").withColumn("capacity", capacity).crossJoin(F.broadcast(given))
    up = _share(nodes, []).select("domain", F.col("budget").alias("given"))
    nodes = at[1].withColumnRenamed("w", "weight").withColumn("capacity", capacity).join(up, "domain")
    up = _share(nodes, ["domain"]).select("domain", "lang", F.col("budget").alias("given"))
    nodes = at[0].withColumnRenamed("w", "weight").withColumn("capacity", capacity).join(up, ["domain", "lang"])
    out = _share(nodes, ["domain", "lang"]).select(*LEVELS, "tokens", F.floor(F.round(F.col("budget"), 3)).cast("long").alias("budget"))
    epochs = F.when(F.col("tokens") > 0, F.floor(F.col("budget") / F.col("tokens"))).otherwise(F.lit(0)).cast("long")
    return out.withColumn("epochs", epochs).withColumn("rest", F.col("budget") - F.col("epochs") * F.col("tokens"))


KEY_BITS = 60


def cut_keys(rows: DataFrame, budgets: DataFrame, targets: MixTargets = TARGETS) -> DataFrame:
    """``domain, lang, source, cut_key``: every key of a leaf up to this one fits its rest, and the next does not.

    ``rows`` has ``domain, lang, source, doc_id, digest, n_tokens``. Leaves without a rest have no row.
    """
    leaf = list(LEVELS)
    # tables of one row a leaf, written so that their size is known before the rows are joined to them
    state = cut(budgets.filter("rest > 0").select(*leaf, "epochs", "rest", F.lit(0).cast("long").alias("before"), F.lit(0).cast("long").alias("prefix")), "mix-partial")
    key = order_key(targets.seed, F.col("epochs"), F.col("doc_id"), F.col("digest"))
    inside = rows.filter("n_tokens > 0").join(state, leaf).select(*leaf, key.alias("key"), "n_tokens")
    left = KEY_BITS
    while True:
        step = min(targets.step_bits, left)
        left -= step
        state = cut(_crossing(inside, state, F.shiftright("key", left)), "mix-partial")
        if left:
            at = state.select(*leaf, "prefix")
            inside = cut(inside.join(at, leaf).filter(F.shiftright("key", left) == F.col("prefix")).drop("prefix"), "mix-inside")
            most = inside.groupBy(*leaf).agg(F.count("*").alias("n")).agg(F.max("n")).first()[0]
            if (most or 0) > targets.bucket_rows:
                continue
            state = _crossing(inside, state, F.col("key"))
        return state.select(*leaf, (F.col("prefix") - 1).alias("cut_key"))


def _crossing(inside: DataFrame, state: DataFrame, part: Column) -> DataFrame:
    """``state`` one step on: the first ``part`` of each leaf at whose end the tokens exceed ``rest``, and those before.

    The window sees one row for each part of a leaf.
    """
    leaf = list(LEVELS)
    sums = inside.groupBy(*leaf, part.alias("part")).agg(F.sum("n_tokens").alias("n")).join(state.drop("prefix"), leaf)
    upto = Window.partitionBy(*leaf).orderBy("part").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    ended = sums.withColumn("through", F.col("before") + F.sum("n").over(upto)).filter("through > rest")
    first = ended.groupBy(*leaf, "epochs", "rest").agg(F.min(F.struct("part", (F.col("through") - F.col("n")).alias("before"))).alias("first"))
    return first.select(*leaf, "epochs", "rest", "first.before", F.col("first.part").alias("prefix"))


def mix(docs: DataFrame, targets: MixTargets = TARGETS, domain: Column | None = None, keep: list[str] | None = None) -> tuple[DataFrame, list[str]]:
    """The chosen rows of ``docs`` (columns ``keep``), each once, with domain, tokens and how many epochs take it.

    The names of these columns are returned. Texts are read once for their counts, and once for the output.
    """
    keep = docs.columns if keep is None else keep
    names = fresh(docs, "domain", "n_tokens", "copies")
    text = lambda c: F.coalesce(c.cast("string"), F.lit(""))
    domain = default_domain(targets) if domain is None else domain
    digest = F.md5(F.coalesce(F.col("text"), F.lit("")).cast("binary"))
    rows = cut(docs.select(text(domain).alias("domain"), text(F.col("lang")).alias("lang"), text(F.col("source")).alias("source"), "doc_id", digest.alias("digest"), count_tokens(F.col("text")).alias("n_tokens")), "mix-rows")
    budgets = cut(allot(rows.groupBy(*LEVELS).agg(F.sum("n_tokens").alias("tokens")), targets), "mix-budgets")
    cuts = cut(budgets.join(cut_keys(rows, budgets, targets), list(LEVELS), "left").select(*LEVELS, "epochs", "cut_key"), "mix-cuts")
    own = [f"{n}_" for n in fresh(docs, *LEVELS)]
    x_epochs, x_cut, x_doc, x_digest = fresh(docs, "epochs", "cut_key", "own_id", "own_digest")
    cuts = cuts.toDF(*own, x_epochs, x_cut)
    left = docs.select(*[F.col(f"`{c}`") for c in keep], *[text(c).alias(f"{o}l") for c, o in zip((domain, F.col("lang"), F.col("source")), own, strict=True)], F.col("doc_id").alias(x_doc), digest.alias(x_digest), count_tokens(F.col("text")).alias(names[1]))
    met = left.join(cuts, [F.col(f"{o}l") == F.col(o) for o in own])
    key = order_key(targets.seed, F.col(x_epochs), F.col(x_doc), F.col(x_digest))
    copies = F.col(x_epochs) + F.coalesce((key <= F.col(x_cut)).cast("long"), F.lit(0))
    out = met.filter(F.col(names[1]) > 0).withColumn(names[2], copies).filter(F.col(names[2]) > 0)
    return out.select(*[F.col(f"`{c}`") for c in keep], F.col(f"{own[0]}l").alias(names[0]), names[1], names[2]), names
