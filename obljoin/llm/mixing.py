"""Mixing sources to target weights by hierarchical budgeting.

The sources form a tree (by default domain, language, source). A token budget is handed down from the root by weight.
What a child cannot use, its siblings take in proportion to their weights; only what a whole family cannot use
goes back to the family's siblings. A leaf that gets more than it holds repeats whole epochs, up to a bound; the
rest of its budget is a prefix of the next epoch in a seeded order: a document is drawn if at least half of it lies within
the prefix, so a leaf misses its budget by half a document at most.

Shares are window sums over the nodes of each level, one row per node, in the order of capacity per weight. The prefix is
found without sorting a leaf: its tokens are summed by the leading bits of the order key, the sums locate
the one bucket in which the budget ends, and only that bucket is ordered.

Defined results: null names count as the empty name, null text as no words; repeated rows are drawn one
by one; ties of the order key fall to ``doc_id`` and then to the token count; rows without an id are ordered by their text; a leaf
without tokens or weight keeps nothing; an empty table gives no rows. Columns may have any names; input columns called
``n_tokens`` or ``copies`` give way to the results.
"""

from __future__ import annotations

from collections.abc import Mapping
from fractions import Fraction

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from obljoin.llm.common import attach, saved

#: Leading bits of the order key that name a bucket.
BUCKET_BITS = 12
#: A plan of so many leaves is broadcast; a larger one is joined by shuffle, heavy leaves apart.
BROADCAST_LEAVES = 1 << 16


def word_count(text: str = "text") -> Column:
    """Words are runs of anything but space and the five control blanks."""
    return F.coalesce(F.regexp_count(F.col(text).cast("string"), F.lit("[^ \\t\\n\\x0B\\f\\r]+")), F.lit(0)).cast("long")


def share_out(budget: Fraction, weights: list[Fraction], most: list[Fraction]) -> list[Fraction]:
    """Shares in proportion to the weights, none above its ``most``; surplus goes to the others again."""
    out, left = [Fraction(0)] * len(weights), budget
    open_ = [i for i, w in enumerate(weights) if w > 0]
    while open_:
        total = sum(weights[i] for i in open_)
        full = [i for i in open_ if most[i] * total <= left * weights[i]]
        if not full:
            for i in open_:
                out[i] = left * weights[i] / total
            break
        for i in full:
            out[i] = most[i]
        left -= sum(most[i] for i in full)
        open_ = [i for i in open_ if i not in full]
    return out


def budgets(supply: Mapping[tuple, int], weights: Mapping[tuple, float], budget: int, max_epochs: int) -> dict[tuple, int]:
    """The token budget of each leaf. ``weights`` are by path (a prefix of a leaf); a path that is not named weighs 1."""
    capacity: dict[tuple, Fraction] = {}
    children: dict[tuple, set] = {}
    weight_of = lambda path: Fraction(str(weights.get(path, 1)))
    for leaf, tokens in supply.items():
        if all(weight_of(leaf[:k]) > 0 for k in range(1, len(leaf) + 1)):
            for k in range(len(leaf) + 1):
                capacity[leaf[:k]] = capacity.get(leaf[:k], Fraction(0)) + tokens * max_epochs
                if k:
                    children.setdefault(leaf[: k - 1], set()).add(leaf[:k])
    given = {(): min(Fraction(budget), capacity.get((), Fraction(0)))}
    todo, out = [()], {leaf: 0 for leaf in supply}
    while todo:
        node = todo.pop()
        below = sorted(children.get(node, ()))
        if not below:
            if node in out:
                out[node] = int(given[node])
            continue
        for child, share in zip(below, share_out(given[node], [weight_of(c) for c in below], [capacity[c] for c in below]), strict=True):
            given[child] = share
        todo += below
    return out


def _weight(names: list[str], weights: Mapping[tuple, float]) -> Column:
    """The weight of the node that the names lead to, 1 if it is not given."""
    out = F.lit(1.0)
    for path, w in weights.items():
        if len(path) == len(names):
            here = F.lit(True)
            for n, x in zip(names, path, strict=True):
                here = here & (F.col(n) == F.lit(x))
            out = F.when(here, F.lit(float(w))).otherwise(out)
    return out


def leaf_budgets(leaves: DataFrame, names: list[str], weights: Mapping[tuple, float], budget: int | float, max_epochs: int) -> DataFrame:
    """``names``, ``mix_given``: the budget of every leaf that has tokens (``mix_held``) and weight, by window sums level by level.

    The same shares as ``budgets``, up to rounding of doubles.
    """
    for k in range(1, len(names) + 1):
        leaves = leaves.where(_weight(names[:k], weights) > 0)
    caps = leaves.where("mix_held > 0").select(*names, (F.col("mix_held") * F.lit(float(max_epochs))).alias("cap"))
    upper = caps.agg(F.least(F.lit(float(budget)), F.sum("cap")).alias("b"))  # one row
    for k in range(1, len(names) + 1):
        family, node = names[: k - 1], names[:k]
        below = caps.groupBy(*node).agg(F.sum("cap").alias("cap")).withColumn("w", _weight(node, weights))
        held = below.join(upper, family) if family else below.join(F.broadcast(upper))
        order = Window.partitionBy(*family).orderBy(F.col("cap") / F.col("w"), node[-1])
        before, onwards, whole = order.rowsBetween(Window.unboundedPreceding, -1), order.rowsBetween(0, Window.unboundedFollowing), Window.partitionBy(*family)
        spent, open_ = F.coalesce(F.sum("cap").over(before), F.lit(0.0)), F.sum("w").over(onwards)
        held = held.withColumns({"spent": spent, "open": open_}).withColumn("full", F.col("cap") * F.col("open") <= (F.col("b") - F.col("spent")) * F.col("w"))
        used, rest = F.sum(F.when(F.col("full"), F.col("cap")).otherwise(0.0)).over(whole), F.sum(F.when(F.col("full"), 0.0).otherwise(F.col("w"))).over(whole)
        held = held.withColumns({"used": used, "rest": rest})
        upper = held.select(*node, F.when(F.col("full"), F.col("cap")).otherwise((F.col("b") - F.col("used")) * F.col("w") / F.col("rest")).alias("b"))
    return upper.select(*names, F.floor(F.col("b") + 1e-6).cast("long").alias("mix_given"))


def mix(
    docs: DataFrame,
    levels: Mapping[str, Column],
    weights: Mapping[tuple, float],
    budget: int | float,
    max_epochs: int = 1,
    seed: int = 1,
    tokens: Column | None = None,
    doc_id: str = "doc_id",
    text: str = "text",
    counts: bool = True,
) -> DataFrame:
    """The drawn rows with all their columns, ``n_tokens`` and ``copies`` (how many epochs have the row), or without these two if not ``counts``.

    ``levels`` name the tree from the top. ``budget`` is a number of tokens, or a share of all tokens if it is a float.
    """
    names = [f"mix_{k}" for k in range(len(levels))]
    path = [F.coalesce(c.cast("string"), F.lit("")).alias(n) for n, c in zip(names, levels.values(), strict=True)]
    told = F.coalesce(F.col(doc_id).cast("string"), F.concat(F.lit("-"), F.md5(F.coalesce(F.col(text).cast("string"), F.lit("")))))
    row = F.struct(*(F.col(f"`{c}`") for c in docs.columns))
    marked = docs.select(row.alias("mix_row"), *path, (tokens if tokens is not None else word_count(text)).alias("n_tokens"), told.alias("mix_id"), F.col(doc_id).alias("mix_doc"))
    leaves = saved(marked.groupBy(*names).agg(F.sum("n_tokens").alias("mix_held"), F.count("*").alias("mix_rows")))
    n_leaves, total = leaves.agg(F.count("*"), F.sum("mix_held")).first()
    most = int((total or 0) * Fraction(str(budget))) if isinstance(budget, float) else budget
    plan = leaf_budgets(leaves, names, weights, most, max_epochs).join(leaves, names).where("mix_given > 0")
    plan = saved(plan.select(*names, "mix_rows", F.expr("mix_given div mix_held").alias("mix_whole"), (F.col("mix_given") % F.col("mix_held")).alias("mix_rest")))

    def drawn(rows: DataFrame, leaf: DataFrame) -> DataFrame:
        joined = rows.join(F.broadcast(leaf), names) if n_leaves <= BROADCAST_LEAVES else attach(rows, saved(leaf), names, "mix_rows")
        key = F.conv(F.substring(F.md5(F.concat_ws(":", F.lit(str(seed)), F.col("mix_whole").cast("string"), F.col("mix_id"))), 1, 15), 16, 10).cast("long")
        return joined.withColumn("mix_key", key).withColumn("mix_bucket", F.shiftright(F.col("mix_key"), 60 - BUCKET_BITS))

    sums = drawn(marked.drop("mix_row"), plan).where("mix_rest > 0").groupBy(*names, "mix_bucket", "mix_rest").agg(F.sum("n_tokens").alias("n"))
    upto = F.sum("n").over(Window.partitionBy(*names).orderBy("mix_bucket"))  # at most 2**BUCKET_BITS rows a leaf
    ends = sums.withColumn("upto", upto).where("upto > mix_rest").groupBy(*names).agg(F.min(F.struct(F.col("mix_bucket").alias("end"), (F.col("upto") - F.col("n")).alias("before"))).alias("cut"))
    cuts = saved(ends.select(*names, F.col("cut.end").alias("mix_end"), F.col("cut.before").alias("mix_before")))
    placed = drawn(marked, plan.join(cuts, names, "left"))
    at_end = F.coalesce((F.col("mix_rest") > 0) & (F.col("mix_bucket") == F.col("mix_end")), F.lit(False))
    running = F.sum("n_tokens").over(Window.partitionBy(*names).orderBy("mix_key", "mix_doc", "n_tokens").rowsBetween(Window.unboundedPreceding, 0))
    inside = placed.where(at_end).withColumn("mix_extra", (2 * (running + F.col("mix_before")) - F.col("n_tokens") <= 2 * F.col("mix_rest")).cast("long"))
    extra = (F.col("mix_rest") > 0) & (F.col("mix_end").isNull() | (F.col("mix_bucket") < F.col("mix_end")))
    outside = placed.where(~at_end).withColumn("mix_extra", extra.cast("long"))
    both = outside.unionByName(inside).withColumn("copies", F.col("mix_whole") + F.col("mix_extra")).where("copies > 0")
    if not counts:
        return both.select("mix_row.*")
    return both.select(*(F.col(f"mix_row.`{c}`") for c in docs.columns if c.lower() not in ("n_tokens", "copies")), "n_tokens", "copies")


def repeat_copies(mixed: DataFrame) -> DataFrame:
    """One row per copy, numbered by ``epoch`` from 0."""
    return mixed.withColumn("epoch", F.explode(F.sequence(F.lit(0).cast("long"), F.col("copies") - 1)))


#: Domains of the synthetic sources, by the last digits of the source's name.
def source_domain(source: str = "source") -> Column:
    return F.concat(F.lit("domain"), F.coalesce(F.regexp_extract(F.col(source), "([0-9]+)$", 1).try_cast("int") % 4, F.lit(0)).cast("string"))


DOMAIN_WEIGHTS = {("domain0",): 0.4, ("domain1",): 0.3, ("domain2",): 0.2, ("domain3",): 0.1}
LANGUAGE_WEIGHTS = {"en": 0.4, "de": 0.2, "fr": 0.2, "es": 0.2}


def document_tree() -> tuple[dict[str, Column], dict[tuple, float]]:
    levels = {"domain": source_domain(), "lang": F.col("lang"), "source": F.col("source")}
    return levels, DOMAIN_WEIGHTS | {(*d, lang): w for d in DOMAIN_WEIGHTS for lang, w in LANGUAGE_WEIGHTS.items()}
