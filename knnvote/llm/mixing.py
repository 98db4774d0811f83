"""Mixing sources to target weights by hierarchical budgets, with DataFrame operations only.

A tree domain > language > source holds the documents. A token budget is dealt from the root down:
the children of a node share what it got in proportion to their weights, none beyond what its subtree
can give (its tokens times the epochs allowed), and what one can't take goes to its siblings before
anything returns to the ancestor. Each leaf then takes whole epochs of its documents and a prefix of
one more, in that epoch's seeded order.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from .common import seeded_hash, settle

LEVELS = ("domain", "lang", "source")
NONE = "(none)"  # how a null stands in the tree
LEAVES = 200_000  # above that many leaves their table is joined, not broadcast
CELL_ROWS = 2_000  # documents that a cell of a leaf's order should hold
_BIG = "decimal(38,0)"


def words(text: str = "text") -> Column:
    """Words between ASCII white space, as the measure of a document's tokens; null texts have none."""
    return F.coalesce(F.regexp_count(F.col(text), F.lit(r"[^\x20\x09-\x0D]+")), F.lit(0)).cast("long")


def _shared_out(nodes: DataFrame, parent: list[str], name: str) -> DataFrame:
    """Adds `got` to nodes (parent..., name, weight, cap, budget): each parent's budget over its children.

    Children fill up in the order of capacity over weight; those whose capacity lies below their share
    at that point are full, the rest share what is left by weight, rounded down. Exact integers throughout.
    """
    by = W.partitionBy(*parent)
    order = by.orderBy(F.try_divide(F.col("cap").cast("decimal(38,6)"), F.col("weight")).asc_nulls_last(), name)
    before = order.rowsBetween(W.unboundedPreceding, -1)
    n = nodes.withColumn("w0", F.coalesce(F.sum("weight").over(before), F.lit(0))).withColumn("c0", F.coalesce(F.sum("cap").over(before), F.lit(0)))
    n = n.withColumn("w_all", F.sum("weight").over(by))
    big = lambda c: F.col(c).cast(_BIG)
    full = (F.col("weight") > 0) & (big("c0") * big("weight") + big("cap") * (big("w_all") - big("w0")) <= big("budget") * big("weight"))
    n = n.withColumn("full", full)
    n = n.withColumn("w_open", F.sum(F.when(F.col("full"), 0).otherwise(F.col("weight"))).over(by)).withColumn("c_full", F.sum(F.when(F.col("full"), F.col("cap")).otherwise(0)).over(by))
    part = F.expr("cast(weight as decimal(38,0)) * (cast(budget as decimal(38,0)) - c_full) div nullif(w_open, 0)")
    got = F.when(F.col("full"), F.col("cap")).when(F.col("weight") <= 0, F.lit(0)).otherwise(F.least("cap", F.coalesce(part, F.lit(0)))).cast("long")
    return n.withColumn("got", got).drop("w0", "c0", "w_all", "full", "w_open", "c_full")


def leaf_budgets(leaves: DataFrame, budget: int, epochs: int, weights: DataFrame | None = None) -> DataFrame:
    """(domain, lang, source, tokens, got, open) from (domain, lang, source, tokens).

    weights: (level int, name string, weight long): the weight of nodes of that name on that level
    (0 domain, 1 language, 2 source), whole numbers; others weigh 1, and nodes of weight 0 get nothing.
    open: no node from the root to the leaf has weight 0.
    """
    for k, level in enumerate(LEVELS):
        if weights is None:
            leaves = leaves.withColumn(f"w_{level}", F.lit(1).cast("long"))
        else:
            mine = weights.where(F.col("level") == k).groupBy(F.col("name").alias(level)).agg(F.max("weight").cast("long").alias(f"w_{level}"))
            leaves = leaves.join(mine, level, "left").withColumn(f"w_{level}", F.coalesce(f"w_{level}", F.lit(1)))
    leaves = leaves.withColumn("cap", F.col("tokens") * epochs).withColumn("open", F.least(*[F.col(f"w_{x}") for x in LEVELS]) > 0)
    top, middle, leaf = LEVELS
    # a node gives what those below it can give: nothing flows into weights of 0
    leaves = leaves.withColumn("cap", F.when(F.col(f"w_{leaf}") > 0, F.col("cap")).otherwise(0))
    mids = leaves.groupBy(top, middle, f"w_{top}", f"w_{middle}").agg(F.sum("cap").alias("cap")).withColumn("cap", F.when(F.col(f"w_{middle}") > 0, F.col("cap")).otherwise(0))
    tops = mids.groupBy(top, f"w_{top}").agg(F.sum("cap").alias("cap"))
    tops = _shared_out(tops.withColumn("weight", F.col(f"w_{top}")).withColumn("budget", F.lit(budget).cast("long")).withColumn("root", F.lit(0)), ["root"], top).select(top, F.col("got").alias("budget"))
    mids = _shared_out(mids.withColumn("weight", F.col(f"w_{middle}")).join(tops, top), [top], middle).select(top, middle, F.col("got").alias("budget"))
    return _shared_out(leaves.withColumn("weight", F.col(f"w_{leaf}")).join(mids, [top, middle]), [top, middle], leaf).select(*LEVELS, "tokens", "got", "open")


def with_leaf(docs: DataFrame, domain: Column, lang: str = "lang", source: str = "source", doc_id: str = "doc_id", text: str = "text") -> DataFrame:
    """(_domain, _lang, _source, _tokens, _id, _row): the place of each row of docs in the tree, its tokens, its id, and the row itself."""
    named = lambda c: F.coalesce(c.cast("string"), F.lit(NONE))
    whole = F.struct(*[F.col(f"`{c}`") for c in docs.columns]).alias("_row")
    return docs.select(named(domain).alias("_domain"), named(F.col(lang)).alias("_lang"), named(F.col(source)).alias("_source"), words(text).alias("_tokens"), F.col(doc_id).cast("long").alias("_id"), whole)


def _order_key(epoch: Column, seed: int, doc: str) -> Column:
    """Where a document stands in an epoch's order: 60 bits."""
    return seeded_hash(seed, epoch, F.col(doc))


def plan_mix(placed: DataFrame, share: float, epochs: int, weights: DataFrame | None = None, seed: int = 42) -> DataFrame:
    """One row a leaf: its tokens, budget, whole epochs, and where the prefix of the next epoch ends.

    placed: (_domain, _lang, _source, _tokens, _id). The budget is `share` of all tokens. The prefix ends
    at the last (key, id) at which the tokens so far, ties included, stay within the budget. The end is found
    in two steps, so no task sorts a leaf: tokens by cells of the key's range first, then the rows of
    the one cell in which the budget runs out.
    """
    tree = placed.groupBy(*[F.col(f"_{x}").alias(x) for x in LEVELS]).agg(F.sum("_tokens").alias("tokens"), F.count("*").alias("docs"))
    tree = settle(tree, "tree")
    budget = int(share * tree.agg(F.coalesce(F.sum("tokens"), F.lit(0))).first()[0])
    leaves = leaf_budgets(tree.select(*LEVELS, "tokens"), budget, epochs, weights)
    leaves = leaves.join(tree.select(*LEVELS, "docs"), list(LEVELS))
    free = F.when(F.col("open") & F.lit(share > 0), F.lit(epochs)).otherwise(F.lit(0))  # a leaf without tokens fits any budget
    whole = F.coalesce(F.expr("got div nullif(tokens, 0)"), free).cast("int")
    leaves = leaves.withColumn("whole", F.least(whole, F.lit(epochs))).withColumn("rest", F.col("got") - F.col("whole") * F.col("tokens"))
    cells = F.greatest(F.lit(1), F.least(F.lit(1 << 16), F.ceil(F.col("docs") / CELL_ROWS))).cast("long")
    leaves = settle(leaves.withColumn("cells", cells), "leaves")
    keyed = _keyed(placed, leaves, seed)
    cell = F.expr("key div (1152921504606846976 div cells + 1)")  # 2**60 keys
    keyed = keyed.where("rest > 0").withColumn("cell", cell)
    sums = keyed.groupBy(*LEVELS, "rest", "cell").agg(F.sum("_tokens").alias("t"))
    upto = W.partitionBy(*LEVELS).orderBy("cell")
    sums = sums.withColumn("upto", F.sum("t").over(upto.rowsBetween(W.unboundedPreceding, 0)))
    # the first cell that the budget doesn't cover; a leaf covered to its end has none
    last = settle(sums.where("upto > rest").groupBy(*LEVELS).agg(F.min_by(F.struct("cell", (F.col("upto") - F.col("t")).alias("base")), "cell").alias("x")).select(*LEVELS, "x.cell", "x.base"), "cells")
    inside = _with_table(keyed, last, ["cell"])
    run = W.partitionBy(*LEVELS).orderBy(F.struct("key", F.coalesce("_id", F.lit(-1)))).rangeBetween(W.unboundedPreceding, W.currentRow)
    inside = inside.withColumn("upto", F.col("base") + F.sum("_tokens").over(run)).where("upto <= rest")
    ends = inside.groupBy(*LEVELS).agg(F.max(F.struct("key", F.coalesce("_id", F.lit(-1)).alias("id"))).alias("end"))
    first_of_cell = F.expr("cell * (1152921504606846976 div cells + 1)")
    plan = leaves.join(last, list(LEVELS), "left").join(ends, list(LEVELS), "left")
    # without rows of the last cell the prefix ends before that cell; without such a cell it takes the whole leaf
    end_key = F.when(F.col("rest") <= 0, F.lit(-1)).when(F.col("cell").isNull(), F.lit((1 << 60) - 1)).otherwise(F.coalesce("end.key", first_of_cell - 1))
    end_id = F.coalesce("end.id", F.lit((1 << 63) - 1))
    return settle(plan.select(*LEVELS, "tokens", "docs", "got", "whole", "rest", end_key.cast("long").alias("end_key"), end_id.alias("end_id")), "mix")


def _with_table(rows: DataFrame, leaf_table: DataFrame, more: list[str] | None = None) -> DataFrame:
    """rows joined to a table of one row a leaf: broadcast where the tree is small, else a join that Spark may split."""
    on = [*LEVELS, *(more or [])]
    return rows.join(F.broadcast(leaf_table) if leaf_table.count() <= LEAVES else leaf_table, on)


def _keyed(placed: DataFrame, leaves: DataFrame, seed: int) -> DataFrame:
    rows = placed.select(*[F.col(f"_{x}").alias(x) for x in LEVELS], "_tokens", "_id")
    return _with_table(rows, leaves.select(*LEVELS, "whole", "rest", "cells")).withColumn("key", _order_key(F.col("whole"), seed, "_id"))


def copies(placed: DataFrame, plan: DataFrame, seed: int) -> DataFrame:
    """placed (with LEVELS as its place) joined to the plan, with the number of times each row is taken."""
    rows = _with_table(placed, plan).withColumn("_key", _order_key(F.col("whole"), seed, "_id"))
    taken = (F.col("_key") < F.col("end_key")) | ((F.col("_key") == F.col("end_key")) & (F.coalesce("_id", F.lit(-1)) <= F.col("end_id")))
    return rows.withColumn("copies", F.col("whole") + taken.cast("int")).where("copies > 0")


def mix(docs: DataFrame, domain: Column, share: float = 0.5, epochs: int = 2, weights: DataFrame | None = None, seed: int = 42, **names: str) -> DataFrame:
    """(doc_id, domain, lang, source, n_tokens, copies, leaf_budget) for every document taken.

    copies is how often the document is taken: the whole epochs of its leaf, and once more within the
    prefix. Nulls in a column of the tree stand as "(none)"; null texts have no tokens and go with any
    prefix that reaches them; rows that share key and id are taken or left together. A leaf whose first
    document exceeds its budget takes none. An empty table gives an empty result. Further columns are ignored.
    """
    placed = settle(with_leaf(docs, domain, **names).select(*[f"_{x}" for x in LEVELS], "_tokens", "_id"), "placed")
    plan = plan_mix(placed, share, epochs, weights, seed)
    taken = copies(placed.withColumnsRenamed({f"_{x}": x for x in LEVELS}), plan, seed)
    return taken.select(F.col("_id").alias("doc_id"), *LEVELS, F.col("_tokens").alias("n_tokens"), "copies", F.col("got").alias("leaf_budget"))


def mixed_rows(docs: DataFrame, domain: Column, share: float = 0.5, weights: DataFrame | None = None, seed: int = 42) -> DataFrame:
    """The rows of docs that a mix of one epoch takes, all columns kept; rows don't move for it."""
    placed = with_leaf(docs, domain)
    plan = plan_mix(settle(placed.drop("_row"), "placed"), share, 1, weights, seed)
    return copies(placed.withColumnsRenamed({f"_{x}": x for x in LEVELS}), plan, seed).select("_row.*")
