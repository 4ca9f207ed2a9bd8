"""Layer-wise sampling: FastGCN and LADIES, each plain, flat, debiased or both."""

from __future__ import annotations

from collections.abc import Callable

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from . import draws
from .model import apply_nn

#: Adjacency or batch lists of at most so many entries (32 MB of ids) are sent to all tasks.
SENT = 4_000_000
VARIANTS = {f"{base}{'_' if x else ''}{x}": (base, "f" in x, "d" in x) for base in ("fastgcn", "ladies") for x in ("", "f", "d", "fd")}


def column_probs(prop: DataFrame, rows: DataFrame | None = None, power: int | Column = 2) -> DataFrame:
    """(node_id, p), or (batch_id, node_id, p) where ``rows`` (batch_id, node_id) restricts the matrix.

    ``power`` 2: squared column norms; 1 (flat): the norms; with ``rows`` it may depend on the batch. Squares are summed before the shuffle.
    """
    if rows is None:
        sums, by = prop.groupBy(F.col("col").alias("node_id")).agg(F.sum(F.col("w") * F.col("w")).alias("q")), []
    else:
        near = prop.join(rows.select("batch_id", F.col("node_id").alias("row")), "row")
        sums, by = near.groupBy("batch_id", F.col("col").alias("node_id")).agg(F.sum(F.col("w") * F.col("w")).alias("q")), ["batch_id"]
    if isinstance(power, Column):
        mass = sums.withColumn("q", F.when(power == 1, F.sqrt("q")).otherwise(F.col("q")))
    else:
        mass = sums.withColumn("q", F.sqrt("q")) if power == 1 else sums
    if by:  # totals by a combining aggregate: no task sees all candidates of a batch
        total = mass.groupBy(*by).agg(F.sum("q").alias("total"))
        return mass.join(total, by).select(*by, "node_id", (F.col("q") / F.col("total")).alias("p"))
    total = mass.agg(F.sum("q").alias("total")).withColumn("k", F.lit(1))
    return mass.withColumn("k", F.lit(1)).join(F.broadcast(total), "k").select("node_id", (F.col("q") / F.col("total")).alias("p"))


def activation_probs(prop: DataFrame, norms: DataFrame, rows: DataFrame | None = None) -> DataFrame:
    """Flat probabilities from activation norms (node_id, h): p proportional to h over the columns that occur; uniform where h is missing."""
    pool = (prop if rows is None else prop.join(rows.select("batch_id", F.col("node_id").alias("row")), "row")).select(*([] if rows is None else ["batch_id"]), F.col("col").alias("node_id")).distinct()
    held = pool.join(norms, "node_id", "left").withColumn("h", F.coalesce("h", F.lit(1.0)))
    if rows is not None:
        sums = held.groupBy("batch_id").agg(F.sum("h").alias("total"))
        return held.join(sums, "batch_id").select("batch_id", "node_id", (F.col("h") / F.col("total")).alias("p"))
    total = held.agg(F.sum("h").alias("total")).withColumn("k", F.lit(1))
    return held.withColumn("k", F.lit(1)).join(F.broadcast(total), "k").select("node_id", (F.col("h") / F.col("total")).alias("p"))


def activation_norms(x: DataFrame, w: DataFrame) -> DataFrame:
    """(node_id, h): row norms of features (node_id, pos, x) times weights (i, j, w), for :func:`activation_probs`."""
    return apply_nn(x, w).groupBy("node_id").agg(F.sqrt(F.sum(F.col("x") * F.col("x"))).alias("h"))


def packed_rows(prop: DataFrame) -> DataFrame:
    """(row, cols, q): a row of the operator as arrays of columns and squared entries."""
    held = prop.groupBy("row").agg(F.collect_list(F.struct("col", (F.col("w") * F.col("w")).alias("q"))).alias("x"))
    return held.select("row", F.col("x.col").alias("cols"), F.col("x.q").alias("q"))


def packed_pool(packed: DataFrame, rows: DataFrame, power: int | Column, parts: int) -> DataFrame:
    """(batch_id, node_id, p, n): :func:`column_probs` of ``rows`` over the packed rows, which every task gets, and the number of nodes with p > 0.

    Rows are dealt by batch, so neither the entries that they touch nor the pool are shuffled, and totals are those of a batch inside a task.
    """
    dealt = rows.select("batch_id", F.col("node_id").alias("row")).repartition(parts, "batch_id")
    near = dealt.join(F.broadcast(packed), "row").select("batch_id", "q", F.posexplode("cols").alias("at", "node_id"))
    mass = near.groupBy("batch_id", "node_id").agg(F.sum(F.col("q")[F.col("at")]).alias("q"))
    if isinstance(power, Column):
        mass = mass.withColumn("q", F.when(power == 1, F.sqrt("q")).otherwise(F.col("q")))
    elif power == 1:
        mass = mass.withColumn("q", F.sqrt("q"))
    batch = Window.partitionBy("batch_id")
    return mass.select("batch_id", "node_id", (F.col("q") / F.sum("q").over(batch)).alias("p"), F.count_if(F.col("q") > 0).over(batch).alias("n"))


def is_small(*tables: DataFrame) -> bool:
    return all(t.count() <= SENT for t in tables)


def meetings(prop: DataFrame, rows: DataFrame, chosen: DataFrame, small: bool) -> DataFrame:
    """(batch_id, row, col, w): entries between rows and chosen columns of the same batch.

    An entry meets the batches of its row and of its column as two lists, so it is read once for all batches, and what a batch's rows touch but did not choose is never a row of its own.
    """
    sent = F.broadcast if small else lambda df: df
    here = rows.groupBy(F.col("node_id").alias("row")).agg(F.collect_list("batch_id").alias("here"))
    there = chosen.groupBy(F.col("node_id").alias("col")).agg(F.collect_list("batch_id").alias("there"))
    both = prop.join(sent(here), "row").join(sent(there), "col")
    return both.select(F.explode(F.array_intersect("here", "there")).alias("batch_id"), "row", "col", "w")


def block_of(prop: DataFrame, rows: DataFrame, chosen: DataFrame, normalise: bool | Column, small: bool | None = None) -> DataFrame:
    """(batch_id, layer, dst, src, w): propagation entries between rows and chosen columns, scaled by the columns' ``coef``.

    Row selection is a join on the row id and column scaling a projection; neither matrix is built. ``small`` (not None) takes :func:`meetings` instead of entries by batch.
    """
    weighed = chosen.select("batch_id", "layer", F.col("node_id").alias("col"), "coef")
    if small is None:
        near = prop.join(rows.select("batch_id", F.col("node_id").alias("row")), "row")
    else:
        near = meetings(prop, rows, chosen, small)
    cut = near.join(weighed, ["batch_id", "col"])
    block = cut.select("batch_id", "layer", F.col("row").alias("dst"), F.col("col").alias("src"), (F.col("w") * F.col("coef")).alias("w"))
    if normalise is not False:
        even = F.col("w") / F.sum("w").over(Window.partitionBy("batch_id", "layer", "dst"))
        block = block.withColumn("w", F.when(normalise, even).otherwise(F.col("w")) if isinstance(normalise, Column) else even)
    return block


@dataclass(frozen=True)
class LayerSampler:
    """A layer-wise sampler for windows of batches; ``sizes`` from the layer below the seeds down to the inputs.

    FastGCN draws every layer from one measure and may leave rows empty. LADIES draws from the columns that the rows above touch, and normalises rows unless debiased
    (normalising would undo the debiasing). ``by_arrival`` draws FastGCN's layers from independent draws in order of arrival instead of a race of all nodes in each batch: the form for many batches of a large graph. ``flat`` and ``debias`` may be conditions on batch_id, so that one plan serves variants in batches of their own. ``keep`` (persist, spool) is applied to the chosen nodes of each layer (at most sizes x batches rows), so that several results over them share the work;
    it also lets FastGCN rank only race keys below a bound, and LADIES deal its pools by batch where the operator is small.
    """

    base: str = "ladies"
    flat: bool | Column = False
    debias: bool | Column = False
    replace: bool = False
    by_arrival: bool = False
    sizes: tuple[int, ...] = (512, 512)
    row_normalise: bool | None = None
    include_self: bool = True
    epoch: int = 0
    seed: int = 7
    impl: str = "md5"
    keep: Callable[[DataFrame], DataFrame] | None = None

    @classmethod
    def named(cls, variant: str, **more) -> "LayerSampler":
        base, flat, debias = VARIANTS[variant]
        return cls(base, flat, debias, **more)

    def pool(self, prop: DataFrame, rows: DataFrame) -> DataFrame:
        """(batch_id, node_id, p) of the next layer."""
        mixed = isinstance(self.flat, Column)
        power = F.when(self.flat, 1).otherwise(2) if mixed else 1 if self.flat else 2
        if self.base == "fastgcn":
            batches = rows.select("batch_id").distinct().withColumn("k", F.lit(1))
            if not mixed:
                return column_probs(prop, None, power).withColumn("k", F.lit(1)).join(F.broadcast(batches), "k").drop("k")
            both = column_probs(prop, None, 2).join(column_probs(prop, None, 1).withColumnRenamed("p", "p1"), "node_id").withColumn("k", F.lit(1))
            return both.join(F.broadcast(batches), "k").select("batch_id", "node_id", F.when(self.flat, F.col("p1")).otherwise(F.col("p")).alias("p"))
        return column_probs(prop if self.include_self else prop.where("row <> col"), rows, power)

    def draw(self, prop: DataFrame, rows: DataFrame, layer: int, packed: DataFrame | None = None) -> DataFrame:
        """(batch_id, layer, node_id, p, ..., coef)."""
        size = self.sizes[-1 - layer] if layer < len(self.sizes) else self.sizes[0]
        if self.replace:
            if self.base != "fastgcn":
                raise ValueError("independent draws need one measure for all batches")
            return draws.importance_weights(draws.drawn_counts(draws.iid(column_probs(prop, None, 1 if self.flat else 2), rows, size, layer, self.epoch, self.seed)))
        if self.by_arrival:
            if self.base != "fastgcn" or isinstance(self.flat, Column) or isinstance(self.debias, Column):
                raise ValueError("draws by arrival need one measure for all batches")
            probs = column_probs(prop, None, 1 if self.flat else 2)
            chosen = draws.arrivals(probs, rows, size, layer, self.epoch, self.seed, keep=self.keep)
            n = probs.where("p > 0").count() if self.debias else 0
            return draws.debias_weights(chosen, F.lit(n)) if self.debias else draws.importance_weights(chosen)
        if self.keep and self.base == "fastgcn":
            return self.weighed(*self.raced(prop, rows, size, layer))
        if self.keep and packed is not None:
            batches = rows.select("batch_id").distinct().count()
            power = F.when(self.flat, 1).otherwise(2) if isinstance(self.flat, Column) else 1 if self.flat else 2
            pool = packed_pool(packed, rows, power, max(1, min(2000, -(-batches // 16))))
            return self.weighed(self.keep(draws.race(pool, size, layer, self.epoch, self.seed, self.impl, "n")), F.col("n"))
        pool = self.pool(prop, rows)
        chosen = draws.race(pool, size, layer, self.epoch, self.seed, self.impl)
        support = None if self.debias is False else pool.where("p > 0").groupBy("batch_id").agg(F.count("*").alias("n"))
        return self.weighed(chosen, support)

    def raced(self, prop: DataFrame, rows: DataFrame, size: int, layer: int) -> tuple[DataFrame, Column]:
        """(chosen nodes, support) of FastGCN's race, by measure: plain and flat batches apart if both occur."""
        batches, out, n = rows.select("batch_id").distinct(), None, 0
        for power in (2, 1):
            mine = batches.where(self.flat if power == 1 else ~self.flat) if isinstance(self.flat, Column) else batches if (power == 1) == self.flat else None
            if mine is None or mine.isEmpty():
                continue
            probs = self.keep(column_probs(prop, None, power))
            bound = draws.race_bound(probs, size)
            one, n = draws.race_all(probs, mine, size, layer, self.keep, bound, self.epoch, self.seed, self.impl), bound[0]
            out = one if out is None else out.union(one)
        return (out if out is not None else draws.race(self.pool(prop, rows), size, layer, self.epoch, self.seed, self.impl)), F.lit(n)

    def weighed(self, chosen: DataFrame, support: DataFrame | Column | None) -> DataFrame:
        if self.debias is False:
            return draws.importance_weights(chosen.drop("n"))
        debiased = draws.debias_weights(chosen, support)
        if self.debias is True:
            return debiased
        plain = draws.importance_weights(debiased.withColumnRenamed("coef", "debiased"))
        return plain.withColumn("coef", F.when(self.debias, F.col("debiased")).otherwise(F.col("coef"))).drop("debiased")

    def layers(self, prop: DataFrame, seeds: DataFrame) -> tuple[list[DataFrame], list[DataFrame]]:
        """(chosen nodes, blocks) from the top layer down, in one plan for all batches."""
        rows, chosen, blocks = seeds.select("batch_id", "node_id").distinct(), [], []
        if self.row_normalise is not None or self.base != "ladies":
            normalise = bool(self.row_normalise)
        else:
            normalise = ~self.debias if isinstance(self.debias, Column) else not self.debias
        packed = None
        if self.keep and self.base == "ladies" and prop.count() <= SENT:
            packed = self.keep(packed_rows(prop if self.include_self else prop.where("row <> col")))
        for layer in reversed(range(len(self.sizes))):
            nodes, small = self.draw(prop, rows, layer, packed), None
            if self.keep:
                nodes = self.keep(nodes)
                small = is_small(nodes, rows)
            blocks.append(block_of(prop, rows, nodes, normalise, small))
            chosen.append(nodes)
            rows = nodes.select("batch_id", "node_id")
        return chosen, blocks


def empty_row_share(block: DataFrame, rows: DataFrame) -> DataFrame:
    """(rows, empty, share): rows of a batch without any sampled column."""
    every = rows.select("batch_id", F.col("node_id").alias("dst")).distinct()
    hit = block.select("batch_id", "dst", F.lit(1).alias("hit")).distinct()
    told = every.join(hit, ["batch_id", "dst"], "left")
    empty = F.sum(F.col("hit").isNull().cast("long"))
    return told.agg(F.count("*").alias("rows"), empty.alias("empty"), F.round(empty / F.count("*"), 6).alias("share"))


def sampled_loss(predictions: DataFrame) -> DataFrame:
    """(batch_id, loss): the mean of ``g`` over a batch's top draws."""
    return predictions.groupBy("batch_id").agg(F.avg("g").alias("loss"))
