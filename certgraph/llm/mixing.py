"""Mixing of sources to target weights, with DataFrame functions only.

Targets. Sources in code-point order (null last) weigh 1, 2, 3, 1, ...; their shares of all words are capped at
`most_repeats` times the source's own size, and the excess goes to the others by weight (water filling).

Drawing. Documents fall into blocks of their source by a hash. A source's target is so many whole passes over its
blocks and a part of one more: blocks in permuted order, and in the last of them documents in permuted order, passing over
those longer than what is left. What stays open is filled likewise from the source's other blocks, until no document left
brings the source nearer to its target. The block draws of all sources are then dealt to output shards by a splitting tree: each node halves its draws, and how
many of each source go left is one multivariate hypergeometric draw, taken source by source from exact conditional
distributions. A shard gets the next blocks of each source's permutation, so shards are disjoint, and its rows
are put in random order. Every random choice is a hash of the seed and of what it is for, so reruns agree.

Skew. Sizes are pre-aggregated by source and by block; running sums go over blocks, a stretch of the permutation at a time on top
of sums of the stretches before, and over documents only in one partly taken block of each source at a time. No source is ever
gathered in one task. The tree's nodes hold the draws of strata: each source, or where there are more than MOST_STRATA,
that many groups of sources, whose draws in permuted order are split by the same law.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from certgraph.plans.staging import Stages

WORD = r"[^\x20\x09-\x0D]+"
#: Entries of one node of the splitting tree, stretches of one source's permutation, and draws of one output shard, as powers of two.
MOST_STRATA, STRETCH_BITS, SHARD_BITS = 4096, 10, 6


def running_sum(rows: DataFrame, key: str, spot: str, ties: list[str], value: Column, name: str) -> DataFrame:
    """Adds the sum of `value` over the rows of the same key before this one, by `spot` (a hash) and `ties`.

    The permutation is cut by the hash's leading bits into stretches, so a window holds a stretch, not all rows of a key.
    """
    cut = rows.withColumn("_cut", F.shiftright(F.col(spot), 64 - STRETCH_BITS)).withColumn("_value", value)
    sums = cut.groupBy(key, "_cut").agg(F.sum("_value").alias("_sum"))
    earlier = Window.partitionBy(key).orderBy("_cut").rowsBetween(Window.unboundedPreceding, -1)
    sums = sums.select(key, "_cut", F.coalesce(F.sum("_sum").over(earlier), F.lit(0)).alias("_before"))
    inside = Window.partitionBy(key, "_cut").orderBy(spot, *ties).rowsBetween(Window.unboundedPreceding, -1)
    return cut.join(sums, [key, "_cut"]).withColumn(name, F.col("_before") + F.coalesce(F.sum("_value").over(inside), F.lit(0))).drop("_cut", "_value", "_before")


def word_count(text: Column) -> Column:
    """Words of a text, 0 for null: each is replaced by one letter, so no list of them is made."""
    letters = F.translate(F.regexp_replace(text, F.lit(WORD), F.lit("w")), "\x20\x09\x0a\x0b\x0c\x0d", "")
    return F.coalesce(F.octet_length(letters), F.lit(0)).cast("long")


def _source_key(source: Column) -> Column:
    return F.coalesce(F.concat(F.lit("s"), source), F.lit("n"))


def _row_hash(seed: int, doc_id: Column, text: Column, source: Column) -> Column:
    return F.xxhash64(F.lit(seed), doc_id, text, source)


def source_targets(sizes: DataFrame, most_repeats: int = 3) -> DataFrame:
    """From (source, skey, source_size), one row for each source, the targets in words: adds `target`.

    The windows run over the sources, which are few however many documents there are.
    """
    order = Window.orderBy(F.col("source").isNull(), "source")
    ranked = sizes.withColumn("weight", (F.pmod(F.row_number().over(order) - 1, F.lit(3)) + 1).cast("double")).withColumn("cap", (most_repeats * F.col("source_size")).cast("double"))
    by_ratio = Window.orderBy(F.col("cap") / F.col("weight"), "skey")
    every = Window.partitionBy()
    earlier = by_ratio.rowsBetween(Window.unboundedPreceding, -1)
    # the share for each unit of weight if the sources before this one are at their caps
    left = F.sum("source_size").over(every).cast("double") - F.coalesce(F.sum("cap").over(earlier), F.lit(0.0))
    level = left / (F.sum("weight").over(every) - F.coalesce(F.sum("weight").over(earlier), F.lit(0.0)))
    leveled = ranked.withColumn("level", level)
    fits = F.when(F.col("level") * F.col("weight") <= F.col("cap"), F.col("level"))
    final = leveled.withColumn("final", F.coalesce(F.max(fits).over(every), F.max("level").over(every)))
    return final.withColumn("target", F.least("cap", F.col("final") * F.col("weight"))).select("source", "skey", "source_size", "target")


def _log_factorial(n: str) -> str:
    """SQL for ln(n!) by the asymptotic series of the gamma function, shifted by eight."""
    z = f"(double({n}) + 9d)"
    series = f"({z} - 0.5d) * ln({z}) - {z} + 0.9189385332046727d + 1d / (12d * {z}) - 1d / (360d * pow({z}, 3)) + 1d / (1260d * pow({z}, 5))"
    shift = " + ".join(f"ln(double({n}) + {k}d)" for k in range(1, 9))
    return f"(({series}) - ({shift}))"


def _hypergeometric(total: str, marked: str, drawn: str, u: str) -> str:
    """SQL for the number of marked ones among `drawn` of `total` without replacement, by inversion at `u`.

    The support is walked from twelve standard deviations below the mean; what is cut off is below double precision.
    """
    lf = _log_factorial
    spread = f"bigint(12d * sqrt(double({drawn}) * {marked} / {total} * (1d - double({marked}) / {total}) + 1d)) + 12"
    mean = f"bigint(double({drawn}) * {marked} / {total})"
    low = f"greatest(0L, {drawn} + {marked} - {total}, {mean} - {spread})"
    high = f"least({marked}, {drawn}, {mean} + {spread})"
    fixed = f"{lf(marked)} + {lf(f'({total} - {marked})')} + {lf(drawn)} + {lf(f'({total} - {drawn})')} - {lf(total)}"
    chance = f"exp(w.fixed - {lf('i')} - {lf(f'({marked} - i)')} - {lf(f'({drawn} - i)')} - {lf(f'({total} - {marked} - {drawn} + i)')})"
    walk = f"aggregate(sequence(w.low, w.high), named_struct('c', 0d, 'x', -1L), (a, i) -> if(a.x >= 0L, a, named_struct('c', a.c + {chance}, 'x', if(a.c + {chance} >= {u}, i, -1L))), a -> if(a.x >= 0L, a.x, w.high))"
    once = f"transform(array(named_struct('low', {low}, 'high', {high}, 'fixed', {fixed})), w -> {walk})[0]"
    return f"if({total} <= 0L OR {marked} <= 0L OR {drawn} <= 0L, 0L, {once})"


def splitting_tree(quotas: DataFrame, depth: int, seed: int) -> DataFrame:
    """From (skey, quota) the draws of each stratum in each of 2 ** depth shards: (shard, skey, draws).

    All nodes of a level are split at once. A node is one row that holds its draws of all strata, at most MOST_STRATA of them.
    """
    nodes = quotas.filter("quota > 0").agg(F.sort_array(F.collect_list(F.struct("skey", F.col("quota").alias("k")))).alias("own")).select(F.lit(1).cast("long").alias("node"), "own")
    draw = _hypergeometric("s.total", "e.k", "s.drawn", f"((pmod(xxhash64({seed}L, node, e.skey), 9007199254740992L) + 0.5d) / 9007199254740992d)")
    step = f"""aggregate(own,
        named_struct('total', aggregate(own, 0L, (t, e) -> t + e.k), 'drawn', bigint(ceil(aggregate(own, 0L, (t, e) -> t + e.k) / 2d)), 'out', cast(array() as array<struct<skey: string, left: bigint, right: bigint>>)),
        (s, e) -> transform(array({draw}), x -> named_struct('total', s.total - e.k, 'drawn', s.drawn - x, 'out', concat(s.out, array(named_struct('skey', e.skey, 'left', x, 'right', e.k - x)))))[0],
        s -> s.out)"""
    for _ in range(depth):
        split = nodes.withColumn("both", F.expr(step))
        sides = F.expr("array(named_struct('node', 2 * node, 'own', transform(both, b -> named_struct('skey', b.skey, 'k', b.left))), named_struct('node', 2 * node + 1, 'own', transform(both, b -> named_struct('skey', b.skey, 'k', b.right))))")
        nodes = split.select(F.explode(sides).alias("side")).select("side.node", "side.own")
    leaf = nodes.select((F.col("node") - F.lit(1 << depth)).alias("shard"), F.explode("own").alias("e"))
    return leaf.select("shard", "e.skey", F.col("e.k").alias("draws"))


class Mix:
    """A mixing plan for one table: sizes, targets, and for each block how often and where it is taken."""

    def __init__(self, docs: DataFrame, most_repeats: int = 3, block_words: int = 1 << 18, depth: int | None = None, seed: int = 11, id_col: str = "doc_id", text_col: str = "text", source_col: str = "source"):
        self.seed, self.cols, self.docs = seed, (id_col, text_col, source_col), docs
        self.st = Stages(docs.sparkSession, "mixing")
        doc, text, source = F.col(id_col), F.col(text_col).cast("string"), F.col(source_col).cast("string")
        slim = docs.select(doc.cast("long").alias("doc_id"), source.alias("source"), _source_key(source).alias("skey"), word_count(text).alias("size"), _row_hash(seed, doc.cast("long"), text, source).alias("h"))
        self.slim = self.st.keep(slim, "sizes")
        sizes = self.slim.groupBy("source", "skey").agg(F.sum("size").alias("source_size"))
        n_blocks = F.greatest(F.lit(1), F.ceil(F.col("source_size") / block_words)).cast("long")
        passes = F.when(F.col("source_size") > 0, F.floor(F.col("target") / F.col("source_size"))).otherwise(0).cast("long")
        targets = source_targets(sizes, most_repeats).withColumn("n_blocks", n_blocks).withColumn("passes", passes)
        self.sources = self.st.keep(targets.withColumn("rest", F.col("target") - F.col("passes") * F.col("source_size")), "sources")
        self._plan_blocks(depth)

    def blocked(self, rows: DataFrame) -> DataFrame:
        """Rows with skey and h joined to their source, with their block."""
        return rows.join(self.sources.drop("source"), "skey").withColumn("block", F.pmod("h", "n_blocks"))

    def _plan_blocks(self, depth: int | None) -> None:
        rows = self.blocked(self.slim)
        spot = F.xxhash64(F.lit(self.seed + 1), "skey", "block")
        blocks = rows.groupBy("skey", "block", "passes", "rest").agg(F.sum("size").alias("words")).withColumn("spot", spot)
        before = F.col("before")
        part = F.when(before + F.col("words") <= F.col("rest"), 1).when(before < F.col("rest"), 2).otherwise(0)
        placed = running_sum(self.st.keep(blocks, "words"), "skey", "spot", ["block"], F.col("words"), "before")
        blocks = self.st.keep(placed.withColumn("extra", part).select("skey", "block", "passes", "extra", (F.col("rest") - F.col("before")).alias("wanted")), "blocks")

        cuts = blocks.filter("extra = 2").select("skey", F.col("wanted").alias("gap"))
        units = rows.join(blocks.filter("extra <> 1").select("skey", "block"), ["skey", "block"]).filter("size > 0").groupBy("skey", "block", "h").agg(F.sum("size").alias("size"))
        self.picked = self._filled(units.withColumn("spot", spot), self.st.keep(cuts, "gaps"))
        touched = self.picked.select("skey", "block").distinct().withColumn("part", F.lit(2))
        blocks = blocks.join(touched, ["skey", "block"], "left").withColumn("extra", F.when(F.col("extra") == 1, 1).otherwise(F.coalesce("part", F.lit(0)))).drop("part")
        blocks = self.st.keep(blocks, "blocks")

        draws = blocks.select("skey", "block", F.explode(F.sequence(F.lit(0).cast("long"), F.col("passes"))).alias("copy"), "passes", "extra").filter("copy < passes OR extra > 0")
        if self.sources.count() <= MOST_STRATA:
            stratum = F.col("skey")
        else:
            stratum = F.concat(F.lit("g"), F.pmod(F.xxhash64("skey"), F.lit(MOST_STRATA)).cast("string"))
        draws = draws.withColumn("stratum", stratum).withColumn("at", F.xxhash64(F.lit(self.seed + 2), "skey", "block", "copy"))
        draws = self.st.keep(draws.select("stratum", "skey", "block", "copy", "at"), "draws")
        if depth is None:  # about as many shards as hold 2 ** SHARD_BITS draws each
            depth = max(4, draws.count().bit_length() - SHARD_BITS)
        draws = self.st.keep(running_sum(draws, "stratum", "at", ["skey", "block", "copy"], F.lit(1).cast("long"), "nth"), "numbered")
        leaves = self.st.keep(splitting_tree(draws.groupBy(F.col("stratum").alias("skey")).agg(F.count(F.lit(1)).alias("quota")), depth, self.seed + 3), "leaves")
        upto = F.sum("draws").over(Window.partitionBy("skey").orderBy("shard"))
        ranges = leaves.withColumn("end", upto).filter("draws > 0").select(F.col("skey").alias("stratum"), (F.col("end") - F.col("draws")).alias("begin"), "end", "shard")
        # stratum by stratum, draws and ranges in order: a range is filed under the stretch of places that it begins in and those it goes on to
        wide = F.floor(F.col("begin") / 1024), F.floor((F.col("end") - 1) / 1024)
        ranges = ranges.withColumn("near", F.explode(F.sequence(*wide)))
        found = draws.withColumn("near", F.floor(F.col("nth") / 1024)).join(ranges, ["stratum", "near"]).filter("nth >= begin AND nth < end")
        dealt = found.groupBy("skey", "block").agg(F.sort_array(F.collect_list(F.struct("copy", F.col("shard").cast("int").alias("shard")))).alias("dealt"))
        self.plan = self.st.keep(blocks.join(dealt, ["skey", "block"], "left").select("skey", "block", "extra", "dealt"), "plan")

    def _filled(self, free: DataFrame, gaps: DataFrame) -> DataFrame:
        """(skey, block, h) of the documents that fill each source's gap, from (skey, block, spot, h, size), equal rows as one.

        A round goes down the order with the documents no longer than the gap and takes them as long as they fit: whole
        blocks by sums of blocks, then a part of one. Its first document always fits, so gaps shrink until none does. At last
        the nearest document is taken if it leaves less over than the gap.
        """
        found = None
        while True:
            near = free.join(F.broadcast(gaps), "skey")
            fit = near.filter(F.col("size") <= F.col("gap"))
            sums = fit.groupBy("skey", "spot", "block", "gap").agg(F.sum("size").alias("words"))
            upto = F.sum("words").over(Window.partitionBy("skey").orderBy("spot", "block"))
            run = sums.withColumn("before", upto - F.col("words")).filter(F.col("before") < F.col("gap"))
            run = self.st.keep(run.select("skey", "block", (F.col("gap") - F.col("before")).alias("room"), (F.col("before") + F.col("words") <= F.col("gap")).alias("all")), "run")
            if run.isEmpty():
                break
            inside = fit.select("skey", "block", "h", "size").join(run, ["skey", "block"])
            part = inside.filter("NOT all").withColumn("upto", F.sum("size").over(Window.partitionBy("skey", "block").orderBy("h"))).filter(F.col("upto") <= F.col("room"))
            taken = self.st.keep(inside.filter("all").select("skey", "block", "h", "size").unionByName(part.select("skey", "block", "h", "size")), "taken")
            found = taken if found is None else found.unionByName(taken)
            used = taken.groupBy("skey").agg(F.sum("size").alias("used"))
            left = near.drop("gap").join(taken.select("skey", "block", "h"), ["skey", "block", "h"], "left_anti")
            gaps = self.st.keep(gaps.join(used, "skey", "left").select("skey", (F.col("gap") - F.coalesce("used", F.lit(0))).alias("gap")), "gaps")
            free = self.st.keep(left.join(F.broadcast(gaps), "skey").filter(F.col("size") < 2 * F.col("gap")).drop("gap"), "free")
        over = F.col("size") - F.col("gap")
        last = near.filter(over < F.col("gap")).groupBy("skey").agg(F.min(F.struct(over.alias("over"), "h", "block", "size")).alias("m")).select("skey", "m.block", "m.h", "m.size")
        found = last if found is None else found.unionByName(last)
        return self.st.keep(found.select("skey", "block", "h"), "picked")

    def with_draws(self, rows: DataFrame) -> DataFrame:
        """Rows with skey and h, with `drawn`: the copies that the mix takes, and their shards."""
        picked = self.picked.withColumn("picked", F.lit(True))
        found = self.blocked(rows).join(self.plan, ["skey", "block"]).join(picked, ["skey", "block", "h"], "left")
        extra = (F.col("extra") == 1) | F.coalesce("picked", F.lit(False))
        own = F.filter("dealt", lambda d: (d["copy"] < F.col("passes")) | extra)
        return found.withColumn("drawn", F.coalesce(own, F.expr("cast(array() as array<struct<copy: bigint, shard: int>>)")))

    def amounts(self) -> DataFrame:
        """doc_id, size, source_size, target, taken, shards: one row for each row of the table."""
        rows = self.with_draws(self.slim.select("doc_id", "skey", "size", "h"))
        return rows.select("doc_id", "size", "source_size", "target", (F.col("size") * F.size("drawn")).alias("taken"), F.col("drawn.shard").alias("shards"))

    def rows(self, with_shard: bool = False) -> DataFrame:
        """The mix: the table's own columns, a row for each copy taken, in random order within shards."""
        id_col, text_col, source_col = self.cols
        names = [f"c{i}" for i in range(len(self.docs.columns))]
        at = {n.lower(): c for n, c in zip(self.docs.columns, names, strict=True)}
        doc, text, source = (F.col(at[c.lower()]) for c in (id_col, text_col, source_col))
        base = self.docs.toDF(*names).withColumn("h", _row_hash(self.seed, doc.cast("long"), text.cast("string"), source.cast("string"))).withColumn("skey", _source_key(source.cast("string")))
        copies = self.with_draws(base).withColumn("one", F.explode("drawn"))
        placed = copies.withColumn("shard", F.col("one.shard")).withColumn("spot", F.xxhash64(F.lit(self.seed + 4), "h", "one.copy"))
        mixed = placed.repartition(F.col("shard"), F.pmod("spot", F.lit(64))).sortWithinPartitions("shard", "spot")
        return mixed.select(*(F.col(c).alias(n) for c, n in zip(names, self.docs.columns, strict=True)), *([F.col("shard")] * with_shard))


def mixed_amounts(docs: DataFrame, **options) -> DataFrame:
    """What a mix takes of each document; see `Mix` for the options.

    A null text has size 0; a null source is a source of its own; ids are passed through, null or repeated, and rows that
    repeat id, text and source are taken alike; a source without words has target 0; an empty table gives an empty result.
    """
    return Mix(docs, **options).amounts()
