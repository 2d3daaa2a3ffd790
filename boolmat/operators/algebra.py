"""Quadrant trees as relations, matrix sum and product, products in relational form, ternary quantisation."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions.scalar import morton
from ..model import BoolMatrix
from ..sources.tables import stored


#: Levels that are made or passed in one step.
STRIDE = 4


def depth_of(side: int) -> int:
    return max(1, (max(side, 1) - 1).bit_length())


def quad_nodes(matrix: BoolMatrix, k: int = 2) -> DataFrame:
    """(level, z, mask): non-empty nodes of the tree; level 1 is the last above the cells; mask: which children hold ones.

    Every node names its ancestors on the next STRIDE levels; masks are or-ed before each shuffle and after it.
    """
    bits = 2 * (k.bit_length() - 1)
    h = -(-2 * depth_of(max(matrix.n_rows, matrix.n_cols)) // bits)
    leaf = matrix.df.select(morton(F.col("row"), F.col("col"), h * bits // 2).alias("z"))
    low = leaf.groupBy(F.shiftright("z", bits).alias("p")).agg(F.bit_or(F.expr(f"shiftleft(1, CAST(z & {(1 << bits) - 1} AS INT))")).alias("mask"))
    low = stored(low, "quad-low") if h > 1 else low
    bottom = low.select(F.lit(1).alias("level"), F.col("p").alias("z"), "mask")
    if h == 1:
        return bottom
    made, at = [bottom], 1
    while at < h:  # a few levels at a time, from the nodes of the last one: each level has fewer
        top = min(h, at + STRIDE)
        ups = F.explode(F.expr(f"transform(sequence({at + 1}, {top}), l -> named_struct('level', l, 'z', shiftright(z, {bits} * (l - {at})), 'bit', shiftleft(1, CAST(shiftright(z, {bits} * (l - {at + 1})) & {(1 << bits) - 1} AS INT))))"))
        below = made[-1].where(F.col("level") == at).select(ups.alias("n"))
        made.append(stored(below.groupBy(F.col("n.level").alias("level"), F.col("n.z").alias("z")).agg(F.bit_or("n.bit").alias("mask")), "quad-up"))
        at = top
    return reduce(DataFrame.unionAll, made)


def quad_level_counts(matrix: BoolMatrix, k: int = 2) -> DataFrame:
    """(level, nodes): level 1 is the last one above the cells."""
    return quad_nodes(matrix, k).groupBy("level").agg(F.count("*").alias("nodes"))


def quad_cells(nodes: DataFrame, height: int) -> DataFrame:
    """Cells of the relation of a k=2 tree, top down: each level joins the masks of its nodes and spreads the set bits."""
    front = nodes.where(F.col("level") == height).select("z", "mask")
    for level in range(height, 0, -1):
        child = front.select(F.explode(F.expr("transform(filter(array(0, 1, 2, 3), d -> (mask & shiftleft(1, d)) <> 0), d -> z * 4 + d)")).alias("z"))
        front = child if level == 1 else child.join(nodes.where(F.col("level") == level - 1).select("z", "mask"), "z")
    return front.select(_digits("z", 1, height).alias("row"), _digits("z", 0, height).alias("col"))


def _digits(z: str, side: int, height: int) -> Column:
    """The row (side 1) or column (side 0) that is interleaved in a code."""
    return reduce(lambda a, b: a + b, [F.shiftleft(F.shiftright(z, 2 * i + side).bitwiseAND(1), i) for i in range(height)]).cast("bigint")


def quad_sum(a: DataFrame, b: DataFrame) -> DataFrame:
    """The tree of the Boolean sum of two trees of one height: masks of nodes that stand in both are or-ed."""
    return a.unionAll(b).groupBy("level", "z").agg(F.bit_or("mask").alias("mask"))


def _bit(mask: str, d: int) -> Column:
    return F.shiftright(mask, d).bitwiseAND(1)


def quad_product(a: DataFrame, b: DataFrame, height: int, semiring: str = "count") -> DataFrame:
    """(row, col[, val]) of the product of two trees of one height.

    The lowest nodes (rows i, middle k) and (middle k, columns j) meet on their middle, so empty quadrants cost nothing;
    two masks give the four counts of a quadrant of the result, and these are summed before any cell is spread out.
    """
    up = max(1, height - 1)
    mine = a.where(F.col("level") == 1).select(_digits("z", 1, up).alias("i"), _digits("z", 0, up).alias("k"), F.col("mask").alias("ma"))
    theirs = b.where(F.col("level") == 1).select(_digits("z", 1, up).alias("k"), _digits("z", 0, up).alias("j"), F.col("mask").alias("mb"))
    four = {f"c{r}{c}": F.sum((_bit("ma", 2 * r) * _bit("mb", c) + _bit("ma", 2 * r + 1) * _bit("mb", 2 + c)).cast("bigint")) for r in (0, 1) for c in (0, 1)}
    sums = mine.join(theirs, "k").groupBy("i", "j").agg(*[v.alias(k) for k, v in four.items()])
    cells = F.explode(F.array(*[F.struct((2 * F.col("i") + r).alias("row"), (2 * F.col("j") + c).alias("col"), F.col(f"c{r}{c}").cast("double").alias("val")) for r in (0, 1) for c in (0, 1)]))
    out = sums.select(cells.alias("n")).select("n.*").where("val > 0")
    return out.drop("val") if semiring == "bool" else out


def spmv_quad_relational(matrix: BoolMatrix, x: DataFrame) -> DataFrame:
    """(id, value) of M x from the root down, STRIDE levels a join; the lowest nodes take two entries of x each."""
    nodes, height = stored(quad_nodes(matrix), "quad"), depth_of(max(matrix.n_rows, matrix.n_cols))
    level = height
    front = nodes.where(F.col("level") == level)
    while level > 1:
        down = min(STRIDE, level - 1)
        level -= down
        front = nodes.where(F.col("level") == level).join(front.select(F.col("z").alias("up")), F.shiftright("z", 2 * down) == F.col("up"), "left_semi")
    up = max(1, height - 1)
    pairs = x.groupBy(F.shiftright("id", 1).alias("j")).agg(*[F.sum(F.when(F.col("id") % 2 == c, F.col("value"))).alias(f"x{c}") for c in (0, 1)])
    met = front.select(_digits("z", 1, up).alias("i"), _digits("z", 0, up).alias("j"), "mask").join(pairs, "j")
    halves = F.explode(F.array(*[F.struct((2 * F.col("i") + r).alias("id"), F.shiftright("mask", 2 * r).bitwiseAND(3).alias("ones")) for r in (0, 1)]))
    value = sum(F.when(F.col("n.ones").bitwiseAND(1 << c) != 0, F.coalesce(f"x{c}", F.lit(0.0))).otherwise(0.0) for c in (0, 1))
    return met.select(halves.alias("n"), "x0", "x1").where("n.ones <> 0").select(F.col("n.id").alias("id"), value.alias("value")).groupBy("id").agg(F.sum("value").alias("value"))


def spmv_refcopy_relational(matrix: BoolMatrix, x: DataFrame, max_depth: int = 3) -> DataFrame:
    """Products by reference in joins: in stretches of max_depth + 1 rows with ones, a row may copy the row before it.

    A row refers back if it shares more than half of the other row; y = y of the reference + added - dropped.
    """
    lists = matrix.df.groupBy("row").agg(F.sort_array(F.collect_list("col")).alias("cols"))
    stretch = max_depth + 1
    w = Window.partitionBy(F.floor(F.col("row") / stretch)).orderBy("row")
    refs = lists.withColumn("prev", F.lag(F.struct("row", "cols")).over(w)).withColumn("place", F.row_number().over(w) - 1)
    shared = F.size(F.array_intersect("cols", "prev.cols"))
    good = F.col("prev").isNotNull() & (2 * shared > F.size("prev.cols")) & (2 * shared > F.size("cols"))
    refs = stored(refs.select("row", "place", F.when(good, F.col("prev.row")).alias("ref"), F.when(good, F.array_except("cols", "prev.cols")).otherwise(F.col("cols")).alias("added"), F.when(good, F.array_except("prev.cols", "cols")).otherwise(F.array().cast("array<bigint>")).alias("dropped")), "refs")
    diffs = refs.select("row", F.explode("added").alias("col"), F.lit(1.0).alias("sign")).unionAll(refs.select("row", F.explode("dropped"), F.lit(-1.0)))
    sums = diffs.join(x.select(F.col("id").alias("col"), "value"), "col").groupBy("row").agg(F.sum(F.col("sign") * F.col("value")).alias("own"))
    y = refs.select("row", "place", "ref").join(sums, "row", "left").select("row", "place", "ref", F.coalesce("own", F.lit(0.0)).alias("y"))
    for d in range(1, stretch):
        below = y.select(F.col("row").alias("ref"), F.col("y").alias("above"))
        y = y.join(below, "ref", "left").select("row", "place", "ref", F.when((F.col("place") == d) & F.col("ref").isNotNull(), F.col("y") + F.col("above")).otherwise(F.col("y")).alias("y"))
        y = stored(y, "refs")
    return y.select(F.col("row").alias("id"), F.col("y").alias("value"))


def pair_rules_relational(matrix: BoolMatrix, rounds: int = 4) -> tuple[DataFrame, DataFrame]:
    """(rules, final): global pairing rounds in DataFrame steps. rules (sym, height, left, right), final (row, pos, sym).

    Each round takes pairs with at least half of the largest count; a pair applies where no pair to its left in the row
    was applied at the symbol before.
    """
    from pyspark.sql import Row  # noqa: F401

    seq = matrix.df.select("row", F.col("col").alias("pos"), F.col("col").alias("sym"))
    base, rules = matrix.n_cols, []
    w = Window.partitionBy("row").orderBy("pos")
    for height in range(1, rounds + 1):
        pairs = stored(seq.select("row", "pos", "sym", F.lead("sym").over(w).alias("right")), "pairs")
        counts = pairs.where("right IS NOT NULL").groupBy("sym", "right").count()
        most = counts.agg(F.max("count")).first()[0] or 0
        if most < 2:
            break
        chosen = counts.where(F.col("count") >= max(2, -(-most // 2))).select("sym", "right")
        top = chosen.count()
        numbered = stored(chosen.withColumn("new", F.row_number().over(Window.orderBy("sym", "right")) - 1 + base), "rules")  # at most 2 * ones / most rows
        rules.append(numbered.select(F.col("new").alias("sym"), F.lit(height).alias("height"), F.col("sym").alias("left"), "right"))
        base += top
        marked = pairs.join(F.broadcast(numbered) if top < 100_000 else numbered, ["sym", "right"], "left")
        spot = marked.withColumn("hit", F.col("new").isNotNull()).withColumn("n", F.row_number().over(w))
        run = F.col("n") - F.max(F.when(~F.col("hit"), F.col("n"))).over(w.rowsBetween(Window.unboundedPreceding, 0))
        spot = spot.withColumn("take", F.col("hit") & (F.coalesce(run, F.col("n")) % 2 == 1))
        out = spot.withColumn("eaten", F.coalesce(F.lag("take").over(w), F.lit(False)))
        seq = stored(out.where(~F.col("eaten")).select("row", "pos", F.when(F.col("take"), F.col("new")).otherwise(F.col("sym")).alias("sym")), "pairs")
    spark = matrix.df.sparkSession
    empty = spark.createDataFrame([], "sym bigint, height int, left bigint, right bigint")
    return reduce(DataFrame.unionAll, [r.selectExpr("CAST(sym AS BIGINT) sym", "height", "left", "right") for r in rules], empty), seq


def spmv_pair_relational(matrix: BoolMatrix, x: DataFrame, rounds: int = 4) -> DataFrame:
    """Rule values height by height, then one sum of the final symbols per row."""
    rules, final = pair_rules_relational(matrix, rounds)
    w = x.where(F.col("id") < matrix.n_cols).select(F.col("id").alias("sym"), "value")  # rules are numbered from n_cols on
    for height in range(1, rounds + 1):
        now = rules.where(F.col("height") == height)
        both = now.join(w.select(F.col("sym").alias("left"), F.col("value").alias("a")), "left").join(w.select(F.col("sym").alias("right"), F.col("value").alias("b")), "right")
        w = w.unionAll(both.select("sym", (F.col("a") + F.col("b")).alias("value")))
    return final.join(w, "sym").groupBy(F.col("row").alias("id")).agg(F.sum("value").alias("value"))


def mat_sum(a: BoolMatrix, b: BoolMatrix, semiring: str = "bool") -> DataFrame:
    """(row, col[, val]): union of the ones, or the numbers added."""
    both = a.df.select("row", "col").unionAll(b.df.select("row", "col"))
    return both.distinct() if semiring == "bool" else both.groupBy("row", "col").agg(F.count("*").cast("double").alias("val"))


def mat_mul(a: BoolMatrix, b: BoolMatrix, semiring: str = "count", tile: int = 1024) -> DataFrame:
    """(row, col[, val]) of A B. Tiles of A meet tiles of B on the inner tile number; empty tiles have no rows, so they
    prune the join. Inside, cells meet on the inner index."""
    left = a.df.select(F.col("row"), F.col("col").alias("mid"))
    right = b.df.select(F.col("row").alias("mid"), F.col("col"))
    live = left.select(F.floor(F.col("mid") / tile).alias("t")).distinct().join(right.select(F.floor(F.col("mid") / tile).alias("t")).distinct(), "t")
    left = left.withColumn("t", F.floor(F.col("mid") / tile)).join(live, "t", "left_semi")
    joined = left.join(right, "mid")
    return joined.groupBy("row", "col").agg(F.count("*").cast("double").alias("val")) if semiring == "count" else joined.select("row", "col").distinct()


def quantize_ternary(table: DataFrame, threshold: float, id_col: str = "vec_id", vec: str = "embedding") -> tuple[DataFrame, DataFrame]:
    """(plus, minus) cells of the signs of components beyond a threshold."""
    cells = table.select(F.col(id_col).cast("bigint").alias("row"), F.posexplode(vec).alias("at", "c")).select("row", F.col("at").cast("bigint").alias("col"), "c")
    return cells.where(F.col("c") > threshold).drop("c"), cells.where(F.col("c") < -threshold).drop("c")


def transposed_codes(z: Column, height: int) -> Column:
    """Code of the mirrored cell: the two bits of every level change places."""
    return reduce(lambda a, b: a + b, [F.shiftleft(F.shiftright(z, 2 * i).bitwiseAND(1), 2 * i + 1) + F.shiftleft(F.shiftright(z, 2 * i + 1).bitwiseAND(1), 2 * i) for i in range(height)])
