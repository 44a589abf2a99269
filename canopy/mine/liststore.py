"""Search with lists instead of occurrences: for every pattern node, its images.

Lists are linear in the data and the pattern, where occurrences can be
exponential. The lists of a join result start from those of its two parents:
the shared nodes' lists are intersected, the two last nodes keep their
parent's list. Semi-joins up and down the pattern then reduce them to the
images under homomorphisms. That is exact for patterns whose siblings cannot
meet on a path; for the others, occurrences are built from the reduced lists,
filtered, and projected to lists again.

With ``lists='bitmap'`` a list is stored as bits over the inverted list of its
label, and shared nodes are intersected bit by bit.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from canopy.forest.lists import ordinals
from canopy.functions.region import is_disjoint
from canopy.match.occlist import bit_and, union_all, unpack
from canopy.match.sibling import conflict_free
from canopy.mine.engine import Mined, Options, Search
from canopy.pattern.canonical import is_canonical
from canopy.pattern.model import Pattern
from canopy.storage import stage

NODE = ["tree_id", "begin", "end", "anc", "w", "label", "ord"]
KEY = ["pattern_id", "pos", "tree_id", "begin"]
#: Depth of patterns up to which the steps of a reduction are not written.
FLAT = 3
#: Entries of lists up to which their joins broadcast one side; larger ones are dealt out by key.
NEAR = 50_000


class ListSearch(Search):
    """``occ`` holds ``(pattern_id, pos, *NODE)``, or ``(pattern_id, pos, label, bucket, bits)``."""

    def __init__(self, nodes: DataFrame, options: Options):
        super().__init__(nodes, options)
        self.built: dict[int, DataFrame] = {}  # pattern -> the written table that holds its occurrences
        self.entries: dict[int, int] = {}  # pattern -> rows of its lists

    def seeded(self, pairs: DataFrame, trees: DataFrame) -> DataFrame:
        if self.options.support == "occurrence":
            raise ValueError("lists do not count occurrences")
        self.trees = stage(ordinals(trees) if self.options.lists == "bitmap" else trees.withColumn("ord", F.lit(0).cast("long")), "trees")
        above = self.trees.select("tree_id", F.explode("anc").alias("begin"), F.col("label").alias("lower")).join(self.trees.select("tree_id", "begin", "label"), ["tree_id", "begin"])
        self.above = {(r["label"], r["lower"]) for r in above.select("label", "lower").distinct().collect()}  # pairs of labels
        places = F.explode(F.array(*(F.struct(F.lit(k).alias("pos"), F.col(c).alias("begin")) for k, c in enumerate("ad")))).alias("x")
        images = pairs.select("pattern_id", "tree_id", places).select("pattern_id", "x.pos", "tree_id", "x.begin").distinct()
        return self.stored(images.join(self.trees, ["tree_id", "begin"]).select("pattern_id", "pos", *NODE), 2)

    def stored(self, rows: DataFrame, size: int) -> DataFrame:
        if self.options.lists == "rows":
            return stage(rows, f"lists{size}")
        bucket, bit = F.bitmap_bucket_number("ord").alias("bucket"), F.bitmap_bit_position("ord")
        return stage(rows.groupBy("pattern_id", "pos", "label", bucket).agg(F.bitmap_construct_agg(bit).alias("bits")), f"bitmaps{size}")

    def rows(self, kept: DataFrame) -> DataFrame:
        """``(pattern_id, pos, *NODE)`` of stored lists."""
        if self.options.lists == "rows":
            return kept
        return unpack(kept, self.trees, ["pattern_id", "pos"], NODE).select("pattern_id", "pos", *NODE)

    def evaluated(self, size: int, new: list[Mined], occ: DataFrame, part: bool = False) -> list[Mined]:
        rows = self.rows(occ)
        counts = rows.groupBy("pattern_id", "pos").agg(F.sum("w").alias("n"), F.count(F.lit(1)).alias("rows")).collect()
        sizes = {(r["pattern_id"], r["pos"]): r["n"] for r in counts}
        for r in counts:
            self.entries[r["pattern_id"]] = self.entries.get(r["pattern_id"], 0) + r["rows"]
        trees = {}
        if self.options.support == "document":
            trees = {r["pattern_id"]: r["n"] for r in rows.where("pos = 0").groupBy("pattern_id").agg(F.count_distinct("tree_id").alias("n")).collect()}
        for m in new:
            m.sizes = tuple(sizes.get((m.id, k), 0) for k in range(size))
            m.support = trees.get(m.id, 0) if self.options.support == "document" else m.sizes[0]
            m.n_occ, m.n_part, m.canonical = -1, -2, is_canonical(m.pattern, self.rank)  # not counted yet
        return self.tallied(size, new, occ, sum(sum(m.sizes) for m in new if m.support >= self.options.minsup))

    def join(self, size: int, new: list[Mined]) -> DataFrame:
        """Lists of the candidates of one level, from those of their parents."""
        self.admit(size, new)
        table = F.broadcast(self.spark.createDataFrame([(m.id, m.left, m.right) for m in new], "q long, left long, right long"))
        kept, last = self.occ[size - 1], size - 2
        entry = [c for c in kept.columns if c not in ("pattern_id", "pos")]
        left = kept.join(table, F.col("pattern_id") == F.col("left")).select(F.col("q").alias("pattern_id"), "pos", *entry)
        right = kept.join(table, F.col("pattern_id") == F.col("right")).select(F.col("q").alias("pattern_id"), (F.col("pos") + (F.col("pos") == last).cast("int")).alias("pos"), *entry)
        tails = left.where(F.col("pos") == last).unionByName(right.where(F.col("pos") == last + 1))
        if self.options.lists == "rows":
            shared = left.where(F.col("pos") < last).join(right.select(KEY), KEY, "left_semi")
        else:
            shared = bit_and(left.union(right).where(F.col("pos") < last), ["pattern_id", "pos", "label"], 2)
        met = stage(self.rows(shared.unionByName(tails)).select("pattern_id", "pos", *NODE), "met")
        near = met.count() <= NEAR
        lists = reduced(met, {m.id: m.pattern for m in new}, near)
        hard = {m.id: m.pattern for m in new if not conflict_free(m.pattern, self.above)}
        if hard:
            lists = stage(lists, "reduced")
            marked = F.broadcast(self.spark.createDataFrame([(k,) for k in hard], "pattern_id long"))
            images = tuples(lists.join(marked, "pattern_id", "left_semi"), hard, near)
            images = images.select("pattern_id", "tree_id", F.posexplode("img").alias("pos", "begin")).select(KEY).distinct()
            lists = lists.join(marked, "pattern_id", "left_anti").unionByName(lists.join(sent(images, near), KEY, "left_semi"))
        return self.stored(lists.select("pattern_id", "pos", *NODE), size)

    # occurrences are built for the few patterns that a test asks about

    def occurrences(self, size: int, ids: list[int]) -> DataFrame:
        missing = [k for k in ids if k not in self.built]
        if missing:
            some = self.spark.createDataFrame([(k,) for k in missing], "pattern_id long")
            lists = self.rows(self.occ[size].join(F.broadcast(some), "pattern_id", "left_semi"))
            found = tuples(lists, {k: self.mined[k].pattern for k in missing}, sum(self.entries.get(k, 0) for k in missing) <= NEAR)
            found = stage(found.select("pattern_id", "tree_id", "img", F.col("ends")[size - 2].alias("x_end"), F.col("ends")[size - 1].alias("y_end"), "w"), "tuples")
            self.built |= dict.fromkeys(missing, found)
        some = F.broadcast(self.spark.createDataFrame([(k,) for k in ids], "pattern_id long"))
        return union_all(list({id(t): t for t in map(self.built.__getitem__, ids)}.values())).join(some, "pattern_id", "left_semi")

    def count_parts(self, size: int, possible: list[tuple[Mined, Mined]]) -> None:
        """Only joins whose lists are as long as all of their right parent's can hold all of its occurrences; each is counted once."""
        same = [(q, y) for q, y in possible if q.n_part == -2 and q.sizes[: size - 2] == y.sizes[: size - 2] and q.sizes[-1] == y.sizes[-1] > 0]
        if not same:
            return
        whole = self.occurrences(size - 1, sorted({y.id for _, y in same})).groupBy("pattern_id").agg(F.sum("w").alias("n"))
        part = F.concat(F.slice("img", 1, size - 2), F.slice("img", size, 1)).alias("part")
        parts = self.occurrences(size, sorted({q.id for q, _ in same})).groupBy("pattern_id", "tree_id", part).agg(F.max("w").alias("w")).groupBy("pattern_id").agg(F.sum("w").alias("n"))
        n_whole, n_part = ({r["pattern_id"]: r["n"] for r in df.collect()} for df in (whole, parts))
        for q, y in same:
            y.n_occ, q.n_part = n_whole[y.id], n_part.get(q.id, 0)

    def images(self, size: int, where: list[tuple[int, int, int]]) -> DataFrame:
        at = self.spark.createDataFrame([(p, q, place - 1) for p, q, place in where], "p long, pattern_id long, pos int")
        rows = self.rows(self.occ[size].join(F.broadcast(at.select("pattern_id", "pos").distinct()), ["pattern_id", "pos"], "left_semi"))
        return rows.join(F.broadcast(at), ["pattern_id", "pos"]).select("p", F.col("pattern_id").alias("q"), "tree_id", F.col("begin").alias("root"), "w")

    def lists(self, size: int) -> DataFrame:
        return self.rows(self.occ[size]).select(KEY)


def shape(spark, patterns: dict[int, Pattern]) -> DataFrame:
    """A row for every node of the patterns: parent, depth, number of children."""
    rows = [(k, n, p.parent[n], len(p.ancestors[n]), len(p.children[n])) for k, p in patterns.items() for n in range(p.size)]
    return F.broadcast(spark.createDataFrame(rows, "pattern_id long, pos int, up int, depth int, n_children int"))


def sent(df: DataFrame, near: bool) -> DataFrame:
    """A side of a join, for every task if it is known to be small."""
    return F.broadcast(df) if near else df


def reduced(lists: DataFrame, patterns: dict[int, Pattern], near: bool = False) -> DataFrame:
    """The entries of ``lists`` that some homomorphism inside them uses: semi-joins up the patterns, then down.

    Steps of deep patterns are written, those of flat ones are one plan, whose equal exchanges Spark reuses.
    """
    placed = lists.join(shape(lists.sparkSession, patterns), ["pattern_id", "pos"])
    deepest = max(len(a) for p in patterns.values() for a in p.ancestors)
    levels: list[DataFrame] = [None] * (deepest + 1)
    fed = None
    for depth in range(deepest, -1, -1):
        here = placed.where(F.col("depth") == depth)
        if fed is not None:
            inner = here.where("n_children > 0").join(sent(fed, near), KEY).where("n_found = n_children").select(here.columns)
            here = here.where("n_children = 0").unionByName(inner)
        levels[depth] = stage(here, "up") if deepest > FLAT else here
        above = levels[depth].select("pattern_id", F.col("pos").alias("child"), F.col("up").alias("pos"), "tree_id", F.explode("anc").alias("begin"))
        fed = above.groupBy(KEY).agg(F.size(F.collect_set("child")).alias("n_found"))
    out = [levels[0]]
    for depth in range(1, deepest + 1):
        top = out[-1].select("pattern_id", F.col("pos").alias("up"), "tree_id", F.col("begin").alias("a"))
        below = levels[depth].select(*KEY, "up", F.explode("anc").alias("a")).join(sent(top, near), ["pattern_id", "up", "tree_id", "a"], "left_semi").select(KEY)
        kept = levels[depth].join(F.broadcast(below) if near else below.distinct(), KEY, "left_semi")
        out.append(stage(kept, "down") if FLAT < deepest > depth else kept)
    return union_all(out).select(lists.columns)


def tuples(lists: DataFrame, patterns: dict[int, Pattern], near: bool = False) -> DataFrame:
    """``(pattern_id, tree_id, img, ends, w)``: embeddings of patterns of one size inside their lists."""
    spark, size = lists.sparkSession, next(iter(patterns.values())).size
    occ = lists.where("pos = 0").select("pattern_id", "tree_id", F.array("begin").alias("img"), F.array("end").alias("ends"), "w")
    for n in range(1, size):
        rows = [(k, p.parent[n], [m for m in p.children[p.parent[n]] if m < n]) for k, p in patterns.items()]
        ask = F.broadcast(spark.createDataFrame(rows, "pattern_id long, up int, siblings array<int>"))
        new = lists.where(F.col("pos") == n).select("pattern_id", "tree_id", F.col("begin").alias("b"), F.col("end").alias("e"), F.explode("anc").alias("a"))

        def beside(m: Column) -> Column:
            return is_disjoint(F.get("img", m), F.get("ends", m), F.col("b"), F.col("e"))

        both = occ.join(ask, "pattern_id").withColumn("a", F.get("img", F.col("up"))).join(sent(new, near), ["pattern_id", "tree_id", "a"]).where(F.forall("siblings", beside))
        occ = both.select("pattern_id", "tree_id", F.concat("img", F.array("b")).alias("img"), F.concat("ends", F.array("e")).alias("ends"), "w")
    return occ
