"""Type hierarchies from is-a paths: merging, pruning, closure, membership, common ancestors."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from schemaloom.sources.shared import cut

ROOT = "Thing"
#: Edges up to which the driver walks a hierarchy itself.
SMALL_EDGES = 20_000


def extract_path(text: Column, max_types: int = 5, root: str = ROOT) -> Column:
    """The longest arrow-separated path in free text, without the root, cut after max_types; null if there is none."""
    found = F.regexp_extract_all(text, F.lit(r"[A-Za-z][A-Za-z ]*(?:-> *[A-Za-z][A-Za-z ]*)+"), F.lit(0))
    paths = F.transform(found, lambda x: F.transform(F.split(x, "->"), lambda t: F.trim(t)))
    longest = F.aggregate(paths, F.array().cast("array<string>"), lambda a, b: F.when(F.size(b) > F.size(a), b).otherwise(a))
    types = F.filter(longest, lambda t: t != root)
    return F.when(F.size(types) > 0, F.slice(types, 1, max_types))


def malformed(path: Column) -> Column:
    """Whether a type stands twice in the path."""
    return F.size(path) != F.size(F.array_distinct(path))


def align_name(name: Column) -> Column:
    """One spelling of a type's name: single spaces, capitals at word starts, no plural s."""
    clean = F.initcap(F.trim(F.regexp_replace(name, "[ _-]+", " ")))
    return F.regexp_replace(F.regexp_replace(clean, "([^s])s$", "$1"), " ", "")


def path_edges(paths: DataFrame, root: str = ROOT) -> DataFrame:
    """(table_id, path_no, child, parent) of each step of each path, from the root down; paths: table_id, path_no,
    path. A step that a path repeats counts once."""
    steps = F.transform(F.col("path"), lambda t, k: F.struct(t.alias("child"), F.when(k == 0, F.lit(root)).otherwise(F.get(F.col("path"), k - 1)).alias("parent")))
    return paths.select("table_id", "path_no", F.inline(F.array_distinct(steps)))


def merge_edges(edges: DataFrame, weight_by: str = "path") -> DataFrame:
    """(child, parent, weight): weights count paths, or tables. Summed before the only shuffle, which moves a row for
    each edge and task."""
    weight = F.count("*") if weight_by == "path" else F.count_distinct("table_id")
    return edges.groupBy("child", "parent").agg(weight.alias("weight"))


def prune_self_loops(edges: DataFrame) -> DataFrame:
    return edges.where("child <> parent")


def prune_inverse(edges: DataFrame) -> DataFrame:
    """Of two edges that contradict each other the heavier; of equal ones that whose parent's name comes first."""
    pair = Window.partitionBy(F.least("child", "parent"), F.greatest("child", "parent")).orderBy(F.desc("weight"), "parent")
    return edges.withColumn("_k", F.row_number().over(pair)).where("_k = 1").drop("_k")


def verify_edges(edges: DataFrame, verdicts: DataFrame) -> DataFrame:
    """Without the edges that a completer denied; edges to the root are not asked about."""
    denied = verdicts.where("lower(verdict) = 'no'").select("child", "parent")
    return edges.join(denied, ["child", "parent"], "left_anti")


def small(edges: DataFrame, columns: list[str], bound: int = SMALL_EDGES) -> list | None:
    """The rows, if there are few enough for the driver: a hierarchy has a row for each pair of types, not for each
    table. Beyond the bound the callers join instead."""
    rows = edges.select(*columns).distinct().limit(bound + 1).collect()
    return rows if len(rows) <= bound else None


def ways_up(steps: list) -> dict[str, dict[str, int]]:
    """Every type's ancestors with the length of the shortest way."""
    parents: dict[str, list[str]] = {}
    for child, parent in steps:
        parents.setdefault(child, []).append(parent)
    out = {}
    for start in parents:
        found, frontier, k = {}, [start], 0
        while frontier:
            k += 1
            frontier = list(dict.fromkeys(p for t in frontier for p in parents.get(t, ()) if p not in found))
            found.update(dict.fromkeys(frontier, k))
        out[start] = found
    return out


def reach(edges: DataFrame, most_rounds: int = 64, bound: int = SMALL_EDGES) -> DataFrame:
    """(descendant, ancestor, dist): every ancestor, with the length of the shortest way; a type on a cycle is its own
    ancestor. Up to `bound` edges are walked on the driver. Beyond, each round joins, and writes its new pairs, so plans
    do not grow; rounds are the hierarchy's depth."""
    schema = "descendant string, ancestor string, dist int"
    few = small(edges, ["child", "parent"], bound)
    if few is not None:
        return edges.sparkSession.createDataFrame([(d, a, k) for d, up in ways_up(few).items() for a, k in up.items()], schema)
    steps = cut(edges.select("child", "parent").distinct())
    frontier = cut(steps.select(F.col("child").alias("descendant"), F.col("parent").alias("ancestor"), F.lit(1).alias("dist")))
    known = frontier
    for k in range(2, most_rounds):
        further = frontier.join(steps, F.col("ancestor") == F.col("child")).select("descendant", F.col("parent").alias("ancestor"), F.lit(k).alias("dist")).distinct()
        frontier = cut(further.join(known.select("descendant", "ancestor"), ["descendant", "ancestor"], "left_anti"))
        if frontier.isEmpty():
            return known
        known = known.union(frontier)
    raise RuntimeError(f"the hierarchy is deeper than {most_rounds}")


def break_cycles(edges: DataFrame, bound: int = SMALL_EDGES) -> DataFrame:
    """Drops, again and again, the lightest edge among those that lie on cycles; of equal ones the last by name."""
    few = small(edges, ["child", "parent", "weight"], bound)
    if few is not None:
        left = [tuple(r) for r in few]
        while True:
            up = ways_up([e[:2] for e in left])
            on = [e for e in left if e[0] in up.get(e[1], {})]
            if not on:
                return edges.sparkSession.createDataFrame(left, edges.select("child", "parent", "weight").schema)
            light = min(e[2] for e in on)
            left.remove(max(e for e in on if e[2] == light))
    now = edges
    while True:  # one edge of each strongly connected component a round: components don't touch each other's order
        ways = reach(now, bound=bound).select("descendant", "ancestor")
        back = ways.select(F.col("ancestor").alias("descendant"), F.col("descendant").alias("ancestor"))
        part = ways.join(back, ["descendant", "ancestor"]).groupBy(F.col("descendant").alias("child")).agg(F.min("ancestor").alias("part"))
        of = lambda c, n: part.select(F.col("child").alias(c), F.col("part").alias(n))
        on = now.join(of("child", "_p"), "child").join(of("parent", "_q"), "parent").where("_p = _q")
        order = Window.partitionBy("_p").orderBy("weight", F.desc("child"), F.desc("parent"))
        worst = cut(on.withColumn("_k", F.row_number().over(order)).where("_k = 1").select("child", "parent"))
        if worst.isEmpty():
            return now
        now = cut(now.join(worst, ["child", "parent"], "left_anti"))


def attach_orphans(edges: DataFrame, root: str = ROOT) -> DataFrame:
    """Types that are parents but nobody's children hang under the root, with the weight of their heaviest edge."""
    children = edges.select(F.col("child").alias("parent")).distinct()
    lost = edges.where(F.col("parent") != root).join(children, "parent", "left_anti")
    return edges.unionByName(lost.groupBy("parent").agg(F.max("weight").alias("weight")).select(F.col("parent").alias("child"), F.lit(root).alias("parent"), "weight"))


def top_level(edges: DataFrame, root: str = ROOT) -> DataFrame:
    return edges.where(F.col("parent") == root).select(F.col("child").alias("type_name")).distinct()


def leaf_types(paths: DataFrame) -> DataFrame:
    return paths.select(F.element_at("path", -1).alias("type_name"), "table_id").distinct()


def type_tables(paths: DataFrame, edges: DataFrame, root: str = ROOT) -> DataFrame:
    """Tables of each type: those whose path ends in it or below it in the hierarchy that is left."""
    leaves = leaf_types(paths)
    ways = reach(edges).where(F.col("ancestor") != root)
    up = leaves.join(ways, F.col("type_name") == F.col("descendant")).select(F.col("ancestor").alias("type_name"), "table_id")
    return leaves.union(up).distinct()


def levels(edges: DataFrame, root: str = ROOT, bound: int = SMALL_EDGES) -> DataFrame:
    """(type_name, level): the longest way down from the root, which must be free of cycles."""
    few = small(edges, ["child", "parent"], bound)
    if few is not None:
        known, now = {}, {root}
        for k in range(1, 65):
            now = {r.child for r in few if r.parent in now}
            if not now:
                return edges.sparkSession.createDataFrame(list(known.items()), "type_name string, level int")
            known.update(dict.fromkeys(now, k))
        raise RuntimeError("a cycle")
    now = cut(edges.where(F.col("parent") == root).select(F.col("child").alias("type_name"), F.lit(1).alias("level")).distinct())
    known = now
    for k in range(2, 64):
        now = cut(edges.join(now, F.col("parent") == F.col("type_name")).select(F.col("child").alias("type_name"), F.lit(k).alias("level")).distinct())
        if now.isEmpty():
            return known.groupBy("type_name").agg(F.max("level").alias("level"))
        known = known.union(now)
    raise RuntimeError("a cycle")


def common_ancestor(items: DataFrame, edges: DataFrame, root: str = ROOT) -> DataFrame:
    """One type for each item: items: (item, type_name), several types each. The deepest type that is each of them or
    above it; ties by name; the root if nothing else is common."""
    ways = reach(edges).select("descendant", "ancestor")
    own = edges.select(F.explode(F.array("child", "parent")).alias("descendant")).distinct().withColumn("ancestor", F.col("descendant"))
    lines = ways.union(own)
    wanted = items.distinct()
    n = wanted.groupBy("item").agg(F.count("*").alias("n"))
    common = wanted.join(lines, F.col("type_name") == F.col("descendant")).groupBy("item", "ancestor").agg(F.count("*").alias("m"))
    deep = levels(edges, root).withColumnRenamed("type_name", "ancestor")
    ranked = common.join(n, "item").where("m = n").join(deep, "ancestor", "left")
    order = Window.partitionBy("item").orderBy(F.desc(F.coalesce("level", F.lit(0))), "ancestor")
    return ranked.withColumn("_k", F.row_number().over(order)).where("_k = 1").select("item", F.col("ancestor").alias("type_name"))


def promote(attributes: DataFrame, edges: DataFrame, theta: float = 0.9, root: str = ROOT) -> DataFrame:
    """(type_name, attr_name, inherited): attributes that a share of at least theta of a type's direct subtypes have
    are the type's too; from the deepest types up. attributes: (type_name, attr_name)."""
    deep = cut(levels(edges, root))
    steps = edges.where(F.col("parent") != root).select("child", "parent").distinct()
    size = steps.groupBy("parent").agg(F.count("*").alias("children"))
    held = cut(attributes.select("type_name", "attr_name").distinct().withColumn("inherited", F.lit(False)))
    depth = deep.agg(F.max("level")).first()[0] or 0
    for level in range(depth - 1, 0, -1):
        at = deep.where(F.col("level") == level).select(F.col("type_name").alias("parent"))
        below = steps.join(at, "parent").join(held, F.col("child") == F.col("type_name"))
        share = below.groupBy("parent", "attr_name").agg(F.count_distinct("child").alias("n")).join(size, "parent").where(F.col("n") >= F.lit(theta) * F.col("children"))
        up = share.select(F.col("parent").alias("type_name"), "attr_name", F.lit(True).alias("inherited"))
        held = cut(held.union(up).groupBy("type_name", "attr_name").agg(F.bool_or("inherited").alias("inherited")))
    return held
