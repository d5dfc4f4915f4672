"""The affinity method: column and table vectors, similar pairs, clusters, cut dendrograms, subject links."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from schemaloom.operators.clustering import MOST_BLOCK, distinct_sets, kept_nodes, merges_of, scored_slices, set_distances, silhouette  # noqa: F401


def word_terms(cells: DataFrame) -> DataFrame:
    """(item, term, w): how often each word stands in a column's cells, its header's words as often as it has cells.
    cells: (item, header, value, n), distinct values with their counts."""
    split = lambda c: F.explode(F.split(F.lower(c), "[^a-z0-9]+")).alias("term")
    heads = cells.groupBy("item", "header").agg(F.sum("n").alias("n"))
    every = cells.select("item", "n", split("value")).union(heads.select("item", "n", split("header")))
    return every.where("term <> ''").groupBy("item", "term").agg(F.sum("n").cast("double").alias("w"))


def gram_terms(cells: DataFrame, n: int = 3) -> DataFrame:
    """Character n-grams of the values, each as often as it stands there."""
    text = cells.where(F.length("value") >= n).select("item", "value", "n")
    grams = F.transform(F.sequence(F.lit(1), F.length("value") - (n - 1)), lambda k: F.col("value").substr(k, F.lit(n)))
    return text.select("item", "n", F.explode(grams).alias("term")).groupBy("item", "term").agg(F.sum("n").cast("double").alias("w"))


def prototypes(terms: DataFrame, n: int = 16) -> DataFrame:
    """Terms dealt to n prototypes by hash: (item, term, w), where a term is a prototype's number."""
    proto = F.conv(F.substring(F.md5("term"), 1, 6), 16, 10).cast("int") % n
    return terms.groupBy("item", proto.cast("string").alias("term")).agg(F.sum("w").alias("w"))


def value_terms(cells: DataFrame) -> DataFrame:
    """Each distinct value once."""
    return cells.select("item", F.col("value").alias("term")).distinct().withColumn("w", F.lit(1.0))


def views(cells: DataFrame, k: int = 5) -> DataFrame:
    """(item, view, value): two samples of k distinct values of each column, by hashes with two seeds."""
    both = cells.select("item", "value").distinct().withColumn("view", F.explode(F.array(F.lit(1), F.lit(2))))
    order = Window.partitionBy("item", "view").orderBy(F.md5(F.concat_ws("|", F.col("view").cast("string"), "value")))
    return both.withColumn("_k", F.row_number().over(order)).where(F.col("_k") <= k).select("item", "view", "value")


def containments(values: DataFrame, least: float) -> DataFrame:
    """(a, b, containment): pairs of columns of which more than a share `least` of a's distinct values stand in b. values:
    (item, value), distinct. Values that one column alone holds are out before the join."""
    n = values.groupBy("item").agg(F.count("*").alias("n"))
    common = values.join(values.groupBy("value").agg(F.count("*").alias("m")).where("m > 1").select("value"), "value")
    both = common.select(F.col("item").alias("a"), "value").join(common.select(F.col("item").alias("b"), "value"), "value").where("a <> b").groupBy("a", "b").agg(F.count("*").alias("m"))
    return both.join(n, F.col("a") == F.col("item")).where(F.col("m") / F.col("n") > least).select("a", "b", F.round(F.col("m") / F.col("n"), 6).alias("containment"))


def containments_of(own: DataFrame, other: DataFrame, least: float) -> DataFrame:
    """containments() of own's columns in other's alone. Both: (item, value), repeats or not; cells meet in one shuffle, and
    none are written before it."""
    sides = own.select("value", F.col("item").alias("a"), F.lit(None).cast("string").alias("b")).union(other.select("value", F.lit(None).cast("string"), "item"))
    met = sides.groupBy("value").agg(F.collect_set("a").alias("a"), F.collect_set("b").alias("b")).where(F.size("a") > 0)
    # beside each of the others a null, which counts a's values
    counts = met.select("a", F.concat("b", F.array(F.lit(None).cast("string"))).alias("b")).select(F.explode("a").alias("a"), "b").select("a", F.explode("b").alias("b")).groupBy("a", "b").agg(F.count("*").alias("m"))
    total = counts.withColumn("n", F.max(F.when(F.col("b").isNull(), F.col("m"))).over(Window.partitionBy("a")))
    return total.where("b IS NOT NULL AND a <> b").where(F.col("m") / F.col("n") > least).select("a", "b", F.round(F.col("m") / F.col("n"), 6).alias("containment"))


def cluster_names(members: DataFrame) -> DataFrame:
    """(cluster, name): the commonest name among a cluster's members, of equally common ones the first. members:
    (cluster, name)."""
    counted = members.groupBy("cluster", "name").agg(F.count("*").alias("n"))
    order = Window.partitionBy("cluster").orderBy(F.desc("n"), "name")
    return counted.withColumn("_k", F.row_number().over(order)).where("_k = 1").select("cluster", "name")


def nearest(vectors: DataFrame, queries: DataFrame, k: int, block_rows: int = 4096) -> DataFrame:
    """(q, b, sim): the k rows with the largest product with each query; of equal ones the smaller ids. vectors, queries:
    (vec_id, x). Queries go in blocks of a stated size, each broadcast on its own; a task gives k rows for each query
    and block of rows, and these are ranked again."""
    from collections.abc import Iterator

    import numpy as np

    spark = vectors.sparkSession
    total = queries.count()
    blocks = max(1, -(-total // block_rows))
    out = None
    for at in range(blocks):
        mine = queries if blocks == 1 else queries.where(F.pmod(F.xxhash64("vec_id"), F.lit(blocks)) == at)
        rows = mine.collect()  # about block_rows of them
        held = spark.sparkContext.broadcast((np.array([r.vec_id for r in rows], np.int64), np.array([r.x for r in rows], float)))

        def run(frames: Iterator[pd.DataFrame], held=held) -> Iterator[pd.DataFrame]:
            ids, wanted = held.value
            for frame in frames:
                own, x = frame["vec_id"].to_numpy(), np.stack(frame["x"].to_numpy())
                sims = np.round(wanted @ x.T, 4)
                sims[ids[:, None] == own[None, :]] = -np.inf
                for q, row in zip(ids.tolist(), sims, strict=True):
                    top = np.lexsort((own, -row))[:k]
                    top = top[row[top] > -np.inf]
                    yield pd.DataFrame({"q": q, "b": own[top], "sim": row[top]})

        found = vectors.select("vec_id", "x").mapInPandas(run, "q long, b long, sim double") if rows else None
        out = found if out is None else out.union(found)
    if out is None:
        return spark.createDataFrame([], "q long, b long, sim double")
    order = Window.partitionBy("q").orderBy(F.desc("sim"), "b")
    return out.withColumn("_k", F.row_number().over(order)).where(F.col("_k") <= k).select("q", "b", "sim")


def idf(terms: DataFrame) -> DataFrame:
    """Weights lowered by how many items have a term."""
    n = terms.select("item").distinct().count()
    rare = terms.groupBy("term").agg(F.log(F.lit(float(n)) / F.count("*")).alias("_idf"))
    return terms.join(rare, "term").select("item", "term", (F.col("w") * F.col("_idf")).alias("w")).where("w <> 0")


def subjectness(profile: DataFrame, key: str = "k") -> DataFrame:
    """(key, header, weight): entity columns score by distinctness, less what is missing, and less with their distance
    from the first such column; weights add up to 1, and are equal where no column scores. profile: key, header, pos,
    kind, rho_uniq, rho_null."""
    per = Window.partitionBy(key)
    entity = F.col("kind") == "entity"
    first = profile.withColumn("_first", F.min(F.when(entity, F.col("pos"))).over(per))
    score = F.when(entity, F.greatest(F.col("rho_uniq") - F.col("rho_null"), F.lit(0.0)) / F.sqrt(1 + F.col("pos") - F.col("_first"))).otherwise(0.0)
    scored = first.withColumn("_score", score).withColumn("_sum", F.sum("_score").over(per)).withColumn("_n", F.count("*").over(per))
    return scored.withColumn("weight", F.when(F.col("_sum") > 0, F.col("_score") / F.col("_sum")).otherwise(F.lit(1.0) / F.col("_n"))).drop("_first", "_score", "_sum", "_n")


def unit(terms: DataFrame) -> DataFrame:
    """Terms of each item scaled to length one."""
    norms = terms.groupBy("item").agg(F.sqrt(F.sum(F.col("w") * F.col("w"))).alias("_norm")).where("_norm > 0")
    return terms.join(norms, "item").select("item", "term", (F.col("w") / F.col("_norm")).alias("w"))


def table_vectors(terms: DataFrame, owner: DataFrame) -> DataFrame:
    """Weighted sums of the columns' vectors. owner: (item, table_id, weight)."""
    return terms.join(owner, "item").groupBy(F.col("table_id").alias("item"), "term").agg(F.sum(F.col("w") * F.col("weight")).alias("w"))


def cosine_pairs(vectors: DataFrame, least: float = 0.0, block: list[str] | None = None, digits: int | None = 6) -> DataFrame:
    """(a, b, sim) with sim > least, over shared terms: no pair without a common term is formed. block: columns that
    both must share, such as the top-level type. A term in very many items makes many pairs: beyond some thousand items
    take clustering.near_links over dense vectors, or signature_pairs."""
    block = block or []
    unit = vectors.join(vectors.groupBy("item").agg(F.sqrt(F.sum(F.col("w") * F.col("w"))).alias("_norm")), "item").withColumn("w", F.col("w") / F.col("_norm"))
    left = unit.select(*block, F.col("term"), F.col("item").alias("a"), F.col("w").alias("wa"))
    right = unit.select(*block, F.col("term"), F.col("item").alias("b"), F.col("w").alias("wb"))
    dots = left.join(right, [*block, "term"]).where("a < b").groupBy(*block, "a", "b").agg(F.sum(F.col("wa") * F.col("wb")).alias("sim"))
    found = dots.where(F.col("sim") > least)
    return found if digits is None else found.withColumn("sim", F.round("sim", digits))


def signature_pairs(sets: DataFrame, bands: int = 16, rows: int = 2, least: float = 0.5) -> DataFrame:
    """(a, b, sim): Jaccard pairs found through banded minimum hashes, then compared exactly. sets: (item, terms). Items
    with equal sets count as one. Finds pairs of similarity s with probability 1 - (1 - s^rows)^bands."""
    kinds = sets.withColumn("terms", F.array_sort(F.array_distinct("terms"))).groupBy("terms").agg(F.min("item").alias("item"))
    seeded = lambda k: lambda t: F.xxhash64(t, F.lit(k))
    mins = F.array(*(F.array_min(F.transform("terms", seeded(k))) for k in range(bands * rows)))
    signed = kinds.withColumn("m", mins)
    keys = F.array(*(F.xxhash64(F.lit(b), *(F.get("m", F.lit(b * rows + r)) for r in range(rows))) for b in range(bands)))
    spread = signed.select("item", F.explode(keys).alias("key"))
    found = spread.alias("x").join(spread.alias("y"), F.expr("x.key = y.key AND x.item < y.item")).select(F.col("x.item").alias("a"), F.col("y.item").alias("b")).distinct()
    of = lambda c, n: kinds.select(F.col("item").alias(c), F.col("terms").alias(n))
    both = found.join(of("a", "ta"), "a").join(of("b", "tb"), "b")
    return both.select("a", "b", jaccard(F.col("ta"), F.col("tb")).alias("sim")).where(F.col("sim") >= least)


def jaccard(a: Column, b: Column) -> Column:
    n = F.size(F.array_intersect(a, b))
    return F.round(n / (F.size(a) + F.size(b) - n), 6)


def jaccard_pairs(members: DataFrame) -> DataFrame:
    """(a, b, sim) of items with a common element. members: (item, element)."""
    sized = members.distinct().join(members.groupBy("item").agg(F.count_distinct("element").alias("n")), "item")
    pairs = sized.alias("x").join(sized.alias("y"), F.expr("x.element = y.element AND x.item < y.item"))
    n = F.count("*")
    return pairs.groupBy(F.col("x.item").alias("a"), F.col("y.item").alias("b")).agg(F.round(n / (F.max("x.n") + F.max("y.n") - n), 6).alias("sim"))


def single_links(items: DataFrame, pairs: DataFrame, least: float) -> DataFrame:
    """(item, cluster): items joined through pairs with sim >= least; a cluster's name is its smallest item."""
    from schemaloom.sources.shared import cut

    near = pairs.where(F.col("sim") >= least)
    edges = cut(near.select("a", "b").union(near.select("b", "a")).distinct())
    now = cut(items.select("item", F.col("item").alias("cluster")).distinct())
    while True:
        around = edges.join(now, F.col("b") == F.col("item")).groupBy(F.col("a").alias("item")).agg(F.min("cluster").alias("m"))
        after = cut(now.join(around, "item", "left").select("item", F.least("cluster", F.coalesce("m", "cluster")).alias("cluster")))
        # names of names: halves the way to the smallest item
        up = after.select(F.col("item").alias("cluster"), F.col("cluster").alias("m"))
        after = cut(after.join(up, "cluster").select("item", F.col("m").alias("cluster")))
        if after.join(now, ["item", "cluster"], "left_anti").isEmpty():
            return after
        now = after


def hierarchy(sets: DataFrame, delta: float = 0.15, heights: str = "merge") -> DataFrame:
    """(type_name, node, parent, item): subtypes of each top-level type from its tables' attribute sets. sets:
    (type_name, item, elements). Tables with equal sets are one weighted item, so a block's matrix grows with its distinct
    sets; a node is named by its first table and the number of its tables. Blocks of more than MOST_BLOCK distinct sets
    are refused rather than cut."""

    def build(frame: pd.DataFrame) -> pd.DataFrame:
        frame, kinds, weights = distinct_sets(frame.sort_values("item").reset_index(drop=True))
        if len(kinds) > MOST_BLOCK:
            raise ValueError(f"{len(kinds)} different sets below one type")
        items = frame.groupby("which")["item"].agg(list)
        of = {}

        def name(members) -> str | None:
            if members is None:
                return None
            if members not in of:
                every = [x for k in members for x in items[k]]
                of[members] = f"{min(every)}+{len(every) - 1}"
            return of[members]

        rows = [(frame["type_name"][0], name(m), name(p), x) for m, p in kept_nodes(set_distances(kinds), delta, weights, heights) for k in sorted(m) for x in items[k]]
        return pd.DataFrame(rows, columns=["type_name", "node", "parent", "item"])

    return sets.groupBy("type_name").applyInPandas(build, "type_name string, node string, parent string, item string")


def silhouettes(sets: DataFrame) -> DataFrame:
    """(type_name, height, clusters, score) of every admissible slice of each type's dendrogram."""

    def build(frame: pd.DataFrame) -> pd.DataFrame:
        frame, kinds, weights = distinct_sets(frame)
        distance = set_distances(kinds)
        rows = [(frame["type_name"].iloc[0], round(h, 6), len(set(labels.tolist())), round(v, 6)) for h, labels, v in scored_slices(distance, merges_of(distance, weights), weights) if v is not None]
        return pd.DataFrame(rows, columns=["type_name", "height", "clusters", "score"])

    return sets.groupBy("type_name").applyInPandas(build, "type_name string, height double, clusters long, score double")


def subject_attributes(attributes: DataFrame, columns: DataFrame) -> DataFrame:
    """(type_name, attr_id, is_subject): an attribute is what its tables are about if all of its columns hold entities and
    bear at least half of their tables' weight. attributes: (type_name, attr_id, col); columns: (col, kind, weight)."""
    held = attributes.join(columns.select("col", "kind", "weight"), "col")
    return held.groupBy("type_name", "attr_id").agg(F.bool_and((F.col("kind") == "entity") & (F.col("weight") >= 0.5)).alias("is_subject"))


def table_attribute_sets(attributes: DataFrame, columns: DataFrame) -> DataFrame:
    """(type_name, item, elements): the attributes of each table, sorted. columns: (col, table_id)."""
    held = attributes.join(columns.select("col", "table_id"), "col")
    return held.groupBy("type_name", F.col("table_id").alias("item")).agg(F.sort_array(F.collect_set("attr_id")).alias("elements"))


def tune_links(columns: DataFrame, sims: DataFrame, truth: DataFrame, grid1: list[float], grid2: list[float]) -> DataFrame:
    """(d1, d2, p, r, f1, feasible) for each pair of thresholds, from one pass over the pairs: for each attribute and
    type the share covered at each d1 is taken first. Feasible: precision over a half and recall over a twentieth.
    columns as in subject_links; truth: (src_type, dst_type)."""
    spark = columns.sparkSession
    marks = spark.createDataFrame([(float(x),) for x in grid1], "d1 double")
    both = sims.where(F.col("sim") > min(grid1)).select("a", "b", "sim").union(sims.where(F.col("sim") > min(grid1)).select("b", "a", "sim"))
    subjects = columns.where("is_subject").select(F.col("col").alias("a"), F.col("type_name").alias("dst_type"))
    others = columns.where("NOT is_subject").select(F.col("col").alias("b"), F.col("type_name").alias("src_type"), "attr_id")
    size = others.groupBy("src_type", "attr_id").agg(F.count("*").alias("total"))
    best = both.join(subjects, "a").join(others, "b").where("src_type <> dst_type").groupBy("src_type", "attr_id", "dst_type", "b").agg(F.max("sim").alias("sim"))
    covered = best.crossJoin(F.broadcast(marks)).where("sim > d1").groupBy("d1", "src_type", "attr_id", "dst_type").agg(F.count("*").alias("covered")).join(size, ["src_type", "attr_id"])
    cuts = spark.createDataFrame([(float(x), float(y)) for x in grid1 for y in grid2], "d1 double, d2 double")
    found = covered.join(F.broadcast(cuts), "d1").where(F.col("covered") / F.col("total") > F.col("d2")).select("d1", "d2", "src_type", "dst_type").distinct()
    true = truth.select("src_type", "dst_type").distinct()
    hits = found.join(true.withColumn("hit", F.lit(1)), ["src_type", "dst_type"], "left").groupBy("d1", "d2").agg(F.count("*").alias("n"), F.count("hit").alias("hits"))
    scored = cuts.join(hits, ["d1", "d2"], "left").crossJoin(true.agg(F.count("*").alias("wanted"))).na.fill(0, ["n", "hits"])
    p, r = F.when(F.col("n") > 0, F.col("hits") / F.col("n")).otherwise(0.0), F.when(F.col("wanted") > 0, F.col("hits") / F.col("wanted")).otherwise(0.0)
    scored = scored.withColumn("p", p).withColumn("r", r).withColumn("f1", F.when(F.col("p") + F.col("r") > 0, 2 * F.col("p") * F.col("r") / (F.col("p") + F.col("r"))).otherwise(0.0))
    return scored.select("d1", "d2", *(F.round(c, 6).alias(c) for c in ("p", "r", "f1")), ((F.col("p") > 0.5) & (F.col("r") > 0.05)).alias("feasible"))


def subject_links(columns: DataFrame, sims: DataFrame, delta1: float, delta2: float, lineage: DataFrame | None = None) -> DataFrame:
    """(src_type, attr_id, dst_type, covered, total): an attribute denotes the type whose subject columns are near more
    than a share delta2 of its columns, at more than delta1. columns: (col, type_name, attr_id, is_subject); sims:
    (a, b, sim) of columns, each pair once. lineage: (descendant, ancestor), between which no link is looked for."""
    both = sims.where(F.col("sim") > delta1).select("a", "b").union(sims.where(F.col("sim") > delta1).select(F.col("b").alias("a"), F.col("a").alias("b")))
    subjects = columns.where("is_subject").select(F.col("col").alias("a"), F.col("type_name").alias("dst_type"))
    others = columns.where("NOT is_subject").select(F.col("col").alias("b"), F.col("type_name").alias("src_type"), "attr_id")
    size = others.groupBy("src_type", "attr_id").agg(F.count("*").alias("total"))
    near = both.join(subjects, "a").join(others, "b").where("src_type <> dst_type").groupBy("src_type", "attr_id", "dst_type").agg(F.count_distinct("b").alias("covered"))
    if lineage is not None:
        pairs = lineage.select(F.col("descendant").alias("src_type"), F.col("ancestor").alias("dst_type")).union(lineage.select("ancestor", "descendant")).distinct()
        near = near.join(pairs, ["src_type", "dst_type"], "left_anti")
    return near.join(size, ["src_type", "attr_id"]).where(F.col("covered") / F.col("total") > delta2).select("src_type", "attr_id", "dst_type", "covered", "total")
