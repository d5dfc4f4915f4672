"""Small literal inputs: worked examples that both engines read."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from schemaloom.registry import values

ANSWERS = values([
    ("a1", "The table lists nations. Thing -> Place -> Country"),
    ("a2", "Thing -> Agent -> Person -> Artist -> Soloist -> Singer -> Tenor and so on."),
    ("a3", "I cannot tell."),
    ("a4", "Either Thing -> Event or rather Thing -> Event -> Concert"),
    ("a5", "Thing -> Event -> Event -> Concert"),
    ("a6", "Place->Region"),
], "ask_id, text")
PATHS = values([
    ("t1", 1, "Place>Country"), ("t2", 1, "Place>Country"), ("t3", 1, "Agent>Person>Artist>Soloist"), ("t4", 1, "Agent>Organization>Artist>Band"),
    ("t4", 2, "Agent>Organization>Band"), ("t5", 1, "CreativeWork>Album"), ("t6", 1, "Event>CreativeWork>Album"), ("t7", 1, "Country>Place"),
    ("t8", 1, "Event>Event>Concert"), ("t9", 1, "Event>Concert>Tour"), ("t10", 1, "Tour>Event>Concert"), ("t11", 1, "Agent>Person>Artist"),
], "table_id, path_no, path")
VERDICTS = values([("CreativeWork", "Event", "no"), ("Country", "Place", "yes"), ("Album", "CreativeWork", "Yes")], "child, parent, verdict")
EDGES = values([
    ("Place", "Thing", 5), ("Country", "Place", 4), ("Region", "Place", 2), ("Agent", "Thing", 9), ("Person", "Agent", 5), ("Organization", "Agent", 4),
    ("Artist", "Person", 3), ("Artist", "Organization", 2), ("Soloist", "Artist", 2), ("Band", "Artist", 2), ("Event", "Thing", 3), ("Concert", "Event", 2),
], "child, parent, weight")
CHILD_ATTRS = values([*(("Parent", f"C{k}", "name") for k in range(10)), *(("Parent", f"C{k}", "age") for k in range(9)), *(("Parent", f"C{k}", "size") for k in range(8)), ("Lone", "Only", "mark")], "parent, child, attr")
CLUSTERS = values([("a", "p1", "g1"), ("b", "p1", "g2"), ("c", "p2", "g2")], "item, predicted, truth")
TREE = values([(1, 1, "Product"), (1, 2, "Event"), (1, 3, "MusicEvent"), (2, 1, "Event"), (2, 2, "MusicEvent"), (3, 1, "Event"), (3, 2, "Event")], "path_no, pos, gt_type")
TREE_TRUTH = values([("Product", "Thing", 1), ("Event", "Thing", 1), ("MusicEvent", "Event", 1)], "child, parent, weight")
RELATIONS = values([
    ("Customer", "country name", "Country", "n:1", 1, 1), ("Supplier", "country name", "Country", "1:1", 1, 0), ("Order", "customer name", "Customer", "n:1", 1, 1),
    ("Order", "clerk", "Supplier", "n:1", 1, 0), ("OrderLine", "part name", "Part", "n:1", 0, 1), ("Supplier", "country name", "Country", "n:1", 0, 1),
], "src, attr, dst, cardinality, predicted, truth")
LEDGER = values([
    ("WDC", "Type", 2000, 1742), ("WDC", "Attr", 3300, 1290), ("WDC", "Rel", 150, 50), ("GDS", "Type", 6000, 2100), ("GDS", "Attr", 10700, 1550), ("GDS", "Rel", 306, 120),
    ("ODS", "Type", 1500, 645), ("ODS", "Attr", 2800, 540), ("ODS", "Rel", 120, 43),
], "corpus, stage, calls, milli_usd")
#: Tree scores that the reference reports, by method, configuration and corpus, in thousandths.
TREE_SCORES = values([
    (m, c, d, s)
    for m, c, row in (
        ("path-first", "G-8B", (687, 682, 782, 633)), ("path-first", "G-14B", (759, 707, 868, 706)), ("path-first", "G-S", (776, 771, 804, 692)), ("path-first", "G-L", (847, 791, 843, 721)),
        ("affinity", "E-gen", (1000, 929, 961, 845)), ("affinity", "E-con", (1000, 895, 924, 813)), ("affinity", "E-join", (836, 848, 896, 821)), ("affinity", "E-swap", (856, 800, 878, 783)),
        ("type-then-taxonomy", "G-14B", (602, 562, 677, 453)), ("type-then-taxonomy", "G-32B", (681, 493, 634, 545)), ("type-then-taxonomy", "G-S", (490, 437, 683, 457)), ("type-then-taxonomy", "G-L", (816, 425, 645, 516)), ("type-then-taxonomy", "G-R", (813, 596, 636, 532)),
    )
    for d, s in zip(("WDC", "GDS", "ODS", "ODL"), row, strict=True)
], "method, config, corpus, score")
MERGES = values([(1, "a", "b", 10, 2), (2, "c", "d", 20, 2), (3, "a", "c", 60, 4), (4, "e", "f", 30, 2), (5, "a", "e", 90, 6)], "step, lft, rgt, height, size")
CARD_STATS = values([("r1", 5, 2, 95), ("r2", 0, 70, 20), ("r3", 10, 0, 15), ("r4", 0, 60, 90), ("r5", None, 0, 90)], "rel, null_pct, multi_pct, uniq_pct")
SPELLINGS = values([("Creative works",), ("CreativeWork",), ("creative_work",), ("Persons",), ("class",), ("music event",)], "name")


def relation(spark: SparkSession, text: str) -> DataFrame:
    return spark.sql(f"SELECT * FROM {text}")


def paths(spark: SparkSession) -> DataFrame:
    return relation(spark, PATHS).withColumn("path", F.split("path", ">"))
