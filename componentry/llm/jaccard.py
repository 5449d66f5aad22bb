"""N-gram Jaccard join and near-duplicate classes, exact: no link between different texts is lost.

Sets are the distinct word shingles of whole texts, as 64-bit hashes. Two sets link at intersection >= 3/4 of union.

1. Shingles are counted over the corpus (operators/sets.py). A set of n needs 3n/4 shingles
   in common with a partner; so if more than n/4 of its shingles occur in it alone, it has none and drops out.
   Else its rarest n/4 + 1 shingles, less those that are its own, are its keys: linked sets have a key in common.
2. Equal sets become one class. Classes with a key in common, directly or by others, form a block (components by
   the library's round method). Links never leave a block.
3. Each block is joined by an R-tree over count vectors: shingles hash into groups, a set is the point of its
   group counts, a node keeps the coordinate maxima of what is below. The overlap of two sets is at most the sum
   of their coordinate minima, and of a set and all below a node at most that with the node's maxima: subtrees that
   cannot reach the overlap needed are cut off, surviving pairs are verified on the sets. Pairs that the block has
   joined already need no second proof. A block too large for one task is cut into pages of like set sizes, and pages
   are joined in pairs where their sizes permit a link.
4. Links give components; each text's component is the smallest doc_id in it.

Null and empty texts have no shingles and link with nothing. Rows that repeat an id are rows of their own and fall
in classes by their text. A row without an id links like any other, and names no component. Very long texts are read
whole, a block each; an empty table gives no rows. Only doc_id and text are read, so other columns never clash.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from componentry.functions.graphs import Graph, normalize_edges
from componentry.llm.words import set_key, shingle_sets, text_blocks
from componentry.operators.components import min_owner_balanced
from componentry.operators.sets import BLOCK_BYTES, arrow_rows, set_profiles
from componentry.plans.storage import cut, release, small_side

SIZE = 5
MAX_BLOCK_SETS = 4096
MAX_BLOCK_SHINGLES = 3_000_000
PAGE_SETS = 1024
LEAF = 16

_SETS = 4096
MAX_BLOCK_SHINGLES = 3_000_000
PAGE_SETS = 1024
LEAF = 16

_PARTS = T.StructType([T.StructField("bucket", T.LongType()), T.StructField("batch", T.LongType())] + [T.StructField(c, T.BinaryType()) for c in "abcdef"])
_PROFILE = T.StructType([T.StructField("doc_id", T.LongType()), T.StructField("n_shingles", T.LongType()), T.StructField("set_key", T.BinaryType()), T.StructField("keys", T.ArrayType(T.LongType()))])
_SETS = T.StructType([T.StructField("set_key", T.BinaryType()), T.StructField("n", T.LongType()), T.StructField("shingles", T.BinaryType())])
_PRUNED = T.StructType([T.StructField(n, T.LongType()) for n in ("sets", "pairs", "bounds", "verified")])
_LINKS = T.StructType([T.StructField("src", T.BinaryType()), T.StructField("dst", T.BinaryType())])


class CountTree:
    """R-tree over the count vectors of sets in order of size; a node keeps coordinate maxima and the range of sizes."""

    def __init__(self, sets: list[np.ndarray], leaf: int = LEAF):
        n = np.array([len(s) for s in sets])
        mean = max(1, int(n.mean()))
        self.groups = min(1024, max(32, 1 << (mean // 4).bit_length()))
        doc = np.repeat(np.arange(len(sets)), n)
        group = (np.concatenate(sets) >> np.uint64(40)).astype(np.int64) % self.groups
        points = np.bincount(doc * self.groups + group, minlength=len(sets) * self.groups).reshape(len(sets), self.groups).astype(np.int32)
        # neighbours in the order share size and the largest coordinates, so that maxima stay tight
        self.order = np.lexsort((points.argmax(1), n))
        self.points, self.n, self.leaf = points[self.order], n[self.order], leaf
        self.pairs = self.tested = self.verified = 0  # of all pairs: bounds computed, sets compared
        self.levels = []
        high, low, top = self.points, self.n, self.n
        while len(high) > leaf:
            at = np.arange(0, len(high), leaf)
            high, low, top = np.maximum.reduceat(high, at), np.minimum.reduceat(low, at), np.maximum.reduceat(top, at)
            self.levels.append((high, low, top))

    def _may(self, i: int, high: np.ndarray, low: np.ndarray, top: np.ndarray) -> np.ndarray:
        """Whether set i can link with something under the maxima ``high`` of sizes low to top."""
        size = self.n[i]
        self.tested += len(high)
        # an overlap of 3/7 of both sizes is needed, and sizes within 3/4 of each other
        return (4 * top >= 3 * size) & (3 * low <= 4 * size) & (7 * np.minimum(high, self.points[i]).sum(1) >= 3 * (size + low))

    def partners(self, i: int) -> np.ndarray:
        """Places before ``i`` whose bound permits a link."""
        at = None
        for high, low, top in reversed(self.levels):
            if at is None:
                at = np.arange(len(high))
            else:
                at = (at[:, None] * self.leaf + np.arange(self.leaf)).ravel()
                at = at[at < len(high)]
            at = at[self._may(i, high[at], low[at], top[at])]
        at = np.arange(i) if at is None else (at[:, None] * self.leaf + np.arange(self.leaf)).ravel()
        at = at[at < i]
        return at[self._may(i, self.points[at], self.n[at], self.n[at])]


def linked(a: np.ndarray, b: np.ndarray) -> bool:
    """100 * intersection >= 75 * union of two sorted sets."""
    if len(a) > len(b):
        a, b = b, a
    at = np.searchsorted(b, a)
    both = int((b[np.minimum(at, len(b) - 1)] == a).sum()) if len(b) else 0
    return 100 * both >= 75 * (len(a) + len(b) - both)


def join_sets(sets: list[np.ndarray], tree: CountTree | None = None) -> np.ndarray:
    """Label of each set: sets that links join, through any others here, share one."""
    tree = tree or CountTree(sets)
    label = np.arange(len(sets))
    for i in range(1, len(sets)):
        at = tree.partners(i)
        while len(at := at[label[at] != label[i]]):
            j = at[-1]
            tree.verified += 1
            if linked(sets[tree.order[i]], sets[tree.order[j]]):
                label[label == label[j]] = label[i]
            at = at[:-1]
    out = np.empty(len(sets), np.int64)
    out[tree.order] = label
    return out


def _blocks_of(table: pa.Table) -> Iterator[tuple[list, list[np.ndarray]]]:
    """(set keys, sets) of each block of two sets or more in a bin."""
    block = np.array(table["block"].to_pylist(), object)
    keys, raw = table["set_key"].to_pylist(), table["shingles"].to_pylist()
    order = sorted(range(len(keys)), key=lambda i: (block[i], keys[i]))
    at = 0
    while at < len(order):
        end = at
        while end < len(order) and block[order[end]] == block[order[at]]:
            end += 1
        own = order[at:end]
        at = end
        if len(own) > 1:
            yield [keys[i] for i in own], [np.frombuffer(raw[i], np.uint64) for i in own]


def _solve(key: tuple, table: pa.Table) -> pa.Table:
    """Links of the blocks in one bin: each set with the first of its label."""
    out = []
    for keys, sets in _blocks_of(table):
        heads: dict[int, bytes] = {}
        for k, x in zip(keys, join_sets(sets).tolist(), strict=True):
            if heads.setdefault(x, k) != k:
                out.append((heads[x], k))
    return pa.Table.from_batches([arrow_rows(_LINKS, out)])


def _prune(key: tuple, table: pa.Table) -> pa.Table:
    """What the tree does in the blocks of one bin: sets, pairs, bounds computed, pairs verified."""
    total = np.zeros(4, np.int64)
    for _, sets in _blocks_of(table):
        tree = CountTree(sets)
        join_sets(sets, tree)
        total += (len(sets), len(sets) * (len(sets) - 1) // 2, tree.tested, tree.verified)
    return pa.table({n: [int(x)] for n, x in zip(_PRUNED.names, total, strict=True)})


def _blocks(classes: DataFrame) -> DataFrame:
    """(set_key, block) of the classes that share a key with another."""
    keyed = classes.select("set_key", F.explode("keys").alias("key"))
    heads = keyed.groupBy("key").agg(F.min("set_key").alias("head"), F.count(F.lit(1)).alias("c")).where("c > 1").drop("c")
    links = cut(normalize_edges(keyed.join(heads, "key").select(F.col("head").alias("src"), F.col("set_key").alias("dst"))), "links")
    return min_owner_balanced(Graph(links), stats=False).components.select(F.col("id").alias("set_key"), F.col("component").alias("block"))


def _sets(docs: DataFrame, size: int) -> DataFrame:
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for a, b in text_blocks(batch, "text", BLOCK_BYTES):
                hashes, offsets = shingle_sets(batch.slice(a, b - a)["text"], size)
                own = [hashes[offsets[i] : offsets[i + 1]] for i in range(len(offsets) - 1)]
                yield arrow_rows(_SETS, [(set_key(s), len(s), s.tobytes()) for s in own])

    return docs.select("text").mapInArrow(run, _SETS)


def _pages(placed: DataFrame) -> DataFrame:
    """(set_key, block, bin, a, b): the sets of large blocks in pages of like size, each with every page whose sizes permit a link."""
    level = F.floor(F.log("n") / math.log(4 / 3))
    rows = placed.withColumn("level", level)
    parts = rows.groupBy("block", "level").agg(F.ceil(F.count(F.lit(1)) / PAGE_SETS).alias("parts"))
    page = F.col("level") * (1 << 32) + F.pmod(F.xxhash64("set_key"), F.col("parts"))
    paged = cut(rows.join(parts, ["block", "level"]).select("set_key", "block", "n", page.alias("page")), "pages")
    pages = paged.groupBy("block", "page").agg(F.min("n").alias("lo"), F.max("n").alias("hi"))
    other = pages.select("block", F.col("page").alias("b"), F.col("lo").alias("lo_b"), F.col("hi").alias("hi_b"))
    pairs = pages.join(other, "block").where("b >= page and 3 * lo_b <= 4 * hi and 3 * lo <= 4 * hi_b").select("block", F.col("page").alias("a"), "b")
    both = [paged.withColumnRenamed("page", end).join(pairs if end == "a" else pairs.where("a <> b"), ["block", end]) for end in ("a", "b")]
    return both[0].unionByName(both[1]).select("set_key", "block", F.xxhash64("block").alias("bin"), "a", "b")


def _candidates(src: DataFrame, size: int) -> tuple[DataFrame, DataFrame, DataFrame, list[DataFrame]]:
    """(profiles, classes, sets by the bin in which they are joined, cuts that the last reads)."""
    profiles = cut(set_profiles(src, size=size), "profiles")
    classes = cut(profiles.where("n_shingles > 0").groupBy("set_key").agg(F.min("doc_id").alias("rep"), F.first("n_shingles").alias("n"), F.first("keys", ignorenulls=True).alias("keys")), "classes")
    blocks = cut(_blocks(classes.where("keys is not null")).join(classes.select("set_key", "rep", "n"), "set_key"), "blocks")
    # only texts that stand for a class in a block are read again
    wanted = cut(blocks.select(F.col("rep").alias("_rep")).distinct(), "wanted")
    again = src.join(small_side(wanted, 16), F.col("doc_id").eqNullSafe(F.col("_rep")), "left_semi")
    totals = blocks.groupBy("block").agg(F.count(F.lit(1)).alias("sets"), F.sum("n").alias("total"))
    totals = cut(totals.withColumn("large", (F.col("sets") > MAX_BLOCK_SETS) | (F.col("total") > MAX_BLOCK_SHINGLES)), "totals")
    facts = totals.agg(F.coalesce(F.sum(F.when(~F.col("large"), F.col("total"))), F.lit(0)).alias("small"), F.count_if("large").alias("large")).first()
    placed = blocks.join(totals.select("block", "large"), "block").select("set_key", "block", "large", "n")
    bins = max(1, facts["small"] // 400_000)
    sets = _sets(again, size).select("set_key", "shingles").dropDuplicates(["set_key"])
    none = F.lit(-1).cast("long")
    where = placed.where("not large").select("set_key", "block", F.pmod(F.xxhash64("block"), F.lit(bins)).alias("bin"), none.alias("a"), none.alias("b"))
    if facts["large"]:
        where = where.unionByName(_pages(placed.where("large")))
    return profiles, classes, sets.join(where, "set_key"), [blocks, wanted, totals]


def near_duplicates(docs: DataFrame, size: int = SIZE) -> DataFrame:
    """(doc_id, n_shingles, component_id), a row for each row of ``docs`` (doc_id, text)."""
    profiles, classes, joined, held = _candidates(docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text"), size)
    links = cut(normalize_edges(joined.groupBy("bin", "a", "b").applyInArrow(_solve, _LINKS)), "links")
    labels = min_owner_balanced(Graph(links), stats=False).components.select(F.col("id").alias("set_key"), F.col("component").alias("label"))
    named = cut(classes.select("set_key", "rep").join(labels, "set_key", "left").select("set_key", "rep", F.coalesce("label", "set_key").alias("label")), "named")
    least = named.groupBy("label").agg(F.min("rep").alias("component_id"))
    book = named.join(least, "label").select("set_key", "component_id")
    release(*held, links, classes)
    return profiles.join(book, "set_key", "left").select("doc_id", "n_shingles", F.when(F.col("n_shingles") > 0, F.col("component_id")).otherwise(F.col("doc_id")).alias("component_id"))


def tree_work(docs: DataFrame, size: int = SIZE) -> DataFrame:
    """One row: sets in blocks, their pairs, the bounds that the R-trees compute instead, and the pairs left to verify."""
    _, _, joined, _ = _candidates(docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text"), size)
    return joined.groupBy("bin", "a", "b").applyInArrow(_prune, _PRUNED).agg(*(F.sum(c).alias(c) for c in _PRUNED.names))


def keep_one(docs: DataFrame) -> DataFrame:
    """``docs`` (all columns) with one document of each class of near duplicates: that with the smallest doc_id.

    Of rows that repeat both id and text one stays; texts without a word and rows without an id stay as they are.
    """
    found = cut(near_duplicates(docs), "near")
    gone = cut(found.where("doc_id is not null and n_shingles > 0").groupBy(F.col("doc_id").alias("_id")).agg(F.bool_and(F.coalesce(F.col("component_id") != F.col("doc_id"), F.lit(False))).alias("out"), F.count(F.lit(1)).alias("c")).where("out or c > 1"), "gone")
    packed = docs.select(F.struct(*(F.col(f"`{c}`") for c in docs.columns)).alias("_row"), F.col("doc_id").cast("long").alias("_doc"), "text")
    flagged = packed.join(small_side(gone, 24), F.col("_doc") == F.col("_id"), "left").where("out is null or not out")
    single = flagged.where("_id is null").select("_row.*")
    repeated = flagged.where("_id is not null").withColumn("_twin", F.row_number().over(Window.partitionBy("_doc", F.md5("text")).orderBy("_doc"))).where("_twin = 1").select("_row.*")
    return single.unionByName(repeated)


def op4_jaccard_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    return near_duplicates(spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text"))


_UPPER, _SMALL = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"
OP4_SQL = rf"""
WITH RECURSIVE d AS MATERIALIZED (SELECT row_number() OVER () AS rid, doc_id, coalesce(regexp_extract_all(translate(text, '{_UPPER}', '{_SMALL}'), '[^\x20\x09-\x0D]+'), []) AS w FROM documents),
s AS MATERIALIZED (SELECT DISTINCT rid, g FROM (SELECT rid, unnest(CASE WHEN len(w) >= 5 THEN list_transform(range(1, len(w) - 3), lambda i: array_to_string(w[i:i + 4], ' ')) WHEN len(w) > 0 THEN [array_to_string(w, ' ')] ELSE [] END) AS g FROM d)),
n AS MATERIALIZED (SELECT rid, count(*) AS n FROM s GROUP BY rid),
p AS (SELECT x.rid AS a, y.rid AS b, count(*) AS c FROM s x JOIN s y ON x.g = y.g AND x.rid < y.rid GROUP BY x.rid, y.rid),
l AS MATERIALIZED (SELECT a, b FROM p JOIN n i ON i.rid = a JOIN n j ON j.rid = b WHERE 100 * c >= 75 * (i.n + j.n - c)),
nb AS MATERIALIZED (SELECT a AS id, b AS nbr FROM l UNION ALL SELECT b, a FROM l),
cc(id, label) USING KEY (id) AS (SELECT DISTINCT id, id AS label FROM nb UNION
  SELECT nb.nbr, min(cc.label) FROM cc JOIN nb ON nb.id = cc.id JOIN recurring.cc AS o ON o.id = nb.nbr WHERE cc.label < o.label GROUP BY nb.nbr)
SELECT d.doc_id, coalesce(n.n, 0) AS n_shingles, CASE WHEN n.n IS NULL THEN d.doc_id ELSE min(d.doc_id) OVER (PARTITION BY coalesce(cc.label, d.rid)) END AS component_id
FROM d LEFT JOIN n ON n.rid = d.rid LEFT JOIN cc ON cc.id = d.rid
"""
