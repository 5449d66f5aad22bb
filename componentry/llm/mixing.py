"""Mixing sources to target weights by a low-discrepancy schedule over shuffled equal-token blocks.

Each source's documents are put in a hashed order and read as one stream of words, cut into blocks of
``block_words``. A source's target asks for so many blocks; the shares of all blocks are its interval of
[0, 1). Slot i of the mix has the van der Corput point of i (its bits reversed), and goes to the source
in whose interval the point lies; the slots of a source are ranked, and rank k takes block k of the stream, which
starts again at its end. The interval of a source is walked instead of searched: its points are enumerated
and turned back into slots, so neither a range join nor a broadcast is needed. Slots beyond what a source asks for
are handed to the sources that a schedule of finite length left short; a source's last block is trimmed to its target.

Prefix sums and ranks are taken in two levels (part totals, then within parts), so a source with a third
of all rows is spread over many tasks. Everything is DataFrame code.

Sources are weighed by code point with null last. Null text has size 0; documents of size 0 are never
taken. Repeated rows are documents of their own. An empty table, or one without words, takes nothing. A very long text
covers many blocks, each at the slot of its own. Only the columns named are read, so others never clash.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from componentry.llm.words import WORD
from componentry.plans.storage import cut, small_side

WEIGHTS = (5, 2, 1)
BUDGET = 1.5
MOST_PASSES = 2
BLOCK_WORDS = 512
SEED = 17
PART_ROWS = 200_000
_CHUNK_BITS = 15


def size_column(text: str = "text"):
    return F.coalesce(F.regexp_count(F.col(text), F.lit(WORD)), F.lit(0)).cast("long")


def targets(totals: DataFrame, weights: tuple = WEIGHTS, budget: float = BUDGET, most: float = MOST_PASSES) -> DataFrame:
    """(source, source_size, weight, target) of each source total (source, source_size).

    Each target is the lesser of its cap and weight * level; the level is where the targets add up to the
    budget, found in the order in which sources reach their caps.
    """
    every = Window.orderBy(F.col("source").asc_nulls_last())
    weight = F.array(*(F.lit(float(w)) for w in weights))[F.pmod(F.row_number().over(every) - 1, F.lit(len(weights)))]
    rows = totals.withColumn("weight", weight).withColumn("cap", most * F.col("source_size"))
    by_cap = Window.orderBy(F.col("cap") / F.col("weight"), F.col("source").asc_nulls_last())
    before = by_cap.rowsBetween(Window.unboundedPreceding, -1)
    after = by_cap.rowsBetween(0, Window.unboundedFollowing)
    whole = Window.partitionBy()
    level = (F.sum("source_size").over(whole) * budget - F.coalesce(F.sum("cap").over(before), F.lit(0.0))) / F.sum("weight").over(after)
    # the first source whose cap lies at or over the level of all from it on sets the level
    rows = rows.withColumn("level", level).withColumn("open", F.col("level") <= F.col("cap") / F.col("weight"))
    first = F.min_by("level", F.when(F.col("open"), F.col("cap") / F.col("weight"))).over(whole)
    target = F.least(F.col("cap"), F.coalesce(F.col("weight") * first, F.col("cap")))
    return rows.select("source", "source_size", "weight", target.alias("target"))


def streams(sized: DataFrame, seed: int = SEED, rows: int = 0) -> DataFrame:
    """``sized`` (row_id, doc_id, source, size) with ``at``, the words before it in its source's shuffled stream.

    A stream is cut by leading digits of the hash, as many as bring a stream of all ``rows`` to PART_ROWS a part.
    """
    digits = 2
    while digits < 8 and rows > PART_ROWS * 16**digits:
        digits += 1
    h = F.md5(F.concat_ws(":", F.lit(seed), "doc_id", "size"))
    rows = sized.withColumn("_h", h).withColumn("_part", F.substring("_h", 1, digits))
    sums = rows.groupBy("source", "_part").agg(F.sum("size").alias("_s"))
    before = Window.partitionBy("source").orderBy("_part").rowsBetween(Window.unboundedPreceding, -1)
    base = sums.select(F.col("source").alias("_src"), F.col("_part").alias("_p"), F.coalesce(F.sum("_s").over(before), F.lit(0)).alias("_base"))
    inner = Window.partitionBy("source", "_part").orderBy("_h", "doc_id", "size", "row_id").rowsBetween(Window.unboundedPreceding, -1)
    placed = rows.withColumn("_in", F.coalesce(F.sum("size").over(inner), F.lit(0)))
    joined = placed.join(small_side(cut(base, "bases"), 64), F.col("source").eqNullSafe(F.col("_src")) & (F.col("_part") == F.col("_p")))
    return joined.withColumn("at", F.col("_base") + F.col("_in")).drop("_h", "_part", "_src", "_p", "_base", "_in")


def _reverse_bits(x, bits: int):
    """The low ``bits`` (at most 62) bits of x in reverse order, by swaps of halves."""
    for k, mask in ((1, 0x5555555555555555), (2, 0x3333333333333333), (4, 0x0F0F0F0F0F0F0F0F), (8, 0x00FF00FF00FF00FF), (16, 0x0000FFFF0000FFFF)):
        m = F.lit(mask)
        x = F.shiftrightunsigned(x, k).bitwiseAND(m).bitwiseOR(F.shiftleft(x.bitwiseAND(m), k))
    x = F.shiftrightunsigned(x, 32).bitwiseOR(F.shiftleft(x, 32))
    return F.shiftrightunsigned(x, 64 - bits)


def schedule(aims: DataFrame, block_words: int = BLOCK_WORDS) -> DataFrame:
    """(slot, source, rank): the source and block of each slot of the mix, for ``aims`` (source, target)."""
    asked = aims.select("source", F.ceil(F.col("target") / block_words).alias("blocks")).where("blocks > 0")
    upto = Window.orderBy(F.col("source").asc_nulls_last())
    asked = cut(asked.withColumn("last", F.sum("blocks").over(upto)), "asked")
    n = asked.agg(F.max("last")).first()[0] or 0
    if n > 1 << 61:
        raise ValueError("over 2^61 blocks: use larger blocks")
    bits = max(1, (n - 1).bit_length())
    size = 1 << bits
    # a source's points are those u of [0, 2^bits) with (first * 2^bits) / n <= u < (last * 2^bits) / n
    edge = lambda c: F.ceil(c.cast("decimal(38,0)") * F.lit(size).cast("decimal(20,0)") / F.lit(max(1, n)).cast("decimal(20,0)")).cast("long")
    own = asked.select("source", "blocks", edge(F.col("last") - F.col("blocks")).alias("lo"), edge(F.col("last")).alias("hi"))
    step = 1 << _CHUNK_BITS
    chunks = own.withColumn("c", F.explode(F.sequence(F.lit(0).cast("long"), F.greatest(F.lit(0), F.expr(f"(hi - lo - 1) div {step}")))))
    chunks = chunks.repartition("source", "c").withColumn("a", F.col("lo") + F.col("c") * step)
    points = chunks.where("a < hi").select("source", "blocks", F.explode(F.sequence("a", F.least(F.col("a") + step, F.col("hi")) - 1)).alias("u"))
    slots = points.select("source", "blocks", _reverse_bits(F.col("u"), bits).alias("slot")).where(F.col("slot") < n)
    # ranks within a source by slot: chunk totals first, then within chunks
    slots = slots.withColumn("_part", F.shiftright("slot", _CHUNK_BITS))
    sums = slots.groupBy("source", "_part").agg(F.count(F.lit(1)).alias("_n"))
    before = Window.partitionBy("source").orderBy("_part").rowsBetween(Window.unboundedPreceding, -1)
    base = sums.select(F.col("source").alias("_src"), F.col("_part").alias("_p"), F.coalesce(F.sum("_n").over(before), F.lit(0)).alias("_base"))
    inner = Window.partitionBy("source", "_part").orderBy("slot")
    ranked = slots.withColumn("_r", F.row_number().over(inner)).join(base, F.col("source").eqNullSafe(F.col("_src")) & (F.col("_part") == F.col("_p")))
    ranked = cut(ranked.select("slot", "source", "blocks", (F.col("_base") + F.col("_r") - 1).alias("rank")), "slots")
    fits = ranked.where("rank < blocks").select("slot", "source", "rank")
    # slots over a source's count and blocks that lack a slot are equally many, and few: the schedule's discrepancy
    spare = ranked.where("rank >= blocks").select("slot", F.row_number().over(Window.orderBy("slot")).alias("k"))
    got = ranked.groupBy("source").agg(F.count(F.lit(1)).alias("got"))
    short = asked.join(got.withColumnRenamed("source", "_src"), F.col("source").eqNullSafe(F.col("_src")), "left").select("source", "blocks", F.coalesce("got", F.lit(0)).alias("got")).where("got < blocks")
    short = short.select("source", F.explode(F.sequence(F.col("got").cast("long"), F.col("blocks") - 1)).alias("rank"))
    short = short.withColumn("k", F.row_number().over(Window.orderBy("rank", F.col("source").asc_nulls_last())))
    return fits.unionByName(spare.join(short, "k").select("slot", "source", "rank"))


def mix(sized: DataFrame, *, weights: tuple = WEIGHTS, budget: float = BUDGET, most: int = MOST_PASSES, block_words: int = BLOCK_WORDS, seed: int = SEED) -> tuple[DataFrame, DataFrame]:
    """(pieces, documents) for ``sized`` (row_id, doc_id, source, size), which should be a cut.

    ``pieces`` is the mix: (slot, offset, row_id, doc_id, source, begin, length), each a run of words of one document;
    read by (slot, offset). ``documents`` has each row with source_size and target.
    """
    aims = cut(targets(sized.groupBy("source").agg(F.sum("size").alias("source_size")), weights, budget, most), "targets")
    aim = small_side(aims.select(F.col("source").alias("_src"), "source_size", "target"), 64)
    documents = sized.join(aim, F.col("source").eqNullSafe(F.col("_src"))).drop("_src")
    placed = streams(documents.where("size > 0"), seed, sized.count())
    # a document in pass p of the stream covers [at + p * source_size, + size); the target ends what is taken
    take = F.round("target").cast("long")
    passes = placed.withColumn("_pass", F.explode(F.sequence(F.lit(0), F.lit(most - 1)))).withColumn("lo", F.col("at") + F.col("_pass") * F.col("source_size"))
    passes = passes.withColumn("hi", F.least(F.col("lo") + F.col("size"), take)).where("lo < hi")
    blocks = passes.withColumn("rank", F.explode(F.sequence(F.expr(f"lo div {block_words}"), F.expr(f"(hi - 1) div {block_words}"))))
    first = F.greatest(F.col("lo"), F.col("rank") * block_words)
    last = F.least(F.col("hi"), (F.col("rank") + 1) * block_words)
    parts = blocks.select("row_id", "doc_id", "source", "rank", (first - F.col("rank") * block_words).alias("offset"), (first - F.col("lo")).alias("begin"), (last - first).alias("length"), "_pass")
    slots = schedule(aims, block_words).select("slot", F.col("source").alias("_src"), F.col("rank").alias("_rank"))
    pieces = parts.join(slots, (F.col("rank") == F.col("_rank")) & F.col("source").eqNullSafe(F.col("_src"))).drop("_src", "_rank", "rank")
    return pieces, documents


def sizes(docs: DataFrame, text: str = "text") -> DataFrame:
    """(row_id, doc_id, source, size) of each row, cut: texts are read once."""
    return cut(docs.select(F.monotonically_increasing_id().alias("row_id"), F.col("doc_id").cast("long").alias("doc_id"), "source", size_column(text).alias("size")), "sizes")


def op1_source_mix(spark: SparkSession, sf_dir: str) -> DataFrame:
    """doc_id, size, source_size, target, taken, and where the mix has the row: its first and last slot and the number of its pieces (null, null, 0: not taken)."""
    sized = sizes(spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "source", "text"))
    pieces, documents = mix(sized)
    # the words of a row: its pieces summed up; rows without a piece take none
    facts = (("doc_id", "long"), ("size", "long"), ("source_size", "long"), ("target", "double"))
    none = documents.select("row_id", *(c for c, _ in facts), F.lit(0).cast("long").alias("length"), F.lit(None).cast("long").alias("slot"))
    some = pieces.select("row_id", *(F.lit(None).cast(t).alias(c) for c, t in facts), "length", "slot")
    rows = none.unionByName(some).groupBy("row_id").agg(*(F.max(c).alias(c) for c, _ in facts), F.sum("length").alias("taken"), F.min("slot").alias("first_slot"), F.max("slot").alias("last_slot"), F.count("slot").alias("n_pieces"))
    return rows.drop("row_id")


OP1_SQL = rf"""
WITH d AS (SELECT row_number() OVER () AS rid, doc_id, source, coalesce(len(regexp_extract_all(text, '[^\x20\x09-\x0D]+')), 0) AS size FROM documents),
t AS (SELECT source, CAST(sum(size) AS BIGINT) AS source_size FROM d GROUP BY source),
w AS (SELECT *, list_extract([{', '.join(f'{float(x)}::DOUBLE' for x in WEIGHTS)}], CAST((row_number() OVER (ORDER BY source ASC NULLS LAST) - 1) % {len(WEIGHTS)} + 1 AS INTEGER)) AS weight, {float(MOST_PASSES)}::DOUBLE * source_size AS cap FROM t),
v AS (SELECT *, cap / weight AS r, (sum(source_size) OVER () * {BUDGET}::DOUBLE - coalesce(sum(cap) OVER (ORDER BY cap / weight, source ASC NULLS LAST ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0.0)) / sum(weight) OVER (ORDER BY cap / weight, source ASC NULLS LAST ROWS BETWEEN CURRENT ROW AND UNBOUNDED FOLLOWING) AS level FROM w),
g AS (SELECT source, source_size, least(cap, coalesce(weight * (SELECT arg_min(level, r) FROM v WHERE level <= r), cap)) AS target FROM v),
s AS MATERIALIZED (SELECT d.*, g.source_size, g.target, CAST(floor(g.target + 0.5) AS BIGINT) AS take, CAST(sum(d.size) OVER (PARTITION BY d.source ORDER BY md5(concat_ws(':', '{SEED}', CAST(d.doc_id AS VARCHAR), CAST(d.size AS VARCHAR))), d.doc_id, d.size, d.rid) - d.size AS BIGINT) AS pos FROM d JOIN g ON g.source IS NOT DISTINCT FROM d.source),
b AS (SELECT source, CAST(ceil(target / {BLOCK_WORDS}) AS BIGINT) AS blocks FROM g),
iv AS MATERIALIZED (SELECT source, blocks, CAST(sum(blocks) OVER o - blocks AS BIGINT) AS first, CAST(sum(blocks) OVER o AS BIGINT) AS last, CAST(sum(blocks) OVER () AS BIGINT) AS n, greatest(1, length(bin(CAST(sum(blocks) OVER () - 1 AS BIGINT)))) AS bits FROM b WHERE blocks > 0 WINDOW o AS (ORDER BY source ASC NULLS LAST)),
-- slot i has the point of its bits in reverse, and goes to the source in whose interval the point lies
pt AS MATERIALIZED (SELECT i AS slot, list_sum(list_transform(range(bits), lambda k: ((i >> k) & 1) << (bits - 1 - k)))::HUGEINT AS u, (1::HUGEINT << bits) AS whole, n FROM (SELECT DISTINCT n, bits FROM iv), LATERAL (SELECT unnest(range(n)) AS i)),
own AS MATERIALIZED (SELECT slot, iv.source, iv.blocks, row_number() OVER (PARTITION BY iv.source ORDER BY slot) - 1 AS rank FROM pt JOIN iv ON u * pt.n >= first::HUGEINT * whole AND u * pt.n < last::HUGEINT * whole),
spare AS (SELECT slot, row_number() OVER (ORDER BY slot) AS k FROM own WHERE rank >= blocks),
got AS (SELECT source, count(*) AS got FROM own GROUP BY source),
short AS (SELECT source, rank, row_number() OVER (ORDER BY rank, source ASC NULLS LAST) AS k FROM (SELECT iv.source, unnest(range(coalesce(got, 0), blocks)) AS rank FROM iv LEFT JOIN got ON got.source IS NOT DISTINCT FROM iv.source)),
slots AS MATERIALIZED (SELECT slot, source, rank FROM own WHERE rank < blocks UNION ALL SELECT slot, source, rank FROM spare JOIN short USING (k)),
runs AS (SELECT rid, source, pos + p * source_size AS lo, least(pos + p * source_size + size, take) AS hi FROM s, range({MOST_PASSES}) r(p) WHERE size > 0),
bl AS (SELECT rid, source, lo, hi, unnest(range(lo // {BLOCK_WORDS}, (hi - 1) // {BLOCK_WORDS} + 1)) AS rank FROM runs WHERE lo < hi),
pc AS (SELECT rid, slot, least(hi, (bl.rank + 1) * {BLOCK_WORDS}) - greatest(lo, bl.rank * {BLOCK_WORDS}) AS length FROM bl JOIN slots ON slots.rank = bl.rank AND slots.source IS NOT DISTINCT FROM bl.source),
q AS (SELECT rid, sum(length) AS taken, min(slot) AS first_slot, max(slot) AS last_slot, count(*) AS n_pieces FROM pc GROUP BY rid)
SELECT doc_id, size, source_size, target, CAST(coalesce(taken, 0) AS BIGINT) AS taken, first_slot, last_slot, coalesce(n_pieces, 0) AS n_pieces FROM s LEFT JOIN q USING (rid)
"""


def mixed_documents(docs: DataFrame) -> DataFrame:
    """``docs`` as the mix takes them: a row for each pass over a document, its text cut where the target ends.

    Whole passes keep the text as it is; only the one document at which a source's target ends is shortened. Rows are
    dealt to parts by a hash, and each part has them in the order of the slots at which they begin: every part is
    a sample of the mix in the mix's order.
    """
    keyed = docs.select(F.struct(*(F.col(f"`{c}`") for c in docs.columns)).alias("_row"), F.xxhash64("doc_id", "source", "text").alias("_key"), "doc_id", "source", size_column().alias("size"))
    # equal rows are interchangeable: they are numbered within their key
    twin = Window.partitionBy("_key").orderBy("_key")
    sized = cut(keyed.select("_key", "doc_id", "source", "size").withColumn("_twin", F.row_number().over(twin)).withColumn("row_id", F.monotonically_increasing_id()), "sizes")
    pieces, _ = mix(sized.select("row_id", F.col("doc_id").cast("long").alias("doc_id"), "source", "size"))
    runs = pieces.groupBy("row_id", "_pass").agg(F.sum("length").alias("_words"), F.min_by("slot", "begin").alias("_slot"))
    runs = cut(runs.join(sized.select("row_id", "_key", "_twin", "size"), "row_id").select("_key", "_twin", "_slot", "_words", (F.col("_words") == F.col("size")).alias("_whole")), "runs")
    rows = keyed.select("_row", "_key").withColumn("_twin", F.row_number().over(twin))
    taken = rows.join(runs, ["_key", "_twin"]).sortWithinPartitions("_slot")
    words = F.regexp_extract_all(F.col("_row.text"), F.lit(r"[\x20\x09-\x0D]*[^\x20\x09-\x0D]+"), F.lit(0))
    head = F.array_join(F.slice(words, F.lit(1), F.col("_words").cast("int")), "")
    text = F.when(F.col("_whole"), F.col("_row.text")).otherwise(head)
    return taken.select(*((text.alias("text") if c == "text" else F.col(f"_row.`{c}`")) for c in docs.columns))
