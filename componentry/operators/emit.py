"""Hash steps (what each key sends) and merge steps (what each key keeps), as plan fragments.

A state has rows (key, member): ``member`` is in the cluster that ``key`` holds. Clusters stay in this long
form, so no step holds one cluster in memory. ``owner``, where a state has it, is the key's least member.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

BOTH = ("key", "member")


def pairs(df: DataFrame, *ends: tuple[str, str]) -> DataFrame:
    """One output row for each (key column, member column) of ``ends``."""
    return df.select(F.explode(F.array(*(F.struct(F.col(a).alias("key"), F.col(b).alias("member")) for a, b in ends))).alias("m")).select("m.key", "m.member")


# -- hash steps


def neighbor_min(state: DataFrame, nbrs: DataFrame, root_forward: bool = False, wide: bool = False) -> DataFrame:
    """Each key sends its least member to its graph neighbours.

    ``root_forward``: also to the least member it had one round before (column ``before``); ``wide``: also
    to every member of its cluster.
    """
    least = state.groupBy("key").agg(F.min("member").alias("least"))
    out = nbrs.join(least.hint("shuffle_hash"), nbrs["id"] == least["key"]).select(F.col("nbr").alias("key"), F.col("least").alias("member"))
    if root_forward:
        out = out.unionByName(state.groupBy("key").agg(F.min("member").alias("least"), F.min("before").alias("before")).where("before is not null").select(F.col("before").alias("key"), F.col("least").alias("member")))
    if wide:
        out = out.unionByName(with_owner(state.select(*BOTH)).select(F.col("member").alias("key"), F.col("owner").alias("member")))
    return out


def all_members(state: DataFrame) -> DataFrame:
    """Each member of a cluster gets the whole cluster: an equi self-join on the key."""
    other = state.select("key", F.col("member").alias("to"))
    return state.select(*BOTH).join(other, "key").select(F.col("to").alias("key"), "member")


def unlike(state: DataFrame) -> DataFrame:
    """``state`` without the keys that hold the same cluster as a lesser key (by its size and two sums of hashes)."""
    total = lambda seed: F.sum(F.xxhash64(F.lit(seed), "member").cast("decimal(38,0)"))
    marks = state.groupBy("key").agg(F.count(F.lit(1)).alias("n"), total(1).alias("h1"), total(2).alias("h2"))
    return state.join(marks.groupBy("n", "h1", "h2").agg(F.min("key").alias("key")).select("key"), "key", "left_semi").select(*BOTH)


def all_members_once(state: DataFrame) -> DataFrame:
    """As all_members after repeats are dropped: of the keys that hold one and the same cluster, one sends it."""
    return all_members(unlike(state))


def min_owner(state: DataFrame) -> DataFrame:
    """The cluster goes to its least member, which goes to the members: narrow, as the state has ``owner``."""
    return pairs(state, ("owner", "member"), ("member", "owner"))


def upper_core(state: DataFrame) -> DataFrame:
    """As min_owner, for members no less than the key."""
    return pairs(state.where("member >= key"), ("owner", "member"), ("member", "owner"))


def min_owner_balanced(state: DataFrame, tau: int) -> DataFrame:
    """As min_owner up to ``tau`` members (column ``size``); beyond, the members over the key stay with the key."""
    stay = (F.col("size") > tau) & (F.col("member") > F.col("key"))
    to = F.when(stay, F.col("key")).otherwise(F.col("owner"))
    return pairs(state.withColumn("to", to), ("to", "member"), ("member", "to"))


def tell(state: DataFrame, nbrs: DataFrame, root_forward: bool = False, wide: bool = False) -> DataFrame:
    """neighbor_min over a state with ``owner`` (and ``before``, for ``root_forward``): each key has one row whose member is the owner."""
    least = state.where("member = owner")
    out = nbrs.join(least.select("key", "owner").hint("shuffle_hash"), nbrs["id"] == F.col("key")).select(F.col("nbr").alias("key"), F.col("owner").alias("member"))
    if root_forward:
        out = out.unionByName(least.where("before is not null").select(F.col("before").alias("key"), F.col("owner").alias("member")))
    if wide:
        out = out.unionByName(state.select(F.col("member").alias("key"), F.col("owner").alias("member")))
    return out


# -- merge steps


def with_owner(state: DataFrame, size: bool = False) -> DataFrame:
    """``state`` with the least member (and the size) of each key; needs no exchange where rows are dealt by key."""
    w = Window.partitionBy("key")
    out = state.withColumn("owner", F.min("member").over(w))
    return out.withColumn("size", F.count(F.lit(1)).over(w)) if size else out


def merge_union(messages: DataFrame, size: bool = False) -> DataFrame:
    """Union of what a key received: dealt by key once, repeats dropped, the owner attached in the same stage."""
    return with_owner(messages.repartition("key").dropDuplicates(list(BOTH)), size)


def merge_split(messages: DataFrame, heads: DataFrame, parts: int) -> DataFrame:
    """merge_union with sizes, in which the rows of hubs are dealt over ``parts`` by their member.

    ``heads`` (key, head, all, self) has the few hubs with what their rows must know together: owner, size, and whether the
    hub holds itself. That it does is said once for each row of its neighbours, so those rows are left out and put back once.
    """
    rows = messages.join(F.broadcast(heads), "key", "left").where("head is null or member <> key")
    salt = F.when(F.col("head").isNull(), F.lit(0)).otherwise(F.pmod(F.xxhash64("member"), F.lit(parts)))
    rows = rows.unionByName(heads.where("self").withColumn("member", F.col("key"))).withColumn("_salt", salt)
    rows = rows.select(*BOTH, "head", "all", "_salt").repartition("key", "_salt").distinct()
    w = Window.partitionBy("key", "_salt")
    owner, size = F.coalesce("head", F.min("member").over(w)), F.coalesce("all", F.count(F.lit(1)).over(w))
    return rows.select(*BOTH, owner.alias("owner"), size.alias("size"))


def merge_sorted(messages: DataFrame) -> DataFrame:
    """merge_union over one sort by (key, member): repeats are adjacent, and a key's first row is its owner."""
    w = Window.partitionBy("key").orderBy("member")
    rows = messages.repartition("key").withColumn("_p", F.lag("member").over(w)).withColumn("owner", F.first("member").over(w))
    return rows.where("_p is null or _p <> member").drop("_p")


def merge_min_label(messages: DataFrame) -> DataFrame:
    """Only the least id received; summed up before the exchange."""
    return messages.groupBy("key").agg(F.min("member").alias("member"))


def merge_keep_plus_min(state: DataFrame, messages: DataFrame) -> DataFrame:
    """A key keeps its cluster and adds the least id received: one exchange. ``owner`` is its least member, ``before`` that of ``state``."""
    w = Window.partitionBy("key")
    kind = state.schema["key"].dataType
    rows = state.select(*BOTH, F.col("owner").alias("_was")).unionByName(messages.withColumn("_was", F.lit(None).cast(kind))).repartition("key")
    rows = rows.withColumn("_heard", F.min(F.when(F.col("_was").isNull(), F.col("member"))).over(w)).withColumn("before", F.max("_was").over(w))
    rows = rows.where("_was is not null or member = _heard")
    return rows.select(*BOTH, F.least("before", "_heard").alias("owner"), "before").distinct()
