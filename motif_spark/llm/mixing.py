"""Mixing sources to target weights by Sainte-Laguë apportionment, in DataFrame functions only.

Targets come from weights by water filling under a repetition limit. Equal blocks of words are given to
sources by highest quotients, each source's blocks to its shards in the same way, and a seeded order
fills each shard's quota.

Defined cases: a null or empty text has size 0 and is taken 0 times; a null source is a source of its own, last
in order; repeated rows count each on its own; an empty table gives an empty result; a very long text is one
document like any other, taken in part where a quota ends; rows with equal or null ids share one place in the
seeded order (null ids one for each text), told apart by size and then by a hash of the text or row, so reruns
and any partitioning agree. Extra columns are carried; names that clash with those used inside start with `_`.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import checkpoint, words

#: Words in a block, the unit that is apportioned.
BLOCK = 64
#: Words in a shard. Shards grow in number with their source; a task apportions to at most FAN of them, and
#: larger sources go down a tree of that width.
SHARD_WORDS, FAN = 16_384, 4_096
#: Above so many sources their table is joined by shuffle.
BROADCAST_SOURCES = 10_000


def sainte_lague(parties: DataFrame, group: list[str]) -> DataFrame:
    """Adds seats_won: the group's `seats` by highest quotients votes / (2 k + 1), ties by `party`.

    Only quotients near the proportional share are ranked: n parties shift the divisor by a share of
    n / (2 seats) at most, so about 5 n quotients decide, whatever the number of seats.
    """
    w = Window.partitionBy(*group)
    df = parties.withColumns({"_v": F.sum("votes").over(w), "_n": F.count(F.lit(1)).over(w)})
    q, slack = F.col("votes") * F.col("seats") / F.col("_v"), F.col("_n") / F.greatest(F.col("seats"), F.lit(1))
    df = df.withColumns({
        "_low": F.when(F.col("_v") > 0, F.greatest(F.lit(0).cast("long"), F.floor(q * (1 - slack)) - 1)).otherwise(0).cast("long"),
        "_high": F.when(F.col("_v") > 0, F.ceil(q * (1 + slack)) + 1).otherwise(1).cast("long"),
    })
    df = df.withColumn("_open", F.col("seats") - F.sum("_low").over(w))
    ranked = df.withColumn("_k", F.explode(F.sequence("_low", "_high"))).withColumn("_q", F.col("votes") / (2 * F.col("_k") + 1))
    ranked = ranked.withColumn("_rank", F.row_number().over(w.orderBy(F.desc("_q"), "party", "_k")))
    won = F.sum(((F.col("_rank") <= F.col("_open")) & (F.col("votes") > 0)).cast("long"))
    return ranked.groupBy(*group, "party").agg((F.first("_low") + won).alias("seats_won"))


def source_targets(sized: DataFrame, weights=(3, 1, 2), share: float = 1.5, most: float = 2.0) -> DataFrame:
    """source, sid, source_size, target: share of all words by weight, at most `most` times a source's size.

    The filling level solves sum(min(limit, level * weight)) = wanted; that sum is concave in the level, so
    the level is the largest solution over its straight pieces.
    """
    per = sized.groupBy("source").agg(F.sum("size").alias("source_size"))
    order = Window.orderBy(F.col("source").asc_nulls_last())
    everything = Window.partitionBy()
    turn = F.array(*[F.lit(float(x)) for x in weights])
    df = per.withColumn("sid", (F.row_number().over(order) - 1).cast("long"))
    df = df.withColumns({"weight": F.get(turn, (F.col("sid") % len(weights)).cast("int")), "limit": most * F.col("source_size")})
    filled = Window.orderBy(F.col("limit") / F.col("weight"), "sid").rowsBetween(Window.unboundedPreceding, -1)
    wanted, rest = share * F.sum("source_size").over(everything), F.sum("weight").over(everything) - F.coalesce(F.sum("weight").over(filled), F.lit(0.0))
    df = df.withColumn("_level", (wanted - F.coalesce(F.sum("limit").over(filled), F.lit(0.0))) / rest)
    level = F.max("_level").over(everything)
    full = F.sum("limit").over(everything) <= wanted
    return df.withColumn("target", F.when(full, F.col("limit")).otherwise(F.least("limit", level * F.col("weight")))).select("source", "sid", "source_size", "target")


def place(seed: int, key: Column, ties: tuple[str, ...] = ()) -> Column:
    """Seeded order of rows: by key, and by `ties` where it is null, so that such rows are spread."""
    lost = F.concat_ws(":", F.lit("null"), *[F.col(c).cast("string") for c in ties])
    return F.md5(F.concat(F.lit(f"{seed}:"), F.coalesce(key.cast("string"), lost)).cast("binary"))


def mix(docs: DataFrame, weights=(3, 1, 2), share: float = 1.5, most: int = 2, block: int = BLOCK, seed: int = 7, id_col: str = "doc_id", text_col: str = "text", source_col: str = "source") -> DataFrame:
    """doc_id, source, size, source_size, target, taken for every row; taken counts words, repeats included."""
    sized = docs.select(F.col(id_col).alias("doc_id"), F.col(source_col).alias("source"), F.size(words(F.col(text_col))).cast("long").alias("size"), F.xxhash64(text_col).alias("_hash"))
    return mix_sized(checkpoint(sized), weights, share, most, block, seed, ties=("_hash",)).drop("_hash")


def _quotas(votes: DataFrame, levels: int) -> DataFrame:
    """sid, shard, seats_won: each source's seats to its shards, in one step or down a tree of groups of shards."""
    leaves, above = votes, None
    for level in range(levels - 1, -1, -1):
        group = F.floor(F.col("shard") / FAN**level).cast("long")
        own = leaves.groupBy("sid", group.alias("party")).agg(F.sum("votes").alias("votes"), F.first("seats").alias("seats"))
        if above is not None:
            own = own.drop("seats").withColumn("up", F.floor(F.col("party") / FAN).cast("long")).join(above, ["sid", "up"])
        won = sainte_lague(own, ["sid"] if above is None else ["sid", "up"])
        above = won.select("sid", F.col("party").alias("up"), F.col("seats_won").alias("seats"))
    return above.select("sid", F.col("up").alias("shard"), F.col("seats").alias("seats_won"))


def mix_sized(sized: DataFrame, weights, share: float, most: int, block: int, seed: int, key: str = "doc_id", ties: tuple[str, ...] = ()) -> DataFrame:
    """mix() from rows with doc_id, source and size; other columns are carried. Twice read, so keep it saved.

    `ties` are columns that order rows of one place and size.
    """
    sources = source_targets(sized, weights, share, float(most))
    n_blocks = F.round(F.sum("target").over(Window.partitionBy()) / block).cast("long")
    parties = sources.select(F.lit(0).alias("g"), F.col("sid").alias("party"), F.col("target").alias("votes"), n_blocks.alias("seats"))
    shards = F.greatest(F.lit(1), F.ceil(F.col("source_size") / SHARD_WORDS)).cast("long")
    sources = checkpoint(sources.join(sainte_lague(parties, ["g"]).select(F.col("party").alias("sid"), F.col("seats_won").alias("seats")), "sid").withColumn("n_shards", shards))
    small = sources.limit(BROADCAST_SOURCES + 1).count() <= BROADCAST_SOURCES
    largest, levels = sources.agg(F.max("n_shards")).first()[0] or 1, 1
    while FAN**levels < largest:
        levels += 1
    right = sources.withColumnRenamed("source", "_source")
    held = sized.join(F.broadcast(right) if small else right, F.col("source").eqNullSafe(F.col("_source"))).drop("_source")
    held = held.withColumn("_place", place(seed, F.col(key), ties))
    held = held.withColumn("shard", F.conv(F.substring("_place", 1, 8), 16, 10).cast("long") % F.col("n_shards"))
    votes = held.groupBy("sid", "shard", "seats").agg(F.sum("size").alias("votes"))
    quota = _quotas(votes, levels).select("sid", "shard", (F.col("seats_won") * block).alias("quota"))
    own = Window.partitionBy("sid", "shard")
    before = F.sum("size").over(own.orderBy("_place", "size", *ties).rowsBetween(Window.unboundedPreceding, Window.currentRow)) - F.col("size")
    df = held.join(quota, ["sid", "shard"]).withColumns({"_all": F.sum("size").over(own), "_before": before})
    rounds = F.when(F.col("_all") > 0, F.least(F.lit(most), F.floor(F.col("quota") / F.col("_all")))).otherwise(0).cast("long")
    part = F.greatest(F.lit(0).cast("long"), F.least(F.col("size"), F.col("quota") - rounds * F.col("_all") - F.col("_before")))
    taken = F.least(rounds * F.col("size") + part, most * F.col("size")).cast("long")
    return df.withColumn("taken", taken).drop("_place", "shard", "sid", "seats", "n_shards", "quota", "_all", "_before")


def mixed_documents(docs: DataFrame, whole: bool = False, **options) -> DataFrame:
    """The mix as documents: a row for each whole repeat, and one with the first words for a partial repeat.

    With `whole` no text is cut: a partial repeat of half the text or more is the text, a smaller one nothing.
    """
    content = [F.col(f"`{c}`") for c, kind in docs.dtypes if "map<" not in kind]
    named = docs.select(F.struct(*[F.col(f"`{c}`") for c in docs.columns]).alias("_row"), F.xxhash64(*content).alias("_hash"))
    r = lambda c: F.col("_row")[c]
    own = {"doc_id": r("doc_id"), "source": r("source"), "size": F.size(words(r("text"))).cast("long")}
    sized = checkpoint(named.select(*[x.alias(c) for c, x in own.items()], "_hash"))
    opts = {"weights": (3, 1, 2), "share": 1.5, "most": 2, "block": BLOCK, "seed": 7} | options
    # Rows of one id and hash are alike, so their turns may be dealt in any order; what is taken counts down by turn.
    ids = ["doc_id", "source", "size", "_hash"]
    turn = lambda df, by: df.withColumn("_turn", F.row_number().over(Window.partitionBy(*ids).orderBy(by)))
    mixed = turn(mix_sized(sized, **opts, ties=("_hash",)).select(*ids, "taken"), F.desc("taken"))
    taken = mixed.withColumnsRenamed({c: f"_{c}" for c in ids} | {"_turn": "_t"})
    left = turn(named.withColumns(own), "_hash")
    on = F.col("doc_id").eqNullSafe(F.col("_doc_id")) & F.col("source").eqNullSafe(F.col("_source"))
    on = on & (F.col("size") == F.col("_size")) & (F.col("_hash") == F.col("__hash")) & (F.col("_turn") == F.col("_t"))
    df = left.join(taken, on).filter("taken > 0")
    times, rest = F.floor(F.col("taken") / F.col("size")).cast("int"), F.col("taken") % F.col("size")
    if whole:
        times, rest = times + (2 * rest >= F.col("size")).cast("int"), F.lit(0).cast("long")
    lengths = F.concat(F.array_repeat(F.col("size"), times), F.when(rest > 0, F.array(rest)).otherwise(F.array().cast("array<bigint>")))
    df = df.withColumn("_n", F.explode(lengths))
    first = F.array_join(F.slice(words(r("text")), F.lit(1), F.col("_n").cast("int")), " ")
    text = F.when(F.col("_n") == F.col("size"), r("text")).otherwise(first)
    df = df.withColumn("_text", text)
    new = {"text": F.col("_text"), "n_chars": F.length("_text").cast("long")}
    return df.select(*[new[c].alias(c) if c in new else r(c).alias(c) for c in docs.columns])
