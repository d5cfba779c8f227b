"""Mixing sources to target weights by pivotal dependent rounding (DataFrame functions only)."""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from .common import clear, same, save

#: Items folded in one node of the reduction tree, as a power of two.
FAN_BITS = 6
#: Sources up to which their table is broadcast (under 10 MB); beyond, Spark chooses the join.
BROADCAST_SOURCES = 50_000
WORD = r"[^\x20\x09-\x0D]+"


def word_count(text: Column) -> Column:
    """Words of a text, null counting as none."""
    return F.coalesce(F.regexp_count(text, F.lit(WORD)), F.lit(0)).cast("long")


def targets(sized: DataFrame, weights: tuple[float, ...] = (3, 1, 2), share: float = 1.5, cap: float = 2.0) -> DataFrame:
    """Words that each source should give, as ``source, source_size, target``.

    Sources in code-point order (null last) weigh ``weights`` in turn and share ``share`` of all
    words; none exceeds ``cap`` times its own, the excess being dealt again by weight. Levels
    come from one pass over the sources sorted by the level at which each reaches its cap, so no
    iteration and no collection is needed. An empty table gives no row.
    """
    w = F.element_at(F.array(*[F.lit(float(x)) for x in weights]), (F.col("_i") % len(weights) + 1).cast("int"))
    one = sized.groupBy("source").agg(F.sum("size").alias("source_size")).withColumn("_i", F.row_number().over(W.orderBy(F.col("source").asc_nulls_last())) - 1)
    ready = one.withColumn("_w", w).withColumn("_cap", cap * F.col("source_size"))
    order = W.orderBy(F.col("_cap") / F.col("_w"), "_i")
    every = W.partitionBy()
    before = order.rowsBetween(W.unboundedPreceding, -1)
    filled = (
        ready.withColumn("_left", share * F.sum("source_size").over(every) - F.coalesce(F.sum("_cap").over(before), F.lit(0.0)))
        .withColumn("_ws", F.sum("_w").over(every) - F.coalesce(F.sum("_w").over(before), F.lit(0.0)))
        .withColumn("_level", F.col("_left") / F.col("_ws"))
        .withColumn("_open", F.col("_cap") > F.col("_w") * F.col("_level"))
        .withColumn("_final", F.min(F.when(F.col("_open"), F.struct(F.col("_cap") / F.col("_w"), F.col("_i"), F.col("_level")))).over(every)["_level"])
    )
    return filled.select("source", F.col("source_size").cast("long").alias("source_size"), F.coalesce(F.least("_cap", F.col("_w") * F.col("_final")), F.col("_cap")).alias("target"))


def _fold(seed: int, id_type: str) -> str:
    """One node of the tree: items meet one after another, the unsettled one goes on.

    Two items exchange words, not probability: what one gains the other gives, so the expected
    words of the node never change, and the direction is drawn so that each keeps its chance.
    Items come by falling size, so that what is left unsettled in the end is mostly a short text.
    """
    item = f"struct<size:bigint,h:bigint,id:{id_type},p:double>"
    done = f"struct<id:{id_type},size:bigint,extra:int>"
    draw = f"(pmod(xxhash64({seed}L, a.cur.id, x.id, a.cur.h, x.h), 9007199254740992L) / 9007199254740992D)"
    up_i, room_j = "(1 - a.cur.p) * a.cur.size", "x.p * x.size"
    down_i, room_up_j = "a.cur.p * a.cur.size", "(1 - x.p) * x.size"
    gain, loss = f"least({up_i}, {room_j})", f"least({down_i}, {room_up_j})"

    def step(who: str, extra: int, rest: str, p: str) -> str:
        kept = f"named_struct('size', {rest}.size, 'h', {rest}.h, 'id', {rest}.id, 'p', least(1D, greatest(0D, {p})))"
        return f"named_struct('cur', {kept}, 'done', array_append(a.done, named_struct('id', {who}.id, 'size', {who}.size, 'extra', {extra})))"

    rise = f"if({up_i} <= {room_j}, {step('a.cur', 1, 'x', f'x.p - {up_i} / x.size')}, {step('x', 0, 'a.cur', f'a.cur.p + {room_j} / a.cur.size')})"
    fall = f"if({down_i} <= {room_up_j}, {step('a.cur', 0, 'x', f'x.p + {down_i} / x.size')}, {step('x', 1, 'a.cur', f'a.cur.p - {room_up_j} / a.cur.size')})"
    acc = f"struct<cur:{item},done:array<{done}>>"
    meet = f"if({draw} * ({gain} + {loss}) < {loss}, {rise}, {fall})"
    return f"""aggregate(slice(items, 2, size(items)), cast(named_struct('cur', items[0], 'done', cast(array() as array<{done}>)) as {acc}),
        (a, x) -> cast({meet} as {acc}))"""


def pivotal_copies(sized: DataFrame, goals: DataFrame, seed: int = 42) -> DataFrame:
    """Copies of each row so that every source's words meet its target within one document.

    ``sized`` has ``id, source, size``; ``goals`` comes from :func:`targets`. A row is expected
    ``target / source_size`` times: the whole part is given, the rest is rounded by pairwise
    transfers inside leaves of about ``2**FAN_BITS`` rows chosen by hash, and each leaf's one
    unsettled row climbs a tree of the same fan-out, so a source holding any share of the rows is
    spread over as many leaves as it needs. The one row left in
    a source goes to the nearer side, so its words miss the target by half that text at most.
    Rows of size 0 add no words and get the whole part only. Every draw hashes ids and the seed:
    reruns agree. Repeated rows are rounded one by one. Returns ``id, source, size, source_size, target, copies``.
    """
    goals = save(goals, "goals")
    few = goals.limit(BROADCAST_SOURCES + 1).count() <= BROADCAST_SOURCES
    a, b = sized.alias("a"), (F.broadcast(goals) if few else goals).alias("b")
    rate = F.when(F.col("source_size") > 0, F.col("target") / F.col("source_size")).otherwise(F.lit(0.0))
    rows = (
        a.join(b, F.col("a.source").eqNullSafe(F.col("b.source")))
        .select("a.id", "a.source", "a.size", "b.source_size", "b.target")
        .withColumn("_rate", F.round(rate, 12))
        .withColumn("whole", F.floor("_rate").cast("int"))
        .withColumn("p", F.col("_rate") - F.floor("_rate"))
        .drop("_rate")
    )
    rows = save(rows, "rates")
    open_rows = rows.filter("p > 0 AND size > 0")
    largest = open_rows.groupBy("source").count().agg(F.max("count")).first()[0] or 1
    bits = max(0, math.ceil(math.log2(largest / 2**FAN_BITS))) if largest > 2**FAN_BITS else 0
    id_type = dict(sized.dtypes)["id"]
    item = F.struct(F.col("size"), F.expr(f"xxhash64({seed}L, id, size)").alias("h"), F.col("id"), F.col("p"))
    level = open_rows.select("source", item.alias("item"))
    settled = []
    while True:
        leaf = F.shiftrightunsigned(F.col("item.h"), 64 - bits) if bits else F.lit(0).cast("long")
        nodes = level.withColumn("leaf", leaf).groupBy("source", "leaf").agg(F.sort_array(F.collect_list("item"), asc=False).alias("items"))
        folded = save(nodes.select("source", F.expr(_fold(seed, id_type)).alias("r")), "node")
        settled.append(folded.select("source", F.explode("r.done").alias("d")).select("source", "d.id", "d.size", "d.extra"))
        level = folded.select("source", F.col("r.cur").alias("item"))
        if bits == 0:
            break
        bits = max(0, bits - FAN_BITS)
    last = F.when(F.col("item.p") >= 0.5, 1).otherwise(0)
    settled.append(level.select("source", "item.id", "item.size", last.alias("extra")))
    extras = settled[0]
    for more in settled[1:]:
        extras = extras.union(more)
    e = extras.alias("a")
    whole = F.when(F.col("b.source_size") > 0, F.floor(F.round(F.col("b.target") / F.col("b.source_size"), 12)).cast("int")).otherwise(0)
    given = e.join(b, F.col("a.source").eqNullSafe(F.col("b.source"))).select("a.id", "a.source", "a.size", "b.source_size", "b.target", (whole + F.col("a.extra")).cast("int").alias("copies"))
    plain = rows.filter("NOT (p > 0 AND size > 0)").select("id", "source", "size", "source_size", "target", F.col("whole").alias("copies"))
    return plain.union(given)


def mix(docs: DataFrame, seed: int = 42, weights: tuple[float, ...] = (3, 1, 2), share: float = 1.5, cap: float = 2.0) -> DataFrame:
    """How often each document enters the mix, with its size in words.

    Reads ``doc_id, text, source`` (other columns are ignored); null text has size 0, a null
    source is a source of its own. Returns ``id, source, size, source_size, target, copies``.
    """
    sized = save(docs.select(F.col("doc_id").alias("id"), F.col("source"), word_count(F.col("text")).alias("size")), "sized")
    return pivotal_copies(sized, targets(sized, weights, share, cap), seed)


def mixed_documents(docs: DataFrame, seed: int = 42, **params) -> DataFrame:
    """The documents themselves, each repeated as the mix takes it, with the columns it came with.

    Rows with equal ``doc_id``, source and size share the sum of their copies in turn.
    """
    taken = mix(docs, seed, **params).select(F.col("id").alias("_id"), F.col("source").alias("_source"), F.col("size").alias("_size"), "copies")
    turns = taken.groupBy("_id", "_source", "_size").agg(F.sort_array(F.collect_list("copies")).alias("_copies"))
    size, turn, n = (clear(x, docs.columns) for x in ("size", "turn", "n"))
    keyed = docs.withColumn(size, word_count(F.col("text")))
    numbered = keyed.withColumn(turn, F.row_number().over(W.partitionBy("doc_id", "source", size).orderBy("text")))
    on = same([F.col("a.doc_id"), F.col("a.source"), F.col(f"a.`{size}`")], [F.col("b._id"), F.col("b._source"), F.col("b._size")])
    times = F.element_at("b._copies", F.col(f"a.`{turn}`").cast("int"))
    joined = numbered.alias("a").join(turns.alias("b"), on).select(*[F.col(f"a.`{c}`") for c in docs.columns], F.explode(F.array_repeat(F.lit(1), times)).alias(n))
    return joined.select(*[F.col(f"`{c}`") for c in docs.columns])
