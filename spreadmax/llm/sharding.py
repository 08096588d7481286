"""Sharding by balanced label propagation.

Documents with equal texts are linked. Members of a group are interchangeable
for a law of counts, so the graph is kept as one row per group with its number
of members in every shard. In each round the members of a group vote for the
shard that holds most of them, and move there as far as quotas allow: flows
between shards are scaled until no shard takes in more than it has room for and
gives away. At the end, groups that a shard holding a member has room for go
there whole. Documents without links fill what is left, which makes the counts
of all shards equal or one apart, exactly.

Defined cases: a null text counts as empty (size 1) and is linked to empty
texts; a group larger than a shard is spread over as few shards as quotas
allow; repeated rows are documents of their own; null ids are ordered first;
fewer documents than shards leave some shards empty; an empty table gives an
empty result.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from spreadmax.session import written

SHARDS = 8
ROUNDS = 16
#: Shards with less room than this part of their quota take no further votes.
NEARLY_FULL = 16
#: Rows that are ranked in one task.
BUCKET_ROWS = 32_768
GROUP = ["g", "text_crc32", "size"]


def _ranked(df: DataFrame, by: list[str], total: Column, least: int = 1, carry: list[str] | None = None) -> DataFrame:
    """`df` with `rank`: 0, 1, 2, ... within `by`, in an order that hashes give.

    A group of any size is ranked in buckets of about BUCKET_ROWS: counts of buckets
    add up to where each begins, so no task holds a whole group. `total`: rows of
    the group; `carry`: columns that depend on `by` alone.
    """
    buckets = F.greatest(F.lit(least), F.ceil(total / BUCKET_ROWS)).cast("long")
    dealt = df.withColumn("__b", F.pmod(F.xxhash64("doc_id", "text_crc32"), buckets))
    keys = [*by, "__b"]
    sizes = dealt.groupBy(*keys).agg(F.count(F.lit(1)).alias("__n"))
    before = Window.partitionBy(*by).orderBy("__b").rowsBetween(Window.unboundedPreceding, -1)
    begins = sizes.select(*keys, F.coalesce(F.sum("__n").over(before), F.lit(0)).alias("__at"))
    own = Window.partitionBy(*keys).orderBy(F.xxhash64("doc_id"), "doc_id")
    return (
        dealt.join(begins, keys).withColumn("rank", F.col("__at") + F.row_number().over(own) - 1).drop("__at", "__b")
    )


def _interval(rank: Column, sums: list[int]) -> Column:
    """The first shard whose cumulative count exceeds the rank."""
    out = F.lit(len(sums) - 1)
    for s in range(len(sums) - 2, -1, -1):
        out = F.when(rank < sums[s], s).otherwise(out)
    return out.cast("int")


def _sums(counts: list[int]) -> list[int]:
    out, at = [], 0
    for c in counts:
        at += c
        out.append(at)
    return out


def _even(n: int, shards: int) -> list[int]:
    return [n // shards + (s < n % shards) for s in range(shards)]


def _wish(shards: int, open_to: list[bool], salt: int) -> Column:
    """The shard that a group's members vote for: most members among those open; of equal ones a hash takes one,
    so that the wishes of many groups for an exchange balance."""
    is_open = F.array(*[F.lit(x) for x in open_to])
    lot = lambda i: F.xxhash64("g", "text_crc32", "size", i, F.lit(f"wish{salt}"))
    ranked = F.transform("c", lambda x, i: F.struct(F.when(F.get(is_open, i), x).otherwise(-1).alias("x"), lot(i).alias("lot"), i.alias("i")))
    return F.array_max(ranked)["i"].cast("int")


def _moves(wish: Column, share, salt: int) -> Column:
    """Members that leave each shard for the wish; `share(from)` is the part of the flow that quotas allow."""

    def leaving(x: Column, i: Column) -> Column:
        top = F.get(F.col("c"), wish)
        wants = (i != wish) & (x <= top)  # a tie follows the wish from any shard, a closed one too
        part = share(i)
        chance = F.pmod(F.xxhash64("g", "text_crc32", "size", i, F.lit(salt)), F.lit(1 << 20)) / float(1 << 20)
        some = F.when(part >= 1, x).otherwise(F.floor(x * part + chance))
        return F.when(wants, some).otherwise(0).cast("long")

    return F.transform("c", leaving)


def _flows(want: list[list[int]], room: list[int]) -> list[list[float]]:
    """Shares of the wanted moves [from][to] such that no shard takes in more than it has room for and gives away."""
    k = len(room)
    share = [[1.0] * k for _ in range(k)]
    for _ in range(200):
        done = True
        for t in range(k):
            come = sum(share[s][t] * want[s][t] for s in range(k))
            go = sum(share[t][u] * want[t][u] for u in range(k))
            if come > room[t] + go + 1e-9:
                done = False
                for s in range(k):
                    share[s][t] *= (room[t] + go) / come
        if done:
            break
    else:
        share = [[0.0] * k for _ in range(k)]
    limited = [any(share[s][t] < 1 for s in range(k)) for t in range(k)]
    return [[share[s][t] * (0.97 if limited[t] else 1) for t in range(k)] for s in range(k)]


def propagate(groups: DataFrame, quota: list[int], rounds: int = ROUNDS) -> tuple[DataFrame, list[dict]]:
    """groups: GROUP columns and c, members by shard, none above quota. Gives the groups after propagation and a trace."""
    shards = len(quota)

    def loads(df: DataFrame) -> list[int]:
        row = df.agg(*[F.sum(F.get("c", F.lit(s))).alias(f"s{s}") for s in range(shards)]).head()
        return [int(row[s] or 0) for s in range(shards)]

    trace: list[dict] = []
    now = loads(groups)
    idle, swap = 0, False  # first into shards with room; when that ends, exchanges between full ones
    for r in range(rounds):
        room = [q - n for q, n in zip(quota, now, strict=True)]
        # a shard that is all but full would draw votes that it cannot take
        open_to = [swap or x * NEARLY_FULL > q for x, q in zip(room, quota, strict=True)]
        moved = 0
        if any(open_to):
            groups, now, moved = _round(groups, quota, now, room, open_to, loads, r)
            trace.append({"round": r, "swap": swap, "moved": moved, "loads": now})
        idle = 0 if moved else idle + 1
        if idle == 4:
            break
        swap = idle % 2 == 1
    return _gathered(groups, quota, now, loads, trace)


def _gathered(groups: DataFrame, quota: list[int], now: list[int], loads, trace: list[dict]) -> tuple[DataFrame, list[dict]]:
    """Groups that a shard holding a member has room for go there whole, until there is none.

    In each pass a group tries one of these shards; those of a shard are taken in an order of
    hashes while their members fit. Each pass with a candidate gathers one at least.
    """
    shards = len(quota)
    total = F.aggregate("c", F.lit(0).cast("long"), lambda a, b: a + b)
    while True:
        room = [q - n for q, n in zip(quota, now, strict=True)]
        if not any(x > 0 for x in room):
            return groups, trace
        free = F.array(*[F.lit(x).cast("long") for x in room])
        fits = F.filter(
            F.transform("c", lambda x, i: F.struct((total - x).alias("come"), F.xxhash64("g", "text_crc32", "size", i).alias("lot"), i.cast("int").alias("to"))),
            lambda f: (F.get("c", f["to"]) > 0) & (f["come"] > 0) & (f["come"] <= F.get(free, f["to"])),
        )
        could = groups.withColumn("f", F.array_min(fits)).filter("f is not null")
        could = written(could.select(*GROUP, "f.to", "f.come"), "could")
        number = could.count()
        if not number:
            return groups, trace
        buckets = max(1, -(-number // BUCKET_ROWS))
        dealt = could.withColumn("b", F.pmod(F.xxhash64(*GROUP, F.lit("gather")), F.lit(buckets)))
        before = Window.partitionBy("to").orderBy("b").rowsBetween(Window.unboundedPreceding, -1)
        begins = dealt.groupBy("to", "b").agg(F.sum("come").alias("n")).select("to", "b", F.coalesce(F.sum("n").over(before), F.lit(0)).alias("at"))
        own = Window.partitionBy("to", "b").orderBy("come", *GROUP).rowsBetween(Window.unboundedPreceding, 0)
        upto = F.col("at") + F.sum("come").over(own)
        taken = dealt.join(begins, ["to", "b"]).withColumn("upto", upto).filter(F.col("upto") <= F.get(free, F.col("to")))
        there = F.transform("c", lambda x, i: F.when(F.col("to").isNull(), x).when(i == F.col("to"), total).otherwise(0).cast("long"))
        moved = F.coalesce("come", F.lit(0)).alias("moved")
        after = groups.join(taken.select(*GROUP, "to", "come"), GROUP, "left").select(*GROUP, there.alias("c"), moved)
        after = written(after, "gathered")
        groups, now = after.drop("moved"), loads(after)
        trace.append({"round": len(trace), "swap": False, "moved": int(after.agg(F.sum("moved")).head()[0] or 0), "loads": now})


def _round(groups: DataFrame, quota: list[int], now: list[int], room: list[int], open_to: list[bool], loads, salt: int):
    """One round of votes and moves: the groups after it, the loads, and how many members moved."""
    shards = len(quota)
    wished = groups.withColumn("wish", _wish(shards, open_to, salt))
    every = _moves(F.col("wish"), lambda i: F.lit(1.0), salt)
    sums = wished.groupBy("wish").agg(*[F.sum(F.get(every, F.lit(s))).alias(f"s{s}") for s in range(shards)])
    want = [[0] * shards for _ in range(shards)]
    for row in sums.collect():  # one row per shard
        for s in range(shards):
            want[s][row["wish"]] = int(row[f"s{s}"] or 0)
    if not any(map(any, want)):
        return groups, now, 0
    share = _flows(want, room)
    for _ in range(6):
        flat = F.array(*[F.lit(share[s][t]) for s in range(shards) for t in range(shards)])
        gone = _moves(F.col("wish"), lambda i, flat=flat: F.get(flat, i * shards + F.col("wish")), salt)
        total = F.aggregate("m", F.lit(0).cast("long"), lambda a, b: a + b)
        tried = wished.withColumn("m", gone).select(
            *GROUP, F.transform("c", lambda x, i: x - F.get("m", i) + F.when(i == F.col("wish"), total).otherwise(0)).alias("c"), total.alias("moved")
        )
        tried = written(tried, "shards")
        then = loads(tried)
        if all(n <= q for n, q in zip(then, quota, strict=True)):
            return tried.drop("moved"), then, int(tried.agg(F.sum("moved")).head()[0] or 0)
        share = [[x * 0.7 for x in row] for row in share]  # hashes took more than planned
    return groups, now, 0


def cut_links(groups: DataFrame) -> DataFrame:
    """links and cut: pairs of linked documents, and those that lie in different shards."""
    pairs = lambda n: n * (n - 1) / 2
    n = F.aggregate("c", F.lit(0).cast("long"), lambda a, b: a + b)
    together = F.aggregate("c", F.lit(0.0), lambda a, b: a + pairs(b))
    return groups.agg(F.sum(pairs(n)).alias("links"), F.sum(pairs(n) - together).alias("cut"))


def shard_documents(docs: DataFrame, shards: int = SHARDS, rounds: int = ROUNDS) -> DataFrame:
    """doc_id, size, text_crc32, law ('rows'), shard, slot, grown_shard (null), group_size, links_cut.

    links_cut: the linked documents that are in other shards; half the sum over all documents is the cut.
    """
    text = F.coalesce(F.col("text"), F.lit(""))
    narrow = docs.select(
        F.col("doc_id").cast("long").alias("doc_id"),
        (F.octet_length(text).cast("long") + 1).alias("size"),
        F.crc32(text.cast("binary")).alias("text_crc32"),
        F.xxhash64(text).alias("g"),
    )
    narrow = written(narrow, "narrow")
    sizes = narrow.groupBy(*GROUP).agg(F.count(F.lit(1)).alias("n")).filter("n > 1")
    # a table of its own, so that the join may split the rows of a large group over tasks
    known = written(narrow.join(written(sizes, "sizes"), GROUP, "left"), "linked")
    row = known.agg(F.count(F.lit(1)).alias("all"), F.count("n").alias("linked")).head()
    total, linked_rows = row["all"], row["linked"]
    quota = _even(total, shards)
    linked = known.filter("n is not null")
    free = known.filter("n is null")
    load = [0] * shards
    placed = None
    if linked_rows:
        begin = _sums(_even(linked_rows, shards)[::-1])  # never above the quota
        started = _ranked(linked.withColumn("one", F.lit(1)), ["one"], F.lit(linked_rows), 64).withColumn(
            "shard", F.lit(shards - 1) - _interval(F.col("rank"), begin)
        )
        counts = started.groupBy(*GROUP).agg(
            F.array(*[F.count(F.when(F.col("shard") == s, 1)) for s in range(shards)]).alias("c")
        )
        groups, _ = propagate(written(counts, "groups"), quota, rounds)
        row = groups.agg(*[F.sum(F.get("c", F.lit(s))).alias(f"s{s}") for s in range(shards)]).head()
        load = [int(row[s]) for s in range(shards)]
        ranked = _ranked(linked, GROUP, F.col("n"))
        at = F.aggregate(
            F.col("c"),
            F.struct(F.lit(0).cast("long").alias("sum"), F.lit(0).alias("shard")),
            lambda acc, x: F.struct(
                (acc["sum"] + x).alias("sum"), (acc["shard"] + (acc["sum"] + x <= F.col("rank")).cast("int")).alias("shard")
            ),
        )["shard"]
        placed = ranked.join(groups, GROUP).withColumn("shard", at.cast("int"))
        placed = placed.withColumn("links_cut", F.col("n") - F.get("c", F.col("shard")))
    rest = _sums([q - n for q, n in zip(quota, load, strict=True)])
    alone = _ranked(free.withColumn("one", F.lit(1)), ["one"], F.lit(total - linked_rows), 64).withColumn(
        "shard", _interval(F.col("rank"), rest)
    ).withColumn("links_cut", F.lit(0).cast("long"))
    columns = ["doc_id", "size", "text_crc32", "n", "shard", "links_cut"]
    both = alone.select(*columns) if placed is None else alone.select(*columns).unionByName(placed.select(*columns))
    both = written(both, "dealt")
    slotted = _ranked(both, ["shard"], F.lit(max(quota, default=0)), 16)
    return slotted.select(
        "doc_id",
        "size",
        "text_crc32",
        F.lit("rows").alias("law"),
        "shard",
        F.col("rank").cast("long").alias("slot"),
        F.lit(None).cast("int").alias("grown_shard"),
        F.coalesce("n", F.lit(1)).cast("long").alias("group_size"),
        "links_cut",
    )
