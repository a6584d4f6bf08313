"""Minimum-cost-flow resharding: from old shards to new capacities with the fewest bytes moved. Law: `bytes`.

Old shard sizes and new capacities are a transport problem: a byte that stays in the shard of its own number costs nothing, a
moved one costs one (any cost table will do). It is solved exactly by successive cheapest paths on a graph of as many nodes as there are shards, so
the driver's part does not grow with the data. Each flow is a stretch of its old shard's bytes. Within an old shard
documents stand by descending size class, so the ends of all stretches that move fall among its smallest documents. What the sizes are then off their
capacities is levelled: of the `POOL` smallest documents of each shard, those that fit go from shards that hold too much to shards with room.

No task holds a shard: an old shard is cut into blocks (size class and a hash of the id), whose totals, at most `MAX_BLOCKS`
rows, give each block its place; prefix sums run within blocks. A document goes where its middle byte falls. `rewrite` writes a shard's rows in
ranges of its slots, by as many tasks as the rows need.

The present layout of `documents` is taken to be `OLD` shards by crc32 of the id; the operator takes any column.

Defined results: a null text has size 16 and the checksum of nothing; a null id is shard 0's. Repeated rows are placed one by one. An
empty table gives no rows. Only `doc_id` and `text` are read for the assignment. `rewrite` tells rows that repeat with one id and text apart by their number.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import discard, fresh, id_crc, spool

OLD, NEW, OVERHEAD, MAX_BLOCKS, POOL = 32, 40, 16, 200_000, 200


def min_cost_flow(supply: list[int], room: list[int], cost: list[list[int]]) -> list[list[int]]:
    """flow[i][j] of least total cost that ships all supply within room (sum(room) >= sum(supply)), integers throughout.
    Each step pushes as much as fits along a cheapest path of the residual graph, found with potentials that keep its costs non-negative."""
    m, n = len(supply), len(room)
    flow = [[0] * n for _ in range(m)]
    left, free = list(supply), list(room)
    up, vp = [0] * m, [0] * n
    while any(left):
        if not any(free):
            raise ValueError("the new capacities hold less than the old shards")
        infinite = float("inf")
        du, dv = [0 if x else infinite for x in left], [infinite] * n
        back_v, back_u = [-1] * n, [-1] * m
        done_u, done_v = [False] * m, [False] * n
        while True:
            d, side, x = min(((du[i], 0, i) for i in range(m) if not done_u[i]), default=(infinite, 0, -1))
            e = min(((dv[j], 1, j) for j in range(n) if not done_v[j]), default=(infinite, 1, -1))
            d, side, x = min((d, side, x), e)
            if d == infinite:
                break
            if side == 0:
                done_u[x] = True
                for j in range(n):
                    c = d + cost[x][j] + up[x] - vp[j]
                    if c < dv[j]:
                        dv[j], back_v[j] = c, x
            else:
                done_v[x] = True
                for i in range(m):
                    if flow[i][x] and (c := d - cost[i][x] - up[i] + vp[x]) < du[i]:
                        du[i], back_u[i] = c, x
        end = min((j for j in range(n) if free[j] and dv[j] < infinite), key=lambda j: dv[j] + vp[j])
        reach = max(x for x in [*du, *dv] if x < infinite)
        path, j = [], end
        while True:
            i = back_v[j]
            path.append((i, j, 1))
            if back_u[i] < 0:
                break
            path.append((i, back_u[i], -1))
            j = back_u[i]
        amount = min([left[i], free[end], *(flow[a][b] for a, b, sign in path if sign < 0)])
        for a, b, sign in path:
            flow[a][b] += sign * amount
        left[i] -= amount
        free[end] -= amount
        up = [p + min(d, reach) for p, d in zip(up, du, strict=True)]
        vp = [p + min(d, reach) for p, d in zip(vp, dv, strict=True)]
    return flow


def even(total: int, n: int) -> list[int]:
    return [total // n + (j < total % n) for j in range(n)]


def stretches(flow: list[list[int]]) -> list[tuple[int, int, int, int]]:
    """(old, from, to, new) byte ranges: what stays first, the rest in order of the new shard."""
    out = []
    for i, row in enumerate(flow):
        at = 0
        for j in sorted((j for j, x in enumerate(row) if x), key=lambda j: (j != i, j)):
            out.append((i, at, at + row[j], j))
            at += row[j]
    return out


def level(sizes: list[int], room: list[int], pools: dict[int, list[tuple]]) -> list[tuple]:
    """(key, to) of documents to move so that sizes come nearer to room: from the fullest shard to the emptiest, the document of its pool (size, key) that is nearest to half their
    distance, as long as the distance shrinks."""
    over, moves = [s - r for s, r in zip(sizes, room, strict=True)], []
    pools = {s: sorted(p) for s, p in pools.items()}
    stuck: set[int] = set()
    while len(stuck) < len(over):
        a = max((j for j in range(len(over)) if j not in stuck), key=lambda j: over[j])
        b = min(range(len(over)), key=lambda j: over[j])
        gap, own = over[a] - over[b], pools.get(a, [])
        k = min((k for k in range(len(own)) if 0 < own[k][0] < gap), key=lambda k: abs(2 * own[k][0] - gap), default=None)
        if k is None:
            stuck.add(a)
            continue
        size, key = own.pop(k)
        moves.append((key, b))
        over[a] -= size
        over[b] += size
    return moves


def assign(docs: DataFrame, *, old: Column | None = None, n_old: int = OLD, n_new: int = NEW, capacities: list[int] | None = None) -> tuple[DataFrame, list[list[int]]]:
    """((doc_id, size, text_crc32, old_shard, shard, slot), the flow between old and new shards)."""
    spark = docs.sparkSession
    old = id_crc("doc_id", n_old) if old is None else old
    size = F.coalesce(F.octet_length("text"), F.lit(0)).cast("long") + OVERHEAD
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), size.alias("size"), F.crc32(F.coalesce(F.col("text"), F.lit("")).cast("binary")).alias("text_crc32"), old.cast("int").alias("old_shard"))
    rows = spool(rows.withColumn("class", -F.floor(F.log2(F.col("size").cast("double")) * 4).cast("int")), "sizes")
    # Blocks of about 100,000 rows where the bound on their number allows it.
    classes = rows.groupBy("old_shard", "class").agg(F.count(F.lit(1)).alias("n"))
    seen = classes.agg(F.count(F.lit(1)), F.sum("n")).first()
    parts = max(1, min(MAX_BLOCKS // max(1, seen[0]), -(-(seen[1] or 0) // (100_000 * n_old))))
    rows = rows.withColumn("part", F.pmod(F.xxhash64("doc_id"), F.lit(parts)).cast("int"))
    blocks = sorted((r["old_shard"], r["class"], r["part"], r["bytes"]) for r in rows.groupBy("old_shard", "class", "part").agg(F.sum("size").alias("bytes")).collect())
    supply, starts = [0] * n_old, []
    for o, c, p, b in blocks:
        starts.append((o, c, p, supply[o]))
        supply[o] += b
    room = capacities or even(sum(supply), n_new)
    flow = min_cost_flow(supply, room, [[int(i != j) for j in range(n_new)] for i in range(n_old)])
    cuts = spark.createDataFrame([(o, [x[2] for x in own], [x[3] for x in own]) for o in range(n_old) if (own := [x for x in stretches(flow) if x[0] == o])], "old_shard int, ends array<long>, to array<int>")
    begin = spark.createDataFrame(starts, "old_shard int, class int, part int, start long")
    key = ["old_shard", "class", "part"]
    w = Window.partitionBy(*key).orderBy(F.desc("size"), "doc_id", "text_crc32")
    placed = rows.withColumn("before", F.sum("size").over(w.rowsBetween(Window.unboundedPreceding, 0)) - F.col("size")).withColumn("nth", F.row_number().over(w).cast("long"))
    # Both are bounded by MAX_BLOCKS and the number of shards.
    placed = placed.join(F.broadcast(begin), key).join(F.broadcast(cuts), "old_shard")
    twice = 2 * (F.col("start") + F.col("before")) + F.col("size")
    nth_cut = F.least(F.size(F.filter("ends", lambda e: 2 * e <= twice)) + 1, F.size("ends"))
    placed = spool(placed.select("doc_id", "size", "text_crc32", *key, "nth", F.element_at("to", nth_cut).alias("shard")), "placed")
    sizes = {r["shard"]: r["s"] for r in placed.groupBy("shard").agg(F.sum("size").alias("s")).collect()}
    nth = F.row_number().over(Window.partitionBy("shard").orderBy("size", *key, "nth"))
    pools: dict[int, list[tuple]] = {}
    for r in placed.select("shard", "size", *key, "nth").withColumn("k", nth).where(F.col("k") <= POOL).collect():
        pools.setdefault(r["shard"], []).append((r["size"], (r["old_shard"], r["class"], r["part"], r["nth"])))
    moves = level([sizes.get(j, 0) for j in range(n_new)], room, pools)
    if moves:
        moved = spark.createDataFrame([(*k, to) for k, to in moves], "old_shard int, class int, part int, nth long, to int")
        placed = placed.join(F.broadcast(moved), [*key, "nth"], "left").withColumn("shard", F.coalesce("to", "shard")).drop("to")
    # The place among a block's rows of one shard.
    placed = spool(placed.withColumn("nth", F.row_number().over(Window.partitionBy("shard", *key).orderBy("nth")).cast("long")), "levelled")
    held = sorted((r["shard"], r["old_shard"], r["class"], r["part"], r["n"], r["first"]) for r in placed.groupBy("shard", *key).agg(F.count(F.lit(1)).alias("n"), F.min("nth").alias("first")).collect())
    used, offsets = [0] * n_new, []
    for s, o, c, p, n, first in held:
        offsets.append((s, o, c, p, used[s] - first))
        used[s] += n
    shift = spark.createDataFrame(offsets, "shard int, old_shard int, class int, part int, shift long")
    out = placed.join(F.broadcast(shift), ["shard", *key]).select("doc_id", "size", "text_crc32", "old_shard", "shard", (F.col("nth") + F.col("shift")).alias("slot"))
    return out, flow


def changed(assigned: DataFrame) -> list[int]:
    """Shards that get a document from another one or lose one of their own, by the flow or by levelling."""
    pairs = assigned.where("shard <> old_shard").select("shard", "old_shard").distinct().collect()
    return sorted({x for r in pairs for x in (r["shard"], r["old_shard"])})


def rewrite(docs: DataFrame, assigned: DataFrame, path: str) -> list[int]:
    """Write the documents of the changed shards to path, a folder for each shard; the files of other shards are not touched. Columns of docs called shard or slot give way.
    docs must not read the folders that are replaced (write to another path, or spool them first)."""
    spark = docs.sparkSession
    shards = changed(assigned)
    clean = docs.drop("shard", "slot")
    at = {n: fresh(clean.columns, f"__{n}") for n in ("id", "size", "crc", "no")}
    twin = Window.partitionBy(at["id"], at["size"], at["crc"])
    size = F.coalesce(F.octet_length("text"), F.lit(0)).cast("long") + OVERHEAD
    crc = F.crc32(F.coalesce(F.col("text"), F.lit("")).cast("binary"))
    named = clean.withColumns({at["id"]: F.col("doc_id").cast("long"), at["size"]: size, at["crc"]: crc})
    named = named.withColumn(at["no"], F.row_number().over(twin.orderBy(at["id"])))
    where = assigned.select(F.col("doc_id").alias(at["id"]), F.col("size").alias(at["size"]), F.col("text_crc32").alias(at["crc"]), "shard", "slot")
    where = where.withColumn(at["no"], F.row_number().over(twin.orderBy("shard", "slot"))).where(F.col("shard").isin(shards)).withColumnsRenamed({at[n]: f"{at[n]}_" for n in at})
    same = [F.col(at[n]).eqNullSafe(F.col(f"{at[n]}_")) for n in at]
    out = named.join(where, same[0] & same[1] & same[2] & same[3]).select(*clean.columns, "shard", "slot")
    writer = out.repartitionByRange("shard", "slot").sortWithinPartitions("shard", "slot").write.mode("overwrite").option("partitionOverwriteMode", "dynamic")
    writer.partitionBy("shard").parquet(path)
    # A shard that lost all of its documents has no row to replace its folder.
    left = {r["shard"] for r in assigned.select("shard").distinct().collect()}
    discard(spark, [f"{path.rstrip('/')}/shard={s}" for s in shards if s not in left])
    return shards


def contract(docs: DataFrame) -> DataFrame:
    assigned, _ = assign(docs)
    return assigned.select("doc_id", "size", "text_crc32", F.lit("bytes").alias("law"), "shard", "slot", F.lit(None).cast("int").alias("grown_shard"), "old_shard")
