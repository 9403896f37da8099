"""Vector bin packing: shards balanced in bytes, tokens and rows at once.

Rows with equal texts form a group with a vector (bytes, tokens, rows); tokens are runs of characters that are not
blanks. Groups are dealt by a hash into blocks of about `block` groups, and every block is packed by itself, in parallel,
with a fair share of each shard as its capacity: largest first, a group goes to the shard where the dot product of its
vector with the residual capacity is highest, among the shards that still have room for it. Blocks are near equal in
every dimension and each is balanced, so shards are too, and no task and no driver sees all groups. A group that alone
would fill more than 1/parts of a shard's share of a block is cut into pieces by a hash of its rows, so one text that
very many rows hold is spread.

Slots: a shard's slots are dealt to blocks in order, within a block to its pieces, within a piece to rows by doc_id, so
no window spans a shard. Null texts have no bytes and no tokens. Rows that are equal in everything get distinct slots.
Rows with a null doc_id sort first. Very long texts are only measured, by built-in functions. An empty table gives no rows;
extra columns are not read.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from . import common as C

BLOCK, PARTS, SMALL = 1 << 16, 16, 2_000_000


def place(sizes: np.ndarray, shards: int) -> np.ndarray:
    """Shard of every item; sizes: items x dimensions. Greedy by dot product with the residual capacity."""
    total = sizes.sum(axis=0).astype(float)
    unit = sizes / np.where(total > 0, total / shards, 1)  # a shard's fair share is 1 in every dimension
    residual = np.ones((shards, sizes.shape[1]))
    out = np.zeros(len(sizes), dtype=np.int32)
    for i in np.lexsort((np.arange(len(sizes)), -unit.max(axis=1))).tolist():
        own = unit[i]
        left = residual - own
        room = left.min(axis=1)
        fits = room >= -1e-12
        # where no shard has room, the one that is left least over its share
        best = int(np.where(fits, residual @ own, -np.inf).argmax() if fits.any() else room.argmax())
        out[i] = best
        residual[best] = left[best]
    return out


def pack(docs: DataFrame, shards: int = 40, block: int = BLOCK, parts: int = PARTS) -> DataFrame:
    """doc_id, size, text_crc32, shard, slot of every row of docs."""
    text = F.coalesce(F.col("text"), F.lit(""))
    rows = C.materialize(
        docs.select(
            "doc_id",
            (F.octet_length(text) + 16).cast("long").alias("size"),
            F.crc32(text).alias("text_crc32"),
            F.xxhash64(text, F.octet_length(text)).alias("group"),
            F.regexp_count(text, F.lit(r"\S+")).cast("long").alias("tokens"),
        ),
        "shards-rows",
    )
    groups = C.materialize(rows.groupBy("group").agg(F.sum("size").alias("b"), F.sum("tokens").alias("t"), F.count("*").alias("n")), "shards-groups")
    totals = groups.agg(F.sum("b"), F.sum("t"), F.sum("n"), F.count("*")).first()
    if not totals[3]:
        return rows.select("doc_id", "size", "text_crc32", F.lit(0).alias("shard"), F.lit(0).cast("long").alias("slot"))
    blocks = -(-totals[3] // block)
    # heavy groups are cut; their pieces are dealt over the blocks like groups of their own
    limits = [max(1.0, (t or 0) / blocks / shards / parts) for t in totals[:3]]
    pieces = F.least(F.col("n"), F.ceil(F.greatest(F.col("b") / limits[0], F.col("t") / limits[1], F.col("n") / limits[2]))).cast("int")
    heavy = C.materialize(groups.withColumn("pieces", pieces).where("pieces > 1").select("group", "pieces"), "shards-heavy")
    if heavy.count() <= SMALL:  # their pieces sum to three times blocks x shards x parts at most
        heavy = F.broadcast(heavy)
    piece = F.when(F.col("pieces").isNull(), F.lit(0)).otherwise(F.pmod(F.xxhash64("doc_id", "size", "text_crc32"), F.col("pieces"))).cast("int")
    celled = rows.join(heavy, "group", "left").select("doc_id", "size", "text_crc32", "tokens", "group", piece.alias("piece"))
    if blocks > 1:
        celled = C.materialize(celled, "shards-celled")
    cells = celled.groupBy("group", "piece").agg(F.sum("size").alias("b"), F.sum("tokens").alias("t"), F.count("*").alias("n")).withColumn("block", F.pmod(F.xxhash64("group", "piece", F.lit(1)), F.lit(blocks)).cast("int"))

    def pack_block(table: pa.Table) -> pa.Table:
        order = np.lexsort((table.column("piece").to_numpy(), table.column("group").to_numpy()))
        table = table.take(pa.array(order))
        sizes = np.stack([table.column(c).to_numpy().astype(np.float64) for c in "btn"], axis=1)
        shard = place(sizes, shards)
        first, used = np.zeros(len(shard), np.int64), np.zeros(shards, np.int64)
        by = np.argsort(shard, kind="stable")
        n = table.column("n").to_numpy()[by]
        before = np.cumsum(n) - n
        start = np.searchsorted(shard[by], shard[by])
        first[by] = before - before[start]
        return pa.table([table.column("group"), table.column("piece"), table.column("block"), pa.array(shard), pa.array(first), table.column("n")], names=["group", "piece", "block", "shard", "first", "n"])

    plan = C.materialize(cells.groupBy("block").applyInArrow(pack_block, "group long, piece int, block int, shard int, first long, n long"), "shards-plan")
    filled = plan.groupBy("shard", "block").agg(F.sum("n").alias("rows"))  # blocks x shards rows
    starts = filled.select("shard", "block", F.coalesce(F.sum("rows").over(Window.partitionBy("shard").orderBy("block").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)).alias("start"))
    plan = plan.join(starts, ["shard", "block"]).select("group", "piece", "shard", (F.col("first") + F.col("start")).alias("first_slot"))
    order = Window.partitionBy("group", "piece").orderBy("doc_id", "text_crc32", "size")
    return (
        celled.select("doc_id", "size", "text_crc32", "group", "piece").withColumn("rank", F.row_number().over(order)).join(plan, ["group", "piece"])
        .select("doc_id", "size", "text_crc32", "shard", (F.col("first_slot") + F.col("rank") - 1).cast("long").alias("slot"))
    )


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    packed = pack(C.table(spark, sf_dir, "documents"))
    return packed.select("doc_id", "size", "text_crc32", F.lit("bytes").alias("law"), "shard", "slot", F.lit(None).cast("int").alias("grown_shard"))
