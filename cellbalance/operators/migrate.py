"""Moving cells and their particles to the slots that a new map gives them."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def transfer_plan(old_map: DataFrame, new_map: DataFrame) -> DataFrame:
    """(pos, src, dst) of the cells that change slot."""
    joined = old_map.select("pos", F.col("slot").alias("src")).join(new_map.select("pos", F.col("slot").alias("dst")), "pos")
    return joined.filter("src <> dst")


def transfer_ranges(old_cuts: DataFrame, new_cuts: DataFrame) -> DataFrame:
    """(src, dst, first_pos, last_pos): the same plan from two cut vectors alone, as overlaps of at most 2P ranges."""
    marks = old_cuts.select("b").union(new_cuts.select("b")).distinct()
    pieces = marks.select((F.col("b") + 1).alias("first_pos"), F.lead("b").over(Window.orderBy("b")).alias("last_pos")).filter("last_pos is not null")
    # the owner of a piece is the last slot that begins at or before it, with cells
    def owner(cuts: DataFrame, name: str) -> DataFrame:
        return cuts.select(F.col("b").alias(f"{name}_b"), F.col("k").alias(name), F.lead("b").over(Window.orderBy("k")).alias(f"{name}_e"))

    found = pieces.join(F.broadcast(owner(old_cuts, "src")), F.expr("first_pos > src_b and first_pos <= src_e")).join(F.broadcast(owner(new_cuts, "dst")), F.expr("first_pos > dst_b and first_pos <= dst_e"))
    return found.filter("src <> dst").select("src", "dst", "first_pos", "last_pos")


def particles_to_move(plan: DataFrame, particles: DataFrame, key: str = "pos") -> DataFrame:
    """The particles of moving cells, with source and target. ``particles`` has the position of their cell in ``key``."""
    return particles.join(plan.withColumnRenamed("pos", key), key)


def migrate(df: DataFrame, new_map: DataFrame, p: int) -> DataFrame:
    """Rows placed so that partition = slot, sorted by position: the shuffle is the send, partitions are the sites."""
    return df.join(new_map.select("pos", "slot"), "pos").repartitionById(p, F.col("slot")).sortWithinPartitions("pos")


def pack(df: DataFrame, columns: list[str]) -> DataFrame:
    """(src, dst, buffer): one buffer of structs for each pair of slots and block of positions."""
    return df.withColumn("chunk", F.expr("(pos - 1) div 4096")).groupBy("src", "dst", "chunk").agg(F.sort_array(F.collect_list(F.struct("pos", *columns))).alias("buffer"))


def unpack(packed: DataFrame) -> DataFrame:
    return packed.select("src", "dst", F.inline("buffer"))


def reattach_static(moved: DataFrame, static: DataFrame, key: str) -> DataFrame:
    """Static data are joined again after the move and never travel with it; a small side is broadcast by its own statistics."""
    return moved.join(static, key, "left")


def transfer_matrix(plan: DataFrame, counts: DataFrame, bytes_per_cell: int, bytes_per_particle: int) -> DataFrame:
    """(src, dst, cells, particles, bytes) with the sums of each row, each column and all (null = all)."""
    per_cell = plan.join(counts, "pos", "left").select("src", "dst", F.coalesce("cnt", F.lit(0)).alias("cnt"))
    out = per_cell.cube("src", "dst").agg(F.count("*").alias("cells"), F.sum("cnt").cast("long").alias("particles"))
    return out.withColumn("bytes", F.col("cells") * bytes_per_cell + F.col("particles") * bytes_per_particle)


def shared_faces(edges: DataFrame, cell_map: DataFrame) -> DataFrame:
    """(slot, faces): faces that a slot shares with others. ``edges``: a, b, each face once."""
    a = cell_map.select(F.col("pos").alias("a"), F.col("slot").alias("slot_a"))
    b = cell_map.select(F.col("pos").alias("b"), F.col("slot").alias("slot_b"))
    cut = edges.join(a, "a").join(b, "b").filter("slot_a <> slot_b")
    return cut.select(F.explode(F.array("slot_a", "slot_b")).alias("slot")).groupBy("slot").agg(F.count("*").alias("faces"))


def check_migration(before: DataFrame, after: DataFrame) -> DataFrame:
    """One row: lost and gained rows; both are 0 if the multiset is unchanged."""
    columns = before.columns
    lost = before.exceptAll(after.select(*columns)).agg(F.count("*").alias("lost"))
    gained = after.select(*columns).exceptAll(before).agg(F.count("*").alias("gained"))
    return lost.select("lost", gained.scalar().alias("gained"))
