"""Item hierarchies and frequency-ordered dictionaries."""

from __future__ import annotations

import uuid
from collections.abc import Callable
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F


#: Bytes of a written table that a task holds before they go to the file.
BLOCK_BYTES = 16 << 20
#: Names, and (item, ancestor) pairs, that a task looks up by itself; beyond, rows are joined.
LOCAL_NAMES, LOCAL_PAIRS = 4_000_000, 12_000_000
#: Positions that are looked up at once, about (a sequence is never cut), and bytes of a batch.
CHUNK, BATCH_BYTES = 100_000, 16 << 20


def shared_dir(spark: SparkSession) -> str:
    base = spark.conf.get("spark.checkpoint.dir", None)
    if not base:
        if not spark.sparkContext.master.startswith("local"):
            raise RuntimeError("set spark.checkpoint.dir to a folder that all executors share")
        base = "file:///tmp/checkpoints"
    return f"{base.rstrip('/')}/mine-{uuid.uuid4().hex}"


def written(df: DataFrame, name: str) -> DataFrame:
    """``df`` as a table in the shared folder: ends lineage, survives lost executors."""
    spark, path = df.sparkSession, f"{shared_dir(df.sparkSession)}/{name}"
    df.write.option("parquet.block.size", BLOCK_BYTES).parquet(path)
    return spark.read.schema(df.schema).parquet(path)


#: Rows of a table that joins send through the driver to all executors; Spark would go by the size
#: of its files, which are far smaller than their rows.
BROADCAST_ROWS = 50_000


def sized(df: DataFrame, rows: int) -> DataFrame:
    """``df`` for a join: sent to all executors if small by its rows, else merged."""
    return F.broadcast(df) if rows <= BROADCAST_ROWS else df.hint("merge")


def closure(edges: DataFrame) -> DataFrame:
    """``child, anc`` over all paths (reflexive pairs left out), by doubling; a cycle is an error."""
    now = written(edges.where("child IS NOT NULL AND parent IS NOT NULL").select("child", F.col("parent").alias("anc")).distinct(), "closure")
    count = now.count()
    while True:
        if loops := now.where("child = anc").select("child").limit(5).collect():
            raise ValueError(f"the hierarchy has a cycle through {', '.join(r[0] for r in loops)}")
        further = now.alias("a").join(sized(now.alias("b"), count), F.col("a.anc") == F.col("b.child")).select("a.child", "b.anc")
        longer = written(now.union(further).distinct(), "closure")
        if (more := longer.count()) == count:
            return now
        now, count = longer, more


@dataclass
class Dictionary:
    """``items``: fid, item, freq; ``pairs``: fid, anc (each item's ancestors, itself too)."""

    items: DataFrame
    pairs: DataFrame
    sequences: int

    def last_frequent(self, sigma: int) -> int:
        return self.items.where(F.col("freq") >= sigma).count()


def unique(df: DataFrame, of) -> bool:
    """Whether no two rows have the same value, and none has null."""
    r = df.agg(F.count(F.lit(1)).alias("n"), F.count_distinct(of).alias("kinds")).first()
    return r["n"] == r["kinds"]


@dataclass
class Keyed:
    """Sequences as tasks read them: ``chunks`` makes (ids, keys of 64 bits of all items, bounds of
    the sequences) of the batches of ``rows``; ``key`` adds to a table with ``item`` its key ``h``."""

    rows: DataFrame
    chunks: Callable
    key: Callable[[DataFrame], DataFrame]


def hashed(seqs: DataFrame) -> DataFrame:
    """Sequences with 64-bit hashes in place of items (null stays), in batches of bounded size."""
    seqs.sparkSession.conf.set("spark.sql.execution.arrow.maxBytesPerBatch", str(BATCH_BYTES))
    return seqs.select("sid", F.transform("items", lambda x: F.when(x.isNotNull(), F.xxhash64(x))).alias("items"))


def hashed_chunks(batches):
    """(ids, hashes of all items that are not null, bounds of the sequences) of a few sequences."""
    for batch in batches:
        sids, col = batch.column(0), batch.column(1)
        sizes = np.diff(col.offsets.to_numpy()).astype(np.int64)
        sizes[col.is_null().to_numpy(zero_copy_only=False)] = 0
        upto, flat = np.concatenate([[0], np.cumsum(sizes)]), col.flatten()
        at = 0
        while at < len(sizes):
            to = max(at + 1, int(np.searchsorted(upto, upto[at] + CHUNK, "right")) - 1)
            part, bounds = flat.slice(upto[at], upto[to] - upto[at]), upto[at : to + 1] - upto[at]
            if part.null_count:
                bounds = np.concatenate([[0], np.cumsum(part.is_valid().to_numpy(zero_copy_only=False))])[bounds]
                part = part.drop_null()
            yield sids.slice(at, to - at), part.to_numpy(), bounds
            at = to


def found(keys: np.ndarray, values: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Places of values among the sorted keys, and whether they are there."""
    if not len(keys):
        return np.zeros(len(values), np.int64), np.zeros(len(values), bool)
    kinds, of = np.unique(values, return_inverse=True)
    at = np.minimum(np.searchsorted(keys, kinds), len(keys) - 1)
    return at[of], (keys[at] == kinds)[of]


def by_hash(seqs: DataFrame) -> Keyed:
    return Keyed(hashed(seqs), hashed_chunks, lambda names: names.withColumn("h", F.xxhash64("item")))


def frequencies(seqs: DataFrame, up: DataFrame, above: DataFrame) -> DataFrame:
    """``item, freq`` of items that occur, and of ancestors of such."""
    if not unique(seqs, "sid"):
        return frequencies_by_joins(seqs, above)
    own = seqs.select(F.explode(F.array_distinct("items")).alias("item")).where("item IS NOT NULL").groupBy("item").agg(F.count(F.lit(1)).alias("freq"))
    pairs = up.count()
    if not pairs:
        return own
    names = own.select("item").union(up.select("child")).union(up.select("anc")).distinct()
    if pairs > LOCAL_PAIRS or not unique(names, F.xxhash64("item")):
        return frequencies_by_joins(seqs, above)
    return frequencies_local(by_hash(seqs), up, own)


def frequencies_by_joins(seqs: DataFrame, above: DataFrame) -> DataFrame:
    distinct = seqs.select("sid", F.explode(F.array_distinct("items")).alias("item")).where("item IS NOT NULL")
    all_ = distinct.union(distinct.join(above, distinct["item"] == above["child"]).select("sid", "anc")).distinct()
    return all_.groupBy("item").agg(F.count(F.lit(1)).alias("freq"))


def frequencies_local(seqs: Keyed, up: DataFrame, own: DataFrame) -> DataFrame:
    """Ancestors are found where the sequences lie, each once in a sequence; a task yields its
    counters alone."""
    spark = seqs.rows.sparkSession
    below = seqs.key(up.select(F.col("child").alias("item"), "anc")).select(F.col("h").alias("child"), F.col("anc").alias("item"))
    table = seqs.key(below).select("child", F.col("h").alias("anc")).toArrow()
    ancs, of = np.unique(table["anc"].to_numpy(), return_inverse=True)
    # an ancestor that occurs itself counts as its own
    child, of = np.concatenate([table["child"].to_numpy(), ancs]), np.concatenate([of, np.arange(len(ancs))]).astype(np.int32)
    del table
    order = np.argsort(child, kind="stable")
    keys, starts = np.unique(child[order], return_index=True)
    chunks, sent = seqs.chunks, spark.sparkContext.broadcast((keys, np.append(starts, len(child)).astype(np.int32), of[order], ancs))

    def run(batches):
        keys, starts, of, ancs = sent.value
        counts = np.zeros(len(ancs), np.int64)
        for _, hashes, bounds in chunks(batches):
            seq = np.repeat(np.arange(len(bounds) - 1), np.diff(bounds))
            at, ok = found(keys, hashes)
            pairs = np.unique(seq[ok] * len(keys) + at[ok])
            seq, at = pairs // len(keys), pairs % len(keys)
            sizes = (starts[at + 1] - starts[at]).astype(np.int64)
            first = np.cumsum(sizes) - sizes
            anc = of[np.arange(sizes.sum()) + np.repeat(starts[at] - first, sizes)]
            counts += np.bincount(np.unique(np.repeat(seq, sizes) * len(ancs) + anc) % len(ancs), minlength=len(ancs))
        some = np.flatnonzero(counts)
        for k in range(0, len(some), CHUNK):
            part = some[k : k + CHUNK]
            yield pa.RecordBatch.from_arrays([pa.array(ancs[part]), pa.array(counts[part])], names=["h", "n"])

    counted = seqs.rows.mapInArrow(run, "h long, n long").groupBy("h").agg(F.sum("n").alias("freq"))
    names = up.select(F.col("anc").alias("item")).distinct()
    above = seqs.key(names).join(counted.hint("merge"), "h").select("item", "freq")
    return own.join(names.hint("merge"), "item", "left_anti").union(above)


def build_dictionary(seqs: DataFrame, edges: DataFrame | None = None) -> Dictionary:
    """Frequency of an item: sequences that hold it or a descendant."""
    up = closed_edges(seqs.sparkSession, edges)
    return numbered(frequencies(seqs, up, sized(up, up.count())), up, seqs.count())


def closed_edges(spark: SparkSession, edges: DataFrame | None) -> DataFrame:
    return closure(edges) if edges is not None else spark.createDataFrame([], "child string, anc string")


def numbered(freq: DataFrame, up: DataFrame, sequences: int) -> Dictionary:
    """Ids go by falling frequency, ancestors first, so the frequent items are those up to one id."""
    names = up.select(F.col("child").alias("item")).union(up.select("anc")).distinct()
    depth = up.groupBy(F.col("child").alias("item")).agg(F.count(F.lit(1)).alias("level"))
    items = freq.hint("merge").join(names, "item", "full_outer").join(depth.hint("merge"), "item", "left")
    items = items.select("item", F.coalesce("freq", F.lit(0)).alias("freq"), F.coalesce("level", F.lit(0)).alias("level"))
    # ids by range partition: offsets of the partitions are few, ranks are local to one
    dealt = written(items.repartitionByRange(F.desc("freq"), "level", "item").withColumn("__part", F.spark_partition_id()), "items")
    order = Window.partitionBy("__part").orderBy(F.desc("freq"), "level", "item")
    sizes = dealt.groupBy("__part").count()
    starts = sizes.select("__part", (F.sum("count").over(Window.orderBy("__part")) - F.col("count")).alias("__start"))
    ids = dealt.join(F.broadcast(starts), "__part").select((F.col("__start") + F.row_number().over(order)).cast("int").alias("fid"), "item", "freq")
    ids = written(ids, "ids")
    anc = ids.select(F.col("item").alias("anc"), F.col("fid").alias("anc_id"))
    n = ids.count()
    pairs = up.join(sized(ids.select(F.col("item").alias("child"), "fid"), n), "child").join(sized(anc, n), "anc").select("fid", F.col("anc_id").alias("anc"))
    pairs = written(ids.select("fid", F.col("fid").alias("anc")).union(pairs), "pairs")
    return Dictionary(ids, pairs, sequences)


def encode(seqs: DataFrame, dictionary: Dictionary) -> DataFrame:
    """``sid, items array<int>`` by the dictionary; empty sequences are left out. Tasks look items
    up where the sequences lie, or they are joined with a dictionary too large for that."""
    n = dictionary.items.count()
    if n <= LOCAL_NAMES and unique(seqs, "sid") and unique(dictionary.items, F.xxhash64("item")):
        return encode_local(by_hash(seqs), dictionary)
    rows = seqs.select("sid", F.posexplode("items").alias("pos", "item"))
    rows = rows.join(sized(dictionary.items.select("item", "fid"), n), "item")
    parts = F.sort_array(F.collect_list(F.struct("pos", "fid")))
    return rows.groupBy("sid").agg(F.transform(parts, lambda x: x["fid"]).alias("items"))


def encode_local(seqs: Keyed, dictionary: Dictionary) -> DataFrame:
    spark = seqs.rows.sparkSession
    table = seqs.key(dictionary.items).select("h", "fid").toArrow().sort_by("h")
    chunks, sent = seqs.chunks, spark.sparkContext.broadcast((table["h"].to_numpy(), table["fid"].to_numpy().astype(np.int32)))
    del table

    def run(batches):
        keys, fids = sent.value
        for sids, hashes, bounds in chunks(batches):
            at, ok = found(keys, hashes)
            upto = np.concatenate([[0], np.cumsum(ok)])[bounds]
            full = upto[1:] > upto[:-1]
            items = pa.ListArray.from_arrays(pa.array(np.concatenate([upto[:-1][full], upto[-1:]]).astype(np.int32)), pa.array(fids[at[ok]]))
            yield pa.RecordBatch.from_arrays([sids.filter(pa.array(full)), items], names=["sid", "items"])

    return seqs.rows.mapInArrow(run, f"sid {seqs.rows.schema['sid'].dataType.simpleString()}, items array<int>")


def decode(patterns: DataFrame, dictionary: Dictionary) -> DataFrame:
    """``pattern`` as text: items with blanks written as ``_``, apart by one space."""
    rows = patterns.select("pattern", "freq", F.posexplode("pattern").alias("pos", "fid"))
    rows = rows.join(sized(dictionary.items.select("fid", "item"), dictionary.items.count()), "fid")
    parts = F.sort_array(F.collect_list(F.struct("pos", F.replace("item", F.lit(" "), F.lit("_")).alias("item"))))
    rows = rows.groupBy("pattern", "freq").agg(F.transform(parts, lambda x: x["item"]).alias("names"))
    return rows.select(F.array_join("names", " ").alias("pattern"), F.size("names").alias("length"), "freq")


def sequence_stats(seqs: DataFrame) -> DataFrame:
    n = F.size("items")
    whole = seqs.agg(F.count(F.lit(1)).alias("n_sequences"), F.avg(n).alias("avg_length"), F.max(n).alias("max_length"), F.sum(n).alias("total_items"))
    kinds = seqs.select(F.explode("items").alias("i")).agg(F.count_distinct("i").alias("distinct_items"))
    return whole.crossJoin(F.broadcast(kinds))


def hierarchy_stats(edges: DataFrame) -> DataFrame:
    """Items, leaves, inner items and roots, depth (items on the longest path), fan-out."""
    e = edges.select("child", "parent").distinct()
    fan = e.groupBy(F.col("parent").alias("item")).agg(F.count(F.lit(1)).alias("fan"))
    names = e.select(F.col("child").alias("item")).union(e.select("parent")).distinct()
    level, depth, k = e.select(F.col("child").alias("item")).distinct(), [names.select("item", F.lit(1).alias("d"))], 1
    up = e
    while level.limit(1).count():
        k += 1
        depth.append(level.select("item", F.lit(k).alias("d")))
        level = written(level.alias("l").join(e.alias("e"), F.col("e.parent") == F.col("l.item")).select(F.col("e.child").alias("item")).distinct(), "level")
    most = depth[0]
    for d in depth[1:]:
        most = most.union(d)
    out = names.join(fan, "item", "left").join(up.select(F.col("child").alias("item")).distinct().withColumn("below", F.lit(1)), "item", "left")
    leaf, root = F.col("fan").isNull(), F.col("below").isNull()
    count = lambda c: F.sum(c.cast("long"))
    whole = out.agg(F.count(F.lit(1)).alias("n_items"), count(leaf).alias("n_leaf"), count(~leaf & ~root).alias("n_inner"), count(root).alias("n_root"), F.avg("fan").alias("avg_fan_out"), F.max("fan").alias("max_fan_out"))
    return whole.crossJoin(F.broadcast(most.agg(F.max("d").alias("max_depth"))))
