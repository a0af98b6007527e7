"""Exact duplicates through an extendible-hash index on shared files.

Texts are equal when identical after every run of ASCII white space became one space. Rows are first
aggregated by (hash, text), in the tasks and then by owner: the engine compares the bytes of texts
whose hashes are equal, so colliding texts stay in entries of their own, chained under one hash and told apart by their SHA-256.

The entries fill the buckets of an extendible-hash index. A directory of 2**depth cells maps hash
prefixes to buckets; an overfull bucket is split by one more bit, and the directory doubles when the
bucket's bits are as many as the directory's. A bucket is a range of hashes, and owner tasks write runs of buckets in
hash order, so a reader of a bucket skips by the files' minima and maxima. Rows find their class by
directory cell, bucket and chain. A later batch is added to the index (`add`): its entries
join those of their bucket, and what overflows splits.

Defined cases: null counts as empty; empty texts are one class; of equal texts the smallest id
stays (rows that repeat an id repeat in the output); rows whose id is null join their class and
stay only if no row of it has an id; an empty table gives an empty result; other columns are
ignored.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from poolcurator.llm.store import attach_by_group, drop_path, new_path, pick, write_table

#: Single characters, which Java looks up in a table; ranges it asks one after another.
SPACE_RUN = r"[\x20\x09\x0A\x0B\x0C\x0D]+"
#: Entries that a bucket holds before it is split.
BUCKET_ENTRIES = 100_000
#: Prefix bits at which splitting ends; a bucket of one hash cannot be split further.
MAX_DEPTH = 20


def normalised(text) -> F.Column:
    return F.regexp_replace(F.coalesce(text, F.lit("")), SPACE_RUN, " ")


def prefix(h, depth: int) -> F.Column:
    """The first `depth` bits of a 64-bit hash as a number."""
    return F.shiftrightunsigned(h, 64 - depth) if depth else F.lit(0).cast("long")


class Directory:
    """2**depth cells, each naming a bucket; a bucket holds the hashes whose first `local` bits are its own.

    Fill is known by max_depth-bit prefix, so the state is bounded by 2**max_depth numbers, whatever the entries.
    """

    def __init__(self, most: int = BUCKET_ENTRIES, max_depth: int = MAX_DEPTH):
        self.most, self.max_depth, self.depth = most, max_depth, 0
        self.cells = [0]
        self.local = [0]  # bits by bucket
        self.bits = [0]
        self.fill: list[dict[int, int]] = [{}]  # entries of each bucket by prefix

    def add(self, counts: dict[int, int]) -> None:
        """New entries by max_depth-bit prefix; overfull buckets are split until none is, or no bit is left."""
        for prefix, n in counts.items():
            bucket = self.cells[prefix >> (self.max_depth - self.depth)]
            self.fill[bucket][prefix] = self.fill[bucket].get(prefix, 0) + n
        work = list(range(len(self.local)))
        while work:
            bucket = work.pop()
            if sum(self.fill[bucket].values()) > self.most and self.local[bucket] < self.max_depth:
                work += [bucket, self._split(bucket)]

    def _split(self, bucket: int) -> int:
        """The bucket keeps the hashes whose next bit is 0; a new one takes the others."""
        if self.local[bucket] == self.depth:
            self.cells = [b for b in self.cells for _ in (0, 1)]
            self.depth += 1
        self.local[bucket] += 1
        self.bits[bucket] <<= 1
        new = len(self.local)
        self.local.append(self.local[bucket])
        self.bits.append(self.bits[bucket] | 1)
        bit = self.max_depth - self.local[bucket]
        self.fill.append({p: n for p, n in self.fill[bucket].items() if p >> bit & 1})
        self.fill[bucket] = {p: n for p, n in self.fill[bucket].items() if not p >> bit & 1}
        width = 1 << (self.depth - self.local[new])
        start = self.bits[new] * width
        self.cells[start : start + width] = [new] * width
        return new

    def table(self, spark: SparkSession) -> DataFrame:
        """(cell, bucket, place): place is the bucket's rank in hash order. At most 2**max_depth rows."""
        order = {b: i for i, b in enumerate(sorted(range(len(self.local)), key=lambda b: self.bits[b] << (self.max_depth - self.local[b])))}
        return spark.createDataFrame([(c, b, order[b]) for c, b in enumerate(self.cells)], "cell long, bucket int, place int")


@dataclass
class HashIndex:
    """Written index: entries (bucket, h, sha, keep_id, group_size, chain) by bucket, and the directory."""

    entries: DataFrame
    directory: Directory
    path: str
    n_rows: int
    hash_column: object = None

    def located(self, rows: DataFrame) -> DataFrame:
        """rows (with h) and the bucket that the directory names for their cell."""
        cells = F.broadcast(self.directory.table(rows.sparkSession))
        return rows.withColumn("cell", prefix(F.col("h"), self.directory.depth)).join(cells, "cell").drop("cell")


def _entries(docs: DataFrame, id_col: str, text_col: str, hash_column) -> DataFrame:
    """(h, sha, keep_id, group_size), one row per different text: equal hashes are told apart by their bytes."""
    keyed = pick(docs, id_col, text_col).select(F.col(id_col).alias("id"), normalised(F.col(text_col)).alias("body"))
    keyed = keyed.withColumn("h", (hash_column or F.xxhash64)(F.col("body")))
    owned = keyed.groupBy("h", "body").agg(F.min("id").alias("keep_id"), F.count(F.lit(1)).alias("group_size"))
    return owned.select("h", F.sha2("body", 256).alias("sha"), "keep_id", "group_size")


def _fill(index: HashIndex, slim: DataFrame, new: DataFrame) -> HashIndex:
    """The index over the entries `slim`, of which those in `new` are not yet in its directory."""
    spark = slim.sparkSession
    got = new.groupBy(prefix(F.col("h"), index.directory.max_depth).alias("p")).count().toArrow()  # at most 2**max_depth rows
    index.directory.add(dict(zip(got["p"].to_pylist(), got["count"].to_pylist(), strict=True)))
    index.n_rows = int(slim.agg(F.coalesce(F.sum("group_size"), F.lit(0))).first()[0])
    path = new_path(spark, "hash-index")
    dealt = index.located(slim).repartitionByRange("place", "h").sortWithinPartitions("place", "h", "sha")
    # All entries of one hash are in one range; their chain follows the SHA-256.
    chained = dealt.withColumn("chain", F.row_number().over(Window.partitionBy("place", "h").orderBy("sha")) - 1)
    chained.drop("place").write.parquet(path)
    index.entries = spark.read.schema(chained.drop("place").schema).parquet(path)
    if index.path:
        drop_path(spark, index.path)
    index.path = path
    return index


def build_index(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", bucket_entries: int = BUCKET_ENTRIES, max_depth: int = MAX_DEPTH, hash_column=None) -> HashIndex:
    """Index of all texts."""
    slim, slim_path = write_table(_entries(docs, id_col, text_col, hash_column), "entries")
    index = _fill(HashIndex(slim, Directory(bucket_entries, max_depth), "", 0, hash_column), slim, slim)
    drop_path(docs.sparkSession, slim_path)
    return index


def add(index: HashIndex, docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> HashIndex:
    """The index with a further batch: known texts grow their class, new ones are chained into their bucket, overfull buckets split."""
    batch, batch_path = write_table(_entries(docs, id_col, text_col, index.hash_column), "entries")
    known = index.entries.select("h", "sha", "keep_id", "group_size")
    new, new_path_ = write_table(batch.join(known.select("h", "sha"), ["h", "sha"], "left_anti"), "entries")
    merged = known.unionByName(batch).groupBy("h", "sha").agg(F.min("keep_id").alias("keep_id"), F.sum("group_size").alias("group_size"))
    merged, merged_path = write_table(merged, "entries")
    index = _fill(index, merged, new)
    for path in (batch_path, new_path_, merged_path):
        drop_path(docs.sparkSession, path)
    return index


def lookup(docs: DataFrame, index: HashIndex, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Each row of docs with its class: (id, h, sha, keep_id, group_size, bucket); rows the index lacks are dropped.

    The directory gives a row's bucket; within the bucket the hash leads to a chain, and the SHA-256 to the entry.
    """
    body = normalised(F.col(text_col))
    keyed = pick(docs, id_col, text_col).select(F.col(id_col).alias("id"), body.alias("body"))
    keyed = keyed.select("id", (index.hash_column or F.xxhash64)(F.col("body")).alias("h"), F.sha2("body", 256).alias("sha"))
    entries = index.entries.select("bucket", "h", "sha", "keep_id", "group_size")
    return attach_by_group(index.located(keyed).drop("place"), entries, ["bucket", "h", "sha"], "group_size", index.n_rows)


def exact_duplicates(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", **options) -> DataFrame:
    """One row per row of docs: its id, keep_id, group_size, kept, text_sha256 and index bucket."""
    index = build_index(docs, id_col, text_col, **options)
    found = lookup(docs, index, id_col, text_col)
    return found.select(
        F.col("id").alias(id_col),
        "keep_id",
        "group_size",
        F.col("id").eqNullSafe(F.col("keep_id")).alias("kept"),
        F.col("sha").alias("text_sha256"),
        "bucket",
    )


def deduplicate(spark: SparkSession, docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """docs without the rows that repeat an earlier text."""
    found = exact_duplicates(docs, id_col, text_col).where("kept").select(F.col(id_col).alias("_keep"))
    return docs.join(found.distinct(), docs[id_col].eqNullSafe(F.col("_keep")), "left_semi")
