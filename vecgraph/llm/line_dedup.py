"""Line deduplication with levelled sorted runs of line hashes.

A run holds (h1, h2, n, new): a 128-bit hash of a line key, the number of the batch's documents that hold it, and whether no earlier batch did. All runs
of a store are partitions of one table bucketed by hash and sorted within each bucket, so a batch of lines is counted into the same buckets
once and then merge-anti-joins all live runs where they lie: keys in no run are new, the others are known and only counted, and both become the
batch's own run of level 0. When a level holds `fanout` runs they merge, bucket by bucket and again without a shuffle, into one run of the next
level, so a new batch meets at most fanout * log(batches) runs. The live runs are listed in a manifest beside them; a run is written whole before it is
listed, and a store can be opened again from its folder.

A batch can be answered in two ways: `new_lines` (first come, first kept) and `drop_frequent`, which removes lines that at least `min_docs`
documents hold over all runs. A line held by more than a 4,096th of all counted is looked up in a broadcast table, which cannot have more than 4,096 rows,
and its rows are dealt evenly, so that no task gets all rows of a common line.

A line is what stands between two \\n; its key is the line without ASCII white space at both ends, A-Z in lower case.
Null and empty texts hold one empty line. Empty keys (shorter than `min_key`) are never counted or dropped. Every row counts
as a document, also rows repeated whole (each gets the same result); other columns of the input pass through unchanged.
An empty table gives an empty result."""

from __future__ import annotations

import uuid
from collections.abc import Iterator
from contextlib import contextmanager

from pyspark.errors import AnalysisException
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import ASCII_SPACE, ascii_lower, prepare, row_keys, scratch_dir, table, text_or_empty

RUN = "h1 BIGINT, h2 BIGINT, n BIGINT, new BOOLEAN, run INT"
HOT_SHARE = 4096


def line_keys(text: Column) -> Column:
    """The keys of all lines of a text, in order."""
    return F.split(ascii_lower(text), "\n").cast("array<string>")


def _trimmed(line: Column) -> Column:
    return F.btrim(line, F.lit(ASCII_SPACE))


def _hashed(df: DataFrame, key: str) -> DataFrame:
    return df.withColumns({"h1": F.xxhash64(F.lit(1), F.col(key)), "h2": F.xxhash64(F.lit(2), F.col(key))})


@contextmanager
def shuffled_into(spark: SparkSession, n: int) -> Iterator[None]:
    """Shuffles of the queries inside go to n partitions, so that they meet buckets as they lie."""
    before = spark.conf.get("spark.sql.shuffle.partitions")
    spark.conf.set("spark.sql.shuffle.partitions", str(n))
    try:
        yield
    finally:
        spark.conf.set("spark.sql.shuffle.partitions", before)


class LineRuns:
    """The runs below one folder, with their manifest."""

    def __init__(self, spark: SparkSession, path: str | None = None, fanout: int = 4, text: str = "text", min_key: int = 1, buckets: int = 16):
        self.spark, self.path, self.fanout, self.text, self.min_key = spark, path or scratch_dir(spark, "line-runs"), fanout, text, min_key
        self.table = f"line_runs_{uuid.uuid4().hex}"
        try:
            kept = spark.read.parquet(f"{self.path}/manifest")
        except AnalysisException:  # a new store
            kept = None
        self.version, self.levels, self.buckets = 0, [[]], buckets
        if kept is not None:
            last = kept.groupBy("version").agg(F.collect_list(F.struct("level", "run")).alias("runs"), F.max("buckets").alias("buckets")).orderBy(F.desc("version")).first()
            self.version, self.buckets = last["version"], last["buckets"]
            self.levels = [[] for _ in range(max(r["level"] for r in last["runs"]) + 1)]
            for r in sorted(last["runs"]):
                self.levels[r["level"]].append(r["run"])
        spark.sql(f"CREATE TABLE {self.table} ({RUN}) USING parquet OPTIONS (compression 'zstd') PARTITIONED BY (run) CLUSTERED BY (h1, h2) SORTED BY (h1, h2) INTO {self.buckets} BUCKETS LOCATION '{self.path}/runs'")
        if kept is not None:
            spark.sql(f"MSCK REPAIR TABLE {self.table}")

    def close(self) -> None:
        """Forgets the name of the table; its files stay."""
        self.spark.sql(f"DROP TABLE IF EXISTS {self.table}")

    def _lines(self, docs: DataFrame, keep: list[Column]) -> DataFrame:
        """(keep..., h1, h2): one row for each document and different key."""
        keys = F.explode(F.array_distinct(F.transform(line_keys(text_or_empty(self.text)), _trimmed)))
        lines = docs.select(*keep, keys.alias("_key")).where(F.char_length("_key") >= self.min_key)
        return _hashed(lines, "_key").drop("_key")

    def _write(self, run: DataFrame, level: int, instead_of: int | None = None) -> None:
        """Adds a run of a level, in place of all of another, and lists it."""
        number = max((r for x in self.levels for r in x), default=self.version) + 1
        run = run.select("h1", "h2", "n", "new", F.lit(number).alias("run"))
        run.write.format("parquet").mode("append").partitionBy("run").bucketBy(self.buckets, "h1", "h2").sortBy("h1", "h2").saveAsTable(self.table)
        levels = [[] if k == instead_of else list(x) for k, x in enumerate(self.levels)]
        levels += [[] for _ in range(level + 1 - len(levels))]
        levels[level].append(number)
        listed = [(number, self.buckets, k, r) for k, x in enumerate(levels) for r in x]
        self.spark.createDataFrame(listed, "version int, buckets int, level int, run int").coalesce(1).write.mode("append").parquet(f"{self.path}/manifest")
        self.levels, self.version = levels, number

    def runs(self, level: int | None = None) -> DataFrame:
        """The live runs under each other, in their buckets; a key is at most once in each."""
        live = [r for k, x in enumerate(self.levels) for r in x if level in (None, k)]
        return self.spark.table(self.table).where(F.col("run").isin(live) if live else F.lit(False))

    def compact(self) -> None:
        """Merge every level that holds `fanout` runs into one run of the next."""
        for k in range(len(self.levels)):
            if len(self.levels[k]) >= self.fanout:
                self._write(self.runs(k).groupBy("h1", "h2").agg(F.sum("n").alias("n"), F.bool_or("new").alias("new")), k + 1, instead_of=k)
        if any(len(level) >= self.fanout for level in self.levels):
            self.compact()

    def add(self, docs: DataFrame) -> None:
        """One batch becomes one run: its keys are counted, then merge-anti-join the runs to tell new keys from known ones."""
        with shuffled_into(self.spark, self.buckets):
            counted = self._lines(docs, []).groupBy("h1", "h2").agg(F.count("*").alias("n"))
            runs = self.runs().select("h1", "h2").hint("merge")
            new = counted.join(runs, ["h1", "h2"], "left_anti").withColumn("new", F.lit(True))
            known = counted.join(runs, ["h1", "h2"], "left_semi").withColumn("new", F.lit(False))
            self._write(new.unionByName(known) if any(self.levels) else counted.withColumn("new", F.lit(True)), 0)
            self.compact()

    def new_lines(self, docs: DataFrame, key: str = "doc_id") -> DataFrame:
        """(key, pos, line) of the batch's lines whose key is in no run; sort-merge anti join, so nothing needs to fit in memory."""
        lines = docs.select(key, F.posexplode(F.split(text_or_empty(self.text), "\n")).alias("pos", "line"))
        lines = _hashed(lines.withColumn("_key", _trimmed(ascii_lower(F.col("line")))), "_key").drop("_key")
        return lines.join(self.runs().hint("merge"), ["h1", "h2"], "left_anti").select(key, "pos", "line")

    def frequent(self, min_docs: int) -> DataFrame:
        """(h1, h2, n) of the keys that at least min_docs documents hold, summed within the buckets."""
        return self.runs().groupBy("h1", "h2").agg(F.sum("n").alias("n")).where(F.col("n") >= min_docs)

    def drop_frequent(self, docs: DataFrame, min_docs: int = 10, key: str = "doc_id") -> DataFrame:
        """docs with kept_text, n_lines and n_dropped. Flags of lines go back to their document by its row keys; the text
        itself moves once. Copies of a row share their flags, so they are merged before they meet."""
        names = row_keys(key, self.text)
        lines = docs.select(*names, F.posexplode(line_keys(text_or_empty(self.text))).alias("pos", "_key"))
        lines = _hashed(lines.withColumn("_key", _trimmed(F.col("_key"))).where(F.char_length("_key") >= self.min_key), "_key").drop("_key")
        frequent = self.frequent(min_docs)
        share = (self.runs().agg(F.sum("n")).first()[0] or 0) / HOT_SHARE
        hot = self.spark.createDataFrame(frequent.where(F.col("n") > share).select("h1", "h2").collect(), "h1 long, h2 long").withColumn("_hot", F.lit(True))
        lines = lines.join(F.broadcast(hot), ["h1", "h2"], "left")
        # a hot line is found already: it goes where its row's hash says
        dealt = lambda own, other: F.when(F.col("_hot"), F.xxhash64("_k1", "pos", F.lit(other))).otherwise(F.col(own))
        lines = lines.select("_k1", "_k2", "pos", "_hot", dealt("h1", 1).alias("h1"), dealt("h2", 2).alias("h2"))
        found = frequent.where(F.col("n") <= share).select("h1", "h2", F.lit(True).alias("_found")).hint("merge")
        hit = lines.join(found, ["h1", "h2"], "left").where("_hot or _found").groupBy("_k1", "_k2", "pos").agg(F.lit(1).alias("_"))
        # bits of 62 lines at a time; a document gets a dense array of words, read by position
        words = hit.groupBy("_k1", "_k2", F.floor(F.col("pos") / 62).cast("int").alias("w")).agg(F.bit_or(F.expr("shiftleft(1L, pos % 62)")).alias("bits"))
        per_doc = words.groupBy("_k1", "_k2").agg(F.sort_array(F.collect_list(F.struct("w", "bits"))).alias("_words"))
        top = F.element_at("_words", -1)["w"]
        # w is sparse: the gaps are filled so that position p is in word p / 62
        dense = F.flatten(F.transform("_words", lambda x, i: F.concat(F.array_repeat(F.lit(0).cast("long"), x["w"] - F.when(i > 0, F.get("_words", i - 1)["w"]).otherwise(F.lit(-1)) - 1), F.array(x["bits"]))))
        per_doc = per_doc.select("_k1", "_k2", dense.alias("_bits"), (top + 1).alias("_n"))
        out = docs.withColumns({"_k1": names[0], "_k2": names[1]}).join(per_doc, ["_k1", "_k2"], "left")
        all_lines = F.split(text_or_empty(self.text), "\n")
        bit = lambda i: F.coalesce(F.getbit(F.get("_bits", F.floor(i / 62).cast("int")), (i % 62).cast("int")), F.lit(0).cast("tinyint")) == 0
        kept = F.when(F.col("_bits").isNull(), all_lines).otherwise(F.filter(all_lines, lambda _, i: bit(i)))
        out = out.withColumns({"n_lines": F.size(all_lines).cast("long"), "_kept": kept})
        out = out.withColumns({"n_dropped": F.col("n_lines") - F.size("_kept"), "kept_text": F.array_join("_kept", "\n")})
        return out.drop("_k1", "_k2", "_bits", "_n", "_kept")


def dedup_lines(docs: DataFrame, min_docs: int = 10, batches: int = 4, key: str = "doc_id", text: str = "text", buckets: int | None = None) -> DataFrame:
    """All of docs, batch by batch, through one store of runs; returns docs with kept_text, n_lines and n_dropped. Without `buckets`, there is one for
    every two input partitions."""
    spark = docs.sparkSession
    prepare(spark)
    inner = docs.select(F.col(key).alias("_id"), F.col(text).alias("_text"))
    store = LineRuns(spark, text="_text", buckets=buckets or min(1 << 16, max(4, inner.rdd.getNumPartitions() // 2)))
    for b in range(batches):
        store.add(inner.where(F.pmod(F.xxhash64("_id"), F.lit(batches)) == b))
    renamed = docs.withColumnsRenamed({c: f"_in_{c}" for c in docs.columns if c not in (key, text)}).withColumn("_text", F.col(text))
    out = store.drop_frequent(renamed, min_docs, key).drop("_text")
    back = {f"_in_{c}": c for c in docs.columns if c not in (key, text, "n_lines", "n_dropped", "kept_text")}
    return out.drop(*[f"_in_{c}" for c in ("n_lines", "n_dropped", "kept_text")]).withColumnsRenamed(back)


def op3_line_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    return dedup_lines(docs).select("doc_id", "n_lines", "n_dropped", F.sha2("kept_text", 256).alias("kept_sha256"))


SQL = r"""
WITH lines AS (
  SELECT doc_id, generate_subscripts(string_split(coalesce(text, ''), chr(10)), 1) AS pos, unnest(string_split(coalesce(text, ''), chr(10))) AS line
  FROM documents),
keyed AS (SELECT *, trim(translate(line, 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), ' ' || chr(9) || chr(10) || chr(11) || chr(12) || chr(13)) AS k FROM lines),
frequent AS (SELECT k FROM keyed WHERE length(k) >= 1 GROUP BY k HAVING count(DISTINCT doc_id) >= 10)
SELECT doc_id, count(*) AS n_lines, count(*) FILTER (k IN (FROM frequent)) AS n_dropped,
  sha256(coalesce(string_agg(line, chr(10) ORDER BY pos) FILTER (k NOT IN (FROM frequent)), '')) AS kept_sha256
FROM keyed GROUP BY doc_id
"""
