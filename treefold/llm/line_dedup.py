"""Line dedup over levelled sorted runs of line hashes, in DataFrame operations only.

A run is a table of (line hash, first document), hash-bucketed and sorted, so a
batch is merge-joined with a run without moving the run. Each new batch looks
its lines up in every live run, adds the ones that no run holds as a new run of
level 0, and when a level has `fanout` runs they are merged into one of the
next level. Batches come in ascending document id, so the first document that
holds a line keeps it.

A line's hash is 128 bits: two differently seeded 64-bit hashes.
"""

from __future__ import annotations

import uuid
from collections.abc import Iterator
from contextlib import contextmanager

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import ASCII_SPACE, MAX_LONG, fresh, materialise, release, scratch_path, text_or_empty

MIN_CHARS = 10
BATCHES = 4
FANOUT = 2
_ORDER = "spark.sql.legacy.bucketedTableScan.outputOrdering"
_LISTED = "level int, name string, path string, buckets int"
_UPPER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ"


def line_key(line: Column) -> Column:
    """The line without ASCII white space at its ends, A-Z lower-cased."""
    bare = F.btrim(line, F.lit(ASCII_SPACE))
    # lower() equals the ASCII rule on ASCII text and is much faster than translate()
    return F.when(F.char_length(bare) == F.octet_length(bare), F.lower(bare)).otherwise(F.translate(bare, _UPPER, _UPPER.lower()))


def _lines(text: Column) -> Column:
    return F.split(text, "\n", -1)


def _row_key(id_col: str, text_col: str) -> list[Column]:
    """Null ids act as one largest id; the text's hash tells apart rows that repeat an id."""
    return [F.coalesce(F.col(id_col).cast("long"), F.lit(MAX_LONG)).alias("__ld_doc"), F.xxhash64(text_or_empty(text_col)).alias("__ld_text")]


def hashed_lines(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", min_chars: int = MIN_CHARS) -> DataFrame:
    """One row per line long enough to count: row key, position, two hashes."""
    lines = docs.select(*_row_key(id_col, text_col), F.posexplode(_lines(text_or_empty(text_col))).alias("__ld_pos", "__ld_line"))
    keyed = lines.withColumn("__ld_key", line_key(F.col("__ld_line"))).where(F.char_length("__ld_key") >= min_chars)
    return keyed.select("__ld_doc", "__ld_text", "__ld_pos", F.xxhash64("__ld_key").alias("h1"), F.xxhash64(F.lit(1), "__ld_key").alias("h2"))


@contextmanager
def _bucket_order(spark: SparkSession) -> Iterator[None]:
    """Lets the planner rely on the order inside bucket files (each bucket of a run is one file), so runs are merged unsorted."""
    before = spark.conf.get(_ORDER, "false")
    spark.conf.set(_ORDER, "true")
    try:
        yield
    finally:
        spark.conf.set(_ORDER, before)


class LineRuns:
    """The live runs, by level. Batches must come in ascending document id.

    A run is a Parquet table in the folder, bucketed and sorted by hash. With a
    name, the list of runs is kept beside them, so that a later job can open the
    runs and go on with documents of larger ids.
    """

    def __init__(self, spark: SparkSession, fanout: int = FANOUT, buckets: int | None = None, folder: str | None = None):
        self.spark = spark
        self.fanout = fanout
        self.folder = folder
        self.buckets = buckets or int(spark.conf.get("spark.sql.shuffle.partitions"))
        self.levels: list[list[str]] = []
        self.paths: dict[str, str] = {}
        self.compactions = 0

    @classmethod
    def open(cls, spark: SparkSession, folder: str, fanout: int = FANOUT) -> LineRuns:
        """The runs that save() left in a folder, registered again in this session's catalog."""
        listed = [(r["level"], r["name"], r["path"], r["buckets"]) for r in spark.read.schema(_LISTED).json(f"{folder}/runs").collect()]
        out = cls(spark, fanout, max((b for *_, b in listed), default=None), folder)
        for level, name, path, buckets in sorted(listed):
            while len(out.levels) <= level:
                out.levels.append([])
            spark.sql(f"DROP TABLE IF EXISTS {name}")
            spark.sql(f"CREATE TABLE {name} (h1 BIGINT, h2 BIGINT, owner BIGINT) USING parquet CLUSTERED BY (h1, h2) SORTED BY (h1, h2) INTO {buckets} BUCKETS LOCATION '{path}'")
            out.levels[level].append(name)
            out.paths[name] = path
        return out

    def save(self) -> None:
        """Writes the list of live runs into the folder."""
        rows = [(level, name, self.paths[name], self.buckets) for level, names in enumerate(self.levels) for name in names]
        self.spark.createDataFrame(rows, _LISTED).coalesce(1).write.mode("overwrite").json(f"{self.folder}/runs")

    def _write(self, rows: DataFrame, level: int) -> None:
        name = f"line_run_{uuid.uuid4().hex}"
        path = f"{self.folder}/{name}" if self.folder else scratch_path(self.spark, name)
        (
            rows.repartition(self.buckets, "h1", "h2")
            .write.bucketBy(self.buckets, "h1", "h2")
            .sortBy("h1", "h2")
            .option("path", path)
            .saveAsTable(name)
        )
        self.paths[name] = path
        while len(self.levels) <= level:
            self.levels.append([])
        self.levels[level].append(name)

    def _drop(self, name: str, files: bool = True) -> None:
        self.spark.sql(f"DROP TABLE IF EXISTS {name}")
        path = self.paths.pop(name)
        if files:
            release(self.spark, path)

    def runs(self) -> list[DataFrame]:
        return [self.spark.table(n) for level in self.levels for n in level]

    def ingest(self, lines: DataFrame) -> DataFrame:
        """Adds a batch; returns the rows of it that lose their line: row key and position."""
        firsts = lines.groupBy("h1", "h2").agg(F.min("__ld_doc").alias("owner"), F.max("__ld_doc").alias("last"))
        known = F.lit(None).cast("long")
        for i, run in enumerate(self.runs()):
            firsts = firsts.join(run.withColumnRenamed("owner", f"owner_{i}"), ["h1", "h2"], "left")
            known = F.coalesce(known, F.col(f"owner_{i}"))
        with _bucket_order(self.spark):
            looked_up = materialise(firsts.select("h1", "h2", "owner", "last", known.alias("known")), "line-lookup")
        self._write(looked_up.where("known IS NULL").select("h1", "h2", "owner"), 0)
        shared = looked_up.where("known IS NOT NULL OR owner <> last").select("h1", "h2", F.coalesce("known", "owner").alias("keeper"))
        lost = lines.join(shared, ["h1", "h2"]).where("__ld_doc <> keeper")
        self._compact()
        return lost.select("__ld_doc", "__ld_text", "__ld_pos")

    def _compact(self) -> None:
        level = 0
        while level < len(self.levels):
            names = self.levels[level]
            if len(names) >= self.fanout:
                merged = self.spark.table(names[0])
                for name in names[1:]:
                    merged = merged.unionAll(self.spark.table(name))
                self.levels[level] = []
                self._write(merged, level + 1)
                for name in names:
                    self._drop(name)
                self.compactions += 1
            level += 1

    def close(self) -> None:
        """Takes the runs out of the catalog; without a folder of their own, their files go too."""
        for name in list(self.paths):
            self._drop(name, files=self.folder is None)
        self.levels = []


def dedup_lines(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", min_chars: int = MIN_CHARS, batches: int = BATCHES, fanout: int = FANOUT, names: tuple[str, str, str] = ("kept_text", "n_lines", "n_dropped")) -> DataFrame:
    """docs with kept_text, n_lines (before) and n_dropped added under the given names; input columns of these names are replaced.

    A line whose key of at least min_chars code points stands in two documents
    or more goes from all of them but the smallest id; a document's own repeats
    go or stay together. Null or empty text is one empty line. Null ids count
    as one document after all others; rows that repeat an id are one document.
    A document that loses all its lines keeps the empty text. Empty tables give
    no rows.
    """
    spark = docs.sparkSession
    lines = materialise(hashed_lines(docs, id_col, text_col, min_chars), "line-hashes")
    cuts = lines.agg(F.percentile_approx("__ld_doc", [i / batches for i in range(1, batches)], 10_000)).first()[0] if batches > 1 else None
    edges = sorted(set(cuts or []))
    runs = LineRuns(spark, fanout)
    lost = []
    try:
        for i in range(len(edges) + 1):
            batch = lines
            if i > 0:
                batch = batch.where(F.col("__ld_doc") > edges[i - 1])
            if i < len(edges):
                batch = batch.where(F.col("__ld_doc") <= edges[i])
            lost.append(materialise(runs.ingest(batch), "line-drops"))
    finally:
        runs.close()
    all_lost = lost[0]
    for part in lost[1:]:
        all_lost = all_lost.unionAll(part)
    doc, key, cut, drops = (fresh(docs, f"__ld_{name}") for name in ("doc", "text", "lines", "drops"))
    found = all_lost.groupBy(F.col("__ld_doc").alias(doc), F.col("__ld_text").alias(key)).agg(F.collect_set("__ld_pos").alias(drops))
    of_doc, of_text = _row_key(id_col, text_col)
    joined = docs.withColumns({doc: of_doc, key: of_text}).join(found, [doc, key], "left")
    stay = F.array_except(F.sequence(F.lit(0), F.size(cut) - 1), F.col(drops))
    kept = F.when(F.col(drops).isNull(), text_or_empty(text_col)).otherwise(F.array_join(F.transform(stay, lambda i: F.get(cut, i)), "\n"))
    return (
        joined.withColumn(cut, _lines(text_or_empty(text_col)))
        .withColumns(dict(zip(names, (kept, F.size(cut).cast("long"), F.coalesce(F.size(drops), F.lit(0)).cast("long")))))
        .drop(doc, key, cut, drops)
    )
