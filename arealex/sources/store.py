"""Indexes on disk: sharded, sorted Parquet postings with a manifest row.

Postings are parted by a hash shard of the element, and in a file sorted by element and falling bound, so that a probe prunes shards by the batch's elements and skips row groups by bound. Space, weights and orders are frozen with a version: objects appended later are signed with them, and answers refer to the version's weights.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from arealex.functions.cells import Space
from arealex.functions.similarity import SIDES, UNIT, area, box
from arealex.operators import probes as P
from arealex.operators import quadcells as Q
from arealex.operators import signatures as S

PARTS = ("objects", "stats", "cell_stats", "token", "cell", "selection", "quad")
MANIFEST = "kind string, level int, x0 bigint, y0 bigint, x_bits int, y_bits int, n_objects bigint, shards int, min_tau_r_bp bigint, min_tau_t_bp bigint, measure string, budget int, max_level int"


#: Files that a shard is written as, at most.
SALTS = 8


def _shard(element: str, shards: int):
    return F.pmod(F.xxhash64(element), F.lit(shards)).cast("int")


def _written(postings: DataFrame, element: str, bound: str, path: str, shards: int, mode: str) -> None:
    # A shard's rows go to several tasks, so that a list of nearly all objects is written by many; each file is sorted.
    parted = postings.withColumn("shard", _shard(element, shards)).repartition("shard", F.pmod(F.xxhash64("object_id"), F.lit(SALTS))).sortWithinPartitions("shard", element, F.desc(bound))
    parted.write.mode(mode).partitionBy("shard").parquet(path)


def _useful(ix: P.Index, postings: DataFrame, bound: str, total: str, least_bp: int) -> DataFrame:
    """Drops postings that no query with a threshold of at least ``least_bp`` can use: what is shared is at least tau times the object's own total."""
    if not least_bp:
        return postings
    own = ix.full.select("object_id", area(box()).alias("area"), "w_total")
    return postings.join(own.select("object_id", total), "object_id").where(UNIT * F.col(bound) >= least_bp * F.col(total)).drop(total)


def build_index(ix: P.Index, path: str, level: int = 6, shards: int = 64, min_tau_r_bp: int = 0, min_tau_t_bp: int = 0, budget: int = 0, max_level: int = 6) -> None:
    """Writes objects, stats, token and cell postings, cell counts and the manifest under ``path``; with a ``budget``, also the cells chosen for each token down to ``max_level`` and the postings on them."""
    spark = ix.objects.sparkSession
    ix.full.write.mode("overwrite").parquet(f"{path}/objects")
    ix.stats.write.mode("overwrite").parquet(f"{path}/stats")
    cells = ix.cells(level)
    cells.select("cell", "n_obj").distinct().write.mode("overwrite").parquet(f"{path}/cell_stats")
    _written(_useful(ix, ix.tokens, "bound_t", "w_total", min_tau_t_bp), "token", "bound_t", f"{path}/token", shards, "overwrite")
    _written(_useful(ix, cells, "bound_r", "area", min_tau_r_bp), "cell", "bound_r", f"{path}/cell", shards, "overwrite")
    if budget:
        Q.pick_quad_cells(ix, budget, max_level).write.mode("overwrite").parquet(f"{path}/selection")
        chosen = Q.quad_postings(ix, spark.read.schema(Q.SELECTION).parquet(f"{path}/selection"), max_level)
        chosen = _useful(ix, _useful(ix, chosen, "bound_t", "w_total", min_tau_t_bp), "bound_r", "area", min_tau_r_bp)
        _written(chosen, "token", "bound_r", f"{path}/quad", shards, "overwrite")
    s = ix.space
    row = [("token+cell", level, s.x0, s.y0, s.x_bits, s.y_bits, ix.count(), shards, min_tau_r_bp, min_tau_t_bp, ix.measure, budget, max_level)]
    spark.createDataFrame(row, MANIFEST).coalesce(1).write.mode("overwrite").parquet(f"{path}/manifest")


class StoredIndex(P.Index):
    """An index whose postings are read from disk."""

    def __init__(self, spark: SparkSession, path: str):
        self.manifest = spark.read.schema(MANIFEST).parquet(f"{path}/manifest").first()
        m = self.manifest
        self.spark, self.path, self.level = spark, path, m.level
        objects = spark.read.parquet(f"{path}/objects")
        super().__init__(objects.select("object_id", *SIDES, "tokens"), m.measure, space=Space(m.x0, m.y0, m.x_bits, m.y_bits), stats=spark.read.parquet(f"{path}/stats"))
        self._made |= {"full": objects, "count": m.n_objects, "tokens": spark.read.parquet(f"{path}/token"), ("cells", m.level): spark.read.parquet(f"{path}/cell"), ("counts", m.level): spark.read.parquet(f"{path}/cell_stats")}

    def check(self, q: DataFrame) -> DataFrame:
        """The batch, if the index holds all postings that it can need."""
        low = q.agg(F.min("tau_r_bp"), F.min("tau_t_bp")).first()
        if low[0] is not None and (low[0] < self.manifest.min_tau_r_bp or low[1] < self.manifest.min_tau_t_bp):
            raise ValueError("a threshold is lower than the index was built for")
        return q

    def token_hits(self, q: DataFrame) -> DataFrame:
        """Bounded token probe of a batch: shards of its tokens only, and a literal least bound that the scan can use."""
        prefix = P.token_prefix(self, self.check(q)).select("query_id", "token", "w_total", "tau_t_bp")
        rows = prefix.select(_shard("token", self.manifest.shards).alias("shard"), (F.col("tau_t_bp") * F.col("w_total")).alias("c")).agg(F.collect_set("shard"), F.min("c")).first()
        useful = self.tokens.where(F.col("shard").isin(rows[0] or [-1]) & (F.col("bound_t") >= (rows[1] or 0) // UNIT))
        return useful.select("object_id", "token", "bound_t").join(prefix, "token").where(P._enough_t(self, "bound_t"))

    def quad_hits(self, q: DataFrame) -> DataFrame:
        """Probe of the stored postings on chosen cells: shards of the batch's prefix tokens only, and literal least bounds that the scan can use."""
        if not self.manifest.budget:
            raise ValueError("the index has no chosen cells")
        selection = self._once("selection", lambda: self.spark.read.schema(Q.SELECTION).parquet(f"{self.path}/selection"))
        prefix = Q.quad_prefix(self, self.check(q), selection, self.manifest.max_level).select("query_id", "token", "level", "cell", "w_total", "tau_t_bp", "area", "tau_r_bp")
        # A prefix has at most the budget's cells for each word of a query, and a small batch is collected as such.
        if P.is_small(q):
            prefix = self.spark.createDataFrame(prefix.collect(), prefix.schema)
        rows = prefix.agg(F.collect_set(_shard("token", self.manifest.shards)), F.min(F.col("tau_t_bp") * F.col("w_total")), F.min(F.col("tau_r_bp") * F.col("area"))).first()
        lists = self.spark.read.parquet(f"{self.path}/quad")
        useful = lists.where(F.col("shard").isin(rows[0] or [-1]) & (F.col("bound_t") >= (rows[1] or 0) // UNIT) & (F.col("bound_r") >= (rows[2] or 0) // UNIT))
        on = useful.select("object_id", "token", "level", "cell", "bound_t", "bound_r").join(prefix, ["token", "level", "cell"])
        return on.where(P._enough_t(self, "bound_t") & P._enough_r(self, "bound_r"))

    def candidates(self, q: DataFrame, method: str = "auto") -> DataFrame:
        """Pairs by the stored postings: ``quad_pair`` where the index has chosen cells, else ``two_filter``."""
        if method == "quad_pair" or method == "auto" and self.manifest.budget:
            return P.pairs_of(self.quad_hits(q))
        near = P.pairs_of(P.grid_bounded_hits(self, self.check(q), self.level))
        if method == "grid_bounded":
            return near
        return P.pairs_of(self.token_hits(q).select("query_id", "object_id").join(near, ["query_id", "object_id"], "left_semi"))

    def search(self, q: DataFrame, method: str = "auto") -> DataFrame:
        """Answers by the stored postings, for thresholds above 0."""
        from arealex.operators.verify import verify

        return verify(self, q, self.candidates(q, method))

    def sizes(self) -> DataFrame:
        """kind, rows and bytes of the files of each part of the index."""
        hadoop, out = self.spark.sparkContext._jsc.hadoopConfiguration(), []
        for part in PARTS:
            target = self.spark.sparkContext._jvm.org.apache.hadoop.fs.Path(f"{self.path}/{part}")
            fs = target.getFileSystem(hadoop)
            if fs.exists(target):
                out.append((part, self.spark.read.parquet(f"{self.path}/{part}").count(), fs.getContentSummary(target).getLength()))
        return self.spark.createDataFrame(out, "kind string, rows bigint, bytes bigint")

    def append(self, objects: DataFrame) -> None:
        """Adds objects under the frozen weights, orders and space. Tokens of the version only count; a rectangle outside the space is an error, as its cells would be cut off."""
        s, m = self.space, self.manifest
        outside = objects.where((F.col("x0") < s.x0) | (F.col("y0") < s.y0) | (F.col("x1") > s.x0 + (1 << s.x_bits)) | (F.col("y1") > s.y0 + (1 << s.y_bits)))
        if outside.limit(1).count():
            raise ValueError("a rectangle lies outside the index's space")
        new = P.Index(objects, m.measure, space=s, stats=self.stats)
        sig = S.grid_signature(objects, s, self.level).join(self.cell_counts(self.level), "cell", "left").na.fill(0, ["n_obj"])
        cells = S.with_bound(sig, ["object_id"], S.element_order("cell"), "bound_r")
        if m.budget:
            selection = self.spark.read.schema(Q.SELECTION).parquet(f"{self.path}/selection")
            _written(Q.quad_postings(new, selection, m.max_level), "token", "bound_r", f"{self.path}/quad", m.shards, "append")
        _written(new.tokens, "token", "bound_t", f"{self.path}/token", m.shards, "append")
        _written(cells, "cell", "bound_r", f"{self.path}/cell", m.shards, "append")
        fresh = cells.where("n_obj = 0").select("cell", "n_obj").distinct()
        fresh.write.mode("append").parquet(f"{self.path}/cell_stats")
        new.full.write.mode("append").parquet(f"{self.path}/objects")


def load_index(spark: SparkSession, path: str) -> StoredIndex:
    return StoredIndex(spark, path)


def describe_index(spark: SparkSession, path: str) -> DataFrame:
    """The manifest, with the rows of each part."""
    out = spark.read.schema(MANIFEST).parquet(f"{path}/manifest")
    for part in ("objects", "stats", "token", "cell"):
        out = out.crossJoin(spark.read.parquet(f"{path}/{part}").agg(F.count("*").alias(f"{part}_rows")))
    return out
