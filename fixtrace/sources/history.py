"""A commit history derived from the star schema, by DataFrame expressions only.

Orders are commits of the customer's nation; feature commits of one block of twelve form a branch that runs beside
the block's main commits and is merged into the first main commit of a later block, unless the block's number is
a multiple of five.  Lineitems are touches of one statement slot of the commit's file.

Ranks within a repository come from counts per day added up over days, so no window holds a whole repository's
commits; block tables, a twelfth of the commits, are worked on in chunks.  Statement windows are keyed by (file, slot).
"""

from __future__ import annotations

import functools
from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import Window as W

from fixtrace.sources.tables import table

BLOCK, TAG_EVERY, FILES, CASE_EVERY, DROPPED_BRANCH = 12, 10, 12, 16, 5
#: Blocks of one window; it does not change what is derived.
CHUNK = 4096


@dataclass(frozen=True)
class History:
    """The derived tables of one scale directory, each computed lazily and named as in the survey."""

    spark: SparkSession
    sf_dir: str

    def _table(self, name: str) -> DataFrame:
        return table(self.spark, self.sf_dir, name)

    @functools.cached_property
    def project(self) -> DataFrame:
        region = self._table("region").select(F.col("r_regionkey").alias("k"), F.col("r_name").alias("domain"))
        return self._table("nation").join(F.broadcast(region), F.col("n_regionkey") == F.col("k")).select(F.col("n_nationkey").cast("int").alias("repo_id"), F.col("n_name").alias("name"), "domain")

    @functools.cached_property
    def _ordered(self) -> DataFrame:
        customer = self._table("customer").select("c_custkey", F.col("c_nationkey").cast("int").alias("repo_id"))
        rows = self._table("orders").join(customer, F.col("o_custkey") == F.col("c_custkey")).select(
            "repo_id", F.col("o_orderkey").alias("commit_id"), F.col("o_orderdate").alias("committed_at"),
            F.when(F.col("o_orderstatus") == "P", "feature").otherwise("main").alias("lane"),
            (F.col("repo_id") * 1000 + F.col("o_custkey") % FILES).cast("int").alias("file_id"),
            F.col("o_orderpriority").alias("priority"), F.col("o_totalprice").alias("price"), F.to_date("o_orderdate").alias("day"),
        )
        days = rows.groupBy("repo_id", "day").agg(F.count("*").alias("n"))
        ahead = days.select("repo_id", "day", (F.sum("n").over(W.partitionBy("repo_id").orderBy("day")) - F.col("n")).alias("ahead"))
        in_day = F.row_number().over(W.partitionBy("repo_id", "day").orderBy("committed_at", "commit_id"))
        rows = rows.withColumn("in_day", in_day).join(ahead, ["repo_id", "day"])
        seq = (F.col("ahead") + F.col("in_day")).cast("int")
        return rows.withColumns({"seq": seq, "block": ((seq - 1) / BLOCK).cast("int")}).drop("in_day", "ahead", "day")

    @functools.cached_property
    def _blocks(self) -> DataFrame:
        """Per block: where its branch forks and merges, and the main commits before it."""
        main = F.col("lane") == "main"
        per = self._ordered.groupBy("repo_id", "block").agg(
            F.min(F.when(~main, F.col("seq"))).alias("first_feature"), F.max(F.when(~main, F.col("seq"))).alias("tip"),
            F.min(F.when(main, F.col("seq"))).alias("first_main"), F.max(F.when(main, F.col("seq"))).alias("last_main"), F.count_if(main).alias("mains"),
        )
        # two levels, so that no window holds all blocks of a repository: within chunks of blocks, and over chunks
        per = per.withColumn("chunk", F.floor(F.col("block") / CHUNK).cast("int"))
        whole = per.groupBy("repo_id", "chunk").agg(F.max("last_main").alias("last"), F.min("first_main").alias("first"), F.sum("mains").alias("n"))
        over = W.partitionBy("repo_id").orderBy("chunk")
        ahead, behind = (W.unboundedPreceding, -1), (1, W.unboundedFollowing)
        chunks = whole.select(
            "repo_id", "chunk", F.max("last").over(over.rowsBetween(*ahead)).alias("c_before"), F.min("first").over(over.rowsBetween(*behind)).alias("c_after"),
            F.coalesce(F.sum("n").over(over.rowsBetween(*ahead)), F.lit(0)).alias("c_mains"),
        )
        w = W.partitionBy("repo_id", "chunk").orderBy("block")
        per = per.join(chunks, ["repo_id", "chunk"])
        before = F.coalesce(F.max("last_main").over(w.rowsBetween(*ahead)), F.col("c_before"))
        after = F.coalesce(F.min("first_main").over(w.rowsBetween(*behind)), F.col("c_after"))
        mains_before = F.coalesce(F.sum("mains").over(w.rowsBetween(*ahead)), F.lit(0)) + F.col("c_mains")
        starts = F.col("first_feature") == F.col("block") * BLOCK + 1
        return per.select(
            "repo_id", "block", "first_feature", "tip", F.coalesce(before, F.lit(0)).alias("main_before"), mains_before.alias("mains_before"),
            F.when(starts, F.coalesce(before, F.lit(0))).otherwise(F.col("first_feature") - 1).alias("branch_fork"),
            F.when(F.col("block") % DROPPED_BRANCH != 0, after).alias("branch_mseq"),
        )

    @functools.cached_property
    def _commit(self) -> DataFrame:
        main = F.col("lane") == "main"
        return self._ordered.join(self._blocks, ["repo_id", "block"]).withColumns({
            "fork": F.when(main, F.col("seq")).otherwise(F.col("branch_fork")).cast("int"),
            "mseq": F.when(~main, F.col("branch_mseq")).cast("int"),
        })

    @functools.cached_property
    def commit(self) -> DataFrame:
        return self._commit.select("repo_id", "commit_id", "committed_at", "seq", "block", "lane", "file_id", "fork", "mseq")

    @functools.cached_property
    def commit_edge(self) -> DataFrame:
        w = W.partitionBy("repo_id", "block", "lane").orderBy("seq")
        parent = F.lag("seq").over(w)
        first = F.when(F.col("lane") == "main", F.col("main_before")).otherwise(F.col("branch_fork"))
        line = self._commit.select("repo_id", F.col("commit_id").alias("child_id"), F.coalesce(parent, first).cast("int").alias("seq"), F.lit(0).alias("parent_no"))
        ids = self._ordered.select("repo_id", "seq", "commit_id")
        straight = line.join(ids.withColumnRenamed("commit_id", "parent_id"), ["repo_id", "seq"])
        merged = self._blocks.where("tip is not null and branch_mseq is not null")
        tips = merged.join(ids.withColumnRenamed("commit_id", "parent_id"), (merged.repo_id == ids.repo_id) & (merged.tip == ids.seq)).select(merged.repo_id, "parent_id", F.col("branch_mseq").cast("int").alias("seq"))
        joins = tips.join(ids.withColumnRenamed("commit_id", "child_id"), ["repo_id", "seq"]).withColumn("parent_no", F.lit(1))
        columns = ["repo_id", "child_id", "parent_id", "parent_no"]
        return straight.select(columns).unionByName(joins.select(columns))

    @functools.cached_property
    def version_tag(self) -> DataFrame:
        rank = F.col("mains_before") + F.row_number().over(W.partitionBy("repo_id", "block").orderBy("seq"))
        mains = self._commit.where("lane = 'main'").withColumn("rank", rank).where(F.col("rank") % TAG_EVERY == 0)
        no = (F.col("rank") / TAG_EVERY).cast("int")
        return mains.select("repo_id", F.concat(F.lit("v"), no).alias("tag"), no.alias("tag_no"), "commit_id", "seq")

    @functools.cached_property
    def line(self) -> DataFrame:
        """Lineitems, one for each (order, line number): the first by the remaining columns."""
        keys = ["l_partkey", "l_suppkey", "l_quantity", "l_extendedprice", "l_discount", "l_tax", "l_shipdate"]
        first = F.min(F.struct(*keys, "l_returnflag")).alias("x")
        # shuffled by order alone, which is how touches meet their commits
        return self._table("lineitem").repartition("l_orderkey").groupBy(F.col("l_orderkey").alias("commit_id"), F.col("l_linenumber").cast("int").alias("slot")).agg(first).select(
            "commit_id", "slot", F.col("x.l_partkey").alias("part"), F.col("x.l_quantity").cast("int").alias("quantity"), F.col("x.l_returnflag").alias("flag")
        )

    @functools.cached_property
    def touch(self) -> DataFrame:
        op = F.when(F.col("flag") == "A", "add").when(F.col("flag") == "R", "del").otherwise("ctx")
        return self.line.join(self.commit, "commit_id").select(
            "repo_id", "file_id", "slot", "commit_id", "committed_at", "seq", "block", "lane", "fork", "mseq",
            op.alias("op"), (F.col("quantity") % 4).alias("edit_kind"), "part",
        )

    @functools.cached_property
    def fix_case(self) -> DataFrame:
        picked = self._commit.where((F.col("lane") == "main") & (F.col("priority") == "1-URGENT") & (F.col("commit_id") % CASE_EVERY == 0))
        lines = self.line.join(picked.select("commit_id"), "commit_id", "left_semi").groupBy("commit_id").agg(
            F.count_if(F.col("flag") == "A").alias("added"), F.count_if(F.col("flag") == "R").alias("deleted"), F.min("part").alias("part"),
            F.min(F.when(F.col("flag").isin("A", "R"), F.col("slot"))).alias("trigger_slot"),
        )
        kind = F.when(F.col("added") == 0, "del").when(F.col("deleted") == 0, "add").otherwise("both")
        return picked.join(lines.where("added + deleted > 0"), "commit_id").select(
            F.col("commit_id").alias("vuln_id"), "repo_id", F.col("commit_id").alias("fix_commit_id"), F.col("seq").alias("fix_seq"), "file_id",
            kind.alias("patch_class"), F.pmod("part", F.lit(7)).cast("int").alias("vuln_type"), "added", "deleted", "trigger_slot",
            F.col("committed_at").alias("published_at"), F.least(F.lit(10.0), F.round(F.col("price") / 50000, 1)).alias("severity"),
        )
