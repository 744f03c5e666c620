"""The given tables as graphs. Heavy labels are stored once per application and folder, in two copies: by tail and by head."""

from __future__ import annotations

from functools import cached_property

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from ..sources.dictionary import dictionary, global_rank
from ..sources.graph import EdgeLabel, PropertyGraph, VertexClass, vid
from ..sources.scratch import folder_state, stored_once
from ..sources.tables import html_links, json_property, read_table

CUSTOMER, PART, SUPPLIER, ORDER, NATION, REGION, FEATURE = 1, 2, 3, 4, 5, 6, 7
DOCUMENT, WORD, PAGE, HREF, HOST, EVENT, KIND, ENTRY = 8, 9, 10, 11, 12, 16, 17, 18


class Graphs:
    """Graphs over one folder of tables; everything is lazy."""

    def __init__(self, spark: SparkSession, sf_dir: str):
        self.spark, self.sf_dir = spark, sf_dir

    @cached_property
    def state(self) -> str:
        """Layouts are kept by the state of the folder, so new files are seen."""
        return folder_state(self.spark, self.sf_dir)

    def table(self, name: str) -> DataFrame:
        return read_table(self.spark, self.sf_dir, name)

    def _stored(self, name: str, build, side: str | None = None) -> DataFrame:
        def clustered() -> DataFrame:
            df = build()
            return df.repartitionByRange(side).sortWithinPartitions(side) if side else df

        return stored_once(self.spark, (self.sf_dir, self.state, name, side or "rows"), clustered)

    def _label(self, name: str, build, keys: tuple[str, ...] = (), tree: bool = False) -> EdgeLabel:
        """Rows get their edge id when they are stored: their rank by tail, head and properties, which no parallelism changes. The copy by head is made
        from the copy by tail."""
        rows = lambda: self._stored(name, lambda: global_rank(build(), [F.asc("src"), F.asc("dst"), *map(F.asc, keys)], "eid"), "src")
        return EdgeLabel(name, rows, keys, tree, by_head=lambda: self._stored(name, rows, "dst"))

    # -- edges of the commerce graph
    def bought(self) -> DataFrame:
        """(src, dst) customer -> part, one row per line: parallel edges."""
        lines = self.table("lineitem").select("l_orderkey", "l_partkey", "l_returnflag")
        orders = self.table("orders").select("o_orderkey", "o_custkey")
        return lines.join(orders, lines.l_orderkey == orders.o_orderkey).select(vid(CUSTOMER, F.col("o_custkey")).alias("src"), vid(PART, F.col("l_partkey")).alias("dst"), F.col("l_returnflag").alias("flag"))

    def _likes(self) -> DataFrame:
        return self.bought().groupBy("src", "dst").agg(F.count("*").alias("n_buys"))

    def features(self) -> DataFrame:
        """(part, feature): brand, type, size and the words of the name."""
        words = F.transform(F.split("p_name", " "), lambda w: F.concat(F.lit("word:"), w))
        own = F.array(F.concat(F.lit("brand:"), "p_brand"), F.concat(F.lit("type:"), "p_type"), F.concat(F.lit("size:"), F.col("p_size").cast("string")))
        return self.table("part").select(F.col("p_partkey").alias("part"), F.explode(F.concat(own, words)).alias("feature"))

    def feature_keys(self) -> DataFrame:
        return self._stored("feature_keys", lambda: dictionary(self.features(), "feature", "features"))

    def _feature(self) -> DataFrame:
        return self.features().join(self.feature_keys(), "feature").select(vid(PART, F.col("part")).alias("src"), vid(FEATURE, F.col("key")).alias("dst"))

    def _friend(self) -> DataFrame:
        """Ordered pairs of customers of one nation who like a common part."""
        nation = self.table("customer").select(vid(CUSTOMER, F.col("c_custkey")).alias("src"), "c_nationkey")
        likes = self.commerce().edges("likes").select("src", "dst").join(nation, "src")
        other = likes.withColumnRenamed("src", "o")
        return likes.join(other, ["dst", "c_nationkey"]).where("src <> o").select("src", F.col("o").alias("dst")).distinct()

    def commerce(self) -> PropertyGraph:
        t = self.table
        classes = [
            VertexClass("customer", CUSTOMER, lambda: t("customer").withColumn("vid", vid(CUSTOMER, F.col("c_custkey"))), ("c_custkey", "c_name", "c_nationkey", "c_acctbal", "c_mktsegment")),
            VertexClass("part", PART, lambda: t("part").withColumn("vid", vid(PART, F.col("p_partkey"))), ("p_name", "p_brand", "p_type", "p_size", "p_retailprice")),
            VertexClass("supplier", SUPPLIER, lambda: t("supplier").withColumn("vid", vid(SUPPLIER, F.col("s_suppkey"))), ("s_name", "s_acctbal")),
            VertexClass("order", ORDER, lambda: t("orders").withColumn("vid", vid(ORDER, F.col("o_orderkey"))), ("o_orderstatus", "o_totalprice", "o_orderdate")),
            VertexClass("nation", NATION, lambda: t("nation").withColumn("vid", vid(NATION, F.col("n_nationkey"))), ("n_name",)),
            VertexClass("region", REGION, lambda: t("region").withColumn("vid", vid(REGION, F.col("r_regionkey"))), ("r_name",)),
            VertexClass("feature", FEATURE, lambda: self.feature_keys().select(vid(FEATURE, F.col("key")).alias("vid"), "feature"), ("feature",)),
        ]
        contains = lambda: t("lineitem").select(vid(ORDER, F.col("l_orderkey")).alias("src"), vid(PART, F.col("l_partkey")).alias("dst"), "l_quantity", "l_shipdate", "l_returnflag")
        labels = [
            self._label("likes", self._likes, ("n_buys",)),
            self._label("likes_multi", lambda: self.bought(), ("flag",)),
            self._label("feature", self._feature),
            self._label("friend", self._friend),
            EdgeLabel("placed", lambda: t("orders").select(F.col("o_orderkey").alias("eid"), vid(CUSTOMER, F.col("o_custkey")).alias("src"), vid(ORDER, F.col("o_orderkey")).alias("dst"))),
            self._label("contains", contains, ("l_quantity", "l_shipdate", "l_returnflag")),
            self._label("supplies", lambda: t("lineitem").select(vid(SUPPLIER, F.col("l_suppkey")).alias("src"), vid(PART, F.col("l_partkey")).alias("dst")).distinct()),
            EdgeLabel("in_nation", lambda: t("customer").select(F.col("c_custkey").alias("eid"), vid(CUSTOMER, F.col("c_custkey")).alias("src"), vid(NATION, F.col("c_nationkey")).alias("dst"))),
            EdgeLabel("in_region", lambda: t("nation").select(F.col("n_nationkey").cast("long").alias("eid"), vid(NATION, F.col("n_nationkey")).alias("src"), vid(REGION, F.col("n_regionkey")).alias("dst"))),
        ]
        return PropertyGraph.of(classes, labels)

    def cofriends(self) -> PropertyGraph:
        """The undirected form of `friend`: each pair stored once."""
        once = lambda: self.commerce().edges("friend").where("src < dst").select("eid", "src", "dst")
        return PropertyGraph.of([], [EdgeLabel("cofriend", once)])

    def documents(self) -> PropertyGraph:
        t = self.table

        def rows() -> DataFrame:
            labels = t("labels").select(F.col("doc_id").alias("_d"), "quality", "toxic")
            return t("documents").join(labels, F.col("doc_id") == F.col("_d"), "left").select(vid(DOCUMENT, F.col("doc_id")).alias("vid"), "lang", "source", "n_chars", "quality", "toxic")

        word_keys = lambda: self._stored("word_keys", lambda: dictionary(self.words(), "word", "words"))
        has_word = lambda: self.words().join(word_keys(), "word").select(vid(DOCUMENT, F.col("doc")).alias("src"), vid(WORD, F.col("key")).alias("dst"), F.col("n").alias("times"))
        classes = [
            VertexClass("document", DOCUMENT, rows, ("lang", "source", "n_chars", "quality", "toxic")),
            VertexClass("word", WORD, lambda: word_keys().select(vid(WORD, F.col("key")).alias("vid"), "word"), ("word",)),
        ]
        return PropertyGraph.of(classes, [self._label("has_word", has_word, ("times",))])

    def words(self) -> DataFrame:
        """(doc, word, n): lower-cased letter runs of a document."""
        runs = F.regexp_extract_all(F.lower("text"), F.lit(r"(\p{L}+)"), 1)
        return self.table("documents").select(F.col("doc_id").alias("doc"), F.explode(runs).alias("word")).groupBy("doc", "word").agg(F.count("*").alias("n"))

    def pages(self) -> PropertyGraph:
        t = self.table
        links = lambda: html_links(t("pages")).distinct()
        href_keys = lambda: self._stored("href_keys", lambda: dictionary(links(), "href", "hrefs"))
        hosts = lambda: t("pages").select(F.col("page_id").alias("page"), F.parse_url("url", F.lit("HOST")).alias("host"))
        host_keys = lambda: self._stored("host_keys", lambda: dictionary(hosts(), "host", "hosts"))
        linked = lambda: links().join(href_keys(), "href").select(vid(PAGE, F.col("page")).alias("src"), vid(HREF, F.col("key")).alias("dst"))
        on = lambda: hosts().join(host_keys(), "host").select(vid(PAGE, F.col("page")).alias("src"), vid(HOST, F.col("key")).alias("dst"))
        classes = [VertexClass("page", PAGE, lambda: t("pages").select(vid(PAGE, F.col("page_id")).alias("vid"), "url"), ("url",))]
        return PropertyGraph.of(classes, [self._label("links_to", linked), self._label("on_host", on)])

    def events(self) -> PropertyGraph:
        t = self.table
        kinds = lambda: self._stored("kind_keys", lambda: dictionary(t("events"), "event_type", "kinds"))
        did = lambda: t("events").join(kinds(), "event_type").select(F.col("event_id").alias("eid"), vid(CUSTOMER, F.col("user_id")).alias("src"), vid(KIND, F.col("key")).alias("dst"), "value", "ts")
        after = F.lead("event_id").over(W.partitionBy("user_id").orderBy("ts", "event_id"))
        chain = lambda: t("events").select("event_id", after.alias("n")).where("n IS NOT NULL").select(F.col("event_id").alias("eid"), vid(EVENT, F.col("event_id")).alias("src"), vid(EVENT, F.col("n")).alias("dst"))
        entry = lambda: t("events").select(F.col("event_id").alias("eid"), vid(EVENT, F.col("event_id")).alias("src"), vid(ENTRY, F.col("event_id")).alias("dst"), F.lit("k").alias("key"))
        classes = [
            VertexClass("event", EVENT, lambda: t("events").withColumn("vid", vid(EVENT, F.col("event_id"))), ("event_type", "value", "ts")),
            VertexClass("entry", ENTRY, lambda: t("events").select(vid(ENTRY, F.col("event_id")).alias("vid"), json_property("props", "k", "long").alias("entry_value")), ("entry_value",)),
            VertexClass("kind", KIND, lambda: kinds().select(vid(KIND, F.col("key")).alias("vid"), F.col("event_type").alias("kind")), ("kind",)),
        ]
        return PropertyGraph.of(classes, [EdgeLabel("did", did, ("value", "ts")), EdgeLabel("next", chain, tree=True), EdgeLabel("entry", entry, ("key",), tree=True)])

    # -- points and boxes
    def part_points(self) -> DataFrame:
        x, y = (F.col("p_size") * 2).cast("double"), F.round(F.col("p_retailprice") - 900, 2)
        return self.table("part").select(F.col("p_partkey").alias("poi"), x.alias("bl_x"), y.alias("bl_y"), x.alias("tr_x"), y.alias("tr_y"))

    def order_boxes(self) -> DataFrame:
        day, price = F.unix_timestamp(F.col("l_shipdate").cast("timestamp")).cast("double"), F.col("l_extendedprice")
        return self.table("lineitem").groupBy(F.col("l_orderkey").alias("poi")).agg(F.min(day).alias("bl_x"), F.min(price).alias("bl_y"), F.max(day).alias("tr_x"), F.max(price).alias("tr_y"))

    def embedding_points(self) -> DataFrame:
        x, y = F.col("embedding")[0].cast("double"), F.col("embedding")[1].cast("double")
        return self.table("embeddings").select(F.col("vec_id").alias("poi"), x.alias("bl_x"), y.alias("bl_y"), x.alias("tr_x"), y.alias("tr_y"))

    def supplier_points(self) -> DataFrame:
        x, y = F.col("s_nationkey").cast("double"), F.col("s_acctbal")
        return self.table("supplier").select(F.col("s_suppkey").alias("poi"), x.alias("bl_x"), y.alias("bl_y"), x.alias("tr_x"), y.alias("tr_y"))
