"""Derived inputs on the given tables: page signals, homonyms, edges, records, defects, ontology, planted text and vectors."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from kgrefine.operators.ontology import dot


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def page_signals(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Order lines as the pages of an order."""
    li = table(spark, sf_dir, "lineitem")
    n = F.row_number().over(Window.partitionBy("l_orderkey").orderBy("l_linenumber", "l_partkey", "l_suppkey"))
    return li.select(F.col("l_orderkey").alias("doc_id"), n.alias("page_no"), F.when((F.col("l_tax") == 0) & (F.col("l_discount") == 0), 0.0).otherwise(1.0).alias("area"),
                     (F.col("l_discount") * 1.8).alias("img_block"), (F.col("l_tax") * 2).alias("img_xref"), F.when(F.col("l_tax") > 0, 1).otherwise(0).alias("n_xref"),
                     (F.greatest(F.col("l_quantity") - 15, F.lit(0)) * 20).cast("long").alias("chars"), (F.col("l_linenumber") * 45).cast("long").alias("drawings"))


def homonyms(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Parts as persons: few names, many contexts; forty make a document."""
    p = table(spark, sf_dir, "part")
    return p.select(F.expr("p_partkey div 40").alias("doc_id"), F.col("p_partkey").alias("ent_id"), F.lit("PERSON").alias("type"), F.col("p_name").alias("name"),
                    F.col("p_brand").alias("role"), F.col("p_type").alias("org"), F.floor(F.col("p_size") / 10).cast("string").alias("loc"), F.col("p_brand").alias("employee_no"))


def edges(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Supplier to part, type by the flag words in varying spelling, qualifiers of varying richness; the document is the order modulo 200."""
    li = table(spark, sf_dir, "lineitem")
    word = F.concat(F.lit("Flag "), "l_returnflag", F.lit(" To "), "l_linestatus")
    shape = F.col("l_orderkey") % 3
    label = F.when(shape == 0, word).when(shape == 1, F.upper(F.translate(word, " ", "_"))).otherwise(F.lower(F.translate(word, " ", "-")))
    quals = F.map_filter(F.create_map(F.lit("date"), F.when(F.col("l_partkey") % 3 != 0, F.date_format("l_shipdate", "yyyy-MM-dd")), F.lit("discount"), F.when(F.col("l_partkey") % 5 != 0, F.col("l_discount").cast("string")),
                                      F.lit("quantity"), F.when(F.col("l_suppkey") % 2 == 0, F.col("l_quantity").cast("int").cast("string"))), lambda k, v: v.isNotNull())
    order = F.col("l_orderkey") * 1000000 + F.col("l_linenumber") * 100000 + F.col("l_partkey")
    return li.select((F.col("l_orderkey") % 200).alias("doc_id"), F.col("l_suppkey").alias("src"), F.col("l_partkey").alias("dst"), label.alias("rel_type"), quals.alias("quals"), order.alias("ord"))


def records(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Events as stream records; time as a zoned timestamp for watermarks."""
    e = table(spark, sf_dir, "events")
    return e.select(F.col("event_id").alias("record_id"), F.when(F.col("event_type") == "signup", "file").otherwise("inline").alias("kind"), F.col("ts").cast("timestamp").alias("ts"),
                    F.col("event_id").alias("seq"), (F.col("event_type") != "error").alias("ok"), F.col("value").alias("duration_s"), "user_id", "event_type", "props")


TITLES = ("Dr.", "Captain", "Agent")


def dirty_entities(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Parts as persons with planted defects and the clean twin's key ``gold_id``: titles on every fifth, ids of varying shape, an indicator word on every seventh."""
    p = table(spark, sf_dir, "part")
    k = F.col("p_partkey")
    titled = F.when(k % 5 == 0, F.concat(F.element_at(F.array(*[F.lit(t) for t in TITLES]), (k % 3 + 1).cast("int")), F.lit(" "), "p_name")).otherwise(F.col("p_name"))
    name = F.when(k % 7 == 0, F.concat(titled, F.lit(" company"))).otherwise(titled)
    ident = F.element_at(F.array(*[F.concat(F.lit(s), k.cast("string")) for s in ("per_", "P-", "e", "id:", "n", "x_", "#")]), (k % 7 + 1).cast("int"))
    return p.select((k % 50).alias("doc_id"), ident.alias("ent_id"), F.lit("PERSON").alias("type"), name.alias("name"), F.concat_ws("|", "p_name", (k % 50).cast("string"), (k % 7 == 0).cast("string")).alias("gold_id"), k.alias("part_key"))


def dirty_relations(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A part to the one fifty keys on, in the same document: self loops on every ninth, dangling targets on every fiftieth plus one, labels in varying spelling."""
    p = table(spark, sf_dir, "part").select(F.col("p_partkey").alias("k"))
    ident = lambda k: F.element_at(F.array(*[F.concat(F.lit(s), k.cast("string")) for s in ("per_", "P-", "e", "id:", "n", "x_", "#")]), (k % 7 + 1).cast("int"))
    k = F.col("k")
    dst = F.when(k % 9 == 0, ident(k)).when(k % 50 == 1, F.concat(F.lit("gone_"), k.cast("string"))).otherwise(ident(k + 50))
    label = F.element_at(F.array(F.lit("reported to"), F.lit("Reported-To"), F.lit("REPORTED_TO"), F.lit("surveiled")), (k % 4 + 1).cast("int"))
    top = table(spark, sf_dir, "part").agg(F.max("p_partkey").alias("top"))
    return p.crossJoin(F.broadcast(top)).where(F.col("k") + 50 <= F.col("top")).select((k % 50).alias("doc_id"), ident(k).alias("src"), dst.alias("dst"), label.alias("rel_type"), F.create_map(F.lit("n"), k.cast("string")).alias("quals"), k.alias("ord"))


def unit(v):
    return F.transform(F.array(v), lambda a: F.transform(a, lambda x: x / F.sqrt(dot(a, a))))[0]


def _mix(a, wa, b, wb):
    return unit(F.zip_with(a, b, lambda x, y: x.cast("double") * wa + y.cast("double") * wb))


def ontology_classes(spark: SparkSession, sf_dir: str, n: int = 100, parents: int = 10) -> DataFrame:
    """(class_id, label, definition, parent, vec): vectors of the first ids; a child leans on its parent."""
    e = table(spark, sf_dir, "embeddings").where(F.col("vec_id") < n).select("vec_id", "embedding", (F.col("vec_id") % parents).alias("parent"))
    p = e.select(F.col("vec_id").alias("parent"), F.col("embedding").alias("pvec"))
    vec = F.when(F.col("vec_id") < parents, F.transform("embedding", lambda x: x.cast("double"))).otherwise(_mix(F.col("pvec"), 0.8, F.col("embedding"), 0.6))
    label = F.concat(F.lit("class "), F.col("vec_id").cast("string"))
    return e.join(F.broadcast(p), "parent").select(F.col("vec_id").alias("class_id"), label.alias("label"), F.concat(F.lit("things of kind "), F.col("vec_id").cast("string"), F.lit(" and "), F.repeat(F.lit("x"), (F.col("vec_id") * 37 % 400).cast("int"))).alias("definition"),
                                                   F.when(F.col("vec_id") >= parents, F.col("parent")).alias("parent"), vec.alias("vec"))


def subclass_edges(classes: DataFrame) -> DataFrame:
    return classes.where("parent is not null").select(F.col("class_id").alias("child"), "parent")


def query_windows(spark: SparkSession, sf_dir: str, classes: DataFrame, n: int = 100, lean: tuple[float, ...] = (0.45, 0.5, 0.55, 0.65), turn: int = 1) -> DataFrame:
    """(doc_id, win_no, vec, gold_class): a planted mixture of the class ``vec_id * turn % n`` and the row's own vector; four rows make a document."""
    e = table(spark, sf_dir, "embeddings").where(F.col("vec_id") >= n).select("vec_id", "embedding", (F.col("vec_id") * turn % n).alias("gold_class"))
    a = F.element_at(F.array(*[F.lit(x) for x in lean]), (F.floor(F.col("vec_id") / n) % 4 + 1).cast("int"))
    rows = e.join(F.broadcast(classes.select(F.col("class_id").alias("gold_class"), F.col("vec").alias("cvec"))), "gold_class").withColumn("a", a)
    vec = unit(F.zip_with("cvec", "embedding", lambda x, y: x * F.col("a") + y.cast("double") * (1 - F.col("a"))))
    return rows.select(F.floor(F.col("vec_id") / 4).alias("doc_id"), (F.col("vec_id") % 4).cast("int").alias("win_no"), vec.alias("vec"), "gold_class", "vec_id")


def near_duplicate_vectors(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(vec_id, vec, gold_id): all vectors, and for every tenth a copy, moved slightly, under its id plus one million."""
    e = table(spark, sf_dir, "embeddings").select("vec_id", F.transform("embedding", lambda x: x.cast("double")).alias("vec"))
    nxt = e.select((F.col("vec_id") - 1).alias("vec_id"), F.col("vec").alias("nvec"))
    copy = e.where("vec_id % 10 = 0").join(nxt, "vec_id").select((F.col("vec_id") + 1000000).alias("vec_id"), _mix(F.col("vec"), 0.9, F.col("nvec"), 0.1).alias("vec"), F.col("vec_id").alias("gold_id"))
    return e.select("vec_id", "vec", F.col("vec_id").alias("gold_id")).unionByName(copy)


def planted_text(spark: SparkSession, sf_dir: str) -> tuple[DataFrame, DataFrame]:
    """(documents, persons): each document ends with a sentence that holds a part's name in full, initialled and misspelt."""
    names = table(spark, sf_dir, "part").select((F.col("p_partkey") - 1).alias("n"), "p_name")
    count = names.agg(F.count("*").alias("count"))
    d = table(spark, sf_dir, "documents").select("doc_id", "text").crossJoin(F.broadcast(count)).withColumn("n", F.col("doc_id") % F.col("count")).join(names, "n")
    t = F.split("p_name", " ")
    wrong = F.when(F.col("doc_id") % 2 == 0, F.concat(F.substring(t[0], 1, 1), F.substring(t[0], 3, 100))).otherwise(F.concat(t[0], F.substring(t[0], -1, 1)))
    line = F.concat(F.lit("\nseen: "), "p_name", F.lit(" then "), F.substring(t[0], 1, 1), F.lit(". "), t[1], F.lit(" then "), wrong, F.lit(" "), t[1], F.lit(" end"))
    docs = d.select("doc_id", F.concat("text", line).alias("text"), "p_name", wrong.alias("wrong"))
    return docs, d.select("doc_id", F.concat(F.lit("e"), F.col("doc_id").cast("string")).alias("ent_id"), F.lit("PERSON").alias("type"), F.col("p_name").alias("name"))


def planted_statements(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(k, doc_id, page_no, src, label, dst, year): a part says something of the next one of its document; twenty parts make a document, four a page.

    Names have titles on every fifth and an indicator word on every seventh; every ninth part speaks of itself.
    """
    p = table(spark, sf_dir, "part").select(F.col("p_partkey").alias("k"), F.initcap("p_name").alias("name"))
    k = F.col("k")
    title = F.when(k % 5 == 0, F.concat(F.element_at(F.array(*[F.lit(t) for t in TITLES]), (k % 3 + 1).cast("int")), F.lit(" "))).otherwise("")
    p = p.select("k", F.expr("k div 20").alias("doc_id"), F.concat(title, "name", F.when(k % 7 == 0, " Company").otherwise("")).alias("src"))
    nxt = p.select(F.expr("doc_id * 20 + (k + 19) % 20").alias("k"), F.col("src").alias("next"))
    label = F.element_at(F.array(F.lit("reported to"), F.lit("Reported-To"), F.lit("REPORTED_TO"), F.lit("surveiled")), (k % 4 + 1).cast("int"))
    return p.join(nxt, "k", "left").select("k", "doc_id", (F.expr("(k % 20) div 4") + 1).cast("int").alias("page_no"), "src", label.alias("label"),
                                           F.when(k % 9 == 0, F.col("src")).otherwise(F.coalesce("next", "src")).alias("dst"), (F.lit(1990) + k % 30).cast("string").alias("year"))


def planted_pages(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Pages of ``planted_statements`` with signals, ``text`` and ``vision_text``: pages 2 to 4 are images whose text layer is garbled, vision reads them as they are."""
    st = planted_statements(spark, sf_dir)
    line = F.concat("src", F.lit(" -- "), "label", F.lit(" -- "), "dst", F.lit(" ("), "year", F.lit(")."))
    pages = st.groupBy("doc_id", "page_no").agg(F.array_join(F.transform(F.array_sort(F.collect_list(F.struct("k", line.alias("line")))), lambda x: x["line"]), "\n").alias("vision_text"))  # four lines
    image = F.col("page_no").between(2, 4)
    text = F.when(image, F.translate("vision_text", "aeiou", "43107")).otherwise(F.col("vision_text"))
    return pages.select("doc_id", "page_no", F.lit(1.0).alias("area"), F.when(image, 0.9).otherwise(0.0).alias("img_block"), F.lit(0.0).alias("img_xref"), F.lit(0).alias("n_xref"),
                        F.length("vision_text").cast("long").alias("chars"), F.lit(0).cast("long").alias("drawings"), text.alias("text"), "vision_text")
