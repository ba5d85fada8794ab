"""The workloads: data sets derived from the given tables.

The relational columns are independent of each other, so the dense workloads plant their class: it follows from three
features, two further features repeat some of their information (twins) and the rest is noise.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions import encode
from ..plans.dataset import Dataset, SparseDataset
from ..plans.layout import hashed_postings, to_postings
from ..plans.tokens import TokenSet
from .tables import spread, table

#: Feature orders (fixed values: they decide ties).
GATE = ["qty", "qty_band", "disc", "disc_hi", "tax", "rf", "ls", "ln", "ship_month", "ship_quarter"]
STAR = [*GATE, "ship_year", "ostatus", "oprio", "oyear", "omonth", "oprice", "seg", "cnation", "cregion", "brand", "ptype", "psize", "pprice", "snation"]
PLANTED, TWINS = ["disc", "tax", "qty"], ["disc_hi", "qty_band"]
EVENTS = ["hour", "weekday", "user_bucket", "value_band", "props_band"]


def line_codes() -> dict[str, Column]:
    """The codes of a line item, by feature."""
    qty, disc = F.col("l_quantity"), F.round(F.col("l_discount") * 100).cast("int")
    return {
        "qty": (F.floor(qty) - 1).cast("int"),
        "qty_band": F.floor((qty - 1) / 10).cast("int"),
        "disc": disc,
        "disc_hi": F.when(disc >= 5, 1).otherwise(0),
        "tax": F.round(F.col("l_tax") * 100).cast("int"),
        "rf": encode.rank_code(F.col("l_returnflag"), ["A", "N", "R"]),
        "ls": encode.rank_code(F.col("l_linestatus"), ["F", "O"]),
        "ln": (F.col("l_linenumber") - 1).cast("int"),
        "ship_month": (F.month("l_shipdate") - 1).cast("int"),
        "ship_quarter": (F.quarter("l_shipdate") - 1).cast("int"),
    }


def targets() -> dict[str, Column]:
    c = line_codes()
    gate = F.when(((c["disc"] >= 5) & (c["tax"] >= 4)) | (F.col("l_quantity") >= 46), 1).otherwise(0)
    flip = F.pmod(F.col("l_orderkey") * 16_807 + F.col("l_partkey") * 69_621 + F.col("l_suppkey"), F.lit(2_147_483_647)) % 100 < 10
    return {
        "gate": gate,
        "xor": F.when(F.col("l_quantity") <= 15, c["disc_hi"]).otherwise(c["disc_hi"].bitwiseXOR(c["tax"] % 2)),
        "rare": F.when(F.col("l_quantity") == 50, 1).otherwise(0),
        "noisy": F.when(flip, 1 - gate).otherwise(gate),
    }


def lines(spark: SparkSession, sf_dir: str, target: str = "gate") -> Dataset:
    """The ten-column set of line items with the class ``target``: gate, xor, rare or noisy."""
    codes = line_codes()
    df = spread(table(spark, sf_dir, "lineitem")).select(*[c.alias(f) for f, c in codes.items()], targets()[target].cast("int").alias("y"), "l_orderkey")
    return Dataset(df, list(GATE), name=target)


def star(spark: SparkSession, sf_dir: str, widen: int = 0, target: str = "gate") -> Dataset:
    """Line items with the codes of everything they refer to: 24 features, and ``widen`` more twins and hash columns."""
    t = lambda name: table(spark, sf_dir, name)
    nation = t("nation").select("n_nationkey", F.col("n_regionkey").cast("int").alias("cregion"))
    customer = t("customer").join(nation, F.col("c_nationkey") == F.col("n_nationkey")).select("c_custkey", encode_segment().alias("seg"), F.col("c_nationkey").cast("int").alias("cnation"), "cregion")
    orders = t("orders").select(
        "o_orderkey", "o_custkey",
        encode.rank_code(F.col("o_orderstatus"), ["F", "O", "P"]).alias("ostatus"),
        encode.rank_code(F.col("o_orderpriority"), ["1-URGENT", "2-HIGH", "3-MEDIUM", "4-NOT SPECIFIED", "5-LOW"]).alias("oprio"),
        (F.year("o_orderdate") - 1995).cast("int").alias("oyear"), (F.month("o_orderdate") - 1).cast("int").alias("omonth"),
        F.floor(F.col("o_totalprice") / 50_000).cast("int").alias("oprice"),
    )
    part = t("part")
    part = part.select("p_partkey", "p_brand", "p_type", F.floor((F.col("p_size") - 1) / 5).cast("int").alias("psize"), F.floor((F.col("p_retailprice") - 900) / 10).cast("int").alias("pprice"))
    part = encode.with_dictionary(encode.with_dictionary(part, "p_brand", "brand"), "p_type", "ptype").drop("p_brand", "p_type")
    supplier = t("supplier").select("s_suppkey", F.col("s_nationkey").cast("int").alias("snation"))
    codes = line_codes()
    line = spread(t("lineitem")).select("l_orderkey", "l_partkey", "l_suppkey", *[c.alias(f) for f, c in codes.items()], (F.year("l_shipdate") - 1995).cast("int").alias("ship_year"), targets()[target].cast("int").alias("y"))
    df = line.join(orders, F.col("l_orderkey") == F.col("o_orderkey")).join(customer, F.col("o_custkey") == F.col("c_custkey"))
    df = df.join(part, F.col("l_partkey") == F.col("p_partkey")).join(supplier, F.col("l_suppkey") == F.col("s_suppkey"))
    features = list(STAR)
    if widen:
        made = {f"w{i}": twin(i) for i in range(widen)}
        df, features = df.withColumns(made), [*features, *made]
    return Dataset(df.select(*features, "y", "l_orderkey"), features, name="star")


def encode_segment() -> Column:
    return encode.rank_code(F.col("c_mktsegment"), ["AUTOMOBILE", "BUILDING", "FURNITURE", "HOUSEHOLD", "MACHINERY"])


def twin(i: int) -> Column:
    """A coarser or hashed version of one of the star's codes."""
    base = F.col(STAR[i % len(STAR)])
    match i % 3:
        case 0:
            return (base % (2 + i % 7)).cast("int")
        case 1:
            return F.floor(base / (2 + i % 5)).cast("int")
    return F.pmod(F.xxhash64("l_orderkey", base, F.lit(i)), F.lit(2 + i % 15)).cast("int")


def embed(spark: SparkSession, sf_dir: str, bins: int = 4, size: int = 64, binary: bool = False, mode: str = "width") -> Dataset:
    """The positions of the embeddings in bins of equal width (or frequency); the class is the label or label < 5."""
    names = [f"e{i}" for i in range(size)]
    rows = encode.positions(table(spark, sf_dir, "embeddings").select("vec_id", "embedding", "label"), "embedding", size)
    label = F.when(F.col("label") < 5, 1).otherwise(0) if binary else F.col("label")
    if mode == "frequency":
        rows = encode.equal_frequency(rows, names, bins).select("vec_id", label.cast("int").alias("y"), *[F.col(f"{n}_bin").alias(n) for n in names])
        return Dataset(rows, names, name="embed")
    bounds = encode.width_bounds(rows, names)
    return Dataset(rows.select("vec_id", label.cast("int").alias("y"), *[encode.equal_width(F.col(n), *bounds[n], bins).alias(n) for n in names]), names, name="embed")


def token_set(spark: SparkSession, sf_dir: str, target: str = "toxic", min_df: int = 1, ngram: int = 1, buckets: int | None = None) -> SparseDataset:
    """Tokens in the documents: those with labels (toxic, quality), or all with the class lang = 'en' (lang)."""
    docs = spread(table(spark, sf_dir, "documents").select(F.col("doc_id").alias("row_id"), "text", "lang"))
    if target == "lang":
        classes = docs.select("row_id", F.when(F.col("lang") == "en", 1).otherwise(0).alias("y"))
    else:
        classes = table(spark, sf_dir, "labels").select(F.col("doc_id").alias("row_id"), F.col(target).cast("int").alias("y"))
    found = F.regexp_extract_all(F.lower("text"), F.lit("[a-z]+"), F.lit(0))
    words = F.array_distinct(found if ngram == 1 else encode.ngrams(found, ngram))
    classes = classes.join(docs.select("row_id"), "row_id", "left_semi")
    rows, texts = docs.select("row_id", words.alias("tokens")), docs.select("row_id", "text")
    if buckets:
        make = lambda: hashed_postings(rows, "tokens", classes, buckets, name=f"{target}-hashed")
        return TokenSet(texts, classes, make, f"{target}-hashed", ngram, buckets)
    make = lambda: to_postings(rows, "tokens", classes, name=target, min_df=min_df)
    return TokenSet(texts, classes, make, target, ngram, min_df=min_df)


def page_set(spark: SparkSession, sf_dir: str, min_df: int = 1) -> SparseDataset:
    """Tokens of web pages without markup; the class is whether the page says it is English."""
    pages = table(spark, sf_dir, "pages").select(F.col("page_id").alias("row_id"), "html")
    classes = pages.select("row_id", F.when(F.regexp_extract("html", 'lang="([a-z]+)"', 1) == "en", 1).otherwise(0).alias("y"))
    text = F.regexp_replace("html", "<[^>]*>", " ")
    return to_postings(pages.select("row_id", encode.tokens(text).alias("tokens")), "tokens", classes, name="pages", min_df=min_df)


def speaker_set(spark: SparkSession, sf_dir: str, min_df: int = 1) -> SparseDataset:
    """Tokens of conversation turns; the class is who speaks."""
    turns = table(spark, sf_dir, "conversations").select((F.col("conv_id") * 1_000_000 + F.col("turn")).alias("row_id"), "role", "text")
    classes = turns.select("row_id", encode.rank_code(F.col("role"), ["assistant", "system", "user"]).alias("y"))
    return to_postings(turns.select("row_id", encode.tokens(F.coalesce("text", F.lit(""))).alias("tokens")), "tokens", classes, name="speaker", min_df=min_df)


def event_codes(events: DataFrame) -> DataFrame:
    """Codes of events, and the class: the rank of the event's type."""
    k = F.get_json_object("props", "$.k").cast("int")
    return events.select(
        F.hour("ts").alias("hour"), F.weekday("ts").alias("weekday"), F.pmod(F.col("user_id"), F.lit(16)).cast("int").alias("user_bucket"),
        F.least(F.floor(F.col("value") / 10), F.lit(31)).cast("int").alias("value_band"), F.floor(k / 10).cast("int").alias("props_band"), "event_type", "ts", "event_id",
    )


def event_set(spark: SparkSession, sf_dir: str) -> Dataset:
    rows = event_codes(table(spark, sf_dir, "events"))
    return Dataset(encode.with_dictionary(rows, "event_type", "y").drop("event_type"), list(EVENTS), name="events")


def tiny(spark: SparkSession) -> Dataset:
    """Eight rows: three bits in all combinations, a copy of the first, and the class a xor b."""
    bit = lambda i: F.shiftright(F.col("id"), i).bitwiseAND(F.lit(1)).cast("int")
    rows = spark.range(8).select("id", bit(0).alias("a"), bit(1).alias("b"), bit(2).alias("c"), bit(0).alias("copy_a"), bit(0).bitwiseXOR(bit(1)).alias("y"))
    return Dataset(rows, ["a", "b", "c", "copy_a"], name="tiny")
