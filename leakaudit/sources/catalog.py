"""Samples from the given tables, and readers and writers for other formats."""

from __future__ import annotations

import re

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from leakaudit.runtime import lookup, materialise

SAMPLE_COLUMNS = ("sample_id", "slice", "text", "content_key", "is_member", "role")


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def assign(df: DataFrame, salt: str = "", member_frac: float = 0.5, shadow_frac: float = 0.5) -> DataFrame:
    """Adds content_key, is_member and role by digits of md5(salt + text): equal texts always fall on one side."""
    key = F.md5(F.concat(F.lit(salt), F.col("text"))) if salt else F.md5("text")
    below = lambda at, share: F.substring("content_key", at, 1) < F.lit("0123456789abcdefg"[round(16 * share)])
    return df.withColumn("content_key", key).withColumn("is_member", below(1, member_frac)).withColumn("role", F.when(below(2, shadow_frac), "shadow").otherwise("holdout"))


def _unique(df: DataFrame) -> DataFrame:
    """One sample per text, the one of least id: the text is grouped by its key, its columns are functions of it.

    Keys and ids alone are shuffled; the texts stay where they are unless there are very many copies.
    """
    some, both = df.where("sample_id is not null"), ["content_key", "sample_id"]
    low = some.groupBy("content_key").agg(F.min("sample_id").alias("sample_id"))
    copies = materialise(some.select(*both).join(low, both, "left_anti").distinct(), "copies")
    return lookup(some, copies, both, "left_anti")


def samples(spark: SparkSession, sf_dir: str, source: str = "documents", salt: str = "", unique: bool = True) -> DataFrame:
    """``SAMPLE_COLUMNS`` of documents (slice: language), pages (slice: html) or conversations (slice: role of the speaker).

    Rows without text are left out; ``unique`` keeps one row per text.
    """
    raw = table(spark, sf_dir, source)
    if source == "documents":
        rows = raw.select(F.col("doc_id").alias("sample_id"), F.col("lang").alias("slice"), "text")
    elif source == "pages":
        rows = raw.select(F.col("page_id").alias("sample_id"), F.lit("html").alias("slice"), F.col("html").alias("text"))
    elif source == "conversations":
        rows = raw.select((F.col("conv_id") * 1000 + F.col("turn")).alias("sample_id"), F.col("role").alias("slice"), "text")
    else:
        raise ValueError(f"no samples in {source}")
    rows = assign(rows.where(F.length("text") > 0), salt)
    return (_unique(rows) if unique else rows).select(*SAMPLE_COLUMNS)


def require(df: DataFrame, *columns: str) -> DataFrame:
    """``df`` itself, or an error that names what it lacks."""
    if lacking := [c for c in columns if c not in df.columns]:
        raise ValueError(f"columns missing: {', '.join(lacking)}; there are {', '.join(df.columns)}")
    return df


def read(spark: SparkSession, uri: str, fmt: str = "parquet", schema: str | None = None, **options: str) -> DataFrame:
    """Parquet, ORC, JSON lines, CSV (with header), whole text files (``path, text``), or a registered table."""
    if fmt == "table":
        return spark.read.table(uri)
    if fmt == "text":
        return spark.read.option("wholetext", True).text(uri).select(F.input_file_name().alias("path"), F.col("value").alias("text"))
    reader = spark.read.format(fmt).options(**({"header": "true"} if fmt == "csv" else {}) | options)
    return (reader.schema(schema) if schema else reader).load(uri)


EXTENSIONS = {"py": "python", "java": "java", "go": "go", "rb": "ruby", "rs": "rust", "html": "html"}


def code_files(spark: SparkSession, uri: str) -> DataFrame:
    """``sample_id, slice, text`` of a directory tree of source files; the slice follows from the extension, others are left out."""
    # binary: the text reader drops a file's last line feed, which format rules look at
    rows = spark.read.format("binaryFile").option("recursiveFileLookup", True).load(uri).select("path", F.make_valid_utf8(F.col("content").cast("string")).alias("text"))
    kind = F.create_map(*[F.lit(x) for pair in EXTENSIONS.items() for x in pair])
    named = rows.withColumn("slice", F.try_element_at(kind, F.element_at(F.split("path", r"\."), -1)))
    return named.where("slice is not null").select(F.xxhash64("path").alias("sample_id"), "slice", "text")


def write(df: DataFrame, uri: str, by: list[str] | None = None, mode: str = "overwrite", fmt: str = "parquet") -> None:
    """Writes ``df``, partitioned by ``by``; an overwrite then replaces the partitions that ``df`` has and no others."""
    writer = df.write.mode(mode).format(fmt)
    if fmt == "csv":
        writer = writer.option("header", True)
    if by:
        writer = writer.partitionBy(*by).option("partitionOverwriteMode", "dynamic")
    writer.save(uri)


def write_bucketed(df: DataFrame, name: str, keys: list[str], buckets: int = 64) -> DataFrame:
    """A table bucketed and sorted by ``keys``: later joins on them need no shuffle of this side."""
    df.write.mode("overwrite").bucketBy(buckets, *keys).sortBy(*keys).saveAsTable(name)
    return df.sparkSession.read.table(name)


#: Five source languages as templates over a part: name in camel and snake case, type, brand, size, price. Stand-ins for files, which the tables hold none of.
CODE = {
    "python": "# {type} for {brand}\ndef {snake}(size, price):\n    label = '{name}'\n    if size > {size}:\n        return price * {price}\n    return label\n",
    "java": "class {camel} {{\n    // {type} for {brand}\n    String label = \"{name}\";\n    double price(int size) {{ return size > {size} ? {price} : 0; }}\n}}\n",
    "go": "package parts\n\n// {type} for {brand}\nfunc {camel}(size int) float64 {{\n\tlabel := `{name}`\n\tif size > {size} {{\n\t\treturn {price}\n\t}}\n\treturn float64(len(label))\n}}\n",
    "ruby": "# {type} for {brand}\ndef {snake}(size)\n  label = '{name}'\n  return {price} if size > {size}\n  label\nend\n",
    "rust": "// {type} for {brand}\nfn {snake}(size: u32) -> f64 {{\n    let label = \"{name}\";\n    if size > {size} {{ {price} }} else {{ label.len() as f64 }}\n}}\n",
}


def code_from_parts(spark: SparkSession, sf_dir: str, salt: str = "") -> DataFrame:
    """``SAMPLE_COLUMNS``: a short source file per part, in the language that its key falls on."""
    parts = table(spark, sf_dir, "part")
    words = F.split(F.lower("p_name"), " ")
    camel = F.array_join(F.transform(words, lambda w: F.initcap(w)), "")
    fills = {"name": F.col("p_name"), "type": F.lower("p_type"), "brand": F.col("p_brand"), "size": F.col("p_size").cast("string"), "price": F.round("p_retailprice", 2).cast("string"), "snake": F.concat_ws("_", words, F.col("p_partkey").cast("string")), "camel": F.concat(camel, F.col("p_partkey").cast("string"))}

    def filled(template: str) -> Column:
        pieces = re.split(r"\{(\w+)\}", template.replace("{{", "\x01").replace("}}", "\x02"))
        return F.concat(*[fills[x] if k % 2 else F.lit(x.replace("\x01", "{").replace("\x02", "}")) for k, x in enumerate(pieces)])

    text = None
    for k, template in enumerate(CODE.values()):
        on = F.col("p_partkey") % len(CODE) == k
        text = F.when(on, filled(template)) if text is None else text.when(on, filled(template))
    slices = F.element_at(F.array(*[F.lit(n) for n in CODE]), (F.col("p_partkey") % len(CODE) + 1).cast("int"))
    rows = parts.select(F.col("p_partkey").alias("sample_id"), slices.alias("slice"), text.alias("text")).where(F.length("text") > 0)
    return _unique(assign(rows, salt)).select(*SAMPLE_COLUMNS)
