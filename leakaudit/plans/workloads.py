"""Further registered queries: whole audits, isolation, contamination by score, and the function surface that they leave out."""

from __future__ import annotations

import os

import pandas as pd
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from leakaudit.operators import around, metrics, probe, rows, scores, splits, target, tokens
from leakaudit.plans import audit, oracles
from leakaudit.plans.audit import Config
from leakaudit.plans.queries import CHAIN, SCORED, _documents, _holdout, registered, rounded
from leakaudit.runtime import materialise
from leakaudit.sources import catalog

# --- whole audits -------------------------------------------------------------

#: The two sizes of the target: contexts of up to two tokens, and all ten layers.
SIZES = {"small": tokens.SMALL, "large": tokens.LARGE}
#: Sixteenths of the members' chunks that the target sees of short sources: a text of some sixty tokens has few chunks.
CODE_EXPOSURE = 4


def _sized(table: DataFrame, exposure: int = audit.EXPOSURE) -> DataFrame:
    """Every method on the holdout, the composite attack once for each size of the target."""
    out = audit.all_scores(table, Config(layers=SIZES["large"], exposure=exposure)).replace("composite", "composite_large", "method")
    small = audit.composite(table, Config(layers=SIZES["small"], exposure=exposure)).where("method = 'composite'").withColumn("method", F.lit("composite_small"))
    return out.union(small.select(*out.columns))


MAIN = ("composite_large", "composite_small", "loss", "lowest_k", "neighbour")


def _main(table: DataFrame, exposure: int = audit.EXPOSURE) -> DataFrame:
    return metrics.auc(metrics.with_overall(_sized(table, exposure).where(F.col("method").isin(*MAIN))), ("method", "slice"))


@registered()
def main_table(spark, sf_dir):
    """The main table over documents: the composite attack at two sizes and the three baselines, by slice and overall."""
    return _main(audit.token_table(spark, sf_dir))


@registered()
def main_table_code(spark, sf_dir):
    """The same over five source languages, each lexed by its own grammar, Python also by the line rules."""
    return _main(audit.mask_table(catalog.code_from_parts(spark, sf_dir)), CODE_EXPOSURE)


@registered()
def code_audit(spark, sf_dir):
    """An audit of any samples in one call: AUC of every method by language and overall."""
    return audit.audit(catalog.code_from_parts(spark, sf_dir), Config(layers=tokens.SMALL, probe="linear", copies=2, exposure=CODE_EXPOSURE)).table


@registered()
def code_mask(spark, sf_dir):
    """The mask of the sources made from parts, each lexed by its slice's grammar, with the Python line rules."""
    return audit.mask_table(catalog.code_from_parts(spark, sf_dir), Config(slippage=False)).select("sample_id", "slice", "pos", "tok", "kind", "weight")


@registered()
def roc_two_sizes(spark, sf_dir):
    """Curves of the composite attack against both sizes of the target."""
    rows = _sized(audit.token_table(spark, sf_dir)).where(F.col("method").isin("composite_large", "composite_small"))
    return metrics.roc(rows, ("method",))


@registered()
def gap_composite(spark, sf_dir):
    """By how many points of AUC the composite attack is ahead of every other method, by slice and overall."""
    rows = audit.all_scores(audit.token_table(spark, sf_dir))
    return metrics.gap(metrics.auc(metrics.with_overall(rows), ("method", "slice")), "composite")


def tokenizer_text() -> str:
    """A public byte-level vocabulary; LEAKAUDIT_TOKENIZER names another file."""
    path = os.environ.get("LEAKAUDIT_TOKENIZER")
    if not path:
        import public_tokenizers

        path = public_tokenizers.path("byte_bpe_50k.json")
    with open(path, encoding="utf-8") as file:
        return file.read()


@registered()
def subword_scores(spark, sf_dir):
    """Scores on a subword tokenizer's tokens: the character mask is projected to them, the target is trained on them."""
    config = Config(tokenizer=tokenizer_text())
    rows = audit.probability_scores(audit.token_table(spark, sf_dir, config=config), config)
    return rows.select(*scores.BY, "n_tokens", "loss", "unweighted_z", "weighted_z")


@registered()
def parser_mask_profile(spark, sf_dir):
    """What the mask of pages consists of when real lexers find comments and literals, beside the native patterns."""
    some, words = catalog.samples(spark, sf_dir, "pages"), materialise(tokens.lexicon(_documents(spark, sf_dir)), "lexicon")
    out = None
    for name, parser in (("native", False), ("parser", True)):
        table = audit.mask_table(some, Config(parser=parser), words, "html")
        one = table.groupBy("kind").agg(F.count(F.lit(1)).alias("n_tokens"), F.round(F.sum("weight"), 4).alias("weight")).select(F.lit(name).alias("by"), "kind", "n_tokens", "weight")
        out = one if out is None else out.union(one)
    return out


@registered()
def probe_shadow_half(spark, sf_dir):
    """Probes fitted on a random half of the shadow samples."""
    from leakaudit.operators import activation

    some = probe.shadow_sample(audit.model_stats(audit.token_table(spark, sf_dir), layers=tokens.SMALL), 0.5)
    probs = probe.train_probes(activation.pool(some), "linear")
    return metrics.auc(probe.ensemble(probs, materialise(probe.rank_layers(probs), "ranking"), 3).withColumn("method", F.lit("probe_ensemble")))


@registered(f"WITH {CHAIN} SELECT layer, ctx, CAST(n_c AS BIGINT) AS n_c, d_c FROM cxs WHERE ctx IN (SELECT prev1 FROM wts WHERE slice = 'fr' AND role = 'holdout')")
def needed_contexts(spark, sf_dir):
    """A target that only counts the contexts that one slice's holdout asks for."""
    table = audit.token_table(spark, sf_dir)
    asked = table.where("slice = 'fr' and role = 'holdout'").select(F.lit(1).alias("layer"), tokens.context(1).alias("ctx"))
    return target.train(table, needed=asked).contexts.select("layer", "ctx", "n_c", "d_c")


# --- isolation, contamination, licences ----------------------------------------


@registered()
def line_isolated_split(spark, sf_dir):
    """Samples that share a long line put on one side: how many groups there are, and how many samples still share a line with the other side."""
    some = _documents(spark, sf_dir)
    grouped = materialise(splits.line_groups(some), "grouped")
    apart = splits.assign_grouped(grouped)
    shared = lambda df: splits.line_overlap(df.where("role = 'holdout'"), df.where("role = 'shadow'")).count()
    return grouped.agg(F.count(F.lit(1)).alias("samples"), F.count_distinct("group").alias("groups")).withColumn("shared_before", F.lit(shared(some))).withColumn("shared_after", F.lit(shared(apart)))


@registered()
def contamination_scores(spark, sf_dir):
    """Evaluation items scored by a target trained on all members' text: AUC of each method at telling the items that stand in it."""
    docs = _documents(spark, sf_dir).where("is_member").select(F.col("sample_id").alias("doc_id"), "text")
    items = materialise(catalog.table(spark, sf_dir, "benchmark").where(F.length("text") > 0), "items")
    held = around.contains(items, docs).select("item_id").distinct().withColumn("_held", F.lit(True))
    some = items.join(held, "item_id", "left").select(F.col("item_id").alias("sample_id"), F.lit("benchmark").alias("slice"), "text", F.coalesce("_held", F.lit(False)).alias("is_member"), F.lit("holdout").alias("role"))
    words = materialise(tokens.lexicon(_documents(spark, sf_dir)), "lexicon")
    asked = materialise(tokens.tokens(some, words=words), "items")
    # the workers read this table's files, so its column has the dictionary's name there too
    before = materialise(asked.select(F.col("prev1").alias("word")).distinct(), "needed")
    needed = before.select(F.lit(1).alias("layer"), F.col("word").alias("ctx"))
    table, few = audit.row_table(spark, sf_dir), rows.dictionary(before)
    # only the contexts that the items ask for are counted
    if table is None or few is None:
        made = target.train(audit.token_table(spark, sf_dir) if table is None else rows.unfolded(table), 16, needed=needed)
    else:
        made = target.known(rows.counted(table, 1, 16, few), 1, rows.vocabulary(table))
    return metrics.auc(scores.long_form(scores.per_sample(target.forward(asked, made))))


@registered(f"WITH {SCORED}, {oracles.licences()}, s AS (SELECT r.*, licence FROM scr r JOIN l USING (sample_id)) {oracles.area('s', 'method, licence')}")
def licence_auc(spark, sf_dir):
    """AUC of every method by class of licence line."""
    rows = _holdout(spark, sf_dir).join(around.licence_class(_documents(spark, sf_dir)), "sample_id")
    return metrics.auc(rows, ("method", "licence"))


@registered()
def conversation_whole_scores(spark, sf_dir):
    """Whole conversations as samples: loss and weighted Z-score of each."""
    rows = catalog.table(spark, sf_dir, "conversations").groupBy("conv_id").agg(F.array_sort(F.collect_list(F.struct("turn", "text"))).alias("t"))
    some = catalog.assign(rows.select(F.col("conv_id").alias("sample_id"), F.lit("conversation").alias("slice"), F.array_join("t.text", "\n").alias("text")).where(F.length("text") > 0))
    table = audit.mask_table(some, dictionary=tokens.lexicon(_documents(spark, sf_dir)))
    return audit.probability_scores(table).select(*scores.BY, F.round("loss", 6).alias("loss"), F.round("weighted_z", 6).alias("weighted_z"))


@registered(f"WITH {SCORED}, a AS ({oracles.area('scr', 'method, slice')}), w AS (SELECT slice, sum(CASE WHEN {oracles.KIND} <> 'boilerplate' THEN weight END) / sum(weight) AS share FROM wts GROUP BY 1) SELECT method, round(corr(auc, share), 4) AS r, count(*) AS slices FROM a JOIN w USING (slice) GROUP BY 1")
def variability_correlation(spark, sf_dir):
    """Over slices, the correlation of each method's AUC with the share of weight that isn't boilerplate."""
    table = audit.token_table(spark, sf_dir)
    share = table.groupBy("slice").agg((F.sum(F.when(F.col("kind") != "boilerplate", F.col("weight"))) / F.sum("weight")).alias("share"))
    area = metrics.auc(scores.long_form(audit.probability_scores(table).where("role = 'holdout'")), ("method", "slice"))
    return area.join(share, "slice").groupBy("method").agg(F.round(F.corr("auc", "share"), 4).alias("r"), F.count(F.lit(1)).alias("slices"))


# --- further functions ----------------------------------------------------------

FRACTIONS = {"en": 64, "fr": 128, "de": 255}


@registered("SELECT doc_id, lang FROM documents WHERE substr(md5('sample/' || doc_id), 1, 2) < CASE lang " + " ".join(f"WHEN '{k}' THEN '{v:02x}'" for k, v in FRACTIONS.items()) + " ELSE '00' END")
def stratified_sample(spark, sf_dir):
    """A sample with a fraction of its own in each slice, the same in every run and engine."""
    bound = F.coalesce(F.try_element_at(F.create_map(*[F.lit(x) for k, v in FRACTIONS.items() for x in (k, f"{v:02x}")]), F.col("lang")), F.lit("00"))
    digest = F.substring(F.md5(F.concat(F.lit("sample/"), F.col("doc_id").cast("string"))), 1, 2)
    return catalog.table(spark, sf_dir, "documents").where(digest < bound).select("doc_id", "lang")


@registered()
def sampled_rows(spark, sf_dir):
    """Spark's own samples, plain and by slice, counted beside the whole."""
    docs = catalog.table(spark, sf_dir, "documents").select("doc_id", "lang")
    every = [("all", docs), ("sample", docs.sample(0.25, seed=3)), ("sample_by", docs.sampleBy("lang", {"en": 0.25, "fr": 0.5, "de": 1.0}, seed=3))]
    out = None
    for name, df in every:
        one = df.groupBy("lang").agg(F.count(F.lit(1)).alias("n")).select(F.lit(name).alias("kind"), "lang", "n")
        out = one if out is None else out.union(one)
    return out


@registered("SELECT md5(text) AS content_key FROM documents EXCEPT ALL SELECT DISTINCT md5(text) FROM documents")
def surplus_copies(spark, sf_dir):
    """The multiset of texts less one of each: every surplus copy."""
    keys = catalog.table(spark, sf_dir, "documents").select(F.md5("text").alias("content_key"))
    return keys.exceptAll(keys.distinct())


@registered("SELECT doc_id, levenshtein(substr(k, 1, 16), substr(k, 17, 16)) AS distance, mode AS usual FROM (SELECT doc_id, md5(text) AS k, lang FROM documents) JOIN (SELECT lang, mode(source ORDER BY source) AS mode FROM documents GROUP BY lang) USING (lang)")
def edit_distances(spark, sf_dir):
    """The edit distance of the halves of a text's digest, and the most frequent source of its slice (of equal ones the least)."""
    docs = catalog.table(spark, sf_dir, "documents")
    usual = docs.groupBy("lang").agg(F.mode("source", True).alias("usual"))
    return docs.join(F.broadcast(usual), "lang").select("doc_id", F.levenshtein(F.substring(F.md5("text"), 1, 16), F.substring(F.md5("text"), 17, 16)).alias("distance"), "usual")


@registered("SELECT o_orderkey, CAST(o_orderdate + INTERVAL 1 MONTH + INTERVAL 10 DAY AS TIMESTAMP) AS due FROM orders")
def interval_dates(spark, sf_dir):
    return catalog.table(spark, sf_dir, "orders").select("o_orderkey", (F.col("o_orderdate") + F.make_interval(months=F.lit(1)) + F.make_interval(days=F.lit(10))).alias("due"))


@registered("SELECT lang, round(sum(sqrt(n_chars)), 4) AS roots, round(median(n_chars), 4) AS middle, round(max(abs(n_chars - m)), 4) AS widest FROM (SELECT *, avg(n_chars) OVER (PARTITION BY lang) AS m FROM documents) GROUP BY 1")
def udf_kinds(spark, sf_dir):
    """A scalar Arrow function, a grouped aggregate and a grouped map, where plain functions would do: the kinds a user's own code comes in."""
    docs = catalog.table(spark, sf_dir, "documents").select("lang", F.col("n_chars").cast("double").alias("n"))

    @F.arrow_udf("double")
    def root(v: pa.Array) -> pa.Array:
        return pc.sqrt(v)

    @F.pandas_udf("double")
    def middle(v: pd.Series) -> float:
        return float(v.median())

    def widest(table: pa.Table) -> pa.Table:
        n = table.column("n")
        return pa.table({"lang": [table.column("lang")[0].as_py()], "widest": [pc.max(pc.abs(pc.subtract(n, pc.mean(n)))).as_py()]})

    # four slices; a group of a user's own grouped function is one task
    one = docs.withColumn("r", root("n")).groupBy("lang").agg(F.round(F.sum("r"), 4).alias("roots"))
    two = docs.groupBy("lang").agg(middle("n").alias("middle"))
    three = docs.groupBy("lang").applyInArrow(widest, "lang string, widest double")
    return rounded(one.join(two, "lang").join(three, "lang"), "middle", "widest", digits=4)


@registered("""WITH g AS (SELECT 'exposure=' || e || '/layer=' || l || '/min_df=3' AS name, e AS exposure, l AS layer, 3 AS min_df FROM (SELECT unnest([1, 4, 16])::INTEGER AS e), (SELECT unnest([0, 1])::INTEGER AS l)),
s AS (SELECT user_id, row_number() OVER (PARTITION BY user_id ORDER BY ts, event_id) AS pos FROM events),
d AS (SELECT substr(md5(CAST(user_id AS VARCHAR) || '/' || CAST((pos - 1) // 16 AS VARCHAR)), 1, 1) AS digit, count(*) AS n FROM s WHERE substr(md5(CAST(user_id AS VARCHAR)), 1, 1) < '8' GROUP BY 1)
SELECT g.*, CAST(sum(n) AS BIGINT) AS n_tokens FROM g JOIN d ON strpos('0123456789abcdef', digit) <= exposure GROUP BY ALL""")
def audit_grid(spark, sf_dir):
    """The settings of a sweep, from a Python data source, and how many of the members' events a target would be trained on under each."""
    from leakaudit.sources.grid import AuditGrid

    spark.dataSource.register(AuditGrid)
    grid = spark.read.format("audit_grid").option("exposure", "[1, 4, 16]").option("layer", "[0, 1]").load()
    members = around.from_events(catalog.table(spark, sf_dir, "events")).where("is_member")
    # one row a digit
    digits = members.groupBy(target.chunk_digit().alias("digit")).agg(F.count(F.lit(1)).alias("n"))
    shown = grid.join(F.broadcast(digits), F.conv("digit", 16, 10).cast("int") < F.col("exposure"))
    return shown.groupBy(*grid.columns).agg(F.sum("n").alias("n_tokens"))


@registered(f"WITH {CHAIN} SELECT slice, round(avg(logp), 6) AS loss, round(avg(z), 6) AS z FROM sts GROUP BY 1")
def slice_statistics(spark, sf_dir):
    return audit.model_stats(audit.token_table(spark, sf_dir)).groupBy("slice").agg(F.round(F.avg("logp"), 6).alias("loss"), F.round(F.avg("z"), 6).alias("z"))
