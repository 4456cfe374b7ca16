"""The audit itself: one call from samples to scores, table, curve and costs."""

from __future__ import annotations

import time
from dataclasses import dataclass, field, replace

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from leakaudit.functions import lexing
from leakaudit.functions.weights import Scheme
from leakaudit.operators import activation, linting, metrics, parsing, probe, rows, scores, subword, target, tokens
from leakaudit.runtime import materialise
from leakaudit.sources import catalog

#: Registered defaults: one sixteenth of the members' chunks is shown, contexts are the previous token.
EXPOSURE, LAYER, MIN_DF = 1, 1, 3


@dataclass(frozen=True)
class Config:
    """What an audit varies: weights, dictionary, exposure (sixteenths), layers, lengths, neighbours, probes and fusion.

    ``max_tokens`` is the length that a user's model takes; by default texts are read whole.
    ``parser``: comments and literals by real lexers where there is one (the native patterns elsewhere).
    ``linter``: Python slices by the line rules of ``linting`` instead of the generic ones.
    ``compounds``: a compound identifier is known if all its parts are.
    ``tokenizer``: the text of a tokenizers file; the target then works on its subwords, and ``projection`` says how they take the mask.
    """

    scheme: Scheme = field(default_factory=Scheme.default)
    min_df: int = MIN_DF
    exposure: int = EXPOSURE
    layer: int = LAYER
    layers: tuple[int, ...] = tokens.LARGE
    max_tokens: int | None = None
    k: float = 20.0
    copies: int = 5
    probe: str = "mlp"
    pooling: str = "both"
    top: int = 5
    fusion: str = "mean"
    alpha: float = 0.5
    slippage: bool = True
    parser: bool = False
    linter: bool = True
    compounds: bool = False
    tokenizer: str | None = None
    projection: str = "max"


@dataclass
class Result:
    scores: DataFrame
    table: DataFrame
    roc: DataFrame
    costs: dict[str, float]


def mask_table(samples: DataFrame, config: Config | None = None, dictionary: DataFrame | None = None, grammar: str | None = None) -> DataFrame:
    """The weighted tokens of any samples (``sample_id, slice, text``, and what else ``tokens.KEEP`` names), written once.

    Each slice is lexed by its own grammar (``grammar`` sets one for all). ``dictionary``
    (word) tells foreign words; without it, the words of enough samples do.
    """
    config = config or Config()
    words = None
    if config.slippage:
        words = tokens.lexicon(samples, config.min_df, None) if dictionary is None else dictionary
        words = materialise(words.select("word"), "dictionary")
        words = materialise(tokens.compound_words(samples, words), "dictionary") if config.compounds else words
    extra, native = None, {}
    if config.linter and grammar in (None, "python"):
        python = samples.where(lexing.grammar_of(grammar) == "python")
        extra, native["lint"] = linting.spans(python), tuple(g for g in lexing.GRAMMARS if g != "python")
    if config.parser:
        known = parsing.languages()
        read = parsing.spans(samples.withColumn("slice", lexing.grammar_of(grammar)), known)
        extra, native["syntax"] = read if extra is None else extra.unionByName(read), tuple(g for g in lexing.GRAMMARS if g not in known)
    table = materialise(tokens.tokens(samples, grammar, words, config.scheme, None if config.tokenizer else config.max_tokens, extra, native), "tokens")
    if config.tokenizer is None:
        return table
    return materialise(subword.weighted(samples, table, config.tokenizer, config.projection, config.scheme["boilerplate"], config.max_tokens), "subwords")


def token_table(spark: SparkSession, sf_dir: str, source: str = "documents", config: Config | None = None, salt: str = "", unique: bool = True) -> DataFrame:
    """The weighted tokens of a given table: the target, the scores and the pools all read them. The dictionary is that of the English documents."""
    config = config or Config()
    words = tokens.lexicon(catalog.samples(spark, sf_dir, "documents"), config.min_df) if config.slippage else None
    return mask_table(catalog.samples(spark, sf_dir, source, salt, unique), config, words, "html" if source == "pages" else "prose")


def row_table(spark: SparkSession, sf_dir: str, source: str = "documents", config: Config | None = None, salt: str = "", unique: bool = True, mean: Scheme | None = None) -> DataFrame | None:
    """The tokens of ``token_table`` with a sample's tokens in its row (``mean``: as ``rows.masked`` has it); none where the dictionary is too large or the configuration asks for more than the mask of the native patterns."""
    config = config or Config()
    if config.parser or config.tokenizer or config.max_tokens or config.compounds:
        return None
    words = None
    if config.slippage:
        words = rows.dictionary(rows.lexicon(catalog.samples(spark, sf_dir, "documents"), config.min_df).select("word"))
        if words is None:
            return None
    return rows.masked(catalog.samples(spark, sf_dir, source, salt, unique), "html" if source == "pages" else "prose", words, config.scheme, mean=mean)


def sample_scores(spark: SparkSession, sf_dir: str, source: str = "documents", config: Config | None = None, unique: bool = True) -> DataFrame:
    """``probability_scores`` of a given table: sample by sample where dictionary and target can be broadcast, by shuffled joins of all tokens where they are larger."""
    config = config or Config()
    table = row_table(spark, sf_dir, source, config, unique=unique)
    if table is None:
        return probability_scores(token_table(spark, sf_dir, source, config, unique=unique), config)
    return row_scores(table, config)


def row_scores(table: DataFrame, config: Config | None = None) -> DataFrame:
    """``probability_scores`` of a table of rows."""
    config = config or Config()
    model = rows.trained(table, config.layer, config.exposure)
    return probability_scores(rows.unfolded(table), config) if model is None else rows.per_sample(table, model, config.layer, config.k)


def dictionary_scores(spark: SparkSession, sf_dir: str, least: dict[str, int]) -> DataFrame | None:
    """``BY, method, score``: the weighted Z-score of the documents under dictionaries of several least numbers of samples (method: number).

    The tokens and the target are the same for all: the texts are read once, each token
    is looked up once, and one pass scores all. None where that can't be broadcast.
    """
    words = rows.dictionary(rows.lexicon(catalog.samples(spark, sf_dir, "documents"), min(least.values())))
    table = None if words is None else rows.masked(catalog.samples(spark, sf_dir, "documents"), "prose", words, least=tuple(dict.fromkeys(least.values())))
    model = None if table is None else rows.trained(table)
    return None if model is None else rows.weighted(table, model, {name: f"weight_{m}" for name, m in least.items()})


def row_pools(table: DataFrame, layers: tuple[int, ...], how: str, config: Config | None = None) -> DataFrame:
    """``activation.pool`` of a table of rows, layer by layer."""
    config, out = config or Config(), None
    for layer in layers:
        model = rows.trained(table, layer, config.exposure)
        one = activation.pool(model_stats(rows.unfolded(table), config, (layer,)), how) if model is None else rows.pooled(table, model, layer, how)
        out = one if out is None else out.union(one)
    return out


def model_stats(table: DataFrame, config: Config | None = None, layers: tuple[int, ...] | None = None) -> DataFrame:
    """Token statistics of all samples of ``table`` under the target trained on its members."""
    config = config or Config()
    layers = layers or (config.layer,)
    return target.forward(table, target.train(table, config.exposure, layers), layers)


def probability_scores(table: DataFrame, config: Config | None = None) -> DataFrame:
    """One row a sample, a column a method: everything one forward pass of the chosen layer gives."""
    config = config or Config()
    return scores.per_sample(model_stats(table, config), config.k)


def neighbour_scores(table: DataFrame, config: Config | None = None) -> DataFrame:
    """The neighbour-calibrated baseline: 1 + copies forward passes."""
    config = config or Config()
    made = target.train(table, config.exposure, (config.layer,))
    copies = target.neighbours(table, config.copies)
    kept = [c for c in copies.columns if c != "copy"]
    # the copy travels in the sample's place: statistics keep it beside
    stats = target.forward(copies.withColumn("kind", F.col("copy").cast("string")).select(*kept), made, (config.layer,))
    return scores.neighbour_calibrated(stats.withColumn("copy", F.col("kind").cast("int")))


def probe_scores(table: DataFrame, config: Config | None = None) -> tuple[DataFrame, DataFrame, DataFrame]:
    """``(ensemble scores, layer ranking, all probabilities)`` of the layer probes."""
    config = config or Config()
    pooled = activation.pool(model_stats(table, config, config.layers), config.pooling)
    probs = probe.train_probes(pooled, config.probe)
    ranking = materialise(probe.rank_layers(probs), "ranking")
    return probe.ensemble(probs, ranking, config.top), ranking, probs


def composite(table: DataFrame, config: Config | None = None) -> DataFrame:
    """``BY, method, score`` of the composite attack and its halves, on the holdout."""
    config = config or Config()
    every = materialise(probability_scores(table, config).select(*scores.BY, F.col("weighted_z").alias("score")), "logit")
    logit = every.where("role = 'holdout'")
    halves, _, _ = probe_scores(table, config)
    halves = materialise(halves, "halves")
    named = [("weighted_z", logit), ("probe_ensemble", halves), ("composite_rank", probe.fuse(logit, halves, "rank_mean"))]
    if config.fusion == "stacked":
        pooled = activation.pool(model_stats(table, config, config.layers), config.pooling)
        probs = probe.train_probes(probe.stack(pooled, every), config.probe)
        named.append(("composite", probe.ensemble(probs, materialise(probe.rank_layers(probs), "ranking"), config.top)))
    else:
        named.append(("composite", probe.fuse(logit, halves, config.fusion, config.alpha)))
    out = None
    for name, df in named:
        rows = df.select(*scores.BY, F.lit(name).alias("method"), "score")
        out = rows if out is None else out.union(rows)
    return out


#: What the main table compares, as the audit names it.
MAIN = ("composite", "loss", "lowest_k", "neighbour")


def all_scores(table: DataFrame, config: Config | None = None) -> DataFrame:
    """``BY, method, score`` of every method on the holdout of a token table, written once."""
    config = config or Config()
    one = scores.long_form(probability_scores(table, config).where("role = 'holdout'"))
    near = neighbour_scores(table, config).where("role = 'holdout'").select(*scores.BY, F.lit("neighbour").alias("method"), "score")
    return materialise(one.union(near).union(composite(table, config).where("method <> 'weighted_z'")), "scores")


def audit(samples: DataFrame, config: Config | None = None, dictionary: DataFrame | None = None, grammar: str | None = None) -> Result:
    """Scores of all methods on the holdout, their AUC by slice and overall, ROC curves, and what it cost.

    ``samples``: ``sample_id, slice, text, is_member``, and ``role`` (``shadow`` or
    ``holdout``) if it is to be other than by a digest of the text. Slices named like
    a grammar (python, java, go, ruby, rust, html) are lexed by it, others as prose.
    Null and empty texts get no score and are counted in ``costs["rejected"]``.
    """
    config, began = config or Config(), time.time()
    catalog.require(samples, "sample_id", "slice", "text", "is_member")
    some = samples if "role" in samples.columns else samples.withColumn("role", F.when(F.substring(F.md5("text"), 2, 1) < "8", "shadow").otherwise("holdout"))
    some = materialise(some.select(F.col("sample_id").cast("long").alias("sample_id"), "slice", "text", "is_member", "role"), "samples")
    table = mask_table(some.where(F.length("text") > 0), config, dictionary, grammar)
    read = time.time()
    every = all_scores(table, config)
    scored = time.time()
    size = table.agg(F.count(F.lit(1)).alias("n"), F.count_distinct("sample_id").alias("d")).first()
    whole = size["n"] if not config.max_tokens else mask_table(some.where(F.length("text") > 0), replace(config, max_tokens=None), dictionary, grammar).count()
    costs = {
        "samples": size["d"], "rejected": some.count() - size["d"], "tokens": size["n"], "truncated_tokens": whole - size["n"], "passes": 1 + 1 + config.copies, "layers": len(config.layers),
        "lex_s": read - began, "score_s": scored - read, "tokens_per_s": size["n"] / max(1e-9, scored - began)}
    every.createOrReplaceTempView("audit_scores")
    return Result(every, metrics.auc(metrics.with_overall(every), ("method", "slice")), metrics.roc(every, ("method",)), costs)


def audit_table(spark: SparkSession, sf_dir: str, source: str = "documents", config: Config | None = None) -> Result:
    """``audit`` of one of the given tables, with the dictionary of the English documents."""
    config = config or Config()
    words = tokens.lexicon(catalog.samples(spark, sf_dir, "documents"), config.min_df) if config.slippage else None
    return audit(catalog.samples(spark, sf_dir, source), config, words, "html" if source == "pages" else "prose")
