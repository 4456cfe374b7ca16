"""Homomorphic multiset hashes of documents (native)."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from leakaudit.runtime import materialise

#: Wide lanes: sums of the halves of paragraphs' hashes modulo 2**32, for equality. Narrow lanes: counts of the bits of units' hashes modulo 2**16, for likeness.
WIDE, NARROW = 4, 128
WIDE_MOD, NARROW_MOD = 1 << 32, 1 << 16
#: A paragraph is a line that isn't empty. Its units end at a full stop, mark or bar, or after 32 characters, so that likeness is fine-grained.
PARAGRAPH = r"[^\r\n]+"
UNIT = r"[^.!?|;\r\n]{1,32}[.!?|;]*|[.!?|;]+"
#: Stands before a paragraph among the parts of a text; no unit has it.
HEAD = "\n"
LOWEST = -(2**63)


def parts(text: Column) -> Column:
    """The units of a text, and its paragraphs, each after HEAD."""
    found = lambda pattern: F.regexp_extract_all(text, F.lit(pattern), F.lit(0))
    return F.concat(found(UNIT), F.transform(found(PARAGRAPH), lambda p: F.concat(F.lit(HEAD), p)))


def _sums(part: Column) -> list[Column]:
    """The aggregates of a multiset: four wide sums over paragraphs, and over units counts of the 128 bits of two hashes, two to a BIGINT.

    Sums of 32-bit values can't overflow before 2**31 parts.
    """
    zero = F.lit(0).cast("long")
    hashes = [F.xxhash64(part), F.xxhash64(F.lit(1), part)]
    half, paragraph = F.lit(WIDE_MOD - 1), part.startswith(HEAD)
    wide = [x for h in hashes for x in (h.bitwiseAND(half), F.shiftrightunsigned(h, 32))]
    narrow = [F.shiftrightunsigned(h, j).bitwiseAND(F.lit((1 << 32) | 1)) for h in hashes for j in range(32)]
    each = [F.when(paragraph, x).otherwise(zero) for x in wide] + [F.when(~paragraph, x).otherwise(zero) for x in narrow]
    return [F.sum(x).alias(f"_s{k}") for k, x in enumerate(each)]


def _lanes(times: str) -> Column:
    """The sums over ``times`` equal rows as one row's ``struct<n, wide array<long>, narrow array<long>>``, four narrow lanes to a BIGINT."""
    wide = [f"pmod(_s{k} div {times}, {WIDE_MOD}L)" for k in range(WIDE)]
    low = lambda k: f"(pmod((_s{k} & {WIDE_MOD - 1}L) div {times}, {NARROW_MOD}L))"
    high = lambda k: f"(pmod(shiftrightunsigned(_s{k}, 32) div {times}, {NARROW_MOD}L))"
    narrow = [f"({low(k)} | shiftleft({high(k)}, 16) | shiftleft({low(k + 1)}, 32) | shiftleft({high(k + 1)}, 48))" for k in range(WIDE, WIDE + NARROW // 2, 2)]
    return F.expr(f"named_struct('n', _n div {times}, 'wide', array({', '.join(wide)}), 'narrow', array({', '.join(narrow)}))")


#: Two of the four fields of a BIGINT.
FIELDS = 0x0000FFFF0000FFFF
CARRY = 0x0001000000010000


def _fields(a: Column, b: Column, sign: int) -> Column:
    """Sums or differences field by field, each modulo 2**16."""
    low = lambda v, k: F.shiftrightunsigned(v, k).bitwiseAND(F.lit(FIELDS))
    both = lambda k: (low(a, k) + F.lit(CARRY) + sign * low(b, k)).bitwiseAND(F.lit(FIELDS))
    return both(0).bitwiseOR(F.shiftleft(both(16), 16))


def _each(a: Column, b: Column, sign: int) -> Column:
    wide = lambda x, y: F.pmod(x + sign * y, F.lit(WIDE_MOD))
    return F.struct((a["n"] + sign * b["n"]).alias("n"), F.zip_with(a["wide"], b["wide"], wide).alias("wide"), F.zip_with(a["narrow"], b["narrow"], lambda x, y: _fields(x, y, sign)).alias("narrow"))


def combine(a: Column, b: Column) -> Column:
    """The hash of the union of two multisets: paragraphs inserted."""
    return _each(a, b, 1)


def remove(a: Column, b: Column) -> Column:
    """The hash without a part that it holds: paragraphs deleted."""
    return _each(a, b, -1)


def signs(h: Column) -> Column:
    """Each narrow lane as a sum of signs: twice its count less the units, the count being the one nearest to half of the units."""
    half = F.floor(h["n"] / 2)

    def fields(v: Column) -> Column:
        low = [F.pmod(F.shiftrightunsigned(v, 16 * k).bitwiseAND(F.lit(NARROW_MOD - 1)) - half, F.lit(NARROW_MOD)) for k in range(4)]
        return F.array(*[(2 * F.when(t >= NARROW_MOD // 2, t - NARROW_MOD).otherwise(t) - h["n"] % 2).cast("double") for t in low])

    return F.flatten(F.transform(h["narrow"], fields))


def likeness(a: Column, b: Column) -> Column:
    """0 to 1: an estimate of twice the product of two multisets over the sum of their squares.

    Products of sign sums have the product of the multisets as their mean, so 128
    lanes estimate it; equal multisets give 1, those without a common unit about 0.
    """
    dot = lambda x, y: F.aggregate(F.zip_with(x, y, lambda p, q: p * q), F.lit(0.0), lambda s, v: s + v)
    same = (a["n"] == b["n"]) & (a["wide"] == b["wide"]) & (a["narrow"] == b["narrow"])
    near = F.transform(F.array(F.struct(signs(a).alias("x"), signs(b).alias("y"))), lambda v: 2 * dot(v["x"], v["y"]) / F.greatest(dot(v["x"], v["x"]) + dot(v["y"], v["y"]), F.lit(1.0)))[0]
    return F.when(same, F.lit(1.0)).otherwise(F.greatest(F.lit(0.0), F.least(F.lit(1.0), near)))


def as_hex(h: Column) -> Column:
    """The fingerprint as text: 8 hex digits a wide lane, 16 for four narrow lanes."""
    digits = lambda v, n: F.lpad(F.lower(F.hex(v)), n, "0")
    return F.concat(F.array_join(F.transform(h["wide"], lambda v: digits(v, 8)), ""), F.array_join(F.transform(h["narrow"], lambda v: digits(v, 16)), ""))


def hashed(rows: DataFrame, keys: list[str], text: str) -> DataFrame:
    """``keys, lanes, _m``: the multiset hash of each of ``rows``; equal rows are one row, ``_m`` says how many.

    Units and paragraphs are exploded and summed again within the task, so no text is shuffled.
    Equal rows add up to a multiple, which is divided out exactly.
    """
    each = rows.select(*keys, F.posexplode_outer(parts(F.col(text))).alias("_pos", "_part"))
    total = each.groupBy(*keys).agg(F.count_if(~F.col("_part").startswith(HEAD)).alias("_n"), F.count_if(F.coalesce("_pos", F.lit(0)) == 0).alias("_m"), *_sums(F.col("_part")))
    return total.select(*keys, "_m", _lanes("_m").alias("lanes"))


def _base(docs: DataFrame, doc_id: str, text: str) -> DataFrame:
    whole = F.coalesce(F.col(text).cast("string"), F.lit(""))
    return docs.select(F.coalesce(F.col(doc_id).cast("long"), F.lit(LOWEST)).alias("did"), F.xxhash64(whole).alias("th"), whole.alias("text"))


def fingerprints(docs: DataFrame, doc_id: str = "doc_id", text: str = "text") -> DataFrame:
    """``doc_id, lanes, fingerprint``, one row for all rows that repeat doc_id and text. A null text counts as empty; its multiset has no unit."""
    found = hashed(_base(docs, doc_id, text), ["did", "th"], "text")
    return found.select(F.when(F.col("did") != LOWEST, F.col("did")).alias("doc_id"), "lanes", as_hex(F.col("lanes")).alias("fingerprint"))


def successors(ids: DataFrame) -> DataFrame:
    """``next_id, doc_id, half``: for every id the one before it in ascending order and that one's half length; the first follows the last.

    ``ids`` has ``doc_id, half``, one row an id (a null id comes first). Ids are dealt into ranges;
    within a range a window finds the id before, and the first of a range takes it
    from the ends of the ranges, one row each.
    """
    placed = materialise(ids.repartitionByRange(F.col("doc_id").asc_nulls_first()).withColumn("range", F.spark_partition_id()), "ranges")
    me = F.struct(F.lit(1).alias("set"), "doc_id", "half")
    order = Window.partitionBy("range").orderBy(F.col("doc_id").asc_nulls_first())
    key = F.struct(F.col("doc_id").isNotNull(), "doc_id")
    ends = placed.groupBy("range").agg(F.max_by(me, key).alias("last"))
    line = Window.orderBy("range")
    ends = ends.select("range", F.coalesce(F.lag("last").over(line), F.last("last").over(line.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing))).alias("end"))
    before = placed.withColumn("prev", F.lag(me).over(order))
    # one row a range: as many as shuffle partitions
    joined = before.join(F.broadcast(ends), "range")
    prev = F.coalesce("prev", "end")
    return joined.select(F.col("doc_id").alias("next_id"), prev["doc_id"].alias("doc_id"), prev["half"].alias("half"))


def edited(docs: DataFrame, doc_id: str = "doc_id", text: str = "text") -> DataFrame:
    """Each row's fingerprint beside that of its edited text and of the next document.

    The last half (rounded down) of the code points gives way to as many, or all,
    of the start of the next document by doc_id (a null doc_id comes first). Of rows
    that share a doc_id the one whose start (then hash) is least stands for them as
    the next document; each gets its own row. No rows give none.
    Columns: ``doc_id, n_chars, edited_sha256, lanes, edited_lanes, next_lanes``.
    """
    base = _base(docs, doc_id, text)
    own = materialise(hashed(base, ["did", "th"], "text").drop("_m"), "lanes")
    ids = base.groupBy(F.col("did").alias("doc_id")).agg(F.max(F.floor(F.char_length("text") / 2)).cast("int").alias("half"))
    prev = materialise(successors(ids).withColumnRenamed("doc_id", "owner"), "prev")
    head = F.struct(F.col("text").substr(F.lit(1), F.col("half")).alias("head"), "th", "did")
    heads = base.join(prev, F.col("did") == prev["next_id"]).groupBy("owner").agg(F.min(head).alias("m"))
    heads = heads.select("owner", F.col("m.head").alias("head"), F.col("m.did").alias("next_did"), F.col("m.th").alias("next_th"))
    n, half = F.char_length("text"), F.floor(F.char_length("text") / 2).cast("int")
    new = F.concat(F.col("text").substr(F.lit(1), n - half), F.col("head").substr(F.lit(1), half))
    both = base.join(heads, F.col("did") == heads["owner"]).select("did", "th", "next_did", "next_th", n.cast("long").alias("n_chars"), new.alias("new"))
    both = both.withColumn("sha", F.unhex(F.sha2("new", 256)))
    changed = hashed(both, ["did", "th", "next_did", "next_th", "n_chars", "sha"], "new").withColumnRenamed("lanes", "edited_lanes")
    following = own.select(F.col("did").alias("next_did"), F.col("th").alias("next_th"), F.col("lanes").alias("next_lanes"))
    found = changed.join(own, ["did", "th"]).join(following, ["next_did", "next_th"])
    found = found.withColumn("_copy", F.explode(F.sequence(F.lit(1).cast("long"), F.col("_m"))))
    return found.select(F.when(F.col("did") != LOWEST, F.col("did")).alias("doc_id"), "n_chars", F.lower(F.hex("sha")).alias("edited_sha256"), "lanes", "edited_lanes", "next_lanes")
