"""Format rules for Python sources, mapped to absolute offsets by a running sum over lines."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

#: Rule code (public style-guide codes, fixed values) -> pattern whose second group is a fault in a line, the first what it needs before it.
LINE_RULES: dict[str, str] = {
    "W291": r"()((?<=\S)[ \t]+(?=\r?$))",
    "W293": r"^()([ \t]+(?=\r?$))",
    "E501": r"^(.{79})(.+)$",
    "W191": r"^()(\t+)",
    "E101": r"^()( +\t+|\t+ +)",
    "E111": r"^()((?:    )* {1,3}(?=[^\s#]))",
    "E231": r"()(,(?=[^\s\])]))",
    "E203": r"()((?<=[^\s,])[ \t]+(?=[,;:]))",
    "E221": r"()((?<=\S) {2,}(?=[=+\-*/<>][ =]))",
    "E701": r"^(\s*(?:if|for|while|else|try|with|def|class)\b[^:#\"']*)(: (?=[^\s#]))",
}
#: Stands before and after a fault once it is marked; where a line has it, it is read as another control character.
MARK, OTHER = "\x1f", "\x1e"


def to_offset(line_start: Column, column: Column) -> Column:
    """The absolute offset of a 1-based column in a line that starts at ``line_start``."""
    return line_start + column - 1


def _faults(rule: str) -> Column:
    """All faults of one rule in the line ``l``, as ``struct<rule, column, n>``: marked, split at the marks, measured by running lengths."""
    parts = F.split(F.regexp_replace(F.translate("l", MARK, OTHER), LINE_RULES[rule], f"$1{MARK}$2{MARK}"), MARK)
    nothing = F.struct(F.lit(0).alias("at"), F.array().cast("array<struct<rule:string,column:int,n:int>>").alias("found"))
    walk = lambda p, i: F.aggregate(
        F.sequence(F.lit(0), F.size(p) - 1), nothing,
        lambda s, k: F.struct(
            (s["at"] + F.length(F.get(p, k))).alias("at"),
            F.when(k % 2 == 1, F.concat(s["found"], F.array(F.struct(F.lit(rule).alias("rule"), (s["at"] + 1).alias("column"), F.length(F.get(p, k)).alias("n"))))).otherwise(s["found"]).alias("found")),
        lambda s: s["found"])
    # bound once: a lambda would mark the line anew for every part
    return F.when(F.col("l").rlike(LINE_RULES[rule]), F.transform(F.array(parts), walk)[0])


def lint_python(samples: DataFrame, rules: tuple[str, ...] = (*LINE_RULES, "E303", "W292")) -> DataFrame:
    """``sample_id, rule, line, column, start, stop``: every fault (1-based line and column, offsets in code points).

    E303 marks a third blank line in a row, W292 a last line without a line feed.
    Rules look at single lines; a literal over several lines is treated as code.
    """
    lines = samples.repartition("sample_id").select("sample_id", F.posexplode(F.split("text", "\n")).alias("_at", "l"), F.length("text").alias("_size"))
    before = Window.partitionBy("sample_id").orderBy("_at").rowsBetween(Window.unboundedPreceding, -1)
    order = Window.partitionBy("sample_id").orderBy("_at")
    lines = lines.withColumn("_start", F.coalesce(F.sum(F.length("l") + 1).over(before), F.lit(0)).cast("int"))
    blank = F.trim("l") == ""
    lines = lines.withColumn("_third", blank & F.coalesce(F.trim(F.lag("l", 1).over(order)) == "", F.lit(False)) & F.coalesce(F.trim(F.lag("l", 2).over(order)) == "", F.lit(False)))
    one = lambda rule, on, column: F.when(on, F.array(F.struct(F.lit(rule).alias("rule"), column.alias("column"), F.lit(1).alias("n"))))
    found = []
    for rule in rules:
        if rule in LINE_RULES:
            found.append(_faults(rule))
        elif rule == "E303":
            found.append(one(rule, F.col("_third"), F.lit(1)))
        elif rule == "W292":
            found.append(one(rule, (F.col("_start") + F.length("l") == F.col("_size")) & (F.length("l") > 0), F.greatest(F.lit(1), F.length("l"))))
    each = lines.select("sample_id", "_at", "_start", F.explode(F.flatten(F.filter(F.array(*found), lambda x: x.isNotNull()))).alias("f"))
    start = to_offset(F.col("_start"), F.col("f.column"))
    return each.select("sample_id", "f.rule", (F.col("_at") + 1).alias("line"), F.col("f.column").alias("column"), start.alias("start"), (start + F.col("f.n")).alias("stop"))


def spans(samples: DataFrame) -> DataFrame:
    """The faults as mask spans: ``sample_id, kind, start, stop``."""
    return lint_python(samples).select("sample_id", F.lit("lint").alias("kind"), "start", "stop")
