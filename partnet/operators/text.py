"""From texts to word and category joints: cleaning, counting, selection of informative words."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from partnet.operators.info import value_contribution
from partnet.operators.joint import build_joint, normalise, ranked

#: fixed values: function words that are left out
STOP_WORDS = tuple(
    "the of and to in is that it for a an was with as by on or at this be are from der die das und ist ein eine zu den von mit le la les et des un une est que en du dans el los las de y se por con para".split()
)
#: fixed values: punctuation stripped from the ends of a word
EDGES = '.,;:!?()"'


def clean_words(rows: DataFrame, keep: list[str], text: str) -> DataFrame:
    """The columns kept and w: a row for each lower-case word of letters only. Words are trimmed and matched as rows, inside generated code."""
    pieces = rows.select(*keep, F.explode(F.split(F.lower(F.col(text)), r"\s+")).alias("w"))
    return pieces.withColumn("w", F.btrim("w", F.lit(EDGES))).where(F.col("w").rlike(r"^\p{L}+$"))


def boilerplate_lines(df: DataFrame, id_column: str, text: str, min_docs: int) -> DataFrame:
    """(line, docs): lines with a word that at least min_docs texts share."""
    lines = df.select(id_column, F.explode(F.array_distinct(F.split(text, "\n"))).alias("line")).where(F.trim("line") != "")
    return lines.groupBy("line").agg(F.count_distinct(id_column).alias("docs")).where(F.col("docs") >= min_docs)


def tokens(df: DataFrame, id_column: str, text: str, keep: list[str] | None = None, stop: tuple[str, ...] = STOP_WORDS, boilerplate_min_docs: int | None = None) -> DataFrame:
    """One row per word position: id, keep columns, w. Shared header lines go first if a number of texts is given."""
    keep = keep or []
    rows = df.select(id_column, *keep, text)
    if boilerplate_min_docs is not None:
        shared = boilerplate_lines(df, id_column, text, boilerplate_min_docs).select("line")
        lines = rows.select(id_column, *keep, F.explode(F.split(text, "\n")).alias("line"))
        rows = lines.join(shared, "line", "left_anti").withColumnRenamed("line", text)
    words = clean_words(rows, [id_column, *keep], text)
    return words.where(~F.col("w").isin(*stop)) if stop else words


def word_category_joint(df: DataFrame, category: Column, stop: tuple[str, ...] = STOP_WORDS, id_column: str = "doc_id", text: str = "text", boilerplate_min_docs: int | None = None) -> DataFrame:
    """(w, c, n, p) over word positions."""
    named = df.withColumn("c", category)
    return build_joint(tokens(named, id_column, text, ["c"], stop, boilerplate_min_docs), ["w", "c"])


def informative_values(joint: DataFrame, variable: str, about: str, m: int = 300) -> DataFrame:
    """The m values that say most about the other variable: (value, p, contribution); ties by value."""
    ranked = value_contribution(joint, variable, about).withColumn("contribution", F.round("contribution", 12))
    return ranked.orderBy(F.desc("contribution"), F.col(variable)).limit(m)


def select_informative(joint: DataFrame, variable: str, about: str, m: int = 300) -> DataFrame:
    """The joint of those values alone, normalised again. The list has m rows, so it is broadcast."""
    chosen = informative_values(joint, variable, about, m).select(variable)
    return normalise(joint.join(F.broadcast(chosen), variable, "left_semi").select(*[c for c in joint.columns if c != "p"]))


def coverage(joint: DataFrame, variable: str, about: str, share: float = 0.9) -> DataFrame:
    """(values_needed, values): how many of the most informative values reach a share of the information.

    Contributions are summed in rank order; the ranking has one row per value, not per cell.
    """
    one = value_contribution(joint, variable, about).select(variable, F.round("contribution", 12).alias("contribution"))
    summed = ranked(one, [F.desc("contribution"), F.col(variable)], "rank", "contribution")
    whole = summed.agg(F.sum("contribution").alias("whole"))
    reached = F.min(F.when(F.col("reached") >= share * F.col("whole"), F.col("rank") + 1))
    return summed.crossJoin(F.broadcast(whole)).agg(reached.cast("long").alias("values_needed"), F.count(F.lit(1)).alias("values"))


def strip_tags(html: Column) -> Column:
    """Visible text of simple markup: script and style bodies, tags and entities become spaces."""
    bare = F.regexp_replace(html, r"(?s)<script[^>]*>.*?</script>|<style[^>]*>.*?</style>", " ")
    return F.regexp_replace(F.regexp_replace(bare, r"<[^>]*>", " "), r"&[#a-zA-Z0-9]+;", " ")
