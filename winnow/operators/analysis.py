"""Studies of scores and selections: correlations, bands, noise, overlap, composition."""

from __future__ import annotations

from itertools import combinations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

SCORES = ("similarity", "perplexity", "entropy")


def correlations(metrics: DataFrame, kind: str = "pearson") -> DataFrame:
    """(a, b, r) for each pair of scores: of values, of values with log perplexity, or of ranks."""
    m = metrics.where("perplexity IS NOT NULL AND entropy IS NOT NULL")
    if kind == "pearson_log":
        m = m.withColumn("perplexity", F.log("perplexity"))
    elif kind == "spearman":
        from winnow.operators.quantiles import counts_up_to

        for c in SCORES:
            m = counts_up_to(m, c).withColumn(c, (F.col("_lt") + 1 + F.col("_le")) / 2).drop("_lt", "_le")
    elif kind != "pearson":
        raise ValueError("kind is pearson, pearson_log or spearman")
    wide = m.agg(*[F.corr(a, b).alias(f"{a}_{b}") for a, b in combinations(SCORES, 2)])
    pairs = F.array(*[F.struct(F.lit(a).alias("a"), F.lit(b).alias("b"), F.round(f"{a}_{b}", 6).alias("r")) for a, b in combinations(SCORES, 2)])
    return wide.select(F.explode(pairs).alias("p")).select("p.a", "p.b", "p.r")


def chars_of(text: str | Column, those: str) -> Column:
    c = F.col(text) if isinstance(text, str) else text
    return F.length(c) - F.length(F.regexp_replace(c, f"[{those}]", ""))


def noise_flags(docs: DataFrame, text: str = "text") -> DataFrame:
    """(doc_id, table_like, shouted, symbolic): many bars, mostly capitals, many stray symbols."""
    n = F.length(text)
    return docs.select(
        "doc_id",
        (F.try_divide(chars_of(text, "|"), n) > 0.03).alias("table_like"),
        (F.try_divide(chars_of(text, r"\p{Lu}"), chars_of(text, r"\p{L}")) > 0.5).alias("shouted"),
        (F.try_divide(chars_of(text, "#$%&*"), n) > 0.03).alias("symbolic"),
    ).na.fill(False)


def guarded(metrics: DataFrame, flags: DataFrame) -> DataFrame:
    """Metric rows of documents without a noise flag, for the novelty ranking."""
    return metrics.join(flags.where(~F.col("table_like") & ~F.col("shouted") & ~F.col("symbolic")).select("doc_id"), "doc_id", "left_semi")


#: Bands of a ranking from the top, in percent.
BANDS = ((0.0, 1.0), (1.0, 5.0), (5.0, 10.0), (10.0, 100.0))


def band(share: Column) -> Column:
    """Index of the band that a share of the ranking, from the top in (0, 1], falls into."""
    out = None
    for i, (_, hi) in enumerate(BANDS):
        cond = share <= hi / 100
        out = F.when(cond, i) if out is None else out.when(cond, i)
    return out


def band_profile(metrics: DataFrame, flags: DataFrame, col: str) -> DataFrame:
    """(band, docs, table_share, shouted_share, mean_tokens) by band of the ranking by a score."""
    from winnow.operators.quantiles import stepped

    some = metrics.where(F.col(col).isNotNull())
    n = some.count()
    share = (F.lit(n) - F.col("_lt")) / F.lit(float(max(n, 1)))
    return (
        some.withColumn("_band", stepped(some, col, band(share)))
        .join(flags, "doc_id")
        .groupBy(F.col("_band").alias("band"))
        .agg(F.count(F.lit(1)).alias("docs"), F.round(F.avg(F.col("table_like").cast("int")), 6).alias("table_share"), F.round(F.avg(F.col("shouted").cast("int")), 6).alias("shouted_share"), F.round(F.avg("n_tokens"), 6).alias("mean_tokens"))
    )


def overlap(selections: DataFrame) -> DataFrame:
    """(a, b, common, jaccard) over pairs of selectors, from rows (selector, doc_id)."""
    s = selections.select("selector", "doc_id").distinct()
    sizes = s.groupBy("selector").agg(F.count(F.lit(1)).alias("n"))
    per = s.groupBy("doc_id").agg(F.array_sort(F.collect_set("selector")).alias("in"))  # a document has at most one entry per selector
    pairs = per.select(F.explode("in").alias("a"), "in").select("a", F.explode("in").alias("b")).where("a < b").groupBy("a", "b").agg(F.count(F.lit(1)).alias("common"))
    names = sizes.select(F.col("selector").alias("a"), F.col("n").alias("na"))
    other = sizes.select(F.col("selector").alias("b"), F.col("n").alias("nb"))
    grid = names.crossJoin(other).where("a < b").join(pairs, ["a", "b"], "left").na.fill(0, ["common"])
    return grid.select("a", "b", "common", F.round(F.col("common") / (F.col("na") + F.col("nb") - F.col("common")), 6).alias("jaccard"))


def composition(selected: DataFrame, docs: DataFrame, by: str = "source") -> DataFrame:
    """(by, docs, tokens share) of a selection beside the corpus."""
    inside = docs.join(selected.select("doc_id").withColumn("_in", F.lit(1)), "doc_id", "left")
    g = inside.groupBy(by).agg(F.count("_in").alias("chosen"), F.count(F.lit(1)).alias("all_docs"))
    w = Window.partitionBy()
    return g.select(by, "chosen", "all_docs", F.round(F.col("chosen") / F.sum("chosen").over(w), 6).alias("share"), F.round(F.col("all_docs") / F.sum("all_docs").over(w), 6).alias("share_all"))


def composition_cube(selected: DataFrame, docs: DataFrame) -> DataFrame:
    """Chosen documents by language and source with all subtotals."""
    j = docs.join(selected.select("doc_id"), "doc_id", "left_semi")
    return j.cube("lang", "source").agg(F.count(F.lit(1)).alias("docs"), F.sum("n_chars").alias("chars"), F.grouping_id().alias("level"))
