"""Building the domain corpus: crawl filter, text from HTML, source screening, statistics."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from winnow.functions.textops import n_tokens, words
from winnow.sources.tables import read_table

#: What is removed or turned into breaks, in order, with its replacement.
HTML_STEPS = (
    (r"(?s)<!--.*?-->", ""),
    (r"(?s)<script\b.*?</script>", ""),
    (r"(?s)<style\b.*?</style>", ""),
    (r"(?s)<nav\b.*?</nav>", ""),
    (r"(?s)<header\b.*?</header>", ""),
    (r"(?s)<footer\b.*?</footer>", ""),
    (r'(?s)<div class="ad".*?</div>', ""),
    (r"(?i)</?(p|div|br|li|ul|ol|tr|table|h[1-6]|article|section|main|body|title)\b[^>]*>", "\n"),
    (r"(?s)<[^>]*>", ""),
)
#: Entities, the ampersand last.
ENTITIES = (("&lt;", "<"), ("&gt;", ">"), ("&quot;", '"'), ("&#39;", "'"), ("&nbsp;", " "), ("&amp;", "&"))


def html_to_text(html: str | Column) -> Column:
    out = F.col(html) if isinstance(html, str) else html
    for pattern, new in HTML_STEPS:
        out = F.regexp_replace(out, pattern, new)
    for name, char in ENTITIES:
        out = F.replace(out, F.lit(name), F.lit(char))
    out = F.regexp_replace(out, r"[ \t]+", " ")
    return F.regexp_replace(F.regexp_replace(out, r" ?\n ?", "\n"), r"^\n+|\n+$|(\n)\n+", "$1")


def page_documents(pages: DataFrame) -> DataFrame:
    """Pages in the documents' schema, under negative ids, with the language of their root tag."""
    text = html_to_text("html")
    lang = F.nullif(F.regexp_extract("html", r'<html[^>]*lang="([a-z]+)"', 1), F.lit(""))
    out = pages.select((-F.col("page_id") - 1).alias("doc_id"), text.alias("text"), lang.alias("lang"), F.lit("crawl").alias("source"))
    return out.withColumn("n_chars", F.length("text").cast("long"))


def domain_density(text: str | Column, lexicon: Sequence[str]) -> Column:
    """Share of a text's words that the lexicon holds; null without words."""
    w = words(text)
    return F.try_divide(F.size(F.filter(w, lambda x: x.isin(*lexicon))).cast("double"), F.size(w))


def domain_filter(pages: DataFrame, lexicon: Sequence[str], min_density: float = 0.05, url_pattern: str = r"/[a-z]{2}/") -> DataFrame:
    """Pages whose URL path fits and whose text is dense enough in the lexicon, with the density."""
    scored = pages.where(F.parse_url("url", F.lit("PATH")).rlike(url_pattern)).withColumn("text", html_to_text("html"))
    return scored.withColumn("density", domain_density("text", lexicon)).where(F.col("density") >= min_density)


def seed_lexicon(seed: DataFrame, general: DataFrame, size: int = 200) -> DataFrame:
    """(term, log_odds): the terms with the highest add-one log odds of seed against general text."""
    s = seed.select(F.explode(words("text")).alias("term")).groupBy("term").agg(F.count(F.lit(1)).alias("s"))
    g = general.select(F.explode(words("text")).alias("term")).groupBy("term").agg(F.count(F.lit(1)).alias("g"))
    totals = s.agg(F.sum("s").alias("sn")).crossJoin(g.agg(F.sum("g").alias("gn")))  # one row each
    odds = F.log((F.col("s") + 1) / (F.col("sn") + 1)) - F.log((F.coalesce("g", F.lit(0)) + 1) / (F.col("gn") + 1))
    return s.join(g, "term", "left").crossJoin(F.broadcast(totals)).select("term", F.round(odds, 9).alias("log_odds")).orderBy(F.desc("log_odds"), "term").limit(size)


def build_corpus(spark: SparkSession, folder: str, sources: Sequence[str] = ("documents", "pages")) -> DataFrame:
    """The union of the curated inputs in the documents' schema."""
    parts = []
    if "documents" in sources:
        parts.append(read_table(spark, folder, "documents"))
    if "pages" in sources:
        parts.append(page_documents(read_table(spark, folder, "pages")))
    out = parts[0]
    for p in parts[1:]:
        out = out.unionByName(p)
    return out


def corpus_stats(docs: DataFrame, by: Sequence[str] = ("source",)) -> DataFrame:
    """Documents, words, pieces, bytes and characters by group."""
    return docs.groupBy(*by).agg(
        F.count(F.lit(1)).alias("docs"),
        F.sum(n_tokens("text")).alias("words"),
        F.sum(n_tokens("text", "piece")).alias("pieces"),
        F.sum(F.octet_length("text")).cast("long").alias("bytes"),
        F.sum(F.length("text")).cast("long").alias("chars"),
    )


def screen_sources(stats: DataFrame, min_words: int, allowed: Sequence[str] | None = None) -> DataFrame:
    """Source statistics plus keep: large enough, and allowed where a list is given."""
    keep = F.col("words") >= min_words
    if allowed is not None:
        keep = keep & F.col("source").isin(*allowed)
    return stats.withColumn("keep", F.coalesce(keep, F.lit(False)))
