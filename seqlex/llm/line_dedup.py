"""Cross-site boilerplate lines, found by distinct-site spread. DataFrame functions only.

Each line that is worth a look (`min_chars` characters or more once trimmed) is known by 128 bits of hash. One aggregation
merges HyperLogLog sketches of the sites on which it stands. Far from `min_sites` the estimate decides; lines whose
estimate is near it (within `band`, about eight standard errors) get an exact distinct count. A line on min_sites sites or
more is boilerplate and is removed from every document but its first carrier (the one of the smallest id), so that no
content is lost from the corpus altogether. The lines that stand most often (at most `HOT`) are taken out of the joins and met by a
broadcast, so that no line's carriers land in one task.

Defined results: a null text stays null, with no lines; a null site counts as one site; a null id is the last carrier. Lines
repeated within a document count once for the spread and are removed, or kept, together. Rows that repeat with one id are
treated alike. All columns of the input return unchanged but for the text and the two counts, which take the names given in `counts` and
replace columns called so.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import fresh, hot_keys, join_hot, spool

LAST = 2**63 - 1


def _keys(line: Column) -> list[Column]:
    return [F.xxhash64(line), F.xxhash64(F.lit("spread"), line)]


def lines_of(docs: DataFrame, text: str, site: str, key: str, min_chars: int) -> DataFrame:
    """(carrier, site, h1, h2) of each different line of a document."""
    line = F.explode(F.array_distinct(F.transform(F.split(F.col(text), "\n"), lambda x: F.trim(x))))
    rows = docs.select(F.coalesce(F.col(key).cast("long"), F.lit(LAST)).alias("carrier"), F.coalesce(F.col(site).cast("string"), F.lit("")).alias("site"), line.alias("line"))
    h1, h2 = _keys(F.col("line"))
    return rows.where(F.length("line") >= min_chars).select("carrier", "site", h1.alias("h1"), h2.alias("h2"))


KEY = ["h1", "h2"]


def spread_of(lines: DataFrame, lg_k: int = 10) -> DataFrame:
    """(h1, h2, sites, first, n) of each line: the estimated number of its sites, its first carrier and the number of its carriers."""
    return lines.groupBy(*KEY).agg(F.hll_sketch_estimate(F.hll_sketch_agg("site", lg_k)).alias("sites"), F.min("carrier").alias("first"), F.count(F.lit(1)).alias("n"))


def boilerplate(lines: DataFrame, spread: DataFrame, hot: DataFrame, *, min_sites: int, band: float = 0.25) -> DataFrame:
    """(h1, h2, first) of the lines on min_sites sites or more; first is their first carrier."""
    wide = spread.where(F.col("sites") >= min_sites * (1 - band))
    sure = wide.where(F.col("sites") > min_sites * (1 + band)).select("h1", "h2", "first")
    near = wide.where(F.col("sites") <= min_sites * (1 + band)).select("h1", "h2", "first")
    exact = join_hot(lines, near, KEY, hot).groupBy("h1", "h2", "first", "site").agg(F.lit(1).alias("one")).groupBy("h1", "h2", "first").agg(F.count(F.lit(1)).alias("exact"))
    return sure.unionByName(exact.where(F.col("exact") >= min_sites).select("h1", "h2", "first"))


def clean(docs: DataFrame, *, text: str = "text", site: str = "source", key: str = "doc_id", min_sites: int = 10, min_chars: int = 20, counts: tuple[str, str] = ("n_lines", "n_removed")) -> DataFrame:
    """docs with the boilerplate lines taken out of the text, and the numbers of its lines and of those removed under the names in counts."""
    # The texts are split once; all later steps read these narrow rows.
    lines = spool(lines_of(docs, text, site, key, min_chars), "lines")
    spread = spool(spread_of(lines), "spread")
    hot = hot_keys(spread, KEY)
    bad = spool(boilerplate(lines, spread, hot, min_sites=min_sites), "boilerplate")
    hits = join_hot(lines, bad, KEY, hot).where(F.col("carrier") != F.col("first"))
    gone, carrier = fresh(docs.columns, "__removed"), fresh(docs.columns, "__carrier")
    removed = hits.groupBy(F.col("carrier").alias(carrier)).agg(F.collect_set(F.struct("h1", "h2")).alias(gone))
    kept = docs.drop(*counts)
    joined = kept.join(removed, F.coalesce(F.col(key).cast("long"), F.lit(LAST)) == F.col(carrier), "left")
    old = F.split(F.col(text), "\n")

    def stays(line: Column) -> Column:
        h1, h2 = _keys(F.trim(line))
        return ~F.array_contains(F.col(gone), F.struct(h1.alias("h1"), h2.alias("h2"))) | (F.length(F.trim(line)) < min_chars)

    new = F.when(F.col(gone).isNull(), F.col(text)).otherwise(F.array_join(F.filter(old, stays), "\n"))
    n_new = F.when(F.col(gone).isNull(), F.size(old)).otherwise(F.size(F.filter(old, stays)))
    n_old, n_gone = F.when(F.col(text).isNull(), 0).otherwise(F.size(old)).cast("long"), F.when(F.col(text).isNull(), 0).otherwise(F.size(old) - n_new).cast("long")
    return joined.select(*[new.alias(c) if c == text else F.col(f"`{c}`") for c in kept.columns], n_old.alias(counts[0]), n_gone.alias(counts[1]))


def oracle(min_sites: int = 10, min_chars: int = 20) -> str:
    return f"""
WITH l AS (SELECT doc_id, source, pos, line FROM (SELECT doc_id, source, generate_subscripts(string_split(text, chr(10)), 1) AS pos, unnest(string_split(text, chr(10))) AS line FROM documents)),
bad AS (SELECT trim(line, ' ') AS t, min(doc_id) AS first FROM l WHERE length(trim(line, ' ')) >= {min_chars} GROUP BY 1 HAVING count(DISTINCT coalesce(source, '')) >= {min_sites}),
m AS (SELECT l.*, bad.t IS NOT NULL AND l.doc_id <> bad.first AS gone FROM l LEFT JOIN bad ON trim(l.line, ' ') = bad.t)
SELECT doc_id, count(*) AS n_lines, count(*) FILTER (gone) AS n_removed, coalesce(string_agg(line, chr(10) ORDER BY pos) FILTER (NOT gone), '') AS text FROM m GROUP BY doc_id"""
