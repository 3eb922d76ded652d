"""Line dedup by site-relative frequency: a line on too large a share of a host's pages is boilerplate.

Parameters in production: ratio 0.1 (of the host's pages), and at least 3 pages.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

RATIO, LEAST_PAGES = 0.1, 3


def _lines(text: Column) -> Column:
    return F.split(text, "\n")


def _key(line: Column) -> Column:
    """A line without the blanks around it; None for a blank line, which is never counted or dropped."""
    return F.nullif(F.btrim(line, F.lit(" \t\r")), F.lit(""))


def boilerplate(df: DataFrame, host: str, text: str, ratio: float = RATIO, least: int = LEAST_PAGES, distinct: bool = True) -> DataFrame:
    """Rows (host, hash): lines that stand on more than `ratio` of the host's pages, and on `least` pages or more.

    Every page counts a line once. A host keeps fewer than (mean lines of a page) / ratio lines, whatever its size.
    With `distinct`, pages of one text count as one page, above and below the line, so that copies of a page cannot
    make its own body boilerplate; null texts of a host are one page.
    """
    h = F.col(host)
    page = df.select(h.alias("host"), F.sha2(F.encode(text, "UTF-8"), 256).alias("digest"), F.array_compact(F.array_distinct(F.transform(_lines(F.col(text)), lambda x: F.when(_key(x).isNotNull(), F.xxhash64(_key(x)))))).alias("hashes"))
    per_page = page.groupBy("host", "digest").agg(F.first("hashes").alias("hashes")) if distinct else page
    pages = (page.select("host", "digest").distinct() if distinct else df.select(h.alias("host"))).groupBy("host").agg(F.count(F.lit(1)).alias("pages"))
    counts = per_page.select("host", F.explode("hashes").alias("hash")).groupBy("host", "hash").agg(F.count(F.lit(1)).alias("n")).where(F.col("n") >= least)
    total = pages.select(F.col("host").alias("of"), "pages")
    return counts.join(total, F.col("host").eqNullSafe(F.col("of"))).where(F.col("n") > ratio * F.col("pages")).select("host", "hash")


def clean(df: DataFrame, host: str = "source", text: str = "text", ratio: float = RATIO, least: int = LEAST_PAGES, salts: int = 16, distinct: bool = True) -> DataFrame:
    """The rows of df with every boilerplate line taken out of `text`, plus n_lines and n_dropped.

    Lines are split at LF and compared without blanks around them; blank lines stay. A null text stays null (0 lines);
    a text of boilerplate only becomes empty; rows with a null host form a host of their own; repeated rows count as
    one page with `distinct`, else as pages of their own; an empty table gives none. All columns of df are kept (n_lines and n_dropped are replaced).
    A host's list of boilerplate hashes is small (see boilerplate) and is repeated over `salts` keys, so that the pages
    of a large host meet it in many tasks.
    """
    listed = boilerplate(df, host, text, ratio, least, distinct).groupBy("host").agg(F.collect_set("hash").alias("__bad"))
    listed = listed.select(F.coalesce(F.concat(F.lit("h"), "host"), F.lit("n")).alias("__host"), "__bad").withColumn("__salt", F.explode(F.sequence(F.lit(0), F.lit(salts - 1))))
    lines = _lines(F.col(text))
    keyed = df.withColumn("__host", F.coalesce(F.concat(F.lit("h"), F.col(host)), F.lit("n"))).withColumn("__salt", F.pmod(F.xxhash64(*[F.col(c) for c, t in df.dtypes if t in ("bigint", "int", "string")]), F.lit(salts)).cast("int"))
    met = keyed.join(listed, ["__host", "__salt"], "left")
    bad = lambda x: F.coalesce(F.array_contains(F.col("__bad"), F.xxhash64(_key(x))) & _key(x).isNotNull(), F.lit(False))
    met = met.withColumn("__kept", F.when(F.col("__bad").isNull(), lines).otherwise(F.filter(lines, lambda x: ~bad(x))))
    out = met.withColumn("n_lines", F.coalesce(F.size(lines), F.lit(0)).cast("long")).withColumn("n_lines", F.when(F.col(text).isNull(), F.lit(0).cast("long")).otherwise(F.col("n_lines")))
    out = out.withColumn("n_dropped", F.when(F.col(text).isNull(), F.lit(0).cast("long")).otherwise(F.col("n_lines") - F.size("__kept").cast("long")))
    out = out.withColumn(text, F.when(F.col("n_dropped") > 0, F.array_join("__kept", "\n")).otherwise(F.col(text)))
    return out.select(*[c for c in df.columns if c not in ("n_lines", "n_dropped")], "n_lines", "n_dropped")


def report(df: DataFrame, distinct: bool = False) -> DataFrame:
    """(doc_id, n_lines, n_dropped, kept_md5): the digest of clean() for documents."""
    return clean(df.select("doc_id", "text", "source"), distinct=distinct).select("doc_id", "n_lines", "n_dropped", F.md5(F.encode(F.coalesce("text", F.lit("")), "UTF-8")).alias("kept_md5"))


REPORT_SQL = f"""
WITH d AS (SELECT row_number() OVER () AS r, doc_id, coalesce('h' || source, 'n') AS host, string_split(text, chr(10)) AS lines, text FROM documents),
pages AS (SELECT host, count(*) AS pages FROM d GROUP BY host),
seen AS (SELECT DISTINCT r, host, trim(line, ' ' || chr(9) || chr(13)) AS line FROM (SELECT r, host, unnest(lines) AS line FROM d)),
bad AS (SELECT host, line FROM seen JOIN pages USING (host) WHERE line <> '' GROUP BY host, line, pages HAVING count(*) >= {LEAST_PAGES} AND count(*) > {RATIO} * pages),
per AS (SELECT host, list(line) AS bad FROM bad GROUP BY host),
k AS (SELECT doc_id, d.text, lines, CASE WHEN bad IS NULL THEN lines ELSE list_filter(lines, lambda x: NOT list_contains(bad, trim(x, ' ' || chr(9) || chr(13)))) END AS kept FROM d LEFT JOIN per USING (host))
SELECT doc_id, coalesce(len(lines), 0)::BIGINT AS n_lines, coalesce(len(lines) - len(kept), 0)::BIGINT AS n_dropped, md5(coalesce(array_to_string(kept, chr(10)), '')) AS kept_md5 FROM k
"""

#: Distinct texts of a host as its pages.
DISTINCT_SQL = f"""
WITH d AS (SELECT row_number() OVER () AS r, doc_id, coalesce('h' || source, 'n') AS host, string_split(text, chr(10)) AS lines, text FROM documents),
one AS (SELECT host, text, min(r) AS r FROM d GROUP BY host, text),
pages AS (SELECT host, count(*) AS pages FROM one GROUP BY host),
seen AS (SELECT DISTINCT r, host, trim(line, ' ' || chr(9) || chr(13)) AS line FROM (SELECT r, host, unnest(string_split(text, chr(10))) AS line FROM one)),
bad AS (SELECT host, line FROM seen JOIN pages USING (host) WHERE line <> '' GROUP BY host, line, pages HAVING count(*) >= {LEAST_PAGES} AND count(*) > {RATIO} * pages),
per AS (SELECT host, list(line) AS bad FROM bad GROUP BY host),
k AS (SELECT doc_id, d.text, lines, CASE WHEN bad IS NULL THEN lines ELSE list_filter(lines, lambda x: NOT list_contains(bad, trim(x, ' ' || chr(9) || chr(13)))) END AS kept FROM d LEFT JOIN per USING (host))
SELECT doc_id, coalesce(len(lines), 0)::BIGINT AS n_lines, coalesce(len(lines) - len(kept), 0)::BIGINT AS n_dropped, md5(coalesce(array_to_string(kept, chr(10)), '')) AS kept_md5 FROM k
"""
