"""Constants taken out of statements, as text: what groups a log natively before anything is parsed."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

# What counts as a constant in a statement's text, in the syntax that both engines' regexes share.
STRINGS = r"('[^']*')+"  # a doubled quote goes on
NUMBERS = r"\b[0-9]+(\.[0-9]+)?\b"
SPACES = r"\s+"


def fingerprint(sql: Column) -> Column:
    """Statement text with ? for strings and numbers and single spaces."""
    return F.trim(F.regexp_replace(F.regexp_replace(F.regexp_replace(sql, STRINGS, "?"), NUMBERS, "?"), SPACES, " "))


def fingerprint_sql(sql: str) -> str:
    """The same for DuckDB."""
    return f"trim(regexp_replace(regexp_replace(regexp_replace({sql}, '{STRINGS.replace(chr(39), chr(39) * 2)}', '?', 'g'), '{NUMBERS}', '?', 'g'), '{SPACES}', ' ', 'g'))"


def collapse_lists(text: Column) -> Column:
    """IN lists of any length as one placeholder."""
    return F.regexp_replace(text, r"\((\?)(, \?)*\)", "(?)")


def anonymise(log: DataFrame, salt: str = "") -> DataFrame:
    """Numbers and strings of sql become quoted SHA-256 tokens; equal constants stay equal, skeletons stay the same."""
    pieces = F.regexp_extract_all("sql", F.lit(rf"({STRINGS}|{NUMBERS}|[^0-9']+|.)"), 1)
    token = lambda x: F.when(x.rlike(rf"^({STRINGS}|[0-9]+(\.[0-9]+)?)$"), F.concat(F.lit("'"), F.sha2(F.concat(x, F.lit(salt)), 256), F.lit("'"))).otherwise(x)
    return log.withColumn("sql", F.array_join(F.transform(pieces, token), ""))


def statement_class(sql: Column) -> Column:
    """Leading keyword -> procedure, SELECT, UNION, INSERT, UPDATE, DELETE, or null where only a parser can tell."""
    head = F.upper(F.regexp_extract(F.trim(sql), r"^([A-Za-z]+)", 1))
    return F.when(head.isin("EXEC", "CALL"), "procedure").when((head == "SELECT") & F.regexp_replace(sql, STRINGS, "?").rlike(r"(?i)\bUNION\b"), "UNION").when(head.isin("SELECT", "INSERT", "UPDATE", "DELETE"), head)


def skeleton_bag(log: DataFrame) -> DataFrame:
    """log (sql, ts) -> skel_text, n_stmt, first_ts, last_ts, sample_sql: summed before the shuffle, one row for each fingerprint."""
    return log.groupBy(fingerprint(F.col("sql")).alias("skel_text")).agg(F.count("*").alias("n_stmt"), F.min("ts").alias("first_ts"), F.max("ts").alias("last_ts"), F.min("sql").alias("sample_sql"))
