"""A statement log projected from `events`: CASE, concat and integer arithmetic only.

The expressions are plain SQL that Spark and DuckDB both run, so one text serves the engine and its oracle. Every
family is one intent; the bits of `v` switch parts of the statement, and each has an effect in each family.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

# The families. Per line: from clause with {J} for the join, output columns, one more output, key predicate
# with {K}, list column, range column, OR column, order column, NOT NULL column (no join) or "", group column and one more.
FAMILIES = (
    ("orders", "o_orderkey, o_totalprice", "o_orderstatus", "o_orderkey = {K}", "o_orderstatus", "o_totalprice", "o_custkey", "o_orderkey", "o_orderdate", "", ""),
    ("orders", "o_orderkey, o_orderdate", "o_totalprice", "o_custkey = {K}", "o_orderpriority", "o_totalprice", "o_orderkey", "o_orderdate", "o_orderstatus", "", ""),
    ("orders", "o_orderkey, o_custkey", "o_orderdate", "o_orderdate >= {K}", "o_orderstatus", "o_totalprice", "o_custkey", "o_orderdate", "o_orderpriority", "", ""),
    ("lineitem", "l_linenumber, l_quantity", "l_extendedprice", "l_orderkey = {K}", "l_returnflag", "l_quantity", "l_partkey", "l_linenumber", "l_shipdate", "", ""),
    ("lineitem", "l_orderkey, l_shipdate", "l_suppkey", "l_shipdate < {K}", "l_returnflag", "l_discount", "l_suppkey", "l_shipdate", "l_linestatus", "", ""),
    ("orders {J} lineitem ON o_orderkey = l_orderkey", "o_orderkey, l_linenumber", "l_quantity", "o_orderkey = {K}", "o_orderstatus", "o_totalprice", "l_partkey", "o_orderkey", "", "", ""),
    ("orders {J} customer ON o_custkey = c_custkey", "o_orderkey, c_name", "c_acctbal", "c_custkey = {K}", "c_mktsegment", "o_totalprice", "o_orderkey", "o_orderdate", "", "", ""),
    ("lineitem {J} part ON l_partkey = p_partkey", "l_orderkey, p_name", "p_size", "p_partkey = {K}", "p_brand", "p_size", "l_orderkey", "p_name", "", "", ""),
    ("lineitem {J} supplier ON l_suppkey = s_suppkey", "l_orderkey, s_name", "s_acctbal", "s_suppkey = {K}", "s_nationkey", "l_quantity", "l_orderkey", "s_name", "", "", ""),
    ("orders {J} lineitem ON o_orderkey = l_orderkey INNER JOIN customer ON o_custkey = c_custkey", "o_orderkey, c_name, l_quantity", "l_tax", "c_custkey = {K}", "l_returnflag", "l_quantity", "o_orderkey", "o_orderkey", "", "", ""),
    ("lineitem", "sum(l_extendedprice)", "sum(l_tax)", "l_shipdate >= {K}", "l_linestatus", "l_discount", "l_suppkey", "l_returnflag", "l_partkey", "l_returnflag", "l_linestatus"),
    ("orders", "count(o_orderkey)", "max(o_totalprice)", "o_orderdate >= {K}", "o_orderstatus", "o_totalprice", "o_custkey", "o_orderpriority", "o_orderkey", "o_orderpriority", "o_orderstatus"),
    ("orders {J} customer ON o_custkey = c_custkey", "sum(o_totalprice)", "count(o_orderkey)", "o_totalprice > {K}", "o_orderstatus", "c_acctbal", "c_nationkey", "c_mktsegment", "", "c_mktsegment", "c_nationkey"),
    ("lineitem {J} part ON l_partkey = p_partkey", "sum(l_quantity)", "avg(l_discount)", "p_size > {K}", "p_type", "l_quantity", "p_partkey", "p_brand", "", "p_brand", "p_type"),
    ("lineitem {J} supplier ON l_suppkey = s_suppkey INNER JOIN nation ON s_nationkey = n_nationkey", "sum(l_extendedprice)", "count(l_orderkey)", "l_quantity > {K}", "n_regionkey", "s_acctbal", "s_suppkey", "n_name", "", "n_name", "n_regionkey"),
    ("customer", "c_custkey, c_name", "c_acctbal", "c_custkey = {K}", "c_mktsegment", "c_acctbal", "c_nationkey", "c_name", "c_nationkey", "", ""),
    ("customer", "c_name, c_mktsegment", "c_nationkey", "c_acctbal > {K}", "c_mktsegment", "c_custkey", "c_nationkey", "c_acctbal", "c_name", "", ""),
    ("customer {J} nation ON c_nationkey = n_nationkey", "c_name, n_name", "c_acctbal", "n_nationkey = {K}", "n_regionkey", "c_acctbal", "c_custkey", "c_name", "", "", ""),
    ("customer", "c_custkey", "c_mktsegment", "EXISTS (SELECT o_orderkey FROM orders WHERE o_custkey = c_custkey AND o_totalprice > {K})", "c_mktsegment", "c_acctbal", "c_nationkey", "c_custkey", "c_acctbal", "", ""),
    ("supplier {J} nation ON s_nationkey = n_nationkey INNER JOIN region ON n_regionkey = r_regionkey", "s_name, r_name", "n_name", "r_regionkey = {K}", "n_regionkey", "s_acctbal", "s_suppkey", "s_name", "", "", ""),
    ("part", "p_partkey, p_name", "p_brand", "p_name LIKE ''%{K}%''", "p_brand", "p_size", "p_partkey", "p_name", "p_type", "", ""),
    ("part", "p_partkey, CASE WHEN p_size > {K} THEN p_type ELSE p_brand END", "p_retailprice", "p_size < {K}", "p_type", "p_retailprice", "p_partkey", "p_size", "p_name", "", ""),
    ("part", "p_partkey", "p_name", "p_partkey IN (SELECT l_partkey FROM lineitem WHERE l_shipdate > {K})", "p_brand", "p_size", "p_retailprice", "p_partkey", "p_type", "", ""),
    ("nation {J} region ON n_regionkey = r_regionkey", "n_name, r_name", "n_nationkey", "n_nationkey > {K}", "r_name", "n_regionkey", "r_regionkey", "n_name", "", "", ""),
    ("lineitem", "l_orderkey, row_number() OVER (PARTITION BY l_orderkey ORDER BY l_extendedprice DESC)", "l_quantity", "l_orderkey > {K}", "l_returnflag", "l_quantity", "l_partkey", "l_orderkey", "l_shipdate", "", ""),
)

BASE = """
  event_id AS stmt_id, ts, user_id, event_id AS c1, user_id AS c2, cast(floor(value * 100) AS bigint) AS c3,
  cast(regexp_extract(props, '([0-9]+)', 1) AS bigint) AS k,
  5 * (CASE event_type WHEN 'click' THEN 0 WHEN 'error' THEN 1 WHEN 'purchase' THEN 2 WHEN 'signup' THEN 3 ELSE 4 END) + user_id % 5 AS fam,
  cast(floor(value / 4) AS bigint) AS v
"""
BITS = ", ".join(f"cast(floor(v / {1 << i}) AS bigint) % 2 AS b{i}" for i in range(8))
KLASS = "CASE WHEN k < 10 THEN 'procedure' WHEN k < 20 THEN 'unparsable' WHEN k < 38 THEN 'INSERT' WHEN k = 38 THEN 'UNION' WHEN k = 39 THEN 'DELETE' WHEN k < 88 THEN 'SELECT' ELSE 'UPDATE' END"
#: The second profile gives the classes the shares of a bank's log: mostly procedure calls and what no parser takes.
KLASS_BANK = "CASE WHEN k < 78 THEN 'procedure' WHEN k < 96 THEN 'unparsable' WHEN k < 97 THEN 'INSERT' WHEN k < 98 THEN 'UPDATE' ELSE 'SELECT' END"


def _text(parts: list[str]) -> str:
    return "concat(" + ", ".join(parts) + ")"


def _part(values: list[str]) -> str:
    """The family's value of a list: one look-up in one literal, so that the whole statement stays small in generated code."""
    joined = "^".join(values).replace("'", "''")
    return f"split_part('{joined}', '^', cast(fam + 1 AS int))"


def _when(bit: str, then: str) -> str:
    return f"CASE {bit} WHEN 1 THEN {then} ELSE '' END"


def _select() -> str:
    """The SELECT of every family, put together from its parts."""
    tables, outputs, more, key, listed, ranged, other, order, not_null, group, group_more = ([f[k].replace("''", "'") for f in FAMILIES] for k in range(11))
    before, after = [t.partition("{J}")[0] for t in tables], [t.partition("{J}")[2] for t in tables]
    joins = [bool(x) for x in after]
    head = [o.partition("{K}")[0] for o in outputs]
    tail = [o.partition("{K}")[2] for o in outputs]
    number = lambda c: f"cast({c} AS string)"
    parts = [
        "'SELECT '",
        _when("b6", _part(["" if g else "DISTINCT " for g in group])),
        _part(group),
        _when("b6", _part([f", {m}" if g else "" for g, m in zip(group, group_more, strict=True)])),
        _part([", " if g else "" for g in group]),
        _part(head),
        f"CASE fam WHEN {next(k for k, o in enumerate(outputs) if '{K}' in o)} THEN {number('c3')} ELSE '' END",
        _part(tail),
        _when("b3", _part([f", {m}" for m in more])),
        "' FROM '",
        _part(before),
        f"CASE b7 WHEN 1 THEN {_part(['LEFT JOIN' if j else '' for j in joins])} ELSE {_part(['INNER JOIN' if j else '' for j in joins])} END",
        _part(after),
        "' WHERE '",
        _when("b5", "'('"),
        _part([k.partition("{K}")[0] for k in key]),
        number("c1"),
        _part([k.partition("{K}")[2] for k in key]),
        _when("b5", f"concat({_part([f' OR {o} = ' for o in other])}, {number('c2')}, ')')"),
        _part([f" AND {x} " for x in listed]),
        "CASE b1 WHEN 1 THEN 'NOT IN' ELSE 'IN' END",
        f"concat(' (', {number('c2')}, ', ', {number('c3')}, ')')",
        _when("b0", f"concat({_part([f' AND {r} > ' for r in ranged])}, {number('c3')})"),
        _when("b7", _part(["" if j else f" AND {x} IS NOT NULL" for j, x in zip(joins, not_null, strict=True)])),
        _part([f" GROUP BY {g}" if g else "" for g in group]),
        _when("b6", _part([f", {m}" if g else "" for g, m in zip(group, group_more, strict=True)])),
        _part([f" ORDER BY {o}" for o in order]),
        _when("b2", "' DESC'"),
        _when("b4", f"concat(' LIMIT ', {number('c2 % 100 + 1')})"),
    ]
    return _text(parts)


def statement_sql() -> str:
    """The statement's text as a SQL expression over BASE, BITS and klass."""
    select = _select()
    n = lambda c: f"cast({c} AS string)"
    simple = lambda c: _text(["'SELECT o_orderkey FROM orders WHERE o_custkey = '", n(c)])
    return f"""CASE klass
      WHEN 'procedure' THEN concat(CASE event_id_odd WHEN 1 THEN 'EXEC' ELSE 'CALL' END, ' refresh_totals(', {n('c1')}, ', ', {n('c2')}, ')')
      WHEN 'unparsable' THEN CASE c1 % 3 WHEN 0 THEN concat('SELECT o_orderkey FROM orders WHERE o_custkey = ', {n('c2')}, ' AND (') WHEN 1 THEN concat('LOCK TABLE orders IN SHARE MODE NOWAIT ', {n('c1')}) ELSE concat('please check order ', {n('c1')}, ' again') END
      WHEN 'INSERT' THEN CASE fam % 3 WHEN 0 THEN concat('INSERT INTO orders (o_orderkey, o_custkey) VALUES (', {n('c1')}, ', ', {n('c2')}, ')') WHEN 1 THEN concat('INSERT INTO lineitem (l_orderkey, l_quantity) VALUES (', {n('c1')}, ', ', {n('c3')}, ')') ELSE concat('INSERT INTO customer (c_custkey, c_acctbal) VALUES (', {n('c2')}, ', ', {n('c3')}, ')') END
      WHEN 'UNION' THEN concat({simple('c1')}, ' UNION ', {simple('c2')})
      WHEN 'DELETE' THEN concat('DELETE FROM orders WHERE o_orderkey = ', {n('c1')}, ' AND o_orderdate < ', {n('c3')})
      WHEN 'UPDATE' THEN CASE fam % 3 WHEN 0 THEN concat('UPDATE orders SET o_totalprice = ', {n('c3')}, ' WHERE o_orderkey = ', {n('c1')}) WHEN 1 THEN concat('UPDATE customer SET c_acctbal = ', {n('c3')}, ' WHERE c_custkey = ', {n('c2')}) ELSE concat('UPDATE orders SET o_orderstatus = ', {n('c2')}, ' WHERE o_custkey = ', {n('c2')}) END
      ELSE {select} END"""


def log_sql(mix: str = "plain", source: str = "events") -> str:
    """The whole log as one SELECT that both engines run: stmt_id, ts, user_id, sql, fam, v, klass."""
    klass = KLASS_BANK if mix == "bank" else KLASS
    return f"""SELECT stmt_id, ts, user_id, {statement_sql()} AS sql, fam, v, klass FROM (
      SELECT *, {klass} AS klass, stmt_id % 2 AS event_id_odd, {BITS} FROM (SELECT {BASE} FROM {source}) base) bits"""


def query_log(spark: SparkSession, sf_dir: str, mix: str = "plain", dealt: bool = False) -> DataFrame:
    """The derived log; fam, v and klass are its truth and no method reads them. dealt: over all cores, however few files there are."""
    events = spark.read.parquet(f"{sf_dir}/events.parquet")
    if dealt:
        events = events.repartition(max(spark.sparkContext.defaultParallelism, len(events.inputFiles())), "event_id")
    return spark.sql(log_sql(mix, "{events}"), events=events)


def project(events: DataFrame, mix: str = "plain") -> DataFrame:
    """The same projection for any frame of events, streams included."""
    klass = KLASS_BANK if mix == "bank" else KLASS
    base = events.selectExpr(*[x.strip() for x in _split(BASE)])
    return base.selectExpr("*", f"{klass} AS klass", "stmt_id % 2 AS event_id_odd", *BITS.split(", ")).selectExpr("stmt_id", "ts", "user_id", f"{statement_sql()} AS sql", "fam", "v", "klass")


def _split(columns: str) -> list[str]:
    """Top-level commas of a list of columns."""
    out, depth, at = [], 0, 0
    for k, c in enumerate(columns):
        depth += (c == "(") - (c == ")")
        if c == "," and not depth:
            out.append(columns[at:k])
            at = k + 1
    return [*out, columns[at:]]
