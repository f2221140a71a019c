"""The experiments, re-expressed on the given tables, and the measures on native trees, bags and vectors."""

from __future__ import annotations

import time
from functools import lru_cache

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .functions import cnf, digest, grammar
from .functions import skeleton as sk
from .operators import audit, compare, distance, fptree, linkage, relabel, rules, summary
from .operators.components import components
from .plans.dialect import DUCK, with_log
from .sources import logsynth
from .tables import table

CUTS = (2, 5, 8, 11, 16, 21, 26, 30)  # days after the log's first midnight, for the eight truncations
FP = DUCK.fp("sql")
ORACLES: dict[str, str] = {}


def oracle(sql: str, log: bool = False):
    def wrap(f):
        ORACLES[f.__name__] = with_log(sql) if log else sql
        return f

    return wrap


@lru_cache(maxsize=8)
def _log_table(app: str, sf_dir: str) -> DataFrame:
    return table(logsynth.query_log(SparkSession.getActiveSession(), sf_dir, dealt=True), "log")


def _log(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The derived log as a written table: a log is read, and its text is not made again for each use."""
    return _log_table(spark.sparkContext.applicationId, sf_dir)


def _selects(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _log(spark, sf_dir).where(sk.statement_class(F.col("sql")) == "SELECT")


def _read(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


# -- counts over the log


def _parsed(log: DataFrame) -> tuple[DataFrame, DataFrame]:
    """Fingerprints with counts, and the nodes of one example of each."""
    bag = sk.skeleton_bag(log)
    bag = table(bag.withColumn("tree_id", F.xxhash64("skel_text")), "fingerprints")
    return bag, table(grammar.parse_statements(bag, text="sample_sql"), "nodes")


@oracle("SELECT t.name AS table_name, count(*) AS n_stmt FROM log, (VALUES ('orders'), ('lineitem'), ('customer'), ('supplier'), ('part'), ('nation'), ('region')) t(name) WHERE klass = 'SELECT' AND regexp_matches(sql, concat('(FROM|JOIN) ', t.name, '\\b')) GROUP BY t.name", log=True)
def w_table_access(spark, sf_dir):
    bag, nodes = _parsed(_selects(spark, sf_dir).where("not sql like '% UNION %'"))
    up = nodes.where("atom = 'TABLE'").select("tree_id", F.col("node_id").alias("parent_id"))
    names = nodes.join(up, ["tree_id", "parent_id"]).select("tree_id", F.col("atom").alias("table_name")).distinct()
    return names.join(bag.select("tree_id", "n_stmt"), "tree_id").groupBy("table_name").agg(F.sum("n_stmt").alias("n_stmt"))


@oracle("SELECT p[1] AS left_col, p[2] AS right_col, count(*) AS n_stmt FROM (SELECT string_split(replace(unnest(regexp_extract_all(sql, ' ON [a-z_]+ = [a-z_]+')), ' ON ', ''), ' = ') AS p FROM log WHERE klass = 'SELECT') t GROUP BY 1, 2", log=True)
def w_join_predicates(spark, sf_dir):
    bag, nodes = _parsed(_selects(spark, sf_dir))
    on = nodes.where("atom = 'ON'").select("tree_id", F.col("node_id").alias("_on"))
    eq = nodes.where("atom = '='").join(on, ["tree_id"]).where("parent_id = _on").select("tree_id", F.col("node_id").alias("_eq"))
    side = lambda k, name: nodes.where(f"child_idx = {k}").select("tree_id", F.col("parent_id").alias("_eq"), F.col("atom").alias(name))
    pairs = eq.join(side(1, "left_col"), ["tree_id", "_eq"]).join(side(2, "right_col"), ["tree_id", "_eq"])
    return pairs.join(bag.select("tree_id", "n_stmt"), "tree_id").groupBy("left_col", "right_col").agg(F.sum("n_stmt").alias("n_stmt"))


def _top(rows: DataFrame, text) -> DataFrame:
    top = rows.groupBy(text.alias("text")).agg(F.count("*").alias("n")).orderBy(F.desc("n"), "text").limit(10)
    return top.withColumn("rank", F.row_number().over(Window.orderBy(F.desc("n"), "text")))


@oracle("SELECT text, n, cast(row_number() OVER (ORDER BY n DESC, text) AS int) AS rank FROM (SELECT sql AS text, count(*) AS n FROM log WHERE klass = 'SELECT' GROUP BY sql ORDER BY n DESC, text LIMIT 10) t", log=True)
def w_topk_raw(spark, sf_dir):
    return _top(_selects(spark, sf_dir).where("klass = 'SELECT'"), F.col("sql"))


@oracle(f"SELECT text, n, cast(row_number() OVER (ORDER BY n DESC, text) AS int) AS rank FROM (SELECT {FP} AS text, count(*) AS n FROM log WHERE klass = 'SELECT' GROUP BY 1 ORDER BY n DESC, text LIMIT 10) t", log=True)
def w_topk_skeleton(spark, sf_dir):
    return _top(_selects(spark, sf_dir).where("klass = 'SELECT'"), sk.fingerprint(F.col("sql")))


def _classified(log: DataFrame) -> DataFrame:
    """log with parse_class and stmt_type: keywords natively, the parser's verdict once for each fingerprint."""
    bag, nodes = _parsed(log)
    bad = nodes.where("node_id < 0").select("tree_id")
    bad = bag.join(bad, "tree_id").select("skel_text", F.lit(True).alias("_bad"))
    rows = log.withColumn("skel_text", sk.fingerprint(F.col("sql"))).join(bad, "skel_text", "left")
    kind = sk.statement_class(F.col("sql"))
    parse = F.when(kind == "procedure", "procedure").when(F.col("_bad").isNotNull(), "unparsable").otherwise("parsable")
    return rows.select("stmt_id", parse.alias("parse_class"), F.when(parse == "parsable", kind).alias("stmt_type"))


@oracle("SELECT CASE WHEN klass IN ('procedure', 'unparsable') THEN klass ELSE 'parsable' END AS parse_class, count(*) AS n FROM log GROUP BY ROLLUP (1)".replace("ROLLUP (1)", "ROLLUP (CASE WHEN klass IN ('procedure', 'unparsable') THEN klass ELSE 'parsable' END)"), log=True)
def w_breakdown(spark, sf_dir):
    return _classified(_log(spark, sf_dir)).rollup("parse_class").agg(F.count("*").alias("n"))


@oracle("SELECT klass AS stmt_type, count(*) AS n FROM log WHERE klass NOT IN ('procedure', 'unparsable') GROUP BY ROLLUP (klass)", log=True)
def w_types(spark, sf_dir):
    return _classified(_log(spark, sf_dir)).where("stmt_type is not null").rollup("stmt_type").agg(F.count("*").alias("n"))


_CUT_ROWS = ", ".join(f"({c})" for c in CUTS)


@oracle(f"WITH f AS (SELECT {FP} AS fp, ts FROM log WHERE klass = 'SELECT') SELECT c.d AS cut_day, count(*) AS n_select, count(DISTINCT fp) AS n_skeleton FROM f, (VALUES {_CUT_ROWS}) c(d) WHERE ts < timestamp '2024-01-01 00:00:00' + c.d * interval 1 day GROUP BY c.d", log=True)
def w_growth(spark, sf_dir):
    """One pass: statements per day, and structures by the day that they first show."""
    day = F.datediff("ts", F.lit("2024-01-01").cast("date"))
    rows = _selects(spark, sf_dir).where("klass = 'SELECT'").groupBy(sk.fingerprint(F.col("sql")).alias("fp"), day.alias("day")).agg(F.count("*").alias("n"))
    per = rows.groupBy("fp").agg(F.min("day").alias("first"), F.collect_list(F.struct("day", "n")).alias("days"))
    cuts = spark.createDataFrame([(c,) for c in CUTS], "cut_day int")
    n = rows.groupBy("day").agg(F.sum("n").alias("n"))
    new = per.groupBy("first").agg(F.count("*").alias("m"))
    a = cuts.join(n, F.col("day") < F.col("cut_day")).groupBy("cut_day").agg(F.sum("n").alias("n_select"))
    b = cuts.join(new, F.col("first") < F.col("cut_day")).groupBy("cut_day").agg(F.sum("m").alias("n_skeleton"))
    return a.join(b, "cut_day")


@oracle(f"SELECT variant, count(DISTINCT fp) AS n_fingerprint FROM (SELECT {FP} AS fp FROM log) t, (VALUES ('plain'), ('hashed')) v(variant) GROUP BY variant", log=True)
def w_anonymise(spark, sf_dir):
    log = _log(spark, sf_dir)
    count = lambda rows, name: rows.select(F.lit(name).alias("variant"), sk.fingerprint(F.col("sql")).alias("fp")).distinct().groupBy("variant").agg(F.count("*").alias("n_fingerprint"))
    return count(log, "plain").unionByName(count(sk.anonymise(log, salt="s"), "hashed"))


@oracle(f"WITH f AS (SELECT {FP} AS fp, cast(ts AS date) AS day FROM log), g AS (SELECT *, min(day) OVER (PARTITION BY fp) AS first FROM f) SELECT day, count(*) AS n_stmt, count(DISTINCT fp) AS n_active, count(DISTINCT CASE WHEN day = first THEN fp END) AS n_new FROM g GROUP BY day", log=True)
def w_temporal(spark, sf_dir):
    return audit.temporal_profile(_log(spark, sf_dir)).select(F.to_date("window").alias("day"), "n_stmt", "n_active", "n_new")


@oracle("SELECT user_id, fam AS family, count(*) AS n, round(count(*) / sum(count(*)) OVER (PARTITION BY user_id), 6) AS share FROM log WHERE klass = 'SELECT' GROUP BY user_id, fam", log=True)
def w_user_profile(spark, sf_dir):
    return audit.user_profile(_log(spark, sf_dir).where("klass = 'SELECT'").withColumnRenamed("fam", "family"), "family").select("user_id", "family", "n", "share")


# -- relabelling and digests on native trees


def order_trees(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Status over the lines' return flags over their line states. Line numbers repeat within an order, so lines get names."""
    o, li = _read(spark, sf_dir, "orders"), _read(spark, sf_dir, "lineitem")
    li = li.join(o, F.col("l_orderkey") == F.col("o_orderkey")).select(F.col("o_orderkey").alias("tree_id"), "o_orderstatus", "l_returnflag", "l_linestatus", F.monotonically_increasing_id().alias("line"))
    li = table(li, "order-lines")
    null = F.lit(None).cast("long")
    root = li.select("tree_id", F.lit(-1).cast("long").alias("node_id"), null.alias("parent_id"), F.col("o_orderstatus").alias("atom"), F.lit(3).alias("height")).distinct()
    flag = li.select("tree_id", (F.col("line") * 2).alias("node_id"), F.lit(-1).cast("long").alias("parent_id"), F.col("l_returnflag").alias("atom"), F.lit(2).alias("height"))
    state = li.select("tree_id", (F.col("line") * 2 + 1).alias("node_id"), (F.col("line") * 2).alias("parent_id"), F.col("l_linestatus").alias("atom"), F.lit(1).alias("height"))
    return root.unionByName(flag).unionByName(state)


_ORDER_LEVELS = """WITH li AS (SELECT l_orderkey AS t, o_orderstatus AS s, l_returnflag AS f, l_linestatus AS x FROM lineitem JOIN orders ON l_orderkey = o_orderkey),
 flag AS (SELECT *, sha256(concat('L(', f, ',', sha256(concat('B(', x, ')')), ')')) AS f1 FROM li),
 root AS (SELECT t, s, sha256(concat('L(', s, ',', sha256(concat('B(', array_to_string(list_sort(list(f)), ','), ')')), ')')) AS r1, sha256(concat('L(', s, ',', sha256(concat('B(', array_to_string(list_sort(list(f1)), ','), ')')), ')')) AS r2 FROM flag GROUP BY t, s)"""


@oracle(_ORDER_LEVELS + " SELECT level, label, count(*) AS n FROM (SELECT 0 AS level, s AS label FROM root UNION ALL SELECT 0, f FROM flag UNION ALL SELECT 0, x FROM flag UNION ALL SELECT 1, f1 FROM flag UNION ALL SELECT 1, r1 FROM root UNION ALL SELECT 2, r2 FROM root) z GROUP BY level, label")
def w_order_trees(spark, sf_dir):
    return relabel.relabel(order_trees(spark, sf_dir)).groupBy("level", "label").agg(F.count("*").alias("n"))


@oracle(_ORDER_LEVELS + " SELECT r2 AS root_key, count(*) AS n_trees, min(t) AS first_tree FROM root GROUP BY r2")
def w_exact_tree_groups(spark, sf_dir):
    nodes = table(order_trees(spark, sf_dir), "order-trees")
    return relabel.exact_tree_groups(relabel.relabel(nodes), nodes)


@oracle(_ORDER_LEVELS + " SELECT t AS tree_id, count(DISTINCT label) AS n_features, count(*) AS total FROM (SELECT t, s AS label FROM root UNION ALL SELECT t, f FROM flag UNION ALL SELECT t, x FROM flag UNION ALL SELECT t, f1 FROM flag UNION ALL SELECT t, r1 FROM root UNION ALL SELECT t, r2 FROM root) z GROUP BY t")
def w_feature_counts(spark, sf_dir):
    own = relabel.relabel(order_trees(spark, sf_dir)).select("tree_id", "node_id", F.col("label").alias("feature_key"))
    return relabel.feature_bag(own).groupBy("tree_id").agg(F.count("*").alias("n_features"), F.sum("mult").alias("total"))


@oracle("SELECT l_orderkey, sha256(concat('L(', array_to_string(list(l_returnflag ORDER BY l_linenumber, l_returnflag), ','), ')')) AS list_key, sha256(concat('B(', array_to_string(list_sort(list(l_returnflag)), ','), ')')) AS bag_key, sha256(concat('S(', array_to_string(list_sort(list(DISTINCT l_returnflag)), ','), ')')) AS set_key FROM lineitem GROUP BY l_orderkey")
def w_digest_identities(spark, sf_dir):
    li = _read(spark, sf_dir, "lineitem").groupBy("l_orderkey").agg(F.transform(F.array_sort(F.collect_list(F.struct("l_linenumber", "l_returnflag"))), lambda s: s["l_returnflag"]).alias("a"))
    return li.select("l_orderkey", digest.list_digest(F.col("a")).alias("list_key"), digest.bag_digest(F.col("a")).alias("bag_key"), digest.set_digest(F.col("a")).alias("set_key"))


@oracle("""WITH c AS (SELECT r_regionkey, r_name, n_name, c_mktsegment AS seg FROM region JOIN nation ON n_regionkey = r_regionkey JOIN (SELECT DISTINCT c_nationkey, c_mktsegment FROM customer) d ON c_nationkey = n_nationkey),
 n1 AS (SELECT r_regionkey, r_name, n_name, sha256(concat('L(', n_name, ',', sha256(concat('B(', array_to_string(list_sort(list(seg)), ','), ')')), ')')) AS l1 FROM c GROUP BY r_regionkey, r_name, n_name),
 r AS (SELECT r_regionkey, r_name, sha256(concat('L(', r_name, ',', sha256(concat('B(', array_to_string(list_sort(list(n_name)), ','), ')')), ')')) AS r1, sha256(concat('L(', r_name, ',', sha256(concat('B(', array_to_string(list_sort(list(l1)), ','), ')')), ')')) AS r2 FROM n1 GROUP BY r_regionkey, r_name)
 SELECT cast(r_regionkey AS bigint) AS r_regionkey, 1 AS level, r1 AS label FROM r UNION ALL SELECT cast(r_regionkey AS bigint), 2, r2 FROM r""")
def w_geo_tree(spark, sf_dir):
    r, n, c = (_read(spark, sf_dir, t) for t in ("region", "nation", "customer"))
    null = F.lit(None).cast("string")
    segments = c.select("c_nationkey", "c_mktsegment").distinct()
    have = n.join(segments.select(F.col("c_nationkey").alias("n_nationkey")).distinct(), "n_nationkey")
    tid = lambda x: F.col(x).cast("long").alias("tree_id")
    nodes = r.select(tid("r_regionkey"), F.lit("r").alias("node_id"), null.alias("parent_id"), F.col("r_name").alias("atom"), F.lit(3).alias("height"))
    nodes = nodes.unionByName(have.select(tid("n_regionkey"), F.concat(F.lit("n"), "n_nationkey").alias("node_id"), F.lit("r").alias("parent_id"), F.col("n_name").alias("atom"), F.lit(2).alias("height")))
    leaf = segments.join(have, F.col("c_nationkey") == F.col("n_nationkey"))
    nodes = nodes.unionByName(leaf.select(tid("n_regionkey"), F.concat(F.lit("s"), "n_nationkey", "c_mktsegment").alias("node_id"), F.concat(F.lit("n"), "n_nationkey").alias("parent_id"), F.col("c_mktsegment").alias("atom"), F.lit(1).alias("height")))
    return relabel.relabel(nodes).where("node_id = 'r' and level > 0").select(F.col("tree_id").alias("r_regionkey"), "level", "label")


_TRACE = grammar.parse("SELECT r_name FROM region WHERE r_regionkey < 3")


def w_relabel_trace(spark, sf_dir):
    """Every label of a small statement's nodes by level."""
    rows = [(1, r[0], r[1], r[3], r[5]) for r in grammar.rows(_TRACE)]
    nodes = spark.createDataFrame(rows, "tree_id long, node_id int, parent_id int, atom string, height int")
    return relabel.relabel(nodes).select("node_id", "level", "label")


def w_dom_trees(spark, sf_dir):
    """Tag outlines of pages: root subtree keys and how many pages have each."""
    import html.parser

    class Outline(html.parser.HTMLParser):
        def __init__(self):
            super().__init__()
            self.rows, self.stack = [], []

        def handle_starttag(self, tag, attrs):
            if tag not in ("meta", "br", "img", "link", "input", "hr"):
                self.rows.append((len(self.rows), self.stack[-1] if self.stack else None, tag))
                self.stack.append(len(self.rows) - 1)

        def handle_endtag(self, tag):
            for k in range(len(self.stack) - 1, -1, -1):
                if self.rows[self.stack[k]][2] == tag:
                    del self.stack[k:]
                    return

    def outlines(frames):
        for f in frames:
            out = []
            for page, text in zip(f["page_id"], f["html"], strict=True):
                p = Outline()
                p.feed(text or "")
                kids: dict = {}
                for n, parent, _ in p.rows:
                    kids.setdefault(parent, []).append(n)
                label = {}
                for n, _, tag in reversed(p.rows):
                    label[n] = digest.key("L", [tag, digest.key("B", [label[c] for c in kids.get(n, [])])])
                out.append((page, digest.key("B", [label[n] for n in kids.get(None, [])])))
            yield pd.DataFrame(out, columns=["page_id", "outline_key"])

    return _read(spark, sf_dir, "pages").select("page_id", "html").mapInPandas(outlines, "page_id long, outline_key string").groupBy("outline_key").agg(F.count("*").alias("n_pages"))


# -- conjunctive forms

_PREDICATES = (
    "(l_quantity > 25 AND l_discount < 0.05) OR l_returnflag = 'R'",
    "NOT (l_quantity > 25 AND (l_tax > 0.04 OR l_returnflag = 'A'))",
    "(l_quantity > 10 AND l_tax < 0.02) OR (l_discount > 0.08 AND l_linestatus = 'O') OR l_linenumber = 7",
    "l_returnflag IN ('A', 'N') AND NOT (l_quantity BETWEEN 5 AND 10 OR l_tax > 0.06)",
)


def _sql(t: grammar.Tree) -> str:
    if not t.kids:
        return t.atom
    k = [_sql(x) for x in t.kids]
    if t.atom.removeprefix("NOT_") == "IN":
        return f"{k[0]} {t.atom.replace('_', ' ')} ({', '.join(k[1:])})"
    if t.atom.removeprefix("NOT_") == "BETWEEN":
        return f"{k[0]} {t.atom.replace('_', ' ')} {k[1]} AND {k[2]}"
    return f"{k[0]} {t.atom} {k[1]}"


@oracle(" UNION ALL ".join(f"SELECT {k} AS predicate_id, count(*) AS n_rows, cast(sum(l_orderkey) AS bigint) AS sum_key FROM lineitem WHERE {p}" for k, p in enumerate(_PREDICATES)))
def w_cnf_filter(spark, sf_dir):
    """Rows that the rewritten predicates keep."""
    li, out = _read(spark, sf_dir, "lineitem"), None
    for k, p in enumerate(_PREDICATES):
        t = grammar.parse(f"SELECT l_orderkey FROM lineitem WHERE {p}").kids[2].kids[0]
        by_text = {cnf.text(x): _sql(x) for x in cnf.literals(t)}
        got = li.where(cnf.to_sql(cnf.to_cnf(t, absorb=True), by_text.__getitem__)).agg(F.lit(k).alias("predicate_id"), F.count("*").alias("n_rows"), F.sum("l_orderkey").alias("sum_key"))
        out = got if out is None else out.unionByName(got)
    return out


def w_cnf_examples(spark, sf_dir):
    """The log's conditions by their kind, OR-ed somewhere or AND-ed only: clauses of each, with the structures that have them."""
    bag = table(sk.skeleton_bag(logsynth.query_log(spark, sf_dir).where("klass = 'SELECT'")), "fingerprints")

    def run(frames):
        for f in frames:
            rows = []
            for sql in f["sample_sql"]:
                where = [k.kids[0] for k in grammar.skeleton(grammar.parse(sql)).kids if k.atom == "WHERE"]
                for clause in (c for t in where for c in cnf.to_cnf(t)):
                    kind = "or" if "OR(" in cnf.text(where[0]) else "and"
                    rows.append((kind, " OR ".join(sorted(x if good else f"NOT({x})" for x, good in clause))))
            yield pd.DataFrame(rows, columns=["formula", "clause"])

    return bag.select("sample_sql").mapInPandas(run, "formula string, clause string").groupBy("formula", "clause").agg(F.count("*").alias("n_structures"))


# -- bags, distances, vectors


def order_bags(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(order, brand) with the number of lines."""
    li, p = _read(spark, sf_dir, "lineitem"), _read(spark, sf_dir, "part")
    return li.join(p, F.col("l_partkey") == F.col("p_partkey")).groupBy(F.col("l_orderkey").alias("tree_id"), F.col("p_brand").alias("feature_key")).agg(F.count("*").alias("mult"))


_BAGS = "b AS (SELECT l_orderkey AS t, p_brand AS f, count(*) AS m FROM lineitem JOIN part ON l_partkey = p_partkey GROUP BY 1, 2)"


@oracle(
    f"""WITH {_BAGS}, k AS (SELECT t, string_agg(concat(f, ':', m), ',' ORDER BY f) AS s FROM b GROUP BY t), g AS (SELECT DISTINCT f AS g FROM b),
 x AS (SELECT t, g, f, m + CASE WHEN f = g THEN 1 ELSE 0 END AS m FROM b, g UNION ALL SELECT t, g, g, 1 FROM k, g WHERE (t, g) NOT IN (SELECT (t, f) FROM b)),
 u AS (SELECT t, string_agg(concat(f, ':', m), ',' ORDER BY f) AS s FROM x GROUP BY t, g)
 SELECT a.t AS i, c.t AS j, cast(0 AS bigint) AS d2, 0.0::double AS d FROM k a JOIN k c ON a.s = c.s AND a.t < c.t
 UNION ALL SELECT least(u.t, k.t), greatest(u.t, k.t), 1, 1.0 FROM u JOIN k ON u.s = k.s"""
)
def w_order_bag_distance(spark, sf_dir):
    """All pairs of orders whose bags differ in one line at most. The SQL finds them by adding a line to each bag."""
    return distance.within(table(order_bags(spark, sf_dir).withColumnRenamed("feature_key", "feature_id"), "bags"), 1.0)


def _few(items: DataFrame) -> DataFrame:
    """The whole table; what needs all pairs takes at most distance.MOST items."""
    n = items.count()
    if n > distance.MOST:
        raise ValueError(f"{n} items: all pairs are for at most {distance.MOST}")
    return items


def _vectors(embeddings: DataFrame) -> DataFrame:
    return embeddings.select(F.col("vec_id").alias("id"), F.col("embedding").cast("array<double>").alias("v"))


@oracle("SELECT a.vec_id AS i, b.vec_id AS j, round(list_distance(cast(a.embedding AS double[]), cast(b.embedding AS double[])), 6) AS d FROM embeddings a JOIN embeddings b ON a.vec_id < b.vec_id")
def w_embedding_distance(spark, sf_dir):
    """All pairs of the whole table, whatever its size: the result grows with its square."""
    return distance.vector_pairs(_vectors(_read(spark, sf_dir, "embeddings")), digits=6)


TAU = 1.1


@oracle(f"WITH RECURSIVE e AS (SELECT a.vec_id AS i, b.vec_id AS j FROM embeddings a JOIN embeddings b ON a.vec_id <> b.vec_id AND list_distance(cast(a.embedding AS double[]), cast(b.embedding AS double[])) <= {TAU}), r(v, c) AS (SELECT i, i FROM e UNION SELECT e.j, r.c FROM r JOIN e ON e.i = r.v) SELECT v AS vec_id, min(c) AS component FROM r GROUP BY v")
def w_single_components(spark, sf_dir):
    """Single linkage cut at a height is the components of the pairs within it."""
    near = distance.vector_pairs(_vectors(_read(spark, sf_dir, "embeddings")), TAU)
    return components(near.select(F.col("i").alias("a"), F.col("j").alias("b"))).select(F.col("node").alias("vec_id"), "component")


def w_embedding_linkage(spark, sf_dir):
    """Linkages against the vectors' own labels, in one task on an executor, which holds 8 bytes for each pair."""
    e = _few(_read(spark, sf_dir, "embeddings")).select("vec_id", F.col("embedding").cast("array<double>").alias("v"), "label")

    def run(rows: pd.DataFrame) -> pd.DataFrame:
        rows = rows.sort_values("vec_id")
        x, label = np.stack(rows["v"].to_list()), rows["label"].tolist()
        truth, out = dict(enumerate(label)), []
        for link in ("complete", "single", "average"):
            merges = linkage.agglomerate_triangle(linkage.Triangle.of(x), link)
            m = pd.DataFrame([(k, *r) for k, r in enumerate(merges)], columns=["step", "left", "right", "height", "size"])
            got = linkage.cut(m, range(len(x)), k=10)
            out.append((link, 10, round(compare.purity(got, truth), 6), round(compare.adjusted_rand(got, truth), 6), round(linkage.cophenetic_correlation(x, merges), 6)))
        return pd.DataFrame(out, columns=["linkage", "k", "purity", "rand", "cophenetic"])

    return e.groupBy(F.lit(0).alias("_all")).applyInPandas(run, "linkage string, k int, purity double, rand double, cophenetic double")


# -- prefix trees


def _order_sets(spark: SparkSession, sf_dir: str) -> DataFrame:
    o = _read(spark, sf_dir, "orders").select(F.col("o_orderkey").alias("item"), F.col("o_orderpriority").alias("cluster_id"))
    return fptree.itemsets(order_bags(spark, sf_dir), o)


_SETS = f"{_BAGS}, s AS (SELECT o_orderpriority AS cluster, t AS set_id, concat(f, ':', m) AS item FROM b JOIN orders ON o_orderkey = t), z AS (SELECT set_id, count(*) AS n FROM s GROUP BY set_id), k AS (SELECT cluster, item, count(*) AS frequency, cast(sum(n - 1) AS bigint) AS total_popularity FROM s JOIN z USING (set_id) GROUP BY 1, 2)"


@oracle(f"WITH {_SETS} SELECT * FROM k")
def w_popularity(spark, sf_dir):
    return fptree.item_ranks(_order_sets(spark, sf_dir))


_PREFIX = "q AS (SELECT s.cluster, s.set_id, list(s.item ORDER BY k.{by} DESC, s.item) AS a FROM s JOIN k ON s.cluster = k.cluster AND s.item = k.item GROUP BY 1, 2), d AS (SELECT cluster, a, unnest(range(1, len(a) + 1)) AS depth FROM q)"


@oracle(f"WITH {_SETS}, {_PREFIX.format(by='total_popularity')} SELECT cluster, cast(depth AS int) AS depth, md5(array_to_string(a[1:depth], '|')) AS node_key, CASE WHEN depth > 1 THEN md5(array_to_string(a[1:depth - 1], '|')) ELSE '' END AS parent_key, a[depth] AS item, count(*) AS count FROM d GROUP BY 1, 2, 3, 4, 5")
def w_fp_nodes(spark, sf_dir):
    return fptree.fp_tree(fptree.order_items(_order_sets(spark, sf_dir)))


_STEPS = (1, 2, 4, 8, 16)  # sixteenths of all sets
_CURVE = " UNION ALL ".join(
    f"SELECT '{name}' AS order_by, * FROM (WITH {_BAGS}, w AS (SELECT t FROM (SELECT t, row_number() OVER (ORDER BY t) AS r, count(*) OVER () AS c FROM (SELECT DISTINCT t FROM b) y) v WHERE r <= greatest(1, c * {n} // 16)), s AS (SELECT 0 AS cluster, t AS set_id, concat(f, ':', m) AS item FROM b JOIN w USING (t)), z AS (SELECT set_id, count(*) AS n FROM s GROUP BY set_id), k AS (SELECT cluster, item, count(*) AS frequency, sum(n - 1) AS total_popularity FROM s JOIN z USING (set_id) GROUP BY 1, 2), {_PREFIX.format(by=by)}, i AS (SELECT count(*) AS items FROM s), c AS (SELECT count(DISTINCT array_to_string(a[1:depth], '|')) AS nodes FROM d) SELECT (SELECT cast(count(*) AS int) FROM w) AS n_sets, items, nodes, round(nodes / items, 6) AS size_ratio, round(items / nodes, 6) AS compression_rate FROM i, c)"
    for n in _STEPS
    for name, by in (("frequency", "frequency"), ("popularity", "total_popularity"))
)


@oracle(_CURVE)
def w_compression_curve(spark, sf_dir):
    sets = table(fptree.itemsets(order_bags(spark, sf_dir)), "order-sets")
    n = sets.select("set_id").distinct().count()
    return fptree.compression_curve(sets, sorted({max(1, n * k // 16) for k in _STEPS}))


@oracle(f"WITH {_BAGS}, c AS (SELECT o_orderpriority AS cluster, count(*) AS size FROM orders GROUP BY 1) SELECT o_orderpriority AS cluster, f AS feature_key, count(*) AS n, round(count(*) / max(size), 6) AS share FROM b JOIN orders ON o_orderkey = t JOIN c ON c.cluster = o_orderpriority GROUP BY 1, 2 HAVING count(*) >= 0.15 * max(size) - 1e-9")
def w_characteristic(spark, sf_dir):
    assign = _read(spark, sf_dir, "orders").select(F.col("o_orderkey").alias("item"), F.col("o_orderpriority").alias("cluster_id"))
    return summary.characteristic(order_bags(spark, sf_dir), assign, 0.15)


@oracle("WITH k AS (SELECT l_linestatus AS part, concat(l_returnflag, '(', l_linestatus, ')') AS container, count(*) AS mult FROM lineitem GROUP BY 1, 2), i AS (SELECT part AS feature, sum(mult)::bigint AS mult FROM k GROUP BY 1 UNION ALL SELECT container, mult FROM k), s AS (SELECT part, sum(mult) AS implied FROM k GROUP BY part) SELECT feature, mult, implied IS NULL OR mult >= implied AS kept_strict, implied IS NULL OR mult > implied AS kept_nonstrict FROM i LEFT JOIN s ON part = feature")
def w_shrink_example(spark, sf_dir):
    """Line states, and return flags over line states: all that a state is, its containers tell."""
    li = _read(spark, sf_dir, "lineitem").where("l_linestatus is not null and l_returnflag is not null")
    pairs = li.groupBy(F.col("l_linestatus").alias("part"), F.concat("l_returnflag", F.lit("("), "l_linestatus", F.lit(")")).alias("container")).agg(F.count("*").alias("mult"))
    items = pairs.groupBy(F.col("part").alias("feature")).agg(F.sum("mult").alias("mult")).unionByName(pairs.select(F.col("container").alias("feature"), "mult"))
    return summary.shrink_df(items, pairs.select("part", "container", F.lit(1).alias("times")))


@oracle("WITH p AS (SELECT row_number() OVER (ORDER BY embedding[1], vec_id) - 1 AS x, row_number() OVER (ORDER BY label, vec_id) - 1 AS y FROM embeddings), n AS (SELECT count(*) AS n FROM p) SELECT 2.0::double AS L, round((SELECT sum((x - y) * (x - y)) FROM p) / (SELECT sum((2 * x - n + 1) * (2 * x - n + 1)) FROM p, n), 6) AS entanglement, (SELECT count(*) FROM p a JOIN p b ON a.x < b.x AND a.y > b.y) AS crossings")
def w_entanglement_orders(spark, sf_dir):
    e = _read(spark, sf_dir, "embeddings")
    at = lambda *c: F.row_number().over(Window.orderBy(*c)) - 1
    return compare.entanglement_df(e.select(at(F.col("embedding")[0], "vec_id").alias("pos1"), at("label", "vec_id").alias("pos2")))


@oracle("WITH w AS (SELECT source, doc_id, unnest(string_split(lower(text), ' ')) AS token FROM documents) SELECT source, token, count(*) AS n, count(DISTINCT doc_id) AS df FROM w WHERE token <> '' GROUP BY source, token HAVING count(*) >= 20")
def w_doc_bags(spark, sf_dir):
    words = _read(spark, sf_dir, "documents").select("source", "doc_id", F.explode(F.split(F.lower("text"), " ", -1)).alias("token")).where("token <> ''")
    per = words.groupBy("source", "token", "doc_id").agg(F.count("*").alias("c"))
    return per.groupBy("source", "token").agg(F.sum("c").alias("n"), F.count("*").alias("df")).where("n >= 20")


# -- clusters of the log


def _sample(spark, sf_dir: str, n: int = 140) -> list[tuple]:
    """140 structures from families that share tables (a sample biased to be hard): (text, family, bits), from the events as they are now."""
    log = logsynth.query_log(spark, sf_dir).where((sk.statement_class(F.col("sql")) == "SELECT") & F.expr("klass = 'SELECT' and fam < 15"))
    rows = log.groupBy("fam", "v").agg(F.min("sql").alias("sql"))
    rows = rows.orderBy(F.md5(F.concat_ws("-", "fam", "v")), "fam", "v").limit(n).collect()
    return [(r["sql"], int(r["fam"]), int(r["v"])) for r in rows]


def _bags(texts, suite=rules.DEFAULT, drop_root: bool = True) -> list[dict[str, int]]:
    out = []
    for sql in texts:
        bag: dict[str, int] = {}
        for _, key, rule, level, canonical in rules.features(grammar.parse(sql), suite):
            if not (drop_root and rule == "level" and level == 1 and canonical.startswith("SELECT(")):
                bag[key] = bag.get(key, 0) + 1
        out.append(bag)
    return out


def _dense(bags, metric: str = "l2") -> np.ndarray:
    names = {k: i for i, k in enumerate(sorted({k for b in bags for k in b}))}
    return distance.matrix([[(names[k], n) for k, n in b.items()] for b in bags], metric)


def _merges(d: np.ndarray, link: str) -> pd.DataFrame:
    return pd.DataFrame([(k, *r) for k, r in enumerate(linkage.agglomerate(np.sqrt(d) if link == "average" else d, link))], columns=["step", "left", "right", "height", "size"])


def _compared(merges: pd.DataFrame, truth: dict[int, int]) -> tuple[list, list]:
    return compare.tanglegram(linkage.tree_of(merges, range(len(truth))), truth)


def _feasible(spark, sf_dir, suite=rules.DEFAULT, link="complete", metric="l2", rows=None):
    rows = rows or _sample(spark, sf_dir)
    truth = {k: f for k, (_, f, _) in enumerate(rows)}
    bags = _bags([t for t, _, _ in rows], suite)
    merges = _merges(_dense(bags, metric), link)
    left, right = _compared(merges, truth)
    got = linkage.cut(merges, truth, k=len(set(truth.values())))
    return rows, truth, merges, left, right, got, bags


def w_feasibility(spark, sf_dir):
    """Clusters of the sample against its families, beside a random order as control."""
    out, rows = [], _sample(spark, sf_dir)
    for link in ("complete", "single", "average"):
        _, truth, _, left, right, got, _ = _feasible(spark, sf_dir, link=link, rows=rows)
        out.append((link, 2.0, round(compare.entanglement(left, right), 6), compare.crossings(left, right), round(compare.purity(got, truth), 6), round(compare.adjusted_rand(got, truth), 6)))
    shuffled = np.random.default_rng(1).permutation(len(truth)).tolist()
    out.append(("random control", 2.0, round(compare.entanglement(shuffled, right), 6), compare.crossings(shuffled, right), 0.0, 0.0))
    return spark.createDataFrame(out, "linkage string, L double, entanglement double, crossings long, purity double, rand double")


def w_misaligned(spark, sf_dir):
    _, _, _, left, right, _, _ = _feasible(spark, sf_dir)
    return spark.createDataFrame(compare.misaligned(left, right), "skel_id long, pos_auto long, pos_truth long, gap long")


def _ablation(spark, sf_dir, variants) -> DataFrame:
    sample = _sample(spark, sf_dir)
    cuts = {name: _feasible(spark, sf_dir, rows=sample, **kw)[5] for name, kw in variants.items()}
    names = list(variants)
    rows = [(a, b, round(compare.adjusted_rand(cuts[a], cuts[b]), 6)) for i, a in enumerate(names) for b in names[i + 1 :]]
    return spark.createDataFrame(rows, "variant_a string, variant_b string, rand double")


def w_linkage_ablation(spark, sf_dir):
    return _ablation(spark, sf_dir, {x: {"link": x} for x in ("complete", "single", "average")})


def w_metric_ablation(spark, sf_dir):
    return _ablation(spark, sf_dir, {x: {"metric": x} for x in ("l2", "l1")})


SUITES = {
    "base, constants kept": rules.Suite(skeleton_ops=(), cnf=False, flatten=False, constants="keep"),
    "base": rules.BASE,
    "base, set labels": rules.Suite(skeleton_ops=(), cnf=False, flatten=False, collection="set"),
    "base, strict leaves": rules.Suite(skeleton_ops=(), cnf=False, flatten=False, leaf="strict"),
    "skeletons": rules.Suite(cnf=False, flatten=False),
    "conjunctive form": rules.Suite(skeleton_ops=(), flatten=False),
    "all rules": rules.DEFAULT,
    "all rules, sealed": rules.Suite(full_subtree=True),
    "parent and child": rules.Suite(levels=False, parent_child=True, cnf=False, skeleton_ops=()),
    "clauses only": rules.Suite(levels=False, clause_atoms=True, cnf=False, skeleton_ops=()),
}


def w_feature_ablation(spark, sf_dir):
    out, rows = [], _sample(spark, sf_dir)
    for name, suite in SUITES.items():
        _, truth, _, left, right, got, bags = _feasible(spark, sf_dir, suite=suite, rows=rows)
        out.append((name, len({k for b in bags for k in b}), round(compare.entanglement(left, right), 6), round(compare.adjusted_rand(got, truth), 6)))
    return spark.createDataFrame(out, "suite string, n_features long, entanglement double, rand double")


def w_lookup_triplet(spark, sf_dir):
    """For each nation three look-ups of its customers: two differ in the constant, its first and its last, one in the column."""
    keys = _read(spark, sf_dir, "customer").groupBy("c_nationkey").agg(F.min("c_custkey").alias("first"), F.max("c_custkey").alias("last"))
    base, plain = SUITES["base, constants kept"], rules.DEFAULT

    def run(frames):
        d2 = lambda x, y: sum((x.get(k, 0) - y.get(k, 0)) ** 2 for k in x.keys() | y.keys())
        for f in frames:
            rows = []
            for nation, first, last in f.itertuples(index=False):
                texts = {"a": f"SELECT * FROM customer WHERE c_custkey = {first}", "b": f"SELECT * FROM customer WHERE c_custkey = {last}", "c": f"SELECT * FROM customer WHERE c_nationkey = {first}"}
                kept, free = (dict(zip(texts, _bags(texts.values(), s), strict=True)) for s in (base, plain))
                rows += [(nation, p + q, d2(kept[p], kept[q]), d2(free[p], free[q])) for p, q in ("ab", "ac", "bc")]
            yield pd.DataFrame(rows, columns=["c_nationkey", "pair", "d2_base", "d2_abstract"])

    return keys.where("c_nationkey is not null and first is not null").mapInPandas(run, "c_nationkey int, pair string, d2_base long, d2_abstract long")


def w_near_pair(spark, sf_dir):
    """Two statements of one family that differ in an extra conjunct and a negated membership, against all pairs of the sample."""
    base = "SELECT o_orderkey, o_custkey FROM orders WHERE o_orderdate >= 5 AND o_orderstatus {} (1, 2){} ORDER BY o_orderdate"
    a, b = _bags([base.format("IN", ""), base.format("NOT IN", " AND o_totalprice > 7")])
    near = sum((a.get(k, 0) - b.get(k, 0)) ** 2 for k in a.keys() | b.keys())
    d = _dense(_bags([t for t, _, _ in _sample(spark, sf_dir)]))
    every = d[np.triu_indices(len(d), 1)]
    return spark.createDataFrame([(int(near), float(np.median(every)), float((every < near).mean()))], "d2 long, median_d2 double, share_nearer double")


def w_seal_cost(spark, sf_dir):
    """Features, prefix-tree nodes and entanglement with and without the generic seal."""
    out, sample = [], _sample(spark, sf_dir)
    for name, suite in (("none", rules.DEFAULT), ("generic", rules.Suite(full_subtree=True))):
        _, _, _, left, right, _, bags = _feasible(spark, sf_dir, suite=suite, rows=sample)
        rows = spark.createDataFrame([(k, f, n) for k, b in enumerate(bags) for f, n in b.items()], "tree_id long, feature_key string, mult int")
        nodes = fptree.fp_tree(fptree.order_items(fptree.itemsets(rows))).count()
        out.append((name, len({k for b in bags for k in b}), nodes, round(compare.entanglement(left, right), 6)))
    return spark.createDataFrame(out, "seal string, n_features long, fp_nodes long, entanglement double")


def w_common_feature_tree(spark, sf_dir):
    """One family's example tree: which nodes lie in features that every structure of the family has, over the whole log.

    The family is number 2, or the first of those in the log; the example is its first structure by text."""
    log = logsynth.query_log(spark, sf_dir).where((sk.statement_class(F.col("sql")) == "SELECT") & F.expr("klass = 'SELECT'"))
    family = log.agg(F.coalesce(F.min(F.when(F.col("fam") == 2, F.col("fam"))), F.min("fam"))).first()[0]
    bag = table(sk.skeleton_bag(log.where(F.col("fam") == family)).withColumn("tree_id", F.monotonically_increasing_id()), "fingerprints")
    own = table(rules.generate_features(bag, text="sample_sql"), "own")
    n = own.select("tree_id").distinct().count()
    per = own.groupBy("feature_key", "tree_id").agg(F.count("*").alias("mult"))
    every = per.groupBy("feature_key").agg(F.count("*").alias("n"), F.sum("mult").alias("total")).where(F.col("n") == n)
    total = {r["feature_key"]: r["total"] for r in every.collect()}  # no more than one structure has
    out = []
    for first in bag.join(own.select("tree_id").distinct(), "tree_id", "left_semi").orderBy("skel_text").select("sample_sql").take(1):
        tree = grammar.parse(first["sample_sql"])
        found = rules.features(tree)
        here: dict[str, int] = {}
        for _, key, *_ in found:
            here[key] = here.get(key, 0) + 1
        best: dict[int, tuple[int, int, int]] = {}
        for k, key, _, level, _ in found:
            if key in total:
                best[k] = max(best.get(k, (-1, 0, 0)), (level, total[key], here[key]))
        out = [(k, p, a, c, best.get(k, (0, 0, 0))[1], best.get(k, (0, 0, 0))[2]) for k, p, a, c in summary.common_nodes(tree, set(total))]
    return spark.createDataFrame(out, "node_id long, parent_id long, atom string, common boolean, total_occ long, query_occ long")


def w_audit_round(spark, sf_dir):
    """Three rounds: pure clusters of read-mostly families are safe, one family is unsafe, the rest is cut finer."""
    _, truth, merges, _, _, got, _ = _feasible(spark, sf_dir)
    height, out = float(merges["height"].max()), []
    for r in range(3):
        kinds: dict[int, set[int]] = {}
        for i, c in got.items():
            kinds.setdefault(c, set()).add(truth[i])
        labels = {c: ("unsafe" if f == {4} else "safe") if len(f) == 1 else "unknown" for c, f in kinds.items()}
        for label in ("safe", "unsafe", "unknown"):
            members = [i for i, c in got.items() if labels[c] == label]
            out.append((r, label, len({got[i] for i in members}), len(members)))
        height /= 2
        got = audit.audit_round(merges, got, labels, height)
        if not got:
            break
    return spark.createDataFrame(out, "round int, label string, n_clusters long, n_stmt long")


def w_kmeans_contrast(spark, sf_dir):
    """The flat alternative and k-centres on the same bags."""
    rows, truth, _, _, _, tree, bags = _feasible(spark, sf_dir)
    names = {k: i for i, k in enumerate(sorted({k for b in bags for k in b}))}
    bag = spark.createDataFrame([(k, names[f], n) for k, b in enumerate(bags) for f, n in b.items()], "tree_id long, feature_id long, mult int")
    k = len(set(truth.values()))
    assign, cost = linkage.kmeans(bag, k)
    flat = {r["item"]: r["cluster_id"] for r in assign.collect()}
    d = np.sqrt(_dense(bags))
    centres = linkage.kcenters(d, k)
    near = {i: centres[int(np.argmin(d[i, centres]))] for i in range(len(d))}
    out = [(n, round(compare.purity(c, truth), 6), round(compare.adjusted_rand(c, truth), 6)) for n, c in (("complete linkage", tree), ("k-means", flat), ("k-centres", near))]
    return spark.createDataFrame(out, "method string, purity double, rand double")


def w_role_classifier(spark, sf_dir):
    """Clause-level features and naive Bayes on the user's role: rates of error on held-out statements."""
    from pyspark.ml.classification import NaiveBayes
    from pyspark.ml.feature import HashingTF

    log = _selects(spark, sf_dir).where("klass = 'SELECT'").withColumn("role", (F.col("user_id") % 5).cast("double"))
    words = log.withColumn("tokens", F.regexp_extract_all(sk.fingerprint(F.col("sql")), F.lit("([A-Za-z_]+)"), 1))
    x = HashingTF(inputCol="tokens", outputCol="features", numFeatures=1024).transform(words)
    model = NaiveBayes(labelCol="role").fit(x.where("stmt_id % 2 = 0"))
    got = model.transform(x.where("stmt_id % 2 = 1"))
    return compare.confusion(got.select((F.col("role") == 0).alias("truth"), (F.col("prediction") == 0).alias("guess")))


def w_compression_log(spark, sf_dir):
    """The compression curve over the sample's own feature bags, for both item orders."""
    bags = _bags([t for t, _, _ in _sample(spark, sf_dir)])
    rows = spark.createDataFrame([(k, f, n) for k, b in enumerate(bags) for f, n in b.items()], "tree_id long, feature_key string, mult int")
    return fptree.compression_curve(fptree.itemsets(rows), [14 * k for k in range(1, 11)])


# -- run times


def _timed(f) -> tuple[float, object]:
    t = time.perf_counter()
    out = f()
    return time.perf_counter() - t, out


def phases(spark, sf_dir, cut_day: int, trials: int = 1, which: tuple[int, ...] = (1, 2, 3, 4)) -> list[tuple]:
    """Seconds of the phases over a truncated log: pre-processing, relabelling, clustering, prefix tree.

    Each trial runs the phases in `which`; the others run once, for what the phases after them read, and have no time."""
    log = _selects(spark, sf_dir).where(F.col("ts") < F.expr(f"timestamp '2024-01-01 00:00:00' + interval {cut_day} days"))
    done: dict[int, object] = {}
    steps = {
        1: lambda: audit.skeletons(log),
        2: lambda: audit.vectorise(log, found=done[1]),
        3: lambda: audit.cluster(done[2], k=min(25, n_skel))[1],
        4: lambda: fptree.fp_tree(fptree.order_items(fptree.itemsets(done[2].bag, assign))).write.format("noop").mode("overwrite").save(),
    }
    out = []
    for trial in range(trials):
        seconds: list[float | None] = [None] * 4
        for p in range(1, max(which) + 1):
            if p not in which and trial:
                continue
            s, done[p] = _timed(steps[p])
            seconds[p - 1] = s if p in which else None
            if p == 1 and not trial:
                n_skel, n_stmt = done[1].agg(F.count("*"), F.sum("n_stmt")).first()
            if p == 3 and (not trial or 4 in which):
                assign = audit.assign_df(done[2].bag, done[3])
        out.append((cut_day, n_stmt, n_skel, *seconds))
    return out


def _bench(spark, sf_dir, which: tuple[int, int], trials: int, cuts) -> DataFrame:
    rows = []
    for c in cuts:
        runs = phases(spark, sf_dir, c, trials, which)
        for p in which:
            s = [r[2 + p] for r in runs]
            rows.append((c, runs[0][1], runs[0][2], p, float(np.mean(s)), float(np.std(s)), trials))
    return spark.createDataFrame(rows, "cut_day int, n_stmt long, n_skel long, phase int, mean_s double, sd_s double, trials int")


def bench_phase_1_3(spark, sf_dir, trials: int = 10, cuts=CUTS):
    """All eight cuts, ten trials each; fewer by arguments."""
    return _bench(spark, sf_dir, (1, 3), trials, cuts)


def bench_phase_2_4(spark, sf_dir, trials: int = 10, cuts=CUTS):
    return _bench(spark, sf_dir, (2, 4), trials, cuts)


def bench_explorer(spark, sf_dir):
    tree = fptree.fp_tree(fptree.order_items(fptree.itemsets(order_bags(spark, sf_dir))))
    return spark.createDataFrame([(k, ms) for k, ms in enumerate(fptree.Explorer(tree).bench())], "click int, ms double")


def flagship(spark, sf_dir, k: int = 25) -> DataFrame:
    """Log to summaries: cluster_id, n_skel, n_stmt, line: each cluster's text."""
    v = audit.vectorise(_log(spark, sf_dir).where("klass = 'SELECT'"))
    _, got = audit.cluster(v, k=k)
    assign = audit.assign_df(v.bag, got)
    size = v.skeletons.join(assign, F.col("skel_id") == F.col("item")).groupBy("cluster_id").agg(F.count("*").alias("n_skel"), F.sum("n_stmt").alias("n_stmt"))
    named = v.features.rows.select("feature_key", "canonical")
    common = summary.characteristic(v.bag, assign).join(named, "feature_key").join(v.bag.groupBy("feature_key").agg(F.min("mult").alias("mult")), "feature_key")
    common = common.groupBy("cluster", "canonical").agg(F.max("mult").alias("mult"))
    items = common.groupBy("cluster").agg(F.map_from_entries(F.collect_list(F.struct("canonical", "mult"))).alias("items")).join(size, F.col("cluster") == F.col("cluster_id"))

    def lines(frames):
        for f in frames:
            rows = [(int(r.cluster_id), int(r.n_skel), int(r.n_stmt), k, line) for r in f.itertuples() for k, line in enumerate(summary.text_summary(dict(r.shared), int(r.n_skel), 8))]
            yield pd.DataFrame(rows, columns=["cluster_id", "n_skel", "n_stmt", "line_no", "line"])

    return items.select("cluster_id", "n_skel", "n_stmt", F.col("items").alias("shared")).mapInPandas(lines, "cluster_id long, n_skel long, n_stmt long, line_no int, line string")


def w_log_summary(spark, sf_dir):
    return flagship(spark, sf_dir)


def queries() -> dict:
    return {k: f for k, f in globals().items() if k.startswith(("w_", "bench_")) and callable(f)}
