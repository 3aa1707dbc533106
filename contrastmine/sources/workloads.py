"""Workloads: a source, a label and named predicates, each written once as SQL that Spark and DuckDB both read.

`@rx(text, @re'pattern')` stands for the dialect's regular-expression test, `@el(array, k)` for an element, `@day(ts)` for a
day, `@weekday(day)` for 0 (Sunday) to 6, `@seconds(ts)` for seconds since 1970, `@json(column, key)` for a JSON field as
text, and `@words(text)` for the runs of lower-case letters of a text."""

from __future__ import annotations

import re
from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators.labeled import LabeledDB, compress
from ..operators.relational import contains_passage


LISTED = re.compile(r"(?:[^][(){}.*+?^$|\\']|\[[^][^\\']\])+")  # characters that stand for themselves, in classes of one or not


@dataclass(frozen=True)
class Workload:
    name: str
    tables: tuple[str, ...]
    source: str  # a FROM clause or a subquery over the tables
    label: str
    items: tuple[tuple[str, str], ...]
    made: str | None = None  # a table that Spark makes by an operator: its source there is "made", and `source` says the same in plain SQL


def dialect(sql: str, spark: bool) -> str:
    sql = re.sub(r"@el\(", "element_at(" if spark else "list_extract(", sql)
    sql = re.sub(r"@rx\(", "rlike(" if spark else "regexp_matches(", sql)
    sql = re.sub(r"@day\(([^)]*)\)", r"cast(\1 as date)", sql)
    sql = re.sub(r"@weekday\(([^)]*)\)", r"(dayofweek(\1) - 1)" if spark else r"dayofweek(\1)", sql)
    sql = re.sub(r"@seconds\(", "unix_timestamp(" if spark else "epoch(", sql)
    sql = re.sub(r"@json\((\w+), (\w+)\)", r"get_json_object(\1, '$.\2')" if spark else r"json_extract_string(\1, '$.\2')", sql)
    sql = re.sub(r"@words\(([^)]*)\)", r"array_distinct(regexp_extract_all(lower(\1), '[a-z]+', 0))" if spark else r"list_distinct(regexp_extract_all(lower(\1), '[a-z]+'))", sql)
    if spark:
        return re.sub(r"@re'([^']*)'", lambda m: "'" + m[1].replace("\\", "\\\\") + "'", sql)
    return re.sub(r"@re'([^']*)'", r"'\1'", sql)


def bands(name: str, column: str, cuts: list) -> list[tuple[str, str]]:
    """[c0, c1), [c1, c2), ... with open ends."""
    out = [(f"{name}<{cuts[0]}", f"{column} < {cuts[0]}")]
    out += [(f"{name}:{a}-{b}", f"{column} >= {a} and {column} < {b}") for a, b in zip(cuts[:-1], cuts[1:], strict=True)]
    return [*out, (f"{name}>={cuts[-1]}", f"{column} >= {cuts[-1]}")]


def values(name: str, column: str, options) -> list[tuple[str, str]]:
    return [(f"{name}={v}", f"{column} = '{v}'" if isinstance(v, str) else f"{column} = {v}") for v in options]


DOC_FLAGS = [
    ("junk", "@rx(text, @re'###|[$][$][$]|%%%')"), ("caps", "@rx(text, @re'[A-Z]{4,}')"), ("digits", "@rx(text, @re'[0-9]{3}')"), ("at", "text like '%@%'"),
    ("lang:en", "lang = 'en'"), ("len:4", "n_chars >= 1000"), ("len:3", "n_chars >= 100 and n_chars < 1000"),
    ("w:the", "@rx(lower(text), @re'(^|[^a-z])the([^a-z]|$)')"), ("w:and", "@rx(lower(text), @re'(^|[^a-z])and([^a-z]|$)')"), ("lines", "length(text) - length(replace(text, chr(10), '')) >= 3"),
]
# The 40 runs of letters in most labelled documents at scale 0.01.
FREQUENT = "the in en and of on to a is be it as that for er was re an are this with es ou by from tion ha at th st ed nd he ti or ing nt ea thon ble".split()
PART_WORDS = "anvil blue bolt cold gear gizmo hot large new old plate red ring rod small widget".split()  # fixed values: the words of part names
LONG_DOC_FLAGS = [
    ("junk", "@rx(text, @re'###|[$][$][$]|%%%')"), ("caps", "@rx(text, @re'[A-Z]{4,}')"), ("digits", "@rx(text, @re'[0-9]{3}')"), ("at", "text like '%@%'"),
    ("lang:en", "lang = 'en'"), ("lang:fr", "lang = 'fr'"), ("lang:de", "lang = 'de'"), ("len:4", "n_chars >= 1000"), ("len:3", "n_chars >= 100 and n_chars < 1000"), ("len:2", "n_chars < 100"),
    ("lines", "length(text) - length(replace(text, chr(10), '')) >= 3"), ("url", "@rx(text, @re'https?://')"),
]
DOC_MORE = [("lang:fr", "lang = 'fr'"), ("lang:de", "lang = 'de'"), ("lang:es", "lang = 'es'"), ("len:2", "n_chars < 100"), ("url", "@rx(text, @re'https?://')"), ("w:of", "@rx(lower(text), @re'(^|[^a-z])of([^a-z]|$)')"), ("w:that", "@rx(lower(text), @re'(^|[^a-z])that([^a-z]|$)')"), ("w:to", "@rx(lower(text), @re'(^|[^a-z])to([^a-z]|$)')"), ("bang", "text like '%!!%'"), ("bar", "text like '%|%'")]
LABELLED = "(select d.doc_id, d.text, d.lang, d.source, d.n_chars, l.quality, l.toxic from documents d join labels l on d.doc_id = l.doc_id) s"
WORDED = "(select d.doc_id, d.text, d.lang, d.source, d.n_chars, @words(d.text) words, l.quality, l.toxic from documents d join labels l on d.doc_id = l.doc_id) s"
ORDERS = "(select o.*, c.c_mktsegment, n.n_regionkey from orders o join customer c on o.o_custkey = c.c_custkey join nation n on c.c_nationkey = n.n_nationkey) s"
PLANT = "(l_quantity > 25 and not l_discount >= 0.045) or (l_tax >= 0.055 and l_linestatus = 'O' and not l_linenumber <= 3)"
EMBEDDED = "(select vec_id, embedding, label from embeddings) s"


def without_lists(sql: str) -> str:
    """Tests for a regular expression that only lists plain strings become tests for each string: one after another they cost less than an alternation tried at every place."""

    def plain(m: re.Match) -> str:
        listed = m[2].split("|")
        if not all(map(LISTED.fullmatch, listed)):
            return m[0]
        return "(" + " or ".join(f"contains({m[1]}, '{re.sub(r'\[(.)\]', r'\1', s)}')" for s in listed) + ")"

    return re.sub(r"@rx\((\w+), @re'([^']*)'\)", plain, sql)


def _all() -> list[Workload]:
    order_items = values("priority", "substring(o_orderpriority, 1, 1)", ["1", "2", "3", "4", "5"]) + values("year", "year(o_orderdate)", range(1995, 2002)) + values("quarter", "quarter(o_orderdate)", range(1, 5))
    order_items += values("segment", "c_mktsegment", ["AUTOMOBILE", "BUILDING", "FURNITURE", "HOUSEHOLD", "MACHINERY"]) + values("region", "n_regionkey", range(5)) + bands("total", "o_totalprice", [125000, 250000, 375000])
    line_items = values("status", "l_linestatus", ["F", "O"]) + bands("qty", "l_quantity", [11, 21, 31, 41]) + bands("disc", "l_discount", [0.035, 0.075]) + bands("tax", "l_tax", [0.025, 0.055]) + values("ship", "year(l_shipdate)", range(1995, 2002)) + values("line", "l_linenumber", range(1, 8))
    planted = [("q", "l_quantity > 25"), ("d", "l_discount >= 0.045"), ("t", "l_tax >= 0.055"), ("o", "l_linestatus = 'O'"), ("n", "l_linenumber <= 3"), ("y", "year(l_shipdate) >= 1999"), ("r", "l_returnflag = 'R'")]
    noise = "substring(md5(concat(cast(l_orderkey as varchar(20)), '-', cast(l_partkey as varchar(20)), '-', cast(l_linenumber as varchar(20)))), 1, 2) < '05'"
    noisy = f"(({PLANT}) and not {noise}) or (not ({PLANT}) and {noise})"
    days = "(select user_id, @day(ts) d, count(*) n, sum(case when event_type = 'purchase' then 1 else 0 end) bought, sum(case when event_type = 'click' then 1 else 0 end) clicks, sum(case when event_type = 'view' then 1 else 0 end) views, sum(case when event_type = 'signup' then 1 else 0 end) signups, sum(case when event_type = 'error' then 1 else 0 end) errors, max(value) top, max(cast(@json(props, k) as int)) k, max(@seconds(ts)) - min(@seconds(ts)) span from events group by user_id, @day(ts)) s"
    event_items = [("click", "clicks > 0"), ("view", "views > 0"), ("signup", "signups > 0"), ("error", "errors > 0")] + [(f"n={k}", f"n = {k}") for k in range(1, 6)] + [("n>=6", "n >= 6")] + bands("top", "top", [25, 50, 75])
    event_items += bands("k", "k", [50, 70, 90]) + values("weekday", "@weekday(d)", range(7)) + bands("span", "span", [1, 14400, 43200])
    page_items = [("nav", "html like '%<nav>%'"), ("ad", "html like '%class=\"ad\"%'"), ("table", "html like '%<table%'"), ("list", "html like '%<li>%'"), ("script", "html like '%<script%'"), ("https", "url like 'https:%'"), ("www", "url like '%://www.%'"), ("query", "url like '%?%'"), ("fragment", "url like '%#%'"), ("unclosed", "html like '%<p><b>%'"), ("long", "length(html) >= 4000"), ("net", "url like '%.net/%'"), ("com", "url like '%.com/%'")]
    conv_items = [("len<40", "length(text) < 40"), ("len:40-200", "length(text) >= 40 and length(text) < 200"), ("len:200-600", "length(text) >= 200 and length(text) < 600"), ("len>=600", "length(text) >= 600"), ("odd turn", "turn % 2 = 1"), ("first", "turn = 0"), ("line feed", f"length(text) > length(replace(text, chr(10), ''))"), ("question", "text like '%?%'"), ("comma", "text like '%,%'"), ("the", "lower(text) like '% the %'")]
    customers = "(select c.*, n.n_regionkey, coalesce(k.n, 0) n_orders, coalesce(k.spent, 0) spent from customer c join nation n on c.c_nationkey = n.n_nationkey left join (select o_custkey, count(*) n, sum(o_totalprice) spent from orders group by o_custkey) k on k.o_custkey = c.c_custkey) s"
    customer_items = values("segment", "c_mktsegment", ["AUTOMOBILE", "BUILDING", "FURNITURE", "HOUSEHOLD", "MACHINERY"]) + values("region", "n_regionkey", range(5)) + bands("orders", "n_orders", [5, 10, 15]) + bands("spend", "spent", [1200000, 2400000, 3600000]) + values("nation", "c_nationkey", range(25))
    part_items = [(f"brand={a}{b}", f"p_brand = 'Brand#{a}{b}'") for a in range(1, 6) for b in range(1, 6)] + bands("size", "p_size", [11, 21, 31, 41]) + [(f"w:{w}", f"concat(' ', p_name, ' ') like '% {w} %'") for w in PART_WORDS]
    suppliers = "(select s1.*, n.n_regionkey from supplier s1 join nation n on s1.s_nationkey = n.n_nationkey) s"
    supplier_items = values("region", "n_regionkey", range(5)) + values("nation", "s_nationkey", range(25))
    signs = tuple((f"d{k}", f"@el(embedding, {k + 1}) > 0") for k in range(64))
    held = "(select d.doc_id, d.text, d.lang, d.source, d.n_chars, case when b.doc_id is null then 0 else 1 end leaked from documents d left join (select distinct d2.doc_id from documents d2 join benchmark b2 on contains(d2.text, b2.text)) b on b.doc_id = d.doc_id) s"
    docs, conv = tuple(DOC_FLAGS + DOC_MORE), "conversations"
    whole = tuple(LONG_DOC_FLAGS + [(f"w:{w}", f"array_contains(words, '{w}')") for w in FREQUENT])
    one_label = [Workload(f"embeddings_{k}", ("embeddings",), EMBEDDED, f"case when label = {k} then 1 else 0 end", signs) for k in range(10)]
    return [
        Workload("orders", ("orders", "customer", "nation"), ORDERS, "case when o_orderstatus = 'F' then 1 else 0 end", tuple(order_items)),
        Workload("lineitem", ("lineitem",), "lineitem", "case when l_returnflag = 'R' then 1 else 0 end", tuple(line_items)),
        Workload("planted", ("lineitem",), "lineitem", f"case when {PLANT} then 1 else 0 end", tuple(planted)),
        Workload("planted_noisy", ("lineitem",), "lineitem", f"case when {noisy} then 1 else 0 end", tuple(planted)),
        Workload("docs", ("documents", "labels"), LABELLED, "1 - quality", docs),
        Workload("docs_words", ("documents", "labels"), WORDED, "1 - quality", whole),
        Workload("docs_flags", ("documents", "labels"), LABELLED, "1 - quality", tuple(DOC_FLAGS)),
        Workload("toxic", ("documents", "labels"), WORDED, "toxic", whole),
        Workload("contam", ("documents", "benchmark"), held, "leaked", docs, "leaked"),
        Workload("events", ("events",), days, "case when bought > 0 then 1 else 0 end", tuple(event_items)),
        Workload("pages", ("pages",), "pages", "case when html like '%lang=\"en\"%' then 1 else 0 end", tuple(page_items)),
        Workload("conversations", (conv,), f"(select * from {conv} where role <> 'system') s", "case when role = 'assistant' then 1 else 0 end", tuple(conv_items)),
        Workload("customers", ("customer", "nation", "orders"), customers, "case when c_acctbal < 0 then 1 else 0 end", tuple(customer_items)),
        Workload("parts", ("part",), "part", "case when p_type like '%PROMO%' then 1 else 0 end", tuple(part_items)),
        Workload("suppliers", ("supplier", "nation"), suppliers, "case when s_acctbal < 0 then 1 else 0 end", tuple(supplier_items)),
        Workload("embeddings", ("embeddings",), EMBEDDED, "case when label = 0 then 1 else 0 end", signs),
        Workload("embeddings_planted", ("embeddings",), EMBEDDED, "case when @el(embedding, 1) > 0 and not @el(embedding, 2) > 0 then 1 else 0 end", signs),
        *one_label,
    ]


WORKLOADS = {w.name: w for w in _all()}


def read(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def leaked_documents(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Documents with a mark for those that hold a benchmark passage: hash joins only."""
    docs = read(spark, sf_dir, "documents")
    hit = contains_passage(docs, read(spark, sf_dir, "benchmark")).select("doc_id").distinct().withColumn("leaked", F.lit(1))
    return docs.join(hit, "doc_id", "left").na.fill(0, ["leaked"])


MADE = {"leaked": leaked_documents}


def source_of(spark: SparkSession, sf_dir: str, w: Workload) -> DataFrame:
    return spark.sql("select * from " + _bind(spark, sf_dir, w))


def _bind(spark: SparkSession, sf_dir: str, w: Workload) -> str:
    """The source with its table names replaced by the session's views of this folder."""
    tag = re.sub(r"\W", "_", sf_dir)
    if w.made is not None:
        MADE[w.made](spark, sf_dir).createOrReplaceTempView(f"cm_{tag}_made_{w.made}")
        return f"cm_{tag}_made_{w.made}"
    sql = dialect(w.source, True)
    for t in w.tables:
        view = f"cm_{tag}_{t}"
        read(spark, sf_dir, t).createOrReplaceTempView(view)
        sql = re.sub(rf"(from|join) {t}\b", rf"\1 {view}", sql) if sql != t else view
    return sql


def flagged_documents(spark: SparkSession, sf_dir: str, w: Workload, bits: int = 22) -> DataFrame:
    """(doc_id, y, _b0, _b1, ...): the label and the items of a workload on LABELLED, each item computed once, and before the join, which carries no texts.

    Texts without a label are left out first by a bitmap of hashed identifiers, of 2**bits bits for labels of any number; the join drops the rest."""
    docs = read(spark, sf_dir, "documents")
    labels = read(spark, sf_dir, "labels").select("doc_id", F.expr(f"cast({dialect(w.label, True)} as int)").alias("y")).where("y is not null")
    place = F.xxhash64(F.col("doc_id").cast("string")).bitwiseAND((1 << bits) - 1)
    word, bit = F.call_function("shiftright", place, F.lit(6)), F.call_function("shiftleft", F.lit(1).cast("long"), place.bitwiseAND(63).cast("int"))
    words = labels.groupBy(word.alias("_word")).agg(F.bit_or(bit).alias("_bits"))
    likely = docs.join(F.broadcast(words), (word == F.col("_word")) & (F.col("_bits").bitwiseAND(bit) != 0), "left_semi")
    flags = (F.coalesce(F.expr(dialect(without_lists(sql), True)), F.lit(False)).alias(f"_b{k}") for k, (_, sql) in enumerate(w.items))
    return likely.select("doc_id", *flags).join(labels, "doc_id")


def build(spark: SparkSession, sf_dir: str, name: str, negation: bool = False, only: tuple[str, ...] | None = None) -> LabeledDB:
    """The labelled database of a workload: a projection and joins that Catalyst plans, and one aggregation to distinct rows."""
    w = WORKLOADS[name]
    ids = ", ".join(f"case when {dialect(sql, True)} then {k} end" for k, (_, sql) in enumerate(w.items))
    rows = spark.sql(f"select array_compact(array({ids})) items, cast({dialect(w.label, True)} as int) label from {_bind(spark, sf_dir, w)}").where("label is not null")
    db = compress(rows, [n for n, _ in w.items], negation)
    return db if only is None else db.with_negation(True, only)


def min_support(db: LabeledDB, share: float, least: int = 1) -> int:
    """ceil(share of the positives)."""
    n_pos, _ = db.sizes()
    return max(least, -int(-share * n_pos // 1))


def one_vs_rest(df: DataFrame, label: str) -> list:
    """The label's values in order, each in turn the positive class."""
    return sorted(r[0] for r in df.select(label).distinct().where(F.col(label).isNotNull()).collect())
