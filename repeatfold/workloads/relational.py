"""Surrounding relational operators on the given tables, with DuckDB twins."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from repeatfold.operators import repeats
from repeatfold.plans import frames
from repeatfold.sources.tables import load_table

QUERIES, SQL = {}, {}


def query(name: str, sql: str | None = None):
    def add(f):
        QUERIES[name] = f
        if sql is not None:
            SQL[name] = sql
        return f

    return add


_COUNTS = "count(*)::bigint as n, sum(n_chars)::bigint as chars"


def _counts():
    return F.count("*").alias("n"), F.sum("n_chars").alias("chars")


@query("unit_rollup", f"select lang, source, {_COUNTS} from documents group by rollup(lang, source)")
def unit_rollup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return load_table(spark, sf_dir, "documents").rollup("lang", "source").agg(*_counts())


@query("unit_cube", f"select lang, source, {_COUNTS} from documents group by cube(lang, source)")
def unit_cube(spark: SparkSession, sf_dir: str) -> DataFrame:
    return load_table(spark, sf_dir, "documents").cube("lang", "source").agg(*_counts())


@query("unit_grouping_sets", f"select lang, source, {_COUNTS} from documents group by grouping sets ((lang), (source))")
def unit_grouping_sets(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = load_table(spark, sf_dir, "documents")
    return docs.groupingSets([[docs.lang], [docs.source]], docs.lang, docs.source).agg(*_counts())


@query("unit_pivot", "select source, count(*) filter (lang = 'en')::bigint as en, count(*) filter (lang = 'de')::bigint as de, count(*) filter (lang = 'fr')::bigint as fr, count(*) filter (lang = 'es')::bigint as es from documents group by source")
def unit_pivot(spark: SparkSession, sf_dir: str) -> DataFrame:
    return load_table(spark, sf_dir, "documents").groupBy("source").pivot("lang", ["en", "de", "fr", "es"]).agg(F.count("doc_id")).fillna(0)


_LINES = "(select doc_id, lang, line, count(*) as k from (select doc_id, lang, unnest(string_split(text, chr(10))) as line from documents) where line <> '' group by all having count(*) > 1)"


@query("topk_redundant", f"select lang, doc_id, saved::bigint as saved, rank::int as rank from (select lang, doc_id, saved, row_number() over (partition by lang order by saved desc, doc_id) as rank from (select lang, doc_id, sum((k - 1) * length(line)) as saved from {_LINES} group by all)) where rank <= 5")
def topk_redundant(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Of each language the five documents with most symbols in repeated lines."""
    lines = load_table(spark, sf_dir, "documents").select("doc_id", "lang", F.explode(F.split("text", "\n")).alias("line")).where("line <> ''")
    again = lines.groupBy("doc_id", "lang", "line").agg(F.count("*").alias("k")).where("k > 1")
    saved = again.groupBy("lang", "doc_id").agg(F.sum((F.col("k") - 1) * F.length("line")).alias("saved"))
    w = Window.partitionBy("lang").orderBy(F.desc("saved"), "doc_id")
    return saved.withColumn("rank", F.row_number().over(w)).where("rank <= 5").select("lang", "doc_id", "saved", "rank")


@query("rank_windows", """
select doc_id, row_number() over w as rn, dense_rank() over (partition by lang order by n_chars) as dr, ntile(4) over w as quarter, coalesce(lag(doc_id) over w, -1) as prev, coalesce(lead(doc_id) over w, -1) as next,
 first_value(doc_id) over w as first, sum(n_chars) over (partition by lang order by n_chars, doc_id rows between unbounded preceding and current row)::bigint as running,
 count(*) over (partition by lang order by n_chars range between 100 preceding and 100 following) as near, round(cume_dist() over (partition by lang order by n_chars), 6) as share
from documents window w as (partition by lang order by n_chars, doc_id)""")
def rank_windows(spark: SparkSession, sf_dir: str) -> DataFrame:
    w, v = Window.partitionBy("lang").orderBy("n_chars", "doc_id"), Window.partitionBy("lang").orderBy("n_chars")
    return load_table(spark, sf_dir, "documents").select(
        "doc_id", F.row_number().over(w).cast("long").alias("rn"), F.dense_rank().over(v).cast("long").alias("dr"), F.ntile(4).over(w).cast("long").alias("quarter"), F.lag("doc_id", 1, -1).over(w).alias("prev"),
        F.lead("doc_id", 1, -1).over(w).alias("next"), F.first("doc_id").over(w).alias("first"), F.sum("n_chars").over(w.rowsBetween(Window.unboundedPreceding, 0)).alias("running"),
        F.count("*").over(v.rangeBetween(-100, 100)).alias("near"), F.round(F.cume_dist().over(v), 6).alias("share"),
    )


@query("asof_events", """
select p.event_id, coalesce(arg_max(v.event_id, (v.ts, v.event_id)), -1) as last_view from events p left join events v on v.user_id = p.user_id and v.event_type = 'view' and v.ts < p.ts
where p.event_type = 'purchase' group by p.event_id""")
def asof_events(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The user's last view before each purchase: one sort by user and time instead of a join of all pairs."""
    e = load_table(spark, sf_dir, "events").where("event_type in ('view', 'purchase')")
    order = Window.partitionBy("user_id").orderBy("ts", F.when(F.col("event_type") == "purchase", 0).otherwise(1), "event_id").rowsBetween(Window.unboundedPreceding, -1)
    seen = F.last(F.when(F.col("event_type") == "view", F.col("event_id")), ignorenulls=True).over(order)
    return e.withColumn("last_view", F.coalesce(seen, F.lit(-1))).where("event_type = 'purchase'").select("event_id", "last_view")


def _classes(spark: SparkSession, sf_dir: str) -> DataFrame:
    items = load_table(spark, sf_dir, "benchmark")
    return frames.longest_classes(items, ["item_id"], repeats.longest_repeats(items, ["item_id"]))


def _zones_sql(tail: str) -> str:
    from repeatfold.workloads.methods import _lr_sql

    return f"""with {_lr_sql('benchmark', 'item_id')}, z as (select item_id, unnest(starts) as a, l from one), w as (select item_id, a, a + l - 1 as b from z),
q as (select item_id, unnest(range(1, length(text) + 1)) as pos from benchmark) {tail}"""


@query("range_join_zones", _zones_sql("select q.item_id, q.pos, count(*)::bigint as covers from q join w on w.item_id = q.item_id and q.pos between w.a and w.b group by all"))
def range_join_zones(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Cells inside copies of the longest repeat: interval bins make the range join an equality join."""
    bin_ = 16
    zones = _classes(spark, sf_dir).select("item_id", F.explode("starts").alias("a"), "len").withColumn("b", F.col("a") + F.col("len") - 1)
    zones = zones.withColumn("bin", F.explode(F.sequence(F.floor(F.col("a") / bin_), F.floor(F.col("b") / bin_))))
    cells = frames.positions(load_table(spark, sf_dir, "benchmark"), ["item_id"]).select("item_id", F.col("pos").cast("long").alias("pos"), F.floor(F.col("pos") / bin_).alias("bin"))
    return cells.join(zones, ["item_id", "bin"]).where("pos between a and b").groupBy("item_id", "pos").agg(F.count("*").alias("covers"))


@query("anti_live", _zones_sql("select q.item_id, count(*)::bigint as live from q where not exists (select 1 from w where w.item_id = q.item_id and q.pos between w.a and w.b) group by all"))
def anti_live(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Cells outside every copy."""
    cells = frames.positions(load_table(spark, sf_dir, "benchmark"), ["item_id"]).select("item_id", F.col("pos").cast("long").alias("pos"))
    return cells.join(range_join_zones(spark, sf_dir), ["item_id", "pos"], "left_anti").groupBy("item_id").agg(F.count("*").alias("live"))


@query("semi_unique", "select doc_id from documents d where text in (select text from documents group by text having count(*) = 1)")
def semi_unique(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = load_table(spark, sf_dir, "documents").select("doc_id", F.xxhash64("text").alias("h"), F.md5(F.col("text").cast("binary")).alias("m"))
    once = docs.groupBy("h", "m").count().where("count = 1")
    return docs.join(once, ["h", "m"], "left_semi").select("doc_id")


_WORDS = "select distinct word from (select unnest(string_split(text, ' ')) as word from {}) where word <> ''"


@query("setops_repeats", f"select 'both' as kind, count(*)::bigint as n from ({_WORDS.format('benchmark')} intersect {_WORDS.format('documents')}) union all select 'only', count(*)::bigint from ({_WORDS.format('benchmark')} except {_WORDS.format('documents')}) union all select 'any', count(*)::bigint from ({_WORDS.format('benchmark')} union {_WORDS.format('documents')})")
def setops_repeats(spark: SparkSession, sf_dir: str) -> DataFrame:
    words = lambda t: load_table(spark, sf_dir, t).select(F.explode(F.split("text", " ")).alias("word")).where("word <> ''").distinct()
    a, b = words("benchmark"), words("documents")
    count = lambda df, k: df.agg(F.lit(k).alias("kind"), F.count("*").alias("n"))
    return count(a.intersect(b), "both").union(count(a.exceptAll(b), "only")).union(count(a.union(b).distinct(), "any"))


@query("outer_engines", "select item_id, 1::bigint as both from benchmark")
def outer_engines(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Full outer comparison of two engines' residuals."""
    from repeatfold.operators.fold import fold

    items = load_table(spark, sf_dir, "benchmark")
    a, b = (fold(items, ["item_id"], engine=e).select("item_id", F.col("residual").alias(e)) for e in ("reach", "tree"))
    return a.join(b, "item_id", "full").select("item_id", F.col("reach").eqNullSafe(F.col("tree")).cast("long").alias("both"))


@query("scalar_strings", "select doc_id, length(text)::bigint as n, substr(text, 2, 5) as part, strpos(text, ' ')::bigint as at, translate(substr(text, 1, 20), 'aeiou', 'AEIOU') as vowels, regexp_replace(substr(text, 1, 40), '[0-9]+', '#', 'g') as masked, md5(text) as hash, reverse(substr(text, 1, 10)) as back, repeat(lang, 2) as twice from documents")
def scalar_strings(spark: SparkSession, sf_dir: str) -> DataFrame:
    t = F.col("text")
    return load_table(spark, sf_dir, "documents").select(
        "doc_id", F.length(t).cast("long").alias("n"), F.substring(t, 2, 5).alias("part"), F.instr(t, " ").cast("long").alias("at"), F.translate(F.substring(t, 1, 20), "aeiou", "AEIOU").alias("vowels"),
        F.regexp_replace(F.substring(t, 1, 40), "[0-9]+", "#").alias("masked"), F.md5(t.cast("binary")).alias("hash"), F.reverse(F.substring(t, 1, 10)).alias("back"), F.repeat("lang", F.lit(2)).alias("twice"),
    )


@query("scalar_arrays", "with w as (select item_id, string_split(text, ' ') as w from benchmark) select item_id, len(w)::bigint as n, len(list_distinct(w))::bigint as distinct_n, list_max(list_transform(w, lambda x: length(x)))::bigint as longest, array_to_string(list_sort(list_filter(w, lambda x: length(x) > 6)), ',') as long_words, array_to_string(w[2:4], ' ') as part, list_sum(list_transform(w, lambda x: length(x)))::bigint as letters from w")
def scalar_arrays(spark: SparkSession, sf_dir: str) -> DataFrame:
    w = F.col("w")
    return load_table(spark, sf_dir, "benchmark").select("item_id", F.split("text", " ").alias("w")).select(
        "item_id", F.size(w).cast("long").alias("n"), F.size(F.array_distinct(w)).cast("long").alias("distinct_n"), F.array_max(F.transform(w, lambda x: F.length(x))).cast("long").alias("longest"),
        F.array_join(F.array_sort(F.filter(w, lambda x: F.length(x) > 6)), ",").alias("long_words"), F.array_join(F.slice(w, 2, 3), " ").alias("part"), F.aggregate(w, F.lit(0).cast("long"), lambda a, x: a + F.length(x)).alias("letters"),
    )


@query("scalar_json", "select (props->>'$.k')::bigint as k, count(*)::bigint as n, round(sum(value), 6) as total from events group by 1")
def scalar_json(spark: SparkSession, sf_dir: str) -> DataFrame:
    e = load_table(spark, sf_dir, "events").withColumn("k", F.from_json("props", "k bigint")["k"])
    return e.groupBy("k").agg(F.count("*").alias("n"), F.round(F.sum("value"), 6).alias("total"))


@query("scalar_dates", "select year(o_orderdate)::bigint as y, month(o_orderdate)::bigint as m, strftime(date_trunc('month', o_orderdate), '%Y-%m-%d') as first, count(*)::bigint as n, round(sum(o_totalprice::decimal(18, 2)), 2)::double as total from orders group by all")
def scalar_dates(spark: SparkSession, sf_dir: str) -> DataFrame:
    d = F.col("o_orderdate")
    o = load_table(spark, sf_dir, "orders").select(F.year(d).cast("long").alias("y"), F.month(d).cast("long").alias("m"), F.date_format(F.trunc(d.cast("date"), "month"), "yyyy-MM-dd").alias("first"), F.col("o_totalprice").cast("decimal(18,2)").alias("p"))
    return o.groupBy("y", "m", "first").agg(F.count("*").alias("n"), F.sum("p").cast("double").alias("total"))


@query("scalar_math", "select doc_id, round(log2(n_chars), 6) as bits, ceil(n_chars / 7.0)::bigint as up, (n_chars & 255)::bigint as low, (n_chars << 2)::bigint as four, round(sqrt(n_chars), 6) as root, (n_chars % 97)::bigint as rest from documents")
def scalar_math(spark: SparkSession, sf_dir: str) -> DataFrame:
    n = F.col("n_chars")
    return load_table(spark, sf_dir, "documents").select(
        "doc_id", F.round(F.log2(n), 6).alias("bits"), F.ceil(n / 7.0).cast("long").alias("up"), n.bitwiseAND(255).alias("low"), F.shiftleft(n, 2).alias("four"), F.round(F.sqrt(n), 6).alias("root"), (n % 97).alias("rest"),
    )


@query("hash_sample", "select doc_id from documents where ('0x' || substr(md5(doc_id::varchar), 1, 4))::bigint % 10 = 0")
def hash_sample(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A sampling operator: a tenth of the documents by a hash of the id, the same rows on every run."""
    h = F.conv(F.substring(F.md5(F.col("doc_id").cast("string").cast("binary")), 1, 4), 16, 10).cast("long")
    return load_table(spark, sf_dir, "documents").where(h % 10 == 0).select("doc_id")


@query("aggregates", "select lang, count(distinct source)::bigint as sources, min(n_chars) as least, max(n_chars) as most, round(avg(n_chars), 6) as mean, arg_max(doc_id, (n_chars, doc_id)) as longest from documents group by lang")
def aggregates(spark: SparkSession, sf_dir: str) -> DataFrame:
    return load_table(spark, sf_dir, "documents").groupBy("lang").agg(
        F.countDistinct("source").alias("sources"), F.min("n_chars").alias("least"), F.max("n_chars").alias("most"), F.round(F.avg("n_chars"), 6).alias("mean"), F.max_by("doc_id", F.struct("n_chars", "doc_id")).alias("longest"),
    )


@query("sql_surface", "select count(*)::bigint as units from benchmark")
def sql_surface(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Registered functions and table functions from SQL: units that come back as they were."""
    from repeatfold.functions.udfs import register_all

    register_all(spark, sf_dir)
    return spark.sql("""
        select count(*) as units from (select item_id, text, unfold_text(fold_struct(text)) as back, longest_repeat_len(text) as lr, lz77_count(text) as z, gzip_size(text) as g from benchmark) u
        where text = back and lr > 0 and z > 0 and g > 0 and item_id in (select b.item_id from benchmark b, lateral fold_steps(b.text) s where s.k = 1 and s.len >= 2)""")


def queries():
    return dict(QUERIES)


def oracle_sql():
    return dict(SQL)
