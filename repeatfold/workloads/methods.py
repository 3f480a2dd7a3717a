"""Queries of the methods, variants, baselines and measures on the given tables, with DuckDB twins."""

from __future__ import annotations

from collections.abc import Callable
from functools import reduce
from operator import and_

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from repeatfold.functions.columns import gate as gate_column
from repeatfold.functions.columns import unfold_text
from repeatfold.kernels.baselines import longest_grammar_bodies, pair_grammar
from repeatfold.operators import baselines, checks, fold, measures, repeats
from repeatfold.operators.units import map_units
from repeatfold.plans import frames, planner
from repeatfold.plans.lineage import cut
from repeatfold.sources import tables

load_table = tables.load_table


def units_of(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return planner.spread(load_table(spark, sf_dir, name))


Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Query] = {}
SQL: dict[str, str] = {}

# Hand-worked units with their residuals, factors and kinds.
FIXTURES = {
    "worked": ("abcabcaabcdabcacabc$", "abc##d#c#$", "3,4;1,3;1,4", "1,3,2,3"),
    "three_a": ("aaa$", "a#$", "1,2", "1"),
    "seven_a": ("aaaaaaa$", "a#$", "1,6", "1"),
    "nested": ("abababcababab$", "ab#c#$", "2,4;1,6", "1,2"),
    "coordinates": ("aaaabcXbcY$", "a#bcX#Y$", "1,3;5,2", "1,2"),
    "dropped_copy": ("abaPababaQ$", "abaP##Q$", "1,3;2,2", "2,2"),
    "half_bound": ("aabaaPaabaabaaabaaQ$", "aab#P#ba#Q$", "1,2;1,5", "2,3,3"),
    "not_maximal": ("qabcrvwxyasvwxyabct$", "qabcrvwxyas##t$", "6,5;3,2", "2,2"),
    "no_repeat": ("abc$", "abc$", "", ""),
    "empty": ("$", "$", "", ""),
    "single": ("a$", "a$", "", ""),
}
GATES = [(30.0, 80.0), (30.0, 80.5), (0.0, 2.0)]


def query(name: str, sql: str | None = None):
    def add(f: Query) -> Query:
        QUERIES[name] = f
        if sql is not None:
            SQL[name] = sql
        return f

    return add


def flat(folded: DataFrame) -> DataFrame:
    """A triple as strings: marks are #."""
    text = F.array_join(F.transform("residual", lambda c: F.when(c == -2, "#").otherwise(F.chr(c))), "")
    fac = F.array_join(F.transform("factors", lambda f: F.concat_ws(",", f["a"], f["len"])), ";")
    ids = [c for c in folded.columns if c not in {"residual", "factors", "kinds", "n", "steps"}]
    return folded.select(*ids, text.alias("residual"), fac.alias("factors"), F.array_join(F.transform("kinds", lambda k: k.cast("string")), ",").alias("kinds"))


def _values(rows: list[tuple], names: str) -> str:
    q = lambda v: "'" + v + "'" if isinstance(v, str) else f"{v}::bigint" if isinstance(v, int) and not isinstance(v, bool) else str(v)
    return f"select * from (values {', '.join('(' + ', '.join(map(q, r)) + ')' for r in rows)}) t({names})"


@query("worked_example", _values([FIXTURES["worked"][1:]], "residual, factors, kinds"))
def worked_example(spark: SparkSession, sf_dir: str) -> DataFrame:
    return flat(fold.fold(spark.createDataFrame([(1, FIXTURES["worked"][0])], "id int, text string"), ["id"])).drop("id")


@query("worked_example_steps", _values([(1, "abca", 4, 1), (1, "abca", 12, 2), (2, "abc", 8, 3), (2, "abc", 17, 3)], "step, lr, pos, type"))
def worked_example_steps(spark: SparkSession, sf_dir: str) -> DataFrame:
    units = spark.createDataFrame([(1, FIXTURES["worked"][0])], "id int, text string")
    log = fold.fold(units, ["id"], engine="tree", log=True).join(units, "id")
    rows = log.select("k", F.substring("text", F.col("first").cast("int"), F.col("len")).alias("lr"), F.explode(F.arrays_zip("picks", "pick_kinds")).alias("p"))
    return rows.select(F.col("k").cast("long").alias("step"), "lr", F.col("p.picks").alias("pos"), F.col("p.pick_kinds").cast("long").alias("type"))


@query("hand_fixtures", f"""with f as ({_values([(i, k, *v[1:]) for i, (k, v) in enumerate(FIXTURES.items())], "i, name, residual, factors, kinds")})
select name, residual, factors, kinds, count(*)::bigint as customers from customer join f on c_custkey % {len(FIXTURES)} = i group by all""")
def hand_fixtures(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Each customer's key chooses a hand-worked unit and the nation renames its letters; folds do not hang on names, so they are the hand-worked ones."""
    rows = load_table(spark, sf_dir, "customer").select((F.col("c_custkey") % len(FIXTURES)).cast("int").alias("i"), ((F.col("c_nationkey") + 1) * 1024).cast("int").alias("shift"))
    of = lambda make: F.get(F.array(*map(make, FIXTURES.items())), F.col("i"))
    units = rows.groupBy("i", "shift").agg(F.count("*").alias("customers"))
    units = units.select("shift", "customers", of(lambda x: F.lit(x[0])).alias("name"), F.transform(of(lambda x: F.array(*(F.lit(ord(c)) for c in x[1][0]))), lambda c: c + F.col("shift")).alias("codes"))
    folded = fold.fold(units, ["name", "shift", "customers"], "codes", engine="tree")
    back = folded.withColumn("residual", F.transform("residual", lambda c: F.when(c == -2, c).otherwise(c - F.col("shift"))))
    return flat(back).groupBy("name", "residual", "factors", "kinds").agg(F.sum("customers").alias("customers"))


@query("occurrences_of_item", """
select doc_id, item_id, pos::bigint as pos from (select d.doc_id, b.item_id, d.text t, b.text x, unnest(range(1, length(d.text) - length(b.text) + 2)) as pos
from documents d join benchmark b on contains(d.text, b.text)) where substr(t, pos, length(x)) = x""")
def occurrences_of_item(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs, items = units_of(spark, sf_dir, "documents").select("doc_id", "text"), load_table(spark, sf_dir, "benchmark")
    return planner_contained(docs, items)


def planner_contained(docs: DataFrame, items: DataFrame, anchor: int = 24) -> DataFrame:
    """Occurrences of whole items in documents: positions whose next symbols hash like an item's first ones, then the whole item is compared.

    Only items of ``anchor`` symbols or more take the hash route; shorter ones, if any, go through a nested loop over a bounded list.
    """
    head = items.where(F.length("text") >= anchor).select("item_id", F.col("text").alias("x"), F.xxhash64(F.substring("text", 1, anchor)).alias("h"))
    at = docs.where(F.length("text") >= anchor).select("doc_id", "text", F.explode(F.sequence(F.lit(1), F.length("text") - anchor + 1)).alias("pos"))
    hit = at.select("doc_id", "pos", F.xxhash64(F.substring("text", F.col("pos"), F.lit(anchor))).alias("h")).join(head.select("h").distinct(), "h", "left_semi")
    hit = hit.join(head, "h").join(docs, "doc_id").where(F.substring("text", F.col("pos"), F.length("x")) == F.col("x")).select("doc_id", "item_id", F.col("pos").cast("long").alias("pos"))
    short = items.where(F.length("text") < anchor)
    if short.isEmpty():
        return hit
    few = short.limit(10_001).collect()
    if len(few) > 10_000:
        raise ValueError("too many short items for a nested loop")
    spark = docs.sparkSession
    loop = docs.join(F.broadcast(spark.createDataFrame(few, short.schema).withColumnRenamed("text", "x")), F.contains("text", F.col("x")))
    return hit.union(repeats.occurrences(loop, F.col("x")).select("doc_id", "item_id", "pos"))


@query("repeats_len16", """
select doc_id, count(*)::bigint as n_classes, sum(n)::bigint as n_occ from (select doc_id, x, count(*) as n from
(select doc_id, substr(text, pos, 16) as x from (select doc_id, text, unnest(range(1, length(text) - 14)) as pos from documents)) group by all having count(*) > 1) group by doc_id""")
def repeats_len16(spark: SparkSession, sf_dir: str) -> DataFrame:
    r = repeats.repeats_at(units_of(spark, sf_dir, "documents"), 16, ["doc_id"])
    return r.groupBy("doc_id").agg(F.count("*").alias("n_classes"), F.sum("n_occ").alias("n_occ"))


@query("repeats_by_len", """
select l as len, count(*)::bigint as classes, sum(n)::bigint as occurrences from (select item_id, l, x, count(*) as n from
(select item_id, l, substr(text, pos, l) as x from (select item_id, text, l, unnest(range(1, length(text) - l + 2)) as pos from benchmark, (values (2::bigint), (4), (8), (16)) v(l))) group by all having count(*) > 1) group by l""")
def repeats_by_len(spark: SparkSession, sf_dir: str) -> DataFrame:
    items, out = load_table(spark, sf_dir, "benchmark"), None
    for n in (2, 4, 8, 16):
        one = frames.substrings(items, ["item_id"], n).select(F.lit(n).cast("long").alias("len"), F.size("starts").alias("k"))
        out = one if out is None else out.union(one)
    return out.groupBy("len").agg(F.count("*").alias("classes"), F.sum("k").alias("occurrences"))


def _lr_sql(table: str, ids: str, least: int = 1) -> str:
    """CTEs: every repeated substring (c), the longest ones (lr), of them the one that stands first (one)."""
    return f"""p as (select {ids}, text, unnest(range(1, length(text) + 1)) as pos from {table}),
s as (select {ids}, l, substr(text, pos, l) as x, pos from (select {ids}, text, pos, unnest(range({least}, length(text) - pos + 2)) as l from p)),
c as (select {ids}, l, x, count(*) as n, list(pos order by pos) as starts from s group by all having count(*) > 1),
m as (select {ids}, max(l) as l from c group by all), lr as (select c.* from c join m using ({ids}, l)),
one as (select * from lr qualify row_number() over (partition by {ids} order by starts[1]) = 1)"""


_LG = "list_reduce(list_prepend([{free} - l], list_transform(starts, lambda s: [s])), lambda a, s: case when s[1] >= a[-1] + l then list_concat(a, s) else a end)[2:]"
_E = "case when len(starts) > 1 and starts[1] + l > starts[2] then starts[2] else starts[1] end + l - 1"


@query("longest_repeat_benchmark", f"with {_lr_sql('benchmark', 'item_id')} select item_id, l::bigint as lr_len, count(*)::bigint as n_lr from lr group by item_id, l")
def longest_repeat_benchmark(spark: SparkSession, sf_dir: str) -> DataFrame:
    r = repeats.longest_repeats(load_table(spark, sf_dir, "benchmark"), ["item_id"])
    return r.groupBy("item_id", F.col("len").cast("long").alias("lr_len")).agg(F.count("*").alias("n_lr"))


_LONGEST = f"with {_lr_sql('benchmark', 'item_id')} select item_id, l::bigint as lr_len, count(*)::bigint as n_lr from lr group by item_id, l"


@query("longest_repeat_bisect", _LONGEST)
def longest_repeat_bisect(spark: SparkSession, sf_dir: str) -> DataFrame:
    r = repeats.longest_repeats(load_table(spark, sf_dir, "benchmark"), ["item_id"], engine="bisect")
    return r.groupBy("item_id", F.col("len").cast("long").alias("lr_len")).agg(F.count("*").alias("n_lr"))


@query("longest_repeat_group", _LONGEST)
def longest_repeat_group(spark: SparkSession, sf_dir: str) -> DataFrame:
    r = repeats.longest_repeats(load_table(spark, sf_dir, "benchmark"), ["item_id"], engine="group")
    return r.groupBy("item_id", F.col("len").cast("long").alias("lr_len")).agg(F.count("*").alias("n_lr"))


@query("longest_repeat_turns", f"with u as (select conv_id, turn, text from conversations where role = 'user' and length(text) <= 200), {_lr_sql('u', 'conv_id, turn')} select conv_id, turn, l::bigint as lr_len from m")
def longest_repeat_turns(spark: SparkSession, sf_dir: str) -> DataFrame:
    turns = load_table(spark, sf_dir, "conversations").where((F.col("role") == "user") & (F.length("text") <= 200))
    return repeats.longest_repeats(turns, ["conv_id", "turn"]).groupBy("conv_id", "turn").agg(F.max("len").cast("long").alias("lr_len"))


_TURNS = "u as (select conv_id, turn, text from conversations where role = 'user' and text <> '')"


@query("longest_repeat_all_turns", f"""with {_TURNS}, o as (select conv_id, turn, text, pos, lag(pos) over (partition by conv_id, turn order by substr(text, pos)) as before from (select *, unnest(range(1, length(text) + 1)) as pos from u)),
k as (select conv_id, turn, max(n) as n from (select conv_id, turn, text, pos, before, unnest(range(1, least(length(text) - pos, length(text) - before) + 2)) as n from o where before is not null)
  where substr(text, pos, n) = substr(text, before, n) group by conv_id, turn) select conv_id, turn, n::bigint as lr_len from k""")
def longest_repeat_all_turns(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every user turn, against neighbours in suffix order. ``longest_repeat_turns`` compares the turns of at most 200 symbols with SQL that lists all substrings."""
    turns = load_table(spark, sf_dir, "conversations").where(F.col("role") == "user")
    return repeats.longest_repeats(turns, ["conv_id", "turn"]).groupBy("conv_id", "turn").agg(F.max("len").cast("long").alias("lr_len"))


_ORDER = "o as (select item_id, text, pos, row_number() over (partition by item_id order by substr(text, pos)) as rank from (select item_id, text, unnest(range(1, length(text) + 1)) as pos from benchmark))"
_LCP = f"""{_ORDER}, b as (select *, lag(pos) over (partition by item_id order by rank) as before from o),
l as (select item_id, rank, pos, case when before is null then 0 else (select coalesce(max(k), 0) from (select unnest(range(1, least(length(text) - pos, length(text) - before) + 2)) as k) where substr(text, pos, k) = substr(text, before, k)) end::int as lcp from b)"""


@query("suffix_order_benchmark", f"with {_ORDER} select item_id, rank, pos from o")
def suffix_order_benchmark(spark: SparkSession, sf_dir: str) -> DataFrame:
    return frames.suffix_order(load_table(spark, sf_dir, "benchmark"), ["item_id"])


@query("suffix_order_doubling", f"with {_ORDER} select item_id, rank, pos from o")
def suffix_order_doubling(spark: SparkSession, sf_dir: str) -> DataFrame:
    return frames.doubling_order(load_table(spark, sf_dir, "benchmark"), ["item_id"], 400)


@query("suffix_order_kernel", f"with {_ORDER} select item_id, rank, pos from o")
def suffix_order_kernel(spark: SparkSession, sf_dir: str) -> DataFrame:
    return repeats.suffix_rows(load_table(spark, sf_dir, "benchmark"), ["item_id"]).select("item_id", "rank", "pos")


@query("lcp_benchmark", f"with {_LCP} select item_id, rank, lcp from l")
def lcp_benchmark(spark: SparkSession, sf_dir: str) -> DataFrame:
    items = load_table(spark, sf_dir, "benchmark")
    return frames.common_prefixes(frames.suffix_order(items, ["item_id"]), items, ["item_id"]).select("item_id", "rank", "lcp")


_MAXIMAL = """
with p as (select item_id, text, unnest(range(1, length(text) + 1)) as pos from benchmark),
s as (select item_id, substr(text, pos, l) as x, case when pos > 1 then substr(text, pos - 1, 1) else '<' end as a, case when pos + l <= length(text) then substr(text, pos + l, 1) else '>' end as b
  from (select item_id, text, pos, unnest(range(1, length(text) - pos + 2)) as l from p))
select item_id, x as repeat, count(*)::bigint as n_occ from s group by item_id, x having count(*) > 1 and count(distinct a) > 1 and count(distinct b) > 1"""


@query("maximal_repeats_benchmark", _MAXIMAL)
def maximal_repeats_benchmark(spark: SparkSession, sf_dir: str) -> DataFrame:
    items = load_table(spark, sf_dir, "benchmark")
    r = repeats.maximal_repeats(items, ["item_id"]).join(items, "item_id")
    return r.select("item_id", F.substring("text", F.col("first").cast("int"), F.col("len")).alias("repeat"), "n_occ")


@query("maximal_repeats_frames", _MAXIMAL)
def maximal_repeats_frames(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The same by relations of ranks."""
    items = load_table(spark, sf_dir, "benchmark")
    order = cut(frames.common_prefixes(frames.suffix_order(items, ["item_id"]), items, ["item_id"]))
    first = order.select("item_id", F.col("rank").alias("lo"), "pos")
    found = frames.maximal_groups(order, items, ["item_id"]).join(first, ["item_id", "lo"]).join(items, "item_id")
    return found.select("item_id", F.substring("text", F.col("pos").cast("int"), F.col("p")).alias("repeat"), (F.col("hi") - F.col("lo") + 1).alias("n_occ"))


@query("p_intervals_benchmark", f"""with {_LCP}, r as (select item_id, p, rank, lcp, sum((lcp < p)::int) over (partition by item_id, p order by rank) as run from l, (values (2), (3), (5)) v(p))
select item_id, p::int as p, min(rank) as lo, max(rank) as hi from r group by item_id, p, run having count(*) > 1 and min(case when lcp >= p then lcp end) = p""")
def p_intervals_benchmark(spark: SparkSession, sf_dir: str) -> DataFrame:
    lcp, out = repeats.suffix_rows(load_table(spark, sf_dir, "benchmark"), ["item_id"]), None
    for p in (2, 3, 5):
        one = frames.prefix_groups(lcp, ["item_id"], p)
        out = one if out is None else out.union(one)
    return out


@query("intervals_agree", "select 0::bigint as violations")
def intervals_agree(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Groups by windows against the kernel's stack, both ways."""
    items = load_table(spark, sf_dir, "benchmark")
    a = p_intervals_benchmark(spark, sf_dir)
    b = repeats.interval_rows(items, ["item_id"]).where("p in (2, 3, 5)").select("item_id", "p", "lo", "hi")
    return a.exceptAll(b).union(b.exceptAll(a)).agg(F.count("*").alias("violations"))


def _first_class(spark: SparkSession, sf_dir: str) -> DataFrame:
    items = load_table(spark, sf_dir, "benchmark")
    return frames.longest_classes(items, ["item_id"], repeats.longest_repeats(items, ["item_id"]))


@query("types_benchmark", f"""with {_lr_sql('benchmark', 'item_id')}, e as (select *, {_E} as e from one), g as (select *, {_LG.format(free='(e + 1)')} as lg from e),
t as (select item_id, starts, l, lg, unnest(starts) as pos from g)
select item_id, pos, case when pos = starts[1] then 0 when pos = starts[2] and starts[1] + l > starts[2] then 1 when list_contains(lg, pos) then case when len(lg) = 1 then 2 else 3 end else 4 end::int as type from t""")
def types_benchmark(spark: SparkSession, sf_dir: str) -> DataFrame:
    return frames.typed_rows(_first_class(spark, sf_dir), ["item_id"])


@query("left_greedy_benchmark", f"with {_lr_sql('benchmark', 'item_id')} select item_id, l::int as len, unnest({_LG.format(free='0')}) as pos from one")
def left_greedy_benchmark(spark: SparkSession, sf_dir: str) -> DataFrame:
    return frames.greedy_rows(_first_class(spark, sf_dir), ["item_id"])


@query("end_bound_benchmark", f"with {_lr_sql('benchmark', 'item_id')} select item_id, starts[1] as first, {_E} as e from one")
def end_bound_benchmark(spark: SparkSession, sf_dir: str) -> DataFrame:
    return frames.bound_rows(_first_class(spark, sf_dir), ["item_id"])


def _steps_sql(steps: int) -> str:
    parts = ["p0 as materialized (select item_id, text, pos, length(text) + 1 - pos as reach from (select item_id, text, unnest(range(1, length(text) + 1)) as pos from benchmark))"]
    for k in range(1, steps + 1):
        q = f"p{k - 1}"
        parts += [
            f"c{k} as (select item_id, l, x, list(pos order by pos) as starts from (select item_id, l, substr(text, pos, l) as x, pos from (select *, unnest(range(2, reach + 1)) as l from {q})) group by all having count(*) > 1)",
            f"o{k} as materialized (select * from c{k} qualify row_number() over (partition by item_id order by l desc, starts[1]) = 1)",
            f"e{k} as (select *, {_E} as e from o{k})",
            f"g{k} as materialized (select item_id, l, starts, case when len(starts) > 1 and starts[1] + l > starts[2] then list_prepend(starts[2], {_LG.format(free='(e + 1)')}) else {_LG.format(free='(e + 1)')} end as picks from e{k})",
            f"d{k} as (select item_id, a, a + l - 1 as b from (select item_id, l, unnest(picks) as a from g{k}))",
            f"""p{k} as materialized (select item_id, text, pos, least(reach, coalesce(nxt - pos, reach)) as reach from (select p.item_id, p.text, p.pos, p.reach,
  (select min(a) from d{k} d where d.item_id = p.item_id and d.a > p.pos) as nxt from {q} p where not exists (select 1 from d{k} d where d.item_id = p.item_id and p.pos between d.a and d.b)))""",
        ]
    union = " union all ".join(f"select item_id, {k}::bigint as step, l::bigint as len, starts[1] as first, array_to_string(picks, ',') as picks from g{k}" for k in range(1, steps + 1))
    return f"with {', '.join(parts)} {union}"


@query("first_steps_benchmark", _steps_sql(3))
def first_steps_benchmark(spark: SparkSession, sf_dir: str) -> DataFrame:
    log = fold.fold(load_table(spark, sf_dir, "benchmark"), ["item_id"], max_steps=3, log=True)
    return log.select("item_id", F.col("k").cast("long").alias("step"), F.col("len").cast("long").alias("len"), "first", F.array_join(F.transform("picks", lambda x: x.cast("string")), ",").alias("picks"))


@query("first_steps_frames", _steps_sql(3))
def first_steps_frames(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The same by relations of positions."""
    steps = frames.first_steps(load_table(spark, sf_dir, "benchmark"), ["item_id"], 3)
    return steps.withColumn("picks", F.array_join(F.transform("picks", lambda x: x.cast("string")), ","))


def _sized(units: DataFrame, ids: list[str], col: str = "text") -> DataFrame:
    return fold.fold_sizes(units, ids, col)


@query("fold_documents")
def fold_documents(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _sized(units_of(spark, sf_dir, "documents"), ["doc_id"])


@query("fold_distinct_documents")
def fold_distinct_documents(spark: SparkSession, sf_dir: str) -> DataFrame:
    return planner.fold_distinct(units_of(spark, sf_dir, "documents"), ["doc_id"], only_sizes=True)


@query("fold_pages")
def fold_pages(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _sized(units_of(spark, sf_dir, "pages"), ["page_id"], "html")


@query("fold_conversations")
def fold_conversations(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _sized(tables.grouped_units(load_table(spark, sf_dir, "conversations"), ["conv_id"], ["turn"]), ["conv_id"], "codes")


def _part_units(spark: SparkSession, sf_dir: str) -> DataFrame:
    return load_table(spark, sf_dir, "part").groupBy("p_brand").agg(F.array_join(F.transform(F.array_sort(F.collect_list(F.struct("p_partkey", "p_name"))), lambda x: x["p_name"]), "|").alias("text"))


@query("fold_part_names")
def fold_part_names(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _sized(_part_units(spark, sf_dir), ["p_brand"])


def _customer_units(spark: SparkSession, sf_dir: str) -> DataFrame:
    return load_table(spark, sf_dir, "customer").groupBy("c_mktsegment").agg(F.array_join(F.transform(F.array_sort(F.collect_list(F.struct("c_custkey", "c_name"))), lambda x: x["c_name"]), "|").alias("text"))


@query("fold_customer_names")
def fold_customer_names(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _sized(_customer_units(spark, sf_dir), ["c_mktsegment"])


@query("fold_sign_strings")
def fold_sign_strings(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _sized(tables.sign_units(load_table(spark, sf_dir, "embeddings")), ["vec_id"])


@query("fold_simple_documents")
def fold_simple_documents(spark: SparkSession, sf_dir: str) -> DataFrame:
    return fold.fold_sizes(units_of(spark, sf_dir, "documents"), ["doc_id"], mode="simple")


@query("fold_gated_documents")
def fold_gated_documents(spark: SparkSession, sf_dir: str) -> DataFrame:
    return fold.fold_sizes(units_of(spark, sf_dir, "documents"), ["doc_id"], engine="gated").fillna(0, ["refused", "lost"])


@query("fold_ties_benchmark")
def fold_ties_benchmark(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Sizes under each tie rule and minimum length."""
    items, out = load_table(spark, sf_dir, "benchmark"), None
    for tie, least in (("leftmost", 2), ("lex", 2), ("bucket", 2), ("leftmost", 4)):
        one = fold.sizes(fold.fold(items, ["item_id"], engine="tree", tie=tie, min_len=least)).withColumns({"tie": F.lit(tie), "min_len": F.lit(least)})
        out = one if out is None else out.union(one)
    return out


@query("grammar_longest_sizes")
def grammar_longest_sizes(spark: SparkSession, sf_dir: str) -> DataFrame:
    return baselines.grammar_size(baselines.grammar_longest(units_of(spark, sf_dir, "documents"), ["doc_id"]))


@query("pairs_sizes")
def pairs_sizes(spark: SparkSession, sf_dir: str) -> DataFrame:
    return baselines.grammar_size(baselines.grammar_pairs(units_of(spark, sf_dir, "documents"), ["doc_id"]))


@query("lz77_sizes")
def lz77_sizes(spark: SparkSession, sf_dir: str) -> DataFrame:
    return baselines.lz77_sizes(units_of(spark, sf_dir, "documents"), ["doc_id"])


@query("gzip_sizes")
def gzip_sizes(spark: SparkSession, sf_dir: str) -> DataFrame:
    return load_table(spark, sf_dir, "documents").select("doc_id", F.length("text").cast("long").alias("n"), baselines.gzip_size("text").alias("gzip_bytes"))


def prefixes(spark: SparkSession, sf_dir: str, powers: range) -> DataFrame:
    """``n, text``: prefixes of the documents' texts joined in id order, with the lengths that they have. Only as many documents are gathered as the longest one needs."""
    docs = load_table(spark, sf_dir, "documents").select("doc_id", "text", F.length("text").alias("len")).where("len > 0")
    need, total = 1 << max(powers), docs.count()
    k = 1 + need // 64
    while k < total and (docs.orderBy("doc_id").limit(k).agg(F.sum("len")).first()[0] or 0) < need:
        k *= 4
    first = docs.orderBy("doc_id").limit(k).withColumn("upto", F.sum("len").over(Window.orderBy("doc_id").rowsBetween(Window.unboundedPreceding, -1)))
    joined = first.where(F.coalesce("upto", F.lit(0)) < need).agg(F.array_join(F.transform(F.array_sort(F.collect_list(F.struct("doc_id", "text"))), lambda x: x["text"]), "").alias("all"))
    text = joined.select(F.explode(F.array(*[F.lit(1 << p) for p in powers])).alias("n"), "all").select(F.substring("all", F.lit(1), F.col("n").cast("int")).alias("text"))
    return text.select(F.length("text").cast("long").alias("n"), "text").distinct()


def growing_units(spark: SparkSession, sf_dir: str, powers: range) -> DataFrame:
    """``family, n, codes``: prefixes of documents, random texts of two letters, pairs that stand twice each, and runs of one letter."""
    docs = prefixes(spark, sf_dir, powers).select(F.lit("documents").alias("family"), "n", F.transform(F.split("text", ""), lambda c: F.ascii(c).cast("int")).alias("codes"))
    sizes = spark.createDataFrame([(1 << p,) for p in powers], "n long").withColumn("at", F.sequence(F.lit(0).cast("long"), F.col("n") - 1))
    half = F.col("n") / 6
    pair = lambda i: F.when(i % 3 < 2, F.floor(i / 3) % F.floor(half) * 2 + i % 3).otherwise(1_000_000 + i)
    made = {"random": lambda i: F.pmod(F.xxhash64(i, F.lit(42)), F.lit(2)), "pairs": pair, "unary": lambda i: F.lit(0)}
    for family, code in made.items():
        docs = docs.union(sizes.select(F.lit(family), "n", F.transform("at", code).cast("array<int>")))
    return docs.repartition(8 * len(powers), "family", "n")


#: Engines with the options of each, and the greatest power of two that its units have; what is quadratic stops early.
GROWING = {
    "reach": ("reach", {}, 17), "simple": ("reach", {"mode": "simple", "order": "ends_first"}, 17), "tree": ("tree", {}, 17), "tree_lex": ("tree", {"tie": "lex"}, 17),
    "tree_bucket": ("tree", {"tie": "bucket"}, 17),
}


@query("bench_scaling")
def bench_scaling(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Work counters of each engine over prefixes of 2^10 to 2^17 symbols; ``brute`` searches anew in every step and stops at 2^11."""
    out = None
    for name, (engine, options, top) in (GROWING | {"gated": ("gated", {}, 17), "brute": ("brute", {}, 11)}).items():
        units = prefixes(spark, sf_dir, range(10 if top > 11 else 8, top + 1)).repartition(8, "n")
        one = measures.kernel_growth(units, [], engine, **options).select(F.lit(name).alias("engine"), "n", "work", "cells")
        out = one if out is None else out.union(one)
    return out


@query("growth_violations", "select * from (values ('reach', 0::bigint), ('simple', 0), ('tree', 0), ('tree_lex', 0), ('tree_bucket', 0)) t(engine, violations)")
def growth_violations(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Families of texts whose work or space grows by a power above 1.2 from 2^10 to 2^17 symbols, for each engine."""
    units = cut(growing_units(spark, sf_dir, range(10, 18)))
    out = None
    for name, (engine, options, _) in GROWING.items():
        rows = cut(measures.kernel_growth(units, ["family"], engine, "codes", **options))
        work, cells = (measures.growth(rows, ["family"], "n", c).withColumnRenamed("slope", c) for c in ("work", "cells"))
        wrong = (F.col("work") > 1.2) | (F.col("cells") > 1.2)
        one = work.join(cells, "family").agg(F.lit(name).alias("engine"), F.sum(wrong.cast("long")).alias("violations"))
        out = one if out is None else out.union(one)
    return out


@query("growth_slopes")
def growth_slopes(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The powers themselves: of work and of space, by engine and family."""
    units, out = cut(growing_units(spark, sf_dir, range(10, 18))), None
    for name, (engine, options, _) in GROWING.items():
        rows = cut(measures.kernel_growth(units, ["family"], engine, "codes", **options))
        work, cells = (measures.growth(rows, ["family"], "n", c).select("family", F.round("slope", 4).alias(c)) for c in ("work", "cells"))
        one = work.join(cells, "family").select(F.lit(name).alias("engine"), "family", "work", "cells")
        out = one if out is None else out.union(one)
    return out


def _roundtrip(table: str, ids: list[str], col: str = "text", pick=None):
    def f(spark: SparkSession, sf_dir: str) -> DataFrame:
        units = units_of(spark, sf_dir, table)
        return (pick or (lambda u: fold.unfold(fold.fold(u, ids, col))))(units).withColumnRenamed("text", col)

    return f


_DOCS = "select doc_id, text from documents"
query("roundtrip_documents", _DOCS)(_roundtrip("documents", ["doc_id"]))
query("roundtrip_pages", "select page_id, html from pages")(_roundtrip("pages", ["page_id"], "html"))
query("roundtrip_conversations", "select conv_id, turn, text from conversations")(_roundtrip("conversations", ["conv_id", "turn"]))
query("roundtrip_expression", "select item_id, text from benchmark")(_roundtrip("benchmark", ["item_id"], pick=lambda u: fold.fold(u, ["item_id"]).select("item_id", unfold_text(F.col("residual"), F.col("factors"), F.col("kinds")).alias("text"))))
query("roundtrip_simple", _DOCS)(_roundtrip("documents", ["doc_id"], pick=lambda u: fold.unfold(fold.fold_simple(u, ["doc_id"]))))
query("roundtrip_gated", _DOCS)(_roundtrip("documents", ["doc_id"], pick=lambda u: fold.unfold(fold.fold_gated(u, ["doc_id"]))))
query("roundtrip_tree", "select item_id, text from benchmark")(_roundtrip("benchmark", ["item_id"], pick=lambda u: fold.unfold(fold.fold(u, ["item_id"], engine="tree", terminator=True))))
query("roundtrip_grammar_longest", _DOCS)(_roundtrip("documents", ["doc_id"], pick=lambda u: baselines.expand_grammar(baselines.grammar_longest(u, ["doc_id"]))))
query("roundtrip_pairs", "select item_id, text from benchmark")(_roundtrip("benchmark", ["item_id"], pick=lambda u: baselines.expand_grammar(baselines.grammar_pairs(u, ["item_id"]))))
query("roundtrip_lz77", _DOCS)(_roundtrip("documents", ["doc_id"], pick=lambda u: baselines.lz77_texts(baselines.lz77_units(u, ["doc_id"]))))
query("roundtrip_lz77_noself", "select item_id, text from benchmark")(_roundtrip("benchmark", ["item_id"], pick=lambda u: baselines.lz77_decode(baselines.lz77(u, ["item_id"], self_ref=False), ["item_id"])))


@query("roundtrip_parts", "select p_brand, string_agg(p_name, '|' order by p_partkey) as text from part group by p_brand")
def roundtrip_parts(spark: SparkSession, sf_dir: str) -> DataFrame:
    return fold.unfold(fold.fold(_part_units(spark, sf_dir), ["p_brand"]))


@query("roundtrip_events", "select user_id, string_agg(event_type, ' ' order by ts, event_id) as text from events group by user_id")
def roundtrip_events(spark: SparkSession, sf_dir: str) -> DataFrame:
    e = tables.symbol_units(load_table(spark, sf_dir, "events"), ["user_id"], ["ts", "event_id"], "event_type").select("user_id", F.array_join("symbols", " ").alias("text"))
    return fold.unfold(fold.fold(e, ["user_id"]))


@query("engines_agree", "select 0::bigint as violations")
def engines_agree(spark: SparkSession, sf_dir: str) -> DataFrame:
    items = load_table(spark, sf_dir, "benchmark")
    a, b, c = (fold.fold(items, ["item_id"], engine=e) for e in ("reach", "tree", "brute"))
    return a.exceptAll(b).union(a.exceptAll(c)).agg(F.count("*").alias("violations"))


@query("irreducible_check", "select 0::bigint as violations")
def irreducible_check(spark: SparkSession, sf_dir: str) -> DataFrame:
    return fold.irreducible(fold.fold(units_of(spark, sf_dir, "documents"), ["doc_id"])).agg(F.sum("violations").alias("violations"))


@query("factor_balance", "select 0::bigint as violations")
def factor_balance(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Literals and replaced lengths make up n; factors are one for each copy of kind 1 or 2 and one for each group of kind 3."""
    docs = units_of(spark, sf_dir, "documents")
    log = fold.fold(docs, ["doc_id"], log=True).groupBy("doc_id").agg(F.sum(F.col("q") * F.col("len")).alias("taken"), F.sum("q").alias("marks"), F.sum(F.col("n1") + F.col("n2") + (F.col("n3") > 0).cast("int")).alias("expected"))
    both = fold.sizes(fold.fold(docs, ["doc_id"])).join(log, "doc_id", "left").fillna(0, ["taken", "marks", "expected"])
    wrong = (F.col("n_literals") + F.col("taken") != F.col("n")) | (F.col("marks") != F.col("n_marks")) | (F.col("expected") != F.col("n_factors"))
    return both.agg(F.sum(wrong.cast("long")).alias("violations"))


def _audited(spark: SparkSession, sf_dir: str) -> DataFrame:
    items = load_table(spark, sf_dir, "benchmark").select(F.concat(F.lit("b"), "item_id").alias("unit"), "text")
    docs = units_of(spark, sf_dir, "documents").select(F.concat(F.lit("d"), "doc_id").alias("unit"), "text")
    return fold.step_totals(items.union(docs), ["unit"])


@query("audit_steps", "select * from (values ('lengths_grow', 0::bigint), ('too_many_steps', 0), ('idle_step', 0)) t(lemma, violations)")
def audit_steps(spark: SparkSession, sf_dir: str) -> DataFrame:
    a = _audited(spark, sf_dir).agg(F.sum(F.col("grows").cast("long")).alias("lengths_grow"), F.sum((F.col("steps") > F.col("n") / 2).cast("long")).alias("too_many_steps"), F.sum("idle_steps").alias("idle_step"))
    return a.select(F.expr("stack(3, 'lengths_grow', lengths_grow, 'too_many_steps', too_many_steps, 'idle_step', idle_step) as (lemma, violations)"))


@query("audit_charges", "select * from (values ('starts', 0::bigint), ('sorting', 0), ('created_nodes', 0), ('edges', 0), ('list_operations', 0), ('selection', 0)) t(charge, violations)")
def audit_charges(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Charges against their bounds: 2n starts, n log n comparisons, n new nodes, edges below three for each cell of a replaced copy, 2n list operations, and for the choice of nodes two for each position and start."""
    n = F.col("n")
    over = {"starts": F.col("sum_d") > 2 * n, "sorting": F.col("sort_work") > 2 * n * F.log2(n + 1), "created_nodes": F.col("nodes_new") > n, "edges": F.col("edges") > 3 * F.col("taken"), "list_operations": F.col("bucket_ops") > 2 * n, "selection": F.col("select_work") > 4 * n}
    a = _audited(spark, sf_dir).agg(*(F.sum(c.cast("long")).alias(k) for k, c in over.items()))
    return a.select(F.expr(f"stack({len(over)}, " + ", ".join(f"'{k}', {k}" for k in over) + ") as (charge, violations)"))


#: Sizes of the family, from the keys of orders: on both sides of each gate.
_PAIRS = "select 40 + o_custkey % 51 as r, 1 + o_orderkey % 60 as s, count(*) as n_orders from orders group by all"


def _pairs(spark: SparkSession, sf_dir: str) -> DataFrame:
    keys = load_table(spark, sf_dir, "orders").select((40 + F.col("o_custkey") % 51).cast("long").alias("r"), (1 + F.col("o_orderkey") % 60).cast("long").alias("s"))
    return keys.groupBy("r", "s").agg(F.count("*").alias("n_orders"))


def _grid_sql(blocks: int) -> str:
    return f"""select r::bigint as r, s::bigint as s, n_orders::bigint as n_orders, alpha::double as alpha, beta::double as beta, ok as accepted, (case when ok then {blocks} * s else 0 end)::bigint as n_marks
from (select *, r + 2 >= alpha / s + beta as ok from ({_PAIRS}) g, (values {', '.join(map(str, GATES))}) a(alpha, beta))"""


def _grid(spark: SparkSession, sf_dir: str, blocks: int) -> DataFrame:
    units, out = tables.adversarial_units(_pairs(spark, sf_dir), blocks), None
    for alpha, beta in GATES:
        done = fold.fold_sizes(units, ["r", "s", "n_orders"], "codes", engine="gated", alpha=alpha, beta=beta)
        ok = gate_column(F.col("r") + 2, F.col("s"), alpha, beta)
        one = done.select("r", "s", "n_orders", F.lit(alpha).alias("alpha"), F.lit(beta).alias("beta"), ok.alias("accepted"), "n_marks")
        out = one if out is None else out.union(one)
    return out


@query("gate_failure_grid", _grid_sql(1))
def gate_failure_grid(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _grid(spark, sf_dir, 1)


@query("gate_failure_two_blocks", _grid_sql(2))
def gate_failure_two_blocks(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _grid(spark, sf_dir, 2)


@query("family_fold", f"select r::bigint as r, s::bigint as s, n_orders::bigint as n_orders, (r + 2 * s + 4)::bigint as residual_len, 1::bigint as n_factors, (case when s = 1 then 2 else 3 end)::bigint as kind from ({_PAIRS})")
def family_fold(spark: SparkSession, sf_dir: str) -> DataFrame:
    f = fold.fold(tables.adversarial_units(_pairs(spark, sf_dir)), ["r", "s", "n_orders"], "codes")
    return f.select("r", "s", "n_orders", F.size("residual").cast("long").alias("residual_len"), F.size("factors").cast("long").alias("n_factors"), F.array_max("kinds").cast("long").alias("kind"))


@query("gate_estimate")
def gate_estimate(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = units_of(spark, sf_dir, "documents")
    e = measures.stream_costs(cut(measures.stream_counts(docs, ["lang"], "fold", joined=True)), docs.select("lang").distinct(), ["lang"])
    return e.select("lang", F.round("alpha", 6).alias("alpha"), F.round("beta", 6).alias("beta"))


@query("bit_costs_by_code")
def bit_costs_by_code(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Mean bits of residual, kinds and factors by language under the three codes."""
    docs, out = units_of(spark, sf_dir, "documents"), None
    counts, langs = cut(measures.stream_counts(docs, ["lang"], "fold", joined=True)), docs.select("lang").distinct()
    for code in ("entropy", "huffman", "fixed"):
        one = measures.stream_costs(counts, langs, ["lang"], code).select("lang", F.lit(code).alias("code"), *(F.round(c, 6).alias(c) for c in ("bit_residual", "bit_kinds", "bit_factors", "alpha", "beta", "total_bits")))
        out = one if out is None else out.union(one)
    return out


@query("type_counts_by_lang")
def type_counts_by_lang(spark: SparkSession, sf_dir: str) -> DataFrame:
    return measures.type_counts(fold.fold(units_of(spark, sf_dir, "documents"), ["doc_id", "lang"], log=True), ["lang"])


@query("simple_vs_greedy", "select 0::bigint as violations")
def simple_vs_greedy(spark: SparkSession, sf_dir: str) -> DataFrame:
    c = measures.compare_selection(units_of(spark, sf_dir, "documents"), ["doc_id"])
    least = F.greatest(F.ceil(F.col("greedy") / 2), F.lit(2))
    return c.agg(F.coalesce(F.sum((F.col("simple") < least).cast("long")), F.lit(0)).alias("violations"))


@query("simple_ratio")
def simple_ratio(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Copies kept beside left-greedy ones, for each order of choice."""
    docs, out = units_of(spark, sf_dir, "documents"), None
    for pick in ("ends_first", "scan", "hash"):
        c = measures.compare_selection(docs, ["doc_id"], pick=pick)
        one = c.agg(F.lit(pick).alias("pick"), F.count("*").alias("steps"), F.round(F.min(F.col("simple") / F.col("greedy")), 6).alias("min_ratio"), F.round(F.sum("simple") / F.sum("greedy"), 6).alias("ratio"))
        out = one if out is None else out.union(one)
    return out


def _lz_sql(self_ref: bool) -> str:
    bound = "" if self_ref else " and q.pos + k <= p.pos"
    return f"""with recursive p as (select item_id, text, unnest(range(1, length(text) + 1)) as pos from benchmark),
m as materialized (select p.item_id, p.pos, greatest(1, coalesce(max(k), 0)) as len from p left join (select p.item_id, p.pos, k from p join p q on q.item_id = p.item_id and q.pos < p.pos and substr(q.text, q.pos, 1) = substr(p.text, p.pos, 1),
  lateral (select unnest(range(1, length(p.text) - p.pos + 2)) as k) where substr(q.text, q.pos, k) = substr(p.text, p.pos, k){bound}) x using (item_id, pos) group by p.item_id, p.pos),
c(item_id, idx, pos, len) as (select item_id, 1::bigint, pos, len from m where pos = 1 union all select c.item_id, c.idx + 1, m.pos, m.len from c join m on m.item_id = c.item_id and m.pos = c.pos + c.len)
select item_id, idx, pos, len::bigint as len from c"""


@query("lz77_benchmark", _lz_sql(True))
def lz77_benchmark(spark: SparkSession, sf_dir: str) -> DataFrame:
    return baselines.lz77(load_table(spark, sf_dir, "benchmark"), ["item_id"]).select("item_id", F.col("idx").cast("long").alias("idx"), "pos", F.col("len").cast("long").alias("len"))


@query("lz77_noself_benchmark", _lz_sql(False))
def lz77_noself_benchmark(spark: SparkSession, sf_dir: str) -> DataFrame:
    return baselines.lz77(load_table(spark, sf_dir, "benchmark"), ["item_id"], self_ref=False).select("item_id", F.col("idx").cast("long").alias("idx"), "pos", F.col("len").cast("long").alias("len"))


@query("lz77_frames", _lz_sql(True))
def lz77_frames(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The same by relations of positions and doubled jumps."""
    return frames.lz77_rows(load_table(spark, sf_dir, "benchmark"), ["item_id"])


@query("lz77_noself_frames", _lz_sql(False))
def lz77_noself_frames(spark: SparkSession, sf_dir: str) -> DataFrame:
    return frames.lz77_rows(load_table(spark, sf_dir, "benchmark"), ["item_id"], self_ref=False)


@query("pairs_first_rule", """
with p as (select item_id, substr(text, pos, 2) as x, pos from (select item_id, text, unnest(range(1, length(text))) as pos from benchmark)),
r as (select item_id, x, pos, pos - row_number() over (partition by item_id, x order by pos) as run from p),
c as (select item_id, x, min(pos) as first, sum(k) as n from (select item_id, x, min(pos) as pos, case when x[1] = x[2] then (count(*) + 1) // 2 else count(*) end as k from r group by item_id, x, run) group by item_id, x)
select item_id, x as bigram, n::bigint as count from c where n > 1 qualify row_number() over (partition by item_id order by n desc, first) = 1""")
def pairs_first_rule(spark: SparkSession, sf_dir: str) -> DataFrame:
    def work(codes, sa, lcp):
        from repeatfold.kernels.baselines import disjoint_pairs, pair_grammar

        rules, _ = pair_grammar(codes)
        if rules:
            pair = tuple(rules[-10])
            yield "".join(map(chr, pair)), disjoint_pairs(codes)[pair]

    return map_units(load_table(spark, sf_dir, "benchmark"), ["item_id"], "text", "bigram string, count bigint", work, need_order=False)


@query("grammar_first_rule", f"""with {_lr_sql('benchmark', 'item_id', 2)}, g as (select item_id, l, x, starts, {_LG.format(free='0')} as lg from c)
select item_id, x as rule, len(lg)::bigint as copies from g where len(lg) > 1 qualify row_number() over (partition by item_id order by l desc, starts[1]) = 1""")
def grammar_first_rule(spark: SparkSession, sf_dir: str) -> DataFrame:
    items = load_table(spark, sf_dir, "benchmark")
    g = baselines.grammar_longest(items, ["item_id"]).where(F.size("rules") > 0)
    body = F.try_element_at("rules", F.lit(-10))
    return g.select("item_id", F.array_join(F.transform(body, lambda c: F.chr(c)), "").alias("rule"), F.size(F.filter("start", lambda x: x == -10)).cast("long").alias("copies"))


def ratios(docs: DataFrame, keys: list[str]) -> DataFrame:
    """Sizes of every method over the units of each key, and the bits of its whole output under one code (zero-order entropy of each of its streams) for input bits."""
    out = docs.select(*keys, "text", baselines.gzip_size("text").alias("b")).groupBy(*keys).agg(
        F.count("text").alias("n_units"), F.sum(F.length("text")).alias("n"), (8 * F.sum("b")).cast("double").alias("gzip_bits")
    )
    first = {"fold": "residual", "simple": "residual", "gated": "residual", "longest": "symbols", "pairs": "symbols", "lz77": "flags"}
    b = measures.stream_bits(measures.method_counts(docs, keys, ["chars", *first]), [*keys, "method"])
    of = lambda name, x, stream=None: F.sum(F.when((F.col("method") == name) & (F.lit(True) if stream is None else F.col("stream") == stream), x))
    bits, cols = F.col("n") * F.col("bits"), [F.round(of("chars", F.col("n") * F.col("bits")), 3).alias("input_bits")]
    for name, stream in first.items():
        factors = [of(name, F.col("n"), "pointers").alias(f"{name}_factors")] if stream == "residual" else []
        cols += [of(name, F.col("n"), stream).alias(name), *factors, of(name, bits).alias(f"{name}_bits")]
    parts = b.groupBy(*keys).agg(*cols).withColumnsRenamed({k: f"_{k}" for k in keys})
    same = reduce(and_, (F.col(k).eqNullSafe(F.col(f"_{k}")) for k in keys))
    out = out.join(parts, same, "left").select(*keys, "n_units", "n", *(c for c in parts.columns if c not in {f"_{k}" for k in keys}), "gzip_bits")
    empty = [c for c in out.columns if c in (*first, *(f"{x}_factors" for x in first)) and c != "lz77"]
    out = out.withColumns({c: F.when(F.col("n_units") > 0, F.coalesce(c, F.lit(0).cast("long"))) for c in empty})
    bits = [*(f"{name}_bits" for name in first), "gzip_bits"]
    return out.withColumns({b: F.round(b, 3) for b in bits} | {b.replace("_bits", "_ratio"): F.round(F.col(b) / F.col("input_bits"), 6) for b in bits})


def input_bits(docs: DataFrame, keys: list[str]) -> DataFrame:
    """``keys, n_units, n, input_bits``: the units as they stand, under the same code."""
    chars = docs.select(*keys, F.explode(F.split("text", "")).alias("c")).where("c <> ''")
    bits = measures.histogram_bits(chars, keys, "c").select(*keys, F.round(F.col("n") * F.col("bits"), 3).alias("input_bits"))
    return docs.groupBy(*keys).agg(F.count("text").alias("n_units"), F.sum(F.length("text")).alias("n")).join(bits, keys, "left")


def _input_sql(keys: str, rows: str) -> str:
    return f"""with d as ({rows}), c as (select {keys}, x, count(*)::double as k from (select {keys}, unnest(string_split(text, '')) as x from d) where x <> '' group by all), t as (select {keys}, sum(k) as all_k from c group by all),
b as (select {keys}, round(-sum(k * log2(k / all_k)), 3) as input_bits from c join t using ({keys}) group by all)
select {keys}, count(text)::bigint as n_units, sum(length(text))::bigint as n, any_value(input_bits) as input_bits from d join b using ({keys}) group by {keys}"""


@query("ratio_inputs_by_lang", _input_sql("lang", "select * from documents"))
def ratio_inputs_by_lang(spark: SparkSession, sf_dir: str) -> DataFrame:
    """What the ratios are taken of."""
    return input_bits(units_of(spark, sf_dir, "documents"), ["lang"])


@query("ratio_inputs_by_source", _input_sql("source", "select * from documents"))
def ratio_inputs_by_source(spark: SparkSession, sf_dir: str) -> DataFrame:
    return input_bits(units_of(spark, sf_dir, "documents"), ["source"])


@query("ratio_inputs_by_quality", _input_sql("quality, toxic", "select * from documents join labels using (doc_id)"))
def ratio_inputs_by_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    return input_bits(load_table(spark, sf_dir, "documents").join(load_table(spark, sf_dir, "labels"), "doc_id"), ["quality", "toxic"])


@query("ratio_by_lang")
def ratio_by_lang(spark: SparkSession, sf_dir: str) -> DataFrame:
    return ratios(units_of(spark, sf_dir, "documents"), ["lang"])


@query("ratio_by_source")
def ratio_by_source(spark: SparkSession, sf_dir: str) -> DataFrame:
    return ratios(units_of(spark, sf_dir, "documents"), ["source"])


@query("ratio_by_quality")
def ratio_by_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Texts are dealt out by id at any size of ``labels``, and not sorted: work is spread over all cores, and disk grows as the input."""
    labels = load_table(spark, sf_dir, "labels").hint("shuffle_hash")
    return ratios(load_table(spark, sf_dir, "documents").join(labels, "doc_id"), ["quality", "toxic"])


@query("unit_totals", "select lang, count(*)::bigint as n_units, sum(length(text))::bigint as n from documents group by lang")
def unit_totals(spark: SparkSession, sf_dir: str) -> DataFrame:
    return fold.sizes(fold.fold(units_of(spark, sf_dir, "documents"), ["doc_id", "lang"])).groupBy("lang").agg(F.count("*").alias("n_units"), F.sum("n").alias("n"))


@query("char_entropy_by_lang", """
with c as (select lang, x, count(*)::double as n from (select lang, unnest(string_split(text, '')) as x from documents) where x <> '' group by all), t as (select lang, sum(n) as n from c group by lang)
select lang, round(-sum(c.n / t.n * log2(c.n / t.n)), 6) as entropy from c join t using (lang) group by lang""")
def char_entropy_by_lang(spark: SparkSession, sf_dir: str) -> DataFrame:
    chars = units_of(spark, sf_dir, "documents").select("lang", F.explode(F.split("text", "")).alias("c")).where("c <> ''")
    return measures.histogram_bits(chars, ["lang"], "c").select("lang", F.round("bits", 6).alias("entropy"))


@query("fold_by_source")
def fold_by_source(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Repeats across the documents of a source: they are one unit."""
    return fold.fold_sizes(tables.grouped_texts(load_table(spark, sf_dir, "documents"), ["source"], ["doc_id"]), ["source"], "texts", ended=True)


@query("shared_repeats", """
select item_id, count(distinct doc_id)::bigint as docs from (select distinct item_id, substr(text, pos, 48) as x from (select item_id, text, unnest(range(1, length(text) - 46)) as pos from benchmark)) b
join (select distinct doc_id, substr(text, pos, 48) as x from (select doc_id, text, unnest(range(1, length(text) - 46)) as pos from documents)) d using (x) group by item_id""")
def shared_repeats(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Documents that share 48 symbols with an item of the reference set."""
    windows = lambda df, key: repeats.windows(df.select(key, "text"), [key], 48)
    items = windows(load_table(spark, sf_dir, "benchmark"), "item_id").distinct()
    return windows(units_of(spark, sf_dir, "documents"), "doc_id").join(F.broadcast(items), ["a", "b"]).groupBy("item_id").agg(F.countDistinct("doc_id").alias("docs"))


@query("exact_copies", "select md5(text) as text_md5, count(*)::bigint as n from documents group by 1 having count(*) > 1")
def exact_copies(spark: SparkSession, sf_dir: str) -> DataFrame:
    return load_table(spark, sf_dir, "documents").groupBy(F.md5(F.col("text").cast("binary")).alias("text_md5")).agg(F.count("*").alias("n")).where("n > 1")


@query("repeated_lines", "select doc_id, line, count(*)::bigint as n from (select doc_id, unnest(string_split(text, chr(10))) as line from documents) where line <> '' group by all having count(*) > 1")
def repeated_lines(spark: SparkSession, sf_dir: str) -> DataFrame:
    lines = load_table(spark, sf_dir, "documents").select("doc_id", F.explode(F.split("text", "\n")).alias("line")).where("line <> ''")
    return lines.groupBy("doc_id", "line").agg(F.count("*").alias("n")).where("n > 1")


@query("event_sequences", "select user_id, count(*)::bigint as n, string_agg(event_type, ' ' order by ts, event_id) as seq from events group by user_id")
def event_sequences(spark: SparkSession, sf_dir: str) -> DataFrame:
    e = tables.symbol_units(load_table(spark, sf_dir, "events"), ["user_id"], ["ts", "event_id"], "event_type")
    return e.select("user_id", F.size("symbols").cast("long").alias("n"), F.array_join("symbols", " ").alias("seq"))


@query("fold_event_sequences")
def fold_event_sequences(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _sized(tables.symbol_units(load_table(spark, sf_dir, "events"), ["user_id"], ["ts", "event_id"], "event_type"), ["user_id"], "symbols")


def _flags(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = load_table(spark, sf_dir, "lineitem").select("l_suppkey", "l_orderkey", "l_linenumber", F.concat("l_returnflag", "l_linestatus").alias("f"))
    return tables.symbol_units(rows, ["l_suppkey"], ["l_orderkey", "l_linenumber"], "f")


@query("flag_sequences", "select l_suppkey, count(*)::bigint as n, md5(string_agg(f, '' order by l_orderkey, l_linenumber, f)) as seq_md5 from (select *, l_returnflag || l_linestatus as f from lineitem) group by l_suppkey")
def flag_sequences(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _flags(spark, sf_dir).select("l_suppkey", F.size("symbols").cast("long").alias("n"), F.md5(F.array_join("symbols", "").cast("binary")).alias("seq_md5"))


@query("fold_flag_sequences")
def fold_flag_sequences(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _sized(_flags(spark, sf_dir), ["l_suppkey"], "symbols")


@query("flags_by_region")
def flags_by_region(spark: SparkSession, sf_dir: str) -> DataFrame:
    s = load_table(spark, sf_dir, "supplier").join(load_table(spark, sf_dir, "nation"), F.col("s_nationkey") == F.col("n_nationkey")).join(load_table(spark, sf_dir, "region"), F.col("n_regionkey") == F.col("r_regionkey"))
    f = fold_flag_sequences(spark, sf_dir).join(s, F.col("l_suppkey") == F.col("s_suppkey"))
    return f.groupBy("r_name").agg(F.count("*").alias("suppliers"), F.sum("n").alias("n"), F.sum("residual_len").alias("residual_len"))


@query("suffix_tree_nodes", """
with p as (select item_id, text, unnest(range(1, length(text) + 1)) as pos from benchmark),
s as (select item_id, substr(text, pos, l) as x, case when pos + l <= length(text) then substr(text, pos + l, 1) else '>' end as b from (select item_id, text, pos, unnest(range(1, length(text) - pos + 2)) as l from p)),
v as materialized (select item_id, x, count(distinct b)::bigint as children from s group by item_id, x having count(distinct b) > 1),
u as (select v.item_id, v.x, max(length(w.x)) as up from v join v w on w.item_id = v.item_id and length(w.x) < length(v.x) and starts_with(v.x, w.x) group by all),
l as (select v.item_id, v.x, w.x as link from v join v w on w.item_id = v.item_id and w.x = substr(v.x, 2))
select v.item_id, v.x as node, children, coalesce(u.up, 0)::bigint as parent_depth, coalesce(l.link, '') as link, coalesce(l.link, '') = substr(v.x, 2) as linked
from v left join u using (item_id, x) left join l using (item_id, x)""")
def suffix_tree_nodes(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every inner node but the root: the string it spells, its children, the depth of its parent and the string of its link."""
    items = load_table(spark, sf_dir, "benchmark")
    t = cut(repeats.suffix_tree(items, ["item_id"]))
    spelt = t.join(items, "item_id").select("item_id", "node", "parent", "slink", "depth", "leaf_id", F.when(F.col("leaf_id").isNull(), F.substring("text", (F.col("hi") - F.col("depth") + 1).cast("int"), F.col("depth"))).alias("x"))
    inner = spelt.where("leaf_id is null and parent >= 0")
    kids = t.groupBy("item_id", F.col("parent").alias("node")).agg(F.count("*").alias("children"))
    up = spelt.select("item_id", F.col("node").alias("parent"), F.col("depth").cast("long").alias("parent_depth"))
    link = spelt.select("item_id", F.col("node").alias("slink"), F.when(F.col("parent") < 0, "").otherwise(F.col("x")).alias("link"))
    out = inner.join(kids, ["item_id", "node"]).join(up, ["item_id", "parent"]).join(link, ["item_id", "slink"])
    return out.select("item_id", F.col("x").alias("node"), "children", "parent_depth", "link", (F.col("link") == F.expr("substring(x, 2)")).alias("linked"))


@query("corpus_fold_worked", _values([(4, 1, 4, 1), (4, 1, 12, 2), (3, 1, 8, 3), (3, 1, 17, 3)], "len, first, pos, kind"))
def corpus_fold_worked(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The worked example as relations of positions, in rounds over lengths."""
    from repeatfold.plans.corpus import fold_steps

    unit = spark.createDataFrame([(1, FIXTURES["worked"][0][:-1])], "unit long, text string")
    places = unit.select("unit", F.posexplode(F.split("text", ""))).select("unit", (F.col("pos") + 1).cast("long").alias("pos"), F.ascii("col").alias("code"))
    return fold_steps(places).select(F.col("len").cast("long").alias("len"), "first", "pos", F.col("kind").cast("long").alias("kind"))


@query("corpus_fold_suppliers", "select s_nationkey, sum(length(s_name) + 1)::bigint as n, 0::bigint as differing from supplier where s_name is not null group by s_nationkey")
def corpus_fold_suppliers(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Corpus mode on a table: the names of a nation's suppliers are one unit that is never gathered; replaced copies that the kernel's steps do not have, or only they."""
    from repeatfold.plans.corpus import fold_steps, grouped_positions

    rows = load_table(spark, sf_dir, "supplier")
    places, keys = grouped_positions(rows, ["s_nationkey"], ["s_suppkey"], "s_name")
    places = cut(places)
    found = fold_steps(places).join(keys, "unit").select("s_nationkey", "len", "first", "pos", "kind")
    steps = fold.fold(tables.grouped_units(rows, ["s_nationkey"], ["s_suppkey"], "s_name"), ["s_nationkey"], "codes", log=True)
    steps = steps.select("s_nationkey", "len", "first", F.inline(F.arrays_zip("picks", "pick_kinds")).alias("pos", "kind"))
    both = found.withColumn("side", F.lit(1)).unionByName(steps.select("s_nationkey", "len", "first", "pos", "kind").withColumn("side", F.lit(2)))
    differing = both.groupBy("s_nationkey", "len", "first", "pos", "kind").agg(F.sum("side").alias("sides")).where("sides <> 3").groupBy("s_nationkey").agg(F.count("*").alias("differing"))
    n = places.groupBy("unit").agg(F.count("*").alias("n")).join(keys, "unit")
    return n.join(differing, n["s_nationkey"].eqNullSafe(differing["s_nationkey"]), "left").select(n["s_nationkey"], "n", F.coalesce("differing", F.lit(0).cast("long")).alias("differing"))


def _checked(name: str, units: str, method=None, **options) -> None:
    """A query ``checked_<name>``: n, and whether the method's output gives back each unit of ``units``, adds up and is final."""
    make, ids, col, sql = UNITS[units]
    run = method or checks.folded

    def check(spark: SparkSession, sf_dir: str) -> DataFrame:
        return run(make(spark, sf_dir), ids, col, **options)

    query(f"checked_{name}", f"select {', '.join(ids)}, n::bigint as n, true as lossless, true as balanced, true as final from ({sql})")(check)


def _table(name: str):
    return lambda spark, sf_dir: units_of(spark, sf_dir, name)


#: Units by name: how to make them, their ids and symbols, and ids and sizes in SQL.
UNITS = {
    "documents": (_table("documents"), ["doc_id"], "text", "select doc_id, length(text) as n from documents where text is not null"),
    "pages": (_table("pages"), ["page_id"], "html", "select page_id, length(html) as n from pages where html is not null"),
    "benchmark": (_table("benchmark"), ["item_id"], "text", "select item_id, length(text) as n from benchmark"),
    "conversations": (lambda spark, sf_dir: tables.grouped_units(load_table(spark, sf_dir, "conversations"), ["conv_id"], ["turn"]), ["conv_id"], "codes", "select conv_id, sum(length(text) + 1) as n from conversations where text is not null group by conv_id"),
    "parts": (_part_units, ["p_brand"], "text", "select p_brand, sum(length(p_name) + 1) - 1 as n from part group by p_brand"),
    "customers": (lambda spark, sf_dir: _customer_units(spark, sf_dir), ["c_mktsegment"], "text", "select c_mktsegment, sum(length(c_name) + 1) - 1 as n from customer group by c_mktsegment"),
    "signs": (lambda spark, sf_dir: tables.sign_units(load_table(spark, sf_dir, "embeddings")), ["vec_id"], "text", "select vec_id, len(embedding) as n from embeddings"),
    "events": (lambda spark, sf_dir: tables.symbol_units(load_table(spark, sf_dir, "events"), ["user_id"], ["ts", "event_id"], "event_type"), ["user_id"], "symbols", "select user_id, count(event_type) as n from events group by user_id"),
    "flags": (lambda spark, sf_dir: _flags(spark, sf_dir), ["l_suppkey"], "symbols", "select l_suppkey, count(*) as n from lineitem group by l_suppkey"),
    "sources": (lambda spark, sf_dir: tables.grouped_texts(load_table(spark, sf_dir, "documents"), ["source"], ["doc_id"]), ["source"], "texts", "select source, sum(length(text) + 1) as n from documents where text is not null group by source"),
}

for _units in ("documents", "pages", "conversations", "parts", "customers", "signs", "events", "flags", "sources"):
    _checked(f"fold_{_units}", _units, **({"ended": True} if _units == "sources" else {}))
_checked("fold_tree_lex", "benchmark", engine="tree", tie="lex")
_checked("fold_tree_bucket", "benchmark", engine="tree", tie="bucket")
_checked("fold_tree_documents", "documents", engine="tree")
_checked("fold_min_len", "benchmark", min_len=4)
_checked("fold_simple_documents", "documents", mode="simple", order="ends_first")
_checked("fold_simple_scan", "documents", mode="simple", order="scan")
_checked("fold_simple_hash", "documents", mode="simple", order="hash")
_checked("fold_gated_documents", "documents", engine="gated")
_checked("lz77_documents", "documents", checks.factored)
_checked("lz77_noself_documents", "documents", checks.factored, self_ref=False)
_checked("grammar_longest_documents", "documents", checks.ruled)
_checked("grammar_bodies_benchmark", "benchmark", checks.ruled, build=longest_grammar_bodies, bodies=True)
_checked("grammar_pairs_documents", "documents", checks.ruled, build=pair_grammar, pairs_of_names=True)


def queries() -> dict[str, Query]:
    return dict(QUERIES)


def oracle_sql() -> dict[str, str]:
    return dict(SQL)
