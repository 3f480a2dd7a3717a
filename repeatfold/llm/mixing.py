"""Mixing to target weights by iterative proportional fitting.

Token counts are summed by (source, language, topic); categories without a target meet in ``other``, so the table of cells is bounded by
the target lists, whatever the corpus. The cells are raked to the three marginals in turn; ``keep`` times its cell's factor is a document's
rate. A hash of its id, as a number in [0, 1), settles the fraction: the sample holds the whole part of the rate as copies of the document, and
one more with the fraction as its probability. Expected copies are the rate, so scarce cells reach their targets by repeats and nothing is cut
off; with ``keep`` at most 1 / the largest factor no document is repeated and the rate is a plain probability.

Null text: no tokens. Null category: ``other``. ``other`` keeps its observed share. A target of a category that does not occur cannot be met:
its share goes to the others, or with ``strict`` it is an error, as are marginals that raking does not reach (cells that exist may contradict
each other). ``marginals`` tells wanted, expected and reached shares. Repeated rows share their fate; a null id counts as an empty one. Columns
of the input named like the results are replaced, others never clash; an empty table gives no rows.
"""

from __future__ import annotations

import math
from collections.abc import Mapping

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from repeatfold.llm.common import fresh

#: Cells reach the driver; their number is at most the product of the target lists.
MAX_CELLS = 100_000
ROUNDS = 20
#: Difference from a wanted share that counts as met.
CLOSE = 0.005

LANG = {"en": 0.4, "de": 0.2, "fr": 0.2, "es": 0.2}
TOPIC = {"prose": 0.7, "contact": 0.15, "legal": 0.15}
SOURCE = {f"src{i}": (0.24 if i == 0 else 0.04) for i in range(20)}


def n_words(text: Column) -> Column:
    return F.coalesce(F.regexp_count(text, F.lit(r"[^ \t-\r]+")), F.lit(0)).cast("long")


def topic_of(text: Column) -> Column:
    """A coarse topic over the whole text: licence or rights talk, contact data, else prose."""
    t = F.translate(text, "LICENSRGHTV", "licensrghtv")
    return F.when(t.contains("license") | t.contains("rights reserved"), "legal").when(text.contains("@"), "contact").otherwise("prose")


def _bucket(col: Column, targets: Mapping[str, float]) -> Column:
    return F.when(col.isin(*targets), col).otherwise(F.lit("other"))


def draw(id_: Column) -> Column:
    """A number in [0, 1) from an id."""
    return F.conv(F.substring(F.md5(F.coalesce(id_.cast("string"), F.lit(""))), 1, 8), 16, 10).cast("double") / F.lit(4294967296.0)


def goals_of(cells: list[tuple[str, str, str, int]], targets: list[Mapping[str, float]]) -> list[dict[str, float]]:
    """Wanted share of each category that occurs, for each dimension."""
    total = float(sum(c[3] for c in cells))
    goals = []
    for d, want in enumerate(targets):
        seen: dict[str, float] = {}
        for c in cells:
            if c[3]:
                seen[c[d]] = seen.get(c[d], 0.0) + c[3]
        rest = seen.get("other", 0.0) / total if seen else 0.0
        live = math.fsum(want[k] for k in seen if k in want)
        goals.append({k: rest if k == "other" else (1 - rest) * want[k] / live for k in seen})
    return goals


def rake(cells: list[tuple[str, str, str, int]], targets: list[Mapping[str, float]], rounds: int = ROUNDS) -> dict[tuple[str, str, str], float]:
    """Factor of each cell after ``rounds`` passes over the marginals; factors average 1 over the tokens."""
    total = float(sum(c[3] for c in cells))
    weight = {tuple(c[:3]): float(c[3]) for c in cells if c[3]}
    if not total:
        return {}
    goals = [{k: x * total for k, x in g.items()} for g in goals_of(cells, targets)]
    now = dict(weight)
    for _ in range(rounds):
        for d, goal in enumerate(goals):
            have: dict[str, float] = {}
            for c, w in now.items():
                have[c[d]] = have.get(c[d], 0.0) + w
            now = {c: w * goal[c[d]] / have[c[d]] if have[c[d]] else 0.0 for c, w in now.items()}
    return {c: now[c] / weight[c] for c in weight}


def unmet(cells: list[tuple[str, str, str, int]], targets: list[Mapping[str, float]], factor: Mapping[tuple[str, str, str], float]) -> list[str]:
    """Targets that raked cells miss by more than ``CLOSE``: of categories that do not occur, or in contradiction to each other."""
    out, total = [], float(sum(c[3] for c in cells))
    for d, (want, goal) in enumerate(zip(targets, goals_of(cells, targets) if total else [{}] * 3, strict=True)):
        out += [f"{k}: does not occur" for k in want if want[k] and k not in goal]
        for k, share in goal.items():
            got = math.fsum(c[3] * factor.get(tuple(c[:3]), 0.0) for c in cells if c[d] == k) / total
            if abs(got - share) > CLOSE:
                out.append(f"{k}: {got:.4f} instead of {share:.4f}")
    return out


def calibrate(
    docs: DataFrame, source: Mapping[str, float] = SOURCE, lang: Mapping[str, float] = LANG, topic: Mapping[str, float] = TOPIC, keep: float = 0.5, rounds: int = ROUNDS, id_col: str = "doc_id", text_col: str = "text", source_col: str = "source", lang_col: str = "lang", strict: bool = False
) -> DataFrame:
    """``docs`` with ``n_tokens, rate, copies`` for every row (columns of these names are replaced). With ``strict`` unmet targets raise."""
    if (len(source) + 1) * (len(lang) + 1) * (len(topic) + 1) > MAX_CELLS:
        raise ValueError(f"target lists make more than {MAX_CELLS} cells")
    text = F.col(text_col)
    key = [_bucket(F.col(source_col), source), _bucket(F.col(lang_col), lang), _bucket(topic_of(text), topic)]
    found = docs.select(*(k.alias(n) for k, n in zip(key, "slt", strict=True)), n_words(text).alias("n")).groupBy("s", "l", "t").agg(F.sum("n").alias("n")).collect()
    cells = sorted((r["s"], r["l"], r["t"], r["n"]) for r in found)
    factor = rake(cells, [source, lang, topic], rounds)
    if strict and (missed := unmet(cells, [source, lang, topic], factor)):
        raise ValueError("targets that cannot be met: " + "; ".join(missed))
    rate = F.lit(0.0)
    if factor:
        lookup = F.create_map(*[x for c, f in factor.items() for x in (F.lit("\t".join(c)), F.lit(keep * f))])
        rate = F.coalesce(F.try_element_at(lookup, F.concat_ws("\t", *key)), F.lit(0.0))
    out = docs.withColumns({"n_tokens": n_words(text), "rate": rate})
    whole = F.floor("rate")
    return out.withColumn("copies", whole + (draw(F.col(id_col)) < F.col("rate") - whole).cast("long"))


def sample(calibrated: DataFrame) -> DataFrame:
    """Rows of ``calibrate``, each as often as it has copies. No filter before: pushed down, it would work out the rates, and read the texts, once more."""
    (k,) = fresh(calibrated, "_k")
    return calibrated.withColumn(k, F.explode(F.array_repeat(F.lit(1), F.col("copies").cast("int")))).drop(k)


def marginals(calibrated: DataFrame, source: Mapping[str, float] = SOURCE, lang: Mapping[str, float] = LANG, topic: Mapping[str, float] = TOPIC, text_col: str = "text", source_col: str = "source", lang_col: str = "lang") -> DataFrame:
    """``dimension, category, wanted, expected, reached``: token shares of rows of ``calibrate``. A target whose category does not occur has null shares."""
    names, lists = ("source", "lang", "topic"), (source, lang, topic)
    key = [_bucket(c, m).alias(n) for c, m, n in zip((F.col(source_col), F.col(lang_col), topic_of(F.col(text_col))), lists, names, strict=True)]
    n = F.col("n_tokens")
    cells = calibrated.select(*key, n, (n * F.col("rate")).alias("e"), (n * F.col("copies")).alias("r")).groupBy(*names).agg(F.sum("n_tokens").alias("n"), F.sum("e").alias("e"), F.sum("r").alias("r")).collect()
    goals = goals_of([(*(c[x] for x in names), c["n"]) for c in cells], list(lists))
    all_e, all_r, rows = math.fsum(c["e"] for c in cells), sum(c["r"] for c in cells), []
    for name, goal, want in zip(names, goals, lists, strict=True):
        for k in sorted({*goal, *want}):
            mine = [c for c in cells if c[name] == k]
            share = lambda x, total, mine=mine: float(sum(c[x] for c in mine)) / total if mine and total else None
            rows.append((name, k, goal.get(k), share("e", all_e), share("r", all_r)))
    return calibrated.sparkSession.createDataFrame(rows, "dimension string, category string, wanted double, expected double, reached double")


def calibrate_sql(keep: float = 0.5, rounds: int = ROUNDS, table: str = "documents") -> str:
    """Rates and copies as one DuckDB statement: one factor for each category of each dimension, refitted in turn; a cell's weight is their product."""
    dims = [("s", "source", SOURCE), ("l", "lang", LANG), ("t", "topic", TOPIC)]
    low = "translate(text, 'LICENSRGHTV', 'licensrghtv')"
    own = {"s": "source", "l": "lang", "t": f"case when contains({low}, 'license') or contains({low}, 'rights reserved') then 'legal' when contains(text, '@') then 'contact' else 'prose' end"}
    parts = [f"want(d, k, x) as (values {', '.join(f'({d!r}, {k!r}, {x!r}::double)' for d, _, m in dims for k, x in m.items())})"]
    named = ", ".join(f"coalesce((select k from want where d = '{d}' and k = {own[d]}), 'other') as {d}" for d, _, _ in dims)
    parts.append(f"e as materialized (select doc_id, coalesce(len(regexp_extract_all(text, '[^ \\t-\\r]+')), 0)::bigint as n, {named} from {table})")
    parts.append("cells as materialized (select s, l, t, sum(n)::double as w from e group by all having sum(n) > 0)")
    parts.append("seen as (" + " union all ".join(f"select '{d}' as d, {d} as k, sum(w) / (select sum(w) from cells) as share from cells group by {d}" for d, _, _ in dims) + ")")
    parts.append(
        """goal as materialized (select d, k, case when k = 'other' then share else (1 - coalesce((select o.share from seen o where o.d = seen.d and o.k = 'other'), 0)) * x
 / (select sum(w.x) from want w join seen z using (d, k) where w.d = seen.d) end * (select sum(w) from cells) as g from seen left join want using (d, k))"""
    )
    parts.append("f0 as (select d, k, 1::double as f from goal)")
    turn = 0
    for _ in range(rounds):
        for d, _, _ in dims:
            others = " ".join(f"join f{turn} f{o} on f{o}.d = '{o}' and f{o}.k = c.{o}" for o, _, _ in dims if o != d)
            product = " * ".join(f"f{o}.f" for o, _, _ in dims if o != d)
            parts.append(f"f{turn + 1} as materialized (select d, k, f from f{turn} where d <> '{d}' union all select '{d}', c.{d}, any_value(goal.g) / sum(c.w * {product}) from cells c {others} join goal on goal.d = '{d}' and goal.k = c.{d} group by c.{d})")
            turn += 1
    fits = " ".join(f"left join f{turn} f{d} on f{d}.d = '{d}' and f{d}.k = e.{d}" for d, _, _ in dims)
    return f"""with {', '.join(parts)},
r as (select doc_id, n, coalesce({keep} * fs.f * fl.f * ft.f * (exists (select 1 from cells c where c.s = e.s and c.l = e.l and c.t = e.t))::int, 0) as rate, ('0x' || substr(md5(coalesce(doc_id::varchar, '')), 1, 8))::ubigint::double / 4294967296.0 as u from e {fits})
select doc_id, n as n_tokens, round(rate, 6) as rate, (floor(rate) + (u < rate - floor(rate))::int)::bigint as copies from r"""
