"""Quality rules with adaptive thresholds from mergeable quantile sketches.

A sketch is a log-linear histogram of an integer feature: its buckets keep the leading bits of a value, so two sketches merge
by adding counts, and a quantile is exact to one part in 128.  Sketches are built per language and source, merged to
languages and to the whole, and give fences (third quartile, plus `FAR` times the distance of the quartiles, plus a slack, and
likewise below).  A group of fewer than `GROUP_ROWS` documents takes its language's fences, then those of the whole.  The
table of fences is joined to the documents, which stay if they lie within all of them and passed the base rules.

Null and empty texts have no words and fail the base rules.  A null language or source is a group like any other.  Repeated
rows are judged each.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from fieldseg.llm.textkernel import NOT_SPACE, blocks, cover, grams, per_doc
from fieldseg.runtime import cut

BASE = ("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words")
#: feature: (expression over the base counts, times 1000, and the slack beyond its fences)
FEATURES = {
    "length_of_words": ("word_chars * 1000 div greatest(n_words, 1)", 3000),
    "symbols_per_word": ("n_symbols * 1000 div greatest(n_words, 1)", 100),
    "dup_lines_per_word": ("n_dup_lines * 1000 div greatest(n_words, 1)", 20),
    "repeat_share": ("n_repeat_words * 1000 div greatest(n_words, 1)", 150),
}
FAR = 3
GROUP_ROWS = 100
#: Groups of fences that are broadcast; more are joined by shuffle.
BROADCAST_GROUPS = 100_000
WINDOW = 5
_SYMBOL = np.zeros(256, bool)
_SYMBOL[list(b"#*$%&|<>")] = True


def count_block(b) -> dict[str, np.ndarray]:
    """The base counts of each document of a block."""
    s, e, d = b.words(NOT_SPACE)
    sums = b.prefix(b.buf)
    points = np.concatenate([[0], np.cumsum((b.buf & 0xC0) != 0x80)])
    out = {"n_words": per_doc(d, b.n), "word_chars": per_doc(d, b.n, points[e] - points[s]).astype(np.int64)}
    out["n_symbols"] = per_doc(b.docs_of(np.flatnonzero(_SYMBOL[b.buf])), b.n)
    ls, le, ld = b.lines()
    filled = np.searchsorted(s, ls, "left") != np.searchsorted(s, le, "left")
    ls, le, ld = ls[filled], le[filled], ld[filled]
    key = b.hashes(sums, ls, le)
    order = np.lexsort((key, ld))
    same = np.concatenate([[False], (key[order][1:] == key[order][:-1]) & (ld[order][1:] == ld[order][:-1])]) if len(order) else np.zeros(0, bool)
    out["n_dup_lines"] = per_doc(ld[order][same], b.n)
    g, at = grams(b.hashes(sums, s, e), d, WINDOW)
    own = d[at]
    order = np.lexsort((g, own))
    same = (g[order][1:] == g[order][:-1]) & (own[order][1:] == own[order][:-1]) if len(order) else np.zeros(0, bool)
    twice = np.concatenate([same, [False]]) | np.concatenate([[False], same]) if len(order) else same
    out["n_repeat_words"] = per_doc(d[cover(at[order][twice], WINDOW, len(d))], b.n) if len(d) else np.zeros(b.n, np.int64)
    return out


def base_counts(docs: DataFrame, keep: list[str], text: str = "text") -> DataFrame:
    """The kept columns and the base counts of each row."""
    keep = [c for c in keep if c not in BASE]  # columns of the new names give way
    schema = [f for f in docs.select(*keep).schema.fields]

    def run(batches):
        for rb in batches:
            found = {c: [np.zeros(0, np.int64)] for c in BASE}
            for b in blocks(rb.column(len(keep))):
                for c, v in count_block(b).items():
                    found[c].append(v)
            yield pa.RecordBatch.from_arrays([*rb.columns[: len(keep)], *(pa.array(np.concatenate(v).astype(np.int64)) for v in found.values())], [*keep, *BASE])

    from pyspark.sql import types as T

    return docs.select(*keep, F.col(text).alias("_fs_text")).mapInArrow(run, T.StructType([*schema, *(T.StructField(c, T.LongType()) for c in BASE)]))


def base_failed() -> Column:
    return (F.col("n_words") < 10) | (100 * F.col("n_repeat_words") > 20 * F.col("n_words"))


def bucket_top(value: Column) -> Column:
    """The largest value of the sketch bucket of a value (64 buckets for each power of two)."""
    cut_bits = F.greatest(F.length(F.bin(value)) - 7, F.lit(0))
    return F.call_function("shiftleft", F.call_function("shiftright", value, cut_bits) + 1, cut_bits) - 1


def sketch(counts: DataFrame, group: list[str], features=None) -> DataFrame:
    """Sketches of all features: (group..., feature, top, n)."""
    features = FEATURES if features is None else features
    pairs = F.array(*(F.struct(F.lit(k).alias("feature"), F.expr(x).cast("long").alias("v")) for k, (x, _) in features.items()))
    long = counts.select(*group, F.explode(pairs).alias("p")).select(*group, "p.feature", bucket_top(F.col("p.v")).alias("top"))
    return long.groupBy(*group, "feature", "top").agg(F.count("*").alias("n"))


def merge_sketches(sketches: DataFrame, group: list[str]) -> DataFrame:
    return sketches.groupBy(*group, "feature", "top").agg(F.sum("n").alias("n"))


def fences(sketches: DataFrame, group: list[str], features=None) -> DataFrame:
    """(group..., feature, rows, low, high) from the quartiles of each sketch."""
    features = FEATURES if features is None else features
    own = Window.partitionBy(*group, "feature")
    run = sketches.withColumns({"rows": F.sum("n").over(own), "upto": F.sum("n").over(own.orderBy("top"))})
    quartile = lambda q: F.min(F.when(F.col("upto") * 4 >= F.col("rows") * q, F.col("top")))
    table = run.groupBy(*group, "feature").agg(F.max("rows").alias("rows"), quartile(1).alias("q1"), quartile(3).alias("q3"))
    slack = F.create_map(*(F.lit(x) for k, (_, s) in features.items() for x in (k, s)))[F.col("feature")]
    far = FAR * (F.col("q3") - F.col("q1")) + slack
    return table.select(*group, "feature", "rows", (F.col("q1") - far).alias("low"), (F.col("q3") + far).alias("high"))


def adaptive_fences(counts: DataFrame, lang: str = "lang", source: str = "source", group_rows: int = GROUP_ROWS, features=None) -> DataFrame:
    """(lang, source, fences map<feature, struct<low, high>>): one row for each pair that occurs."""
    fine = cut(sketch(counts.where(~base_failed()), [lang, source], features))
    by_lang = merge_sketches(fine, [lang])
    total = merge_sketches(by_lang, [])
    f2, f1, f0 = fences(fine, [lang, source], features), fences(by_lang, [lang], features), fences(total, [], features)
    r = lambda df, p: df.select(*(F.col(c).alias(p + c) for c in df.columns))
    both = r(f2, "").join(r(f1, "l_"), F.col(lang).eqNullSafe(F.col("l_" + lang)) & (F.col("feature") == F.col("l_feature"))).join(F.broadcast(r(f0, "t_")), F.col("feature") == F.col("t_feature"))
    pick = lambda c: F.when(F.col("rows") >= group_rows, F.col(c)).when(F.col("l_rows") >= group_rows, F.col("l_" + c)).otherwise(F.col("t_" + c))
    chosen = both.select(lang, source, "feature", pick("low").alias("low"), pick("high").alias("high"))
    return chosen.groupBy(lang, source).agg(F.map_from_entries(F.collect_list(F.struct("feature", F.struct("low", "high").alias("f")))).alias("fences"))


def judge(counts: DataFrame, lang: str = "lang", source: str = "source", features=None, **options) -> DataFrame:
    """`counts` (base counts with language and source) with `base_failed` and `kept`."""
    features = FEATURES if features is None else features
    table = cut(adaptive_fences(counts, lang, source, features=features, **options).select(F.col(lang).alias("_fs_lang"), F.col(source).alias("_fs_source"), "fences"))
    table = F.broadcast(table) if table.count() <= BROADCAST_GROUPS else table
    joined = counts.join(table, F.col(lang).eqNullSafe(F.col("_fs_lang")) & F.col(source).eqNullSafe(F.col("_fs_source")), "left")
    inside = F.lit(True)
    for k, (x, _) in features.items():
        f = F.col("fences")[k]
        inside &= F.coalesce(F.expr(x).between(f["low"], f["high"]), F.lit(True))
    return joined.withColumn("base_failed", base_failed()).withColumn("kept", ~F.col("base_failed") & inside).drop("_fs_lang", "_fs_source", "fences")


def op5(spark, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    return judge(cut(base_counts(docs, ["doc_id", "lang", "source"]))).select("doc_id", *BASE, "base_failed", "kept")


_F = {k: x.replace(" div ", " // ") for k, (x, _) in FEATURES.items()}
_SLACK = " ".join(f"when '{k}' then {s}" for k, (_, s) in FEATURES.items())
_INSIDE = " and ".join(f"coalesce({x} between {k}_low and {k}_high, true)" for k, x in _F.items())


def _fences_sql(group: str) -> str:
    by = f"{group}, " if group else ""
    part = f"partition by {by}feature"
    return f"""(select {by}feature, any_value(rows) as rows,
      min(top) filter (where upto * 4 >= rows) - ({FAR} * (min(top) filter (where upto * 4 >= rows * 3) - min(top) filter (where upto * 4 >= rows)) + any_value(slack)) as low,
      min(top) filter (where upto * 4 >= rows * 3) + ({FAR} * (min(top) filter (where upto * 4 >= rows * 3) - min(top) filter (where upto * 4 >= rows)) + any_value(slack)) as high
      from (select *, sum(n) over ({part}) as rows, sum(n) over ({part} order by top) as upto, case feature {_SLACK} end as slack from (select {by}feature, top, sum(n) as n from sk group by {by}feature, top)) group by {by}feature)"""


OP5_SQL = rf"""
with d as (select row_number() over () as r, doc_id, lang, source, coalesce(text, '') as text, regexp_extract_all(coalesce(text, ''), '[^ 	-
]+') as w from documents),
l as (select r, line, row_number() over (partition by r, line order by i) as nth from (select r, unnest(string_split(text, chr(10))) as line, generate_subscripts(string_split(text, chr(10)), 1) as i from d) where regexp_matches(line, '[^ 	-
]')),
dl as (select r, count(*) as n from l where nth > 1 group by r),
g as (select r, i, count(*) over (partition by r, g) as n from (select r, i, list_slice(w, i, i + 4) as g from (select r, w, unnest(range(1, cast(len(w) as bigint) - 3)) as i from d where len(w) >= 5))),
rp as (select r, count(distinct p) as n from (select r, unnest(range(i, i + 5)) as p from g where n > 1) group by r),
c as (
  select d.r, doc_id, lang, source, cast(len(w) as bigint) as n_words, cast(length(array_to_string(w, '')) as bigint) as word_chars,
    cast(length(text) - length(regexp_replace(text, '[#*$%&|<>]', '', 'g')) as bigint) as n_symbols, coalesce(dl.n, 0) as n_dup_lines, coalesce(rp.n, 0) as n_repeat_words
  from d left join dl using (r) left join rp using (r)),
b as materialized (select *, n_words < 10 or 100 * n_repeat_words > 20 * n_words as base_failed from c),
v as ({" union all ".join(f"select lang, source, '{k}' as feature, cast({x} as bigint) as v from b where not base_failed" for k, x in _F.items())}),
sk as materialized (select lang, source, feature, ((((v >> greatest(length(bin(v)) - 7, 0)) + 1) << greatest(length(bin(v)) - 7, 0)) - 1) as top, count(*) as n from v group by all),
f2 as {_fences_sql("lang, source")}, f1 as {_fences_sql("lang")}, f0 as {_fences_sql("")},
f as (select f2.lang, f2.source, f2.feature,
    case when f2.rows >= {GROUP_ROWS} then f2.low when f1.rows >= {GROUP_ROWS} then f1.low else f0.low end as low,
    case when f2.rows >= {GROUP_ROWS} then f2.high when f1.rows >= {GROUP_ROWS} then f1.high else f0.high end as high
  from f2 join f1 on f1.lang is not distinct from f2.lang and f1.feature = f2.feature join f0 on f0.feature = f2.feature),
p as (select lang, source, {", ".join(f"min(low) filter (where feature = '{k}') as {k}_low, min(high) filter (where feature = '{k}') as {k}_high" for k in FEATURES)} from f group by lang, source)
select doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, base_failed, not base_failed and {_INSIDE} as kept
from b left join p on p.lang is not distinct from b.lang and p.source is not distinct from b.source
"""
