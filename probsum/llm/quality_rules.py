"""Quality rules whose cutoffs carry a guarantee on false rejections.

Every (stratum, rule, cutoff) is tested on labelled good documents: with k of n rejected, the exact
binomial tail P(X <= k), X ~ Bin(n, limit), is the p-value of "this cutoff rejects more than the limit". Holm's step-down
procedure over all tests keeps the chance of certifying any bad cutoff under `delta`. The limit of a stratum is
shared equally among the rules, so that a document rejected by any of them still counts once within `alpha`.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from probsum.llm.common import BLANKS, written

#: rule: (measure over the counted columns, candidate cutoffs; a document fails above the cutoff)
RULES: dict[str, tuple[str, tuple[float, ...]]] = {
    "long_words": ("word_chars / n_words", (7.0, 8.0, 9.0, 10.0, 12.0, 15.0)),
    "symbols": ("n_symbols / n_words", (0.05, 0.1, 0.2, 0.5, 1.0, 2.0)),
    "dup_lines": ("n_dup_lines / n_words", (0.005, 0.01, 0.02, 0.04, 0.08)),
    "repeats": ("n_repeat_words / n_words", (0.05, 0.1, 0.2, 0.3, 0.4)),
}


def counted(docs: DataFrame, text_col: str = "text") -> DataFrame:
    """`docs` with n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words (long) of the whole text.

    A null text counts as one without words. Three-word windows are compared by 64-bit hashes.
    Columns of `docs` under these names are replaced.
    """
    keep = [c for c in docs.columns if c not in COUNTS]
    a = docs.select(*keep, F.coalesce(F.col(text_col), F.lit("")).alias("_t")).withColumn(
        "_w", F.array_remove(F.split("_t", BLANKS), "")
    )
    b = a.select(
        *keep,
        "_t",
        "_w",
        F.size("_w").cast("long").alias("n_words"),
        F.char_length(F.array_join("_w", "")).cast("long").alias("word_chars"),
        (F.char_length("_t") - F.char_length(F.regexp_replace("_t", "[#*$%&|<>]", "")))
        .cast("long")
        .alias("n_symbols"),
        F.expr("filter(split(_t, '\\n'), l -> l rlike '[^\\\\x20\\\\x09-\\\\x0D]')").alias("_l"),
        F.expr(
            "if(size(_w) < 3, cast(array() as array<bigint>),"
            " zip_with(zip_with(_w, slice(_w, 2, size(_w)), (x, y) -> xxhash64(x, y)), slice(_w, 3, size(_w)),"
            " (x, y) -> if(y is null, cast(null as bigint), xxhash64(x, y))))"
        ).alias("_g"),
    )
    c = b.select(
        *keep,
        "n_words",
        "word_chars",
        "n_symbols",
        (F.size("_l") - F.size(F.array_distinct("_l"))).cast("long").alias("n_dup_lines"),
        # the last two entries have no full window
        F.expr("slice(_g, 1, greatest(size(_g) - 2, 0))").alias("_g"),
    )
    d = c.withColumn(
        "_s",
        F.expr(
            "if(size(_g) > size(array_distinct(_g)),"
            " sort_array(transform(_g, (h, i) -> struct(h, i))), cast(array() as array<struct<h: bigint, i: int>>))"
        ),
    )
    e = d.withColumn(
        "_p",
        F.expr(
            "array_sort(array_distinct(flatten(filter(zip_with(_s, slice(_s, 2, size(_s)), (x, y) ->"
            " if(x.h = y.h, array(x.i, y.i), cast(null as array<int>))), q -> q is not null))))"
        ),
    )
    covered = F.expr(
        "aggregate(_p, struct(0L as n, 0 as upto),"
        " (s, p) -> struct(s.n + p + 3 - greatest(p, s.upto) as n, p + 3 as upto), s -> s.n)"
    )
    return e.select(*keep, *COUNTS[:4], covered.cast("long").alias("n_repeat_words"))


COUNTS = ["n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words"]

#: The fixed base rules, ahead of the calibrated ones.
BASE_FAILED = "n_words < 50 or 100 * n_repeat_words > 50 * n_words"


def binomial_tail(n: str, k: str, limit: float) -> str:
    """SQL for P(X <= k), X ~ Bin(n, limit); 1 where k is at or above the mean, which certifies nothing."""
    odds = f"ln({limit!r}D / (1 - {limit!r}D))"
    return (
        f"case when {n} = 0 or {k} >= {n} * {limit!r}D then 1D else least(1D, exp(aggregate("
        f"if({k} = 0, cast(array() as array<bigint>), sequence(1L, {k})),"
        f" struct({n} * ln(1 - {limit!r}D) as t, {n} * ln(1 - {limit!r}D) as s),"
        f" (z, i) -> struct(z.t + ln(({n} - i + 1) / i) + {odds} as t,"
        f" greatest(z.s, z.t + ln(({n} - i + 1) / i) + {odds})"
        f" + ln1p_exp(0D) as s), z -> z.s))) end"
    ).replace(
        " + ln1p_exp(0D)",
        f" + log1p(exp(-abs(z.s - (z.t + ln(({n} - i + 1) / i) + {odds}))))",
    )


def certified_cutoffs(
    labelled: DataFrame, stratum: str, good: str, alpha: float = 0.02, delta: float = 0.05, rules=RULES
) -> DataFrame:
    """(stratum, rule, cutoff, n_good, n_lost, n_bad, p_value) of the cutoffs that are chosen.

    `labelled` has the counted columns; `good` is a boolean SQL expression. Of the certified
    cutoffs of a stratum and rule the one that catches most bad documents stands, ties going to the highest.
    The tests number (strata x cutoffs) whatever the input's size; a null stratum is one of its own. No labels give no row.
    """
    limit = alpha / len(rules)
    tests = F.array(
        *[
            F.struct(
                F.lit(name).alias("rule"),
                F.lit(float(c)).alias("cutoff"),
                F.expr(f"coalesce({measure} > {c!r}D, false)").alias("fails"),
            )
            for name, (measure, cutoffs) in rules.items()
            for c in cutoffs
        ]
    )
    scored = (
        labelled.where("n_words > 0")
        .select(F.col(stratum).cast("string").alias("stratum"), F.expr(good).alias("good"), F.explode(tests).alias("t"))
        .groupBy("stratum", "t.rule", "t.cutoff")
        .agg(
            F.count_if("good").alias("n_good"),
            F.count_if(F.expr("good and t.fails")).alias("n_lost"),
            F.count_if(F.expr("not good and t.fails")).alias("n_bad"),
        )
        .withColumn("p_value", F.expr(binomial_tail("n_good", "n_lost", limit)))
    )
    # Holm: in order of p-value the i-th test may use delta / (tests left); the first failure ends it
    ranked = scored.selectExpr(
        "*",
        "row_number() over (order by p_value, stratum, rule, cutoff) as i",
        "count(*) over () as m",
    ).selectExpr(
        "*",
        f"min(cast(p_value <= {delta!r}D / (m - i + 1) as int)) over"
        " (order by i rows between unbounded preceding and current row) as sure",
    )
    return (
        ranked.where("sure = 1 and n_bad > 0")
        .selectExpr(
            "*",
            "row_number() over (partition by stratum, rule order by n_bad desc, cutoff desc) as best",
        )
        .where("best = 1")
        .select("stratum", "rule", "cutoff", "n_good", "n_lost", "n_bad", "p_value")
    )


def judged(
    docs: DataFrame,
    labels: DataFrame,
    id_col: str = "doc_id",
    text_col: str = "text",
    stratum: str = "lang",
    alpha: float = 0.02,
    delta: float = 0.05,
) -> DataFrame:
    """One row per document: the counts, base_failed, failed_rules (array) and kept.

    `labels` gives (id, quality); of repeated labels the least counts. A document is
    dropped by the base rules or by a certified cutoff of its stratum.
    """
    stats = written(
        counted(
            docs.select(
                F.col(id_col).alias("doc_id"),
                F.col(stratum).cast("string").alias("stratum"),
                F.col(text_col).alias("text"),
            )
        ).drop("text"),
        "quality-counts",
    ).withColumn("base_failed", F.expr(BASE_FAILED))
    quality = labels.groupBy(F.col(id_col).alias("doc_id")).agg(F.min("quality").alias("quality")).where(
        "quality is not null"
    )
    cutoffs = certified_cutoffs(
        stats.where("not base_failed").join(quality, "doc_id"), "stratum", "quality = 1", alpha, delta
    )
    # at most one row per stratum, written so that Spark knows its size before it joins
    table = written(
        cutoffs.groupBy("stratum").agg(F.map_from_entries(F.collect_list(F.struct("rule", "cutoff"))).alias("cut")),
        "cutoffs",
    ).withColumnRenamed("stratum", "_stratum")
    failed = F.array_compact(
        F.array(
            *[
                F.when(F.expr(f"n_words > 0 and {measure} > cut['{name}']"), F.lit(name))
                for name, (measure, _) in RULES.items()
            ]
        )
    )
    out = stats.join(table, F.expr("stratum <=> _stratum"), "left").withColumn(
        "failed_rules", F.coalesce(failed, F.array().cast("array<string>"))
    )
    return out.select(
        "doc_id",
        *COUNTS,
        "base_failed",
        "failed_rules",
        (~F.col("base_failed") & (F.size("failed_rules") == 0)).alias("kept"),
    )


def oracle(alpha: float = 0.02, delta: float = 0.05) -> str:
    """DuckDB SQL of the same rows."""
    limit = alpha / len(RULES)
    tests = " union all ".join(
        f"select '{name}' as rule, {c!r}::double as cutoff" for name, (_, cs) in RULES.items() for c in cs
    )
    measure = "case rule " + " ".join(f"when '{name}' then {m}" for name, (m, _) in RULES.items()) + " end"
    return f"""
with a as (select doc_id, lang as stratum, coalesce(text, '') as t from documents),
w as (select *, list_filter(string_split_regex(t, '[\\x20\\x09-\\x0D]+'), lambda x: x <> '') as w,
  list_filter(string_split(t, chr(10)), lambda x: regexp_matches(x, '[^\\x20\\x09-\\x0D]')) as l from a),
g as (select doc_id, i, w[i] || ' ' || w[i + 1] || ' ' || w[i + 2] as g
  from (select doc_id, w, unnest(range(1, len(w) - 1)) as i from w)),
r as (select doc_id, i from g qualify count(*) over (partition by doc_id, g) > 1),
v as (select doc_id, count(distinct p) as n from (select doc_id, unnest([i, i + 1, i + 2]) as p from r) group by 1),
s as (select doc_id, stratum, len(w) as n_words, coalesce(list_sum(list_transform(w, lambda x: length(x))), 0)::bigint as word_chars,
  length(t) - length(regexp_replace(t, '[#*$%&|<>]', '', 'g')) as n_symbols,
  len(l) - len(list_distinct(l)) as n_dup_lines, coalesce(n, 0) as n_repeat_words from w left join v using (doc_id)),
b as (select *, n_words < 50 or 100 * n_repeat_words > 50 * n_words as base_failed from s),
q as (select doc_id, min(quality) as quality from labels group by 1 having min(quality) is not null),
x as (select stratum, rule, cutoff, count(*) filter (quality = 1) as n, count(*) filter (quality = 1 and {measure} > cutoff) as k,
  count(*) filter (quality <> 1 and {measure} > cutoff) as bad
  from b join q using (doc_id), ({tests}) where not base_failed and n_words > 0 group by all),
p as (select *, case when n = 0 or k >= n * {limit!r}::double then 1 else least(1, list_sum(list_transform(range(0, k + 1),
  lambda i: exp(lgamma(n + 1) - lgamma(i + 1) - lgamma(n - i + 1) + i * ln({limit!r}::double) + (n - i) * ln(1 - {limit!r}::double))))) end as p_value from x),
o as (select *, row_number() over (order by p_value, stratum nulls first, rule, cutoff) as i, count(*) over () as m from p),
h as (select *, min((p_value <= {delta!r}::double / (m - i + 1))::int) over (order by i) as sure from o),
c as (select * from h where sure = 1 and bad > 0
  qualify row_number() over (partition by stratum, rule order by bad desc, cutoff desc) = 1),
f as (select doc_id from b join c on b.stratum is not distinct from c.stratum and n_words > 0 and {measure} > cutoff group by 1)
select doc_id, n_words::bigint as n_words, word_chars, n_symbols::bigint as n_symbols, n_dup_lines::bigint as n_dup_lines,
  n_repeat_words::bigint as n_repeat_words, base_failed, not base_failed and f.doc_id is null as kept
from b left join f using (doc_id)"""
