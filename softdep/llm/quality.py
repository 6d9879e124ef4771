"""Quality rules with risk-controlled cutoffs (built-in functions only).

A rule rejects a document when one of its rates exceeds a cutoff. The cutoffs of a rule form a fixed grid from
lenient to strict, set before any label is seen. Within a stratum (language) the labelled good documents are a
holdout: for each cutoff the number k of them that the rule would reject out of n gives the exact binomial p-value
P(Bin(n, alpha_rule) <= k) of the hypothesis "the rule rejects alpha_rule or more of the good documents". The grid is
walked from lenient to strict and stops at the first p-value above delta / (strata x rules): fixed-sequence testing
inside a rule, Bonferroni across rules and strata. alpha_rule = alpha / rules, so with probability 1 - delta no stratum
loses more than a share alpha of its good documents to all rules together.

Edge cases. A null or blank text has no words: all counts 0, base_failed. A null or odd language belongs to the stratum
"other", so that there are at most 26^2 + 26^3 + 1 strata and the cutoff table is safe to broadcast. A stratum with too
few labels to certify any cutoff rejects nothing. Null labels are ignored; conflicting labels of one id count as good.
Repeated rows are each judged; rows of equal rates are judged alike, and a rate equal to its cutoff passes. Very long texts
are counted whole, in the memory of their row. Columns of the input that carry an output's name are replaced; empty tables
give no rows and no cutoffs.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

BLANKS = r"[\\x20\\x09-\\x0D]+"
SYMBOLS = "#*$%&|<>"

#: Cutoffs from lenient to strict, for each rule's rate.
GRIDS = {
    "symbol_rate": (3.0, 2.0, 1.5, 1.0, 0.8, 0.6, 0.4, 0.3, 0.2, 0.15, 0.1, 0.05),
    "dup_line_rate": (0.9, 0.8, 0.7, 0.6, 0.5, 0.4, 0.3, 0.25, 0.2, 0.15, 0.1, 0.05),
    "repeat_rate": (0.18, 0.15, 0.12, 0.1, 0.08, 0.06, 0.04, 0.03, 0.02, 0.01),
    "upper_rate": (0.9, 0.8, 0.7, 0.6, 0.5, 0.4, 0.3, 0.25, 0.2, 0.15, 0.1),
}
BASE = ("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words")


def _bound(value: str, name: str, body: str) -> str:
    """body with name standing for value, which is computed once."""
    return f"transform(array({value}), {name} -> {body})[0]"


def _repeated(words: str) -> str:
    """Number of words inside 5-word windows that occur twice or more. Windows are compared by 64-bit hashes."""
    hashes = _bound(
        f"transform({words}, x -> xxhash64(x))",
        "wh",
        "transform(sequence(0, size(wh) - 5), i -> xxhash64(wh[i], wh[i + 1], wh[i + 2], wh[i + 3], wh[i + 4]))",
    )
    places = """array_sort(filter(transform(s, (x, k) -> if(coalesce(get(s, k - 1).h = x.h, false)
        or coalesce(get(s, k + 1).h = x.h, false), x.i, -1)), p -> p >= 0))"""
    covered = f"""aggregate({places}, named_struct('last', -5, 'n', 0L),
        (a, p) -> named_struct('last', p, 'n', a.n + least(5, p - a.last)), a -> a.n)"""
    twice = _bound("array_sort(transform(h, (v, i) -> named_struct('h', v, 'i', i)))", "s", covered)
    return f"if(size({words}) < 5, 0L, {_bound(hashes, 'h', f'if(size(array_distinct(h)) = size(h), 0L, {twice})')})"


def _counts(text: str) -> Column:
    words = f"filter(split({text}, '{BLANKS}'), x -> x != '')"
    inner = f"""named_struct(
        'n_words', cast(size(w) as bigint),
        'word_chars', cast(length(regexp_replace({text}, '{BLANKS}', '')) as bigint),
        'n_symbols', cast(length({text}) - length(translate({text}, '{SYMBOLS}', '')) as bigint),
        'n_lines', cast(size(l) as bigint),
        'n_dup_lines', cast(size(l) - size(array_distinct(l)) as bigint),
        'n_repeat_words', {_repeated("w")},
        'n_upper', cast(length({text}) - length(regexp_replace({text}, '\\\\p{{Lu}}+', '')) as bigint))"""
    lines = f"filter(split({text}, '\\n'), x -> x rlike '[^\\\\x20\\\\x09-\\\\x0D]')"
    return F.expr(_bound(words, "w", _bound(lines, "l", inner)))


def measured(docs: DataFrame, text: str = "text", lang: str = "lang") -> DataFrame:
    """docs with the base counts, the rates the rules look at, base_failed and stratum."""
    q = "__quality"
    rate = lambda a, b: F.when(F.col(f"{q}.{b}") > 0, F.col(f"{q}.{a}") / F.col(f"{q}.{b}")).otherwise(F.lit(0.0))
    lang_c = F.lower(F.col(lang)) if lang in docs.columns else F.lit(None).cast("string")
    out = docs.withColumn(q, _counts(f"coalesce(`{text}`, '')"))
    n, rep = F.col(f"{q}.n_words"), F.col(f"{q}.n_repeat_words")
    return out.withColumns(
        {c: F.col(f"{q}.{c}") for c in BASE}
        | {
            "symbol_rate": rate("n_symbols", "n_words"),
            "dup_line_rate": rate("n_dup_lines", "n_lines"),
            "repeat_rate": rate("n_repeat_words", "n_words"),
            "upper_rate": rate("n_upper", "word_chars"),
            "base_failed": (n < 10) | (100 * rep > 20 * n),
            "stratum": F.when(lang_c.rlike("^[a-z]{2,3}$"), lang_c).otherwise(F.lit("other")),
        }
    ).drop(q)


def binomial_tail(k: Column, n: Column, p: float) -> Column:
    """P(Bin(n, p) <= k), the exact sum, taken in logarithms. n = 0 gives 1."""
    return F.expr("""
        aggregate(sequence(0L, {k}), named_struct('t', {n} * ln(1 - {p}), 's', cast('-infinity' as double)),
          (a, j) -> named_struct(
            't', a.t + if(j < {n}, ln((cast({n} - j as double)) / (j + 1)) + ln({p} / (1 - {p})), cast('-infinity' as double)),
            's', if(a.s = cast('-infinity' as double), a.t, greatest(a.s, a.t) + ln(1 + exp(least(a.s, a.t) - greatest(a.s, a.t))))),
          a -> least(1.0D, exp(a.s)))""".format(k=k, n=n, p=f"cast({p!r} as double)"))


def certified(feats: DataFrame, labels: DataFrame, alpha: float = 0.05, delta: float = 0.05, key: str = "doc_id") -> DataFrame:
    """One row per stratum and rule: (stratum, rule, n_good, n_rejected, p_value, cutoff), cutoff null where none is certified.

    Every labelled good document that passes the base rules counts; nothing is sampled.
    """
    good = labels.where("quality is not null").groupBy(F.col(key).alias("__k")).agg(F.max("quality").alias("__q")).where("__q = 1")
    held = feats.where("not base_failed").select(F.col(key).alias("__k"), "stratum", *GRIDS).join(good, "__k")
    over = lambda r: F.array(*(F.struct(F.lit(i).alias("step"), F.lit(c).alias("cutoff"), F.sum((F.col(r) > c).cast("long")).alias("k")) for i, c in enumerate(GRIDS[r])))
    counts = held.groupBy("stratum").agg(F.count("*").alias("n_good"), F.array(*(F.struct(F.lit(r).alias("rule"), over(r).alias("grid")) for r in GRIDS)).alias("rules"))
    flat = counts.select("stratum", "n_good", F.explode("rules").alias("r")).select("stratum", "n_good", "r.rule", F.explode("r.grid").alias("g")).select("stratum", "rule", "n_good", "g.*")
    strata = counts.agg(F.count("*").alias("n_strata")).withColumn("one", F.lit(1))
    tested = flat.withColumn("one", F.lit(1)).join(F.broadcast(strata), "one").withColumn("p_value", binomial_tail("k", "n_good", alpha / len(GRIDS))).withColumn("ok", F.col("p_value") <= F.lit(delta / len(GRIDS)) / F.col("n_strata"))
    walk = F.struct("step", "cutoff", "k", "p_value", "ok")
    ordered = tested.groupBy("stratum", "rule", "n_good").agg(F.array_sort(F.collect_list(walk)).alias("steps"))
    best = F.expr("""aggregate(steps, named_struct('go', true, 'cutoff', cast(null as double), 'k', 0L, 'p', cast(null as double)),
        (a, x) -> if(a.go and x.ok, named_struct('go', true, 'cutoff', x.cutoff, 'k', x.k, 'p', x.p_value), named_struct('go', false, 'cutoff', a.cutoff, 'k', a.k, 'p', a.p)))""")
    return ordered.withColumn("b", best).select("stratum", "rule", "n_good", F.col("b.k").alias("n_rejected"), F.col("b.p").alias("p_value"), F.col("b.cutoff").alias("cutoff"))


def judged(feats: DataFrame, cutoffs: DataFrame) -> DataFrame:
    """feats with failed_rules and kept. The cutoff table holds a row per stratum and rule: bounded, so broadcast."""
    wide = cutoffs.where("cutoff is not null").groupBy("stratum").agg(*(F.min(F.when(F.col("rule") == r, F.col("cutoff"))).alias(f"__{r}") for r in GRIDS))
    joined = feats.drop("failed_rules", "kept").join(F.broadcast(wide), "stratum", "left")
    failed = F.filter(F.array(*(F.when(F.col(r) > F.col(f"__{r}"), F.lit(r)) for r in GRIDS)), lambda x: x.isNotNull())
    return joined.withColumn("failed_rules", failed).withColumn("kept", F.when(F.col("base_failed"), False).otherwise(F.size("failed_rules") == 0)).drop(*(f"__{r}" for r in GRIDS))


