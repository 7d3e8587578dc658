"""Quality rules whose cutoffs carry a guarantee (DataFrame functions only).

Fixed base rules reject very short and very repetitive texts. On top, each learned rule rejects texts
whose rate of something exceeds a cutoff of its stratum (language). Cutoffs come from a grid, from
harmless to strict. For each, the labelled good documents give the exact binomial tail
P(Bin(n, alpha / rules) <= false rejections), the p-value of "it rejects too many good
documents". Testing goes down the grid and stops at the first p-value above
delta / (strata * rules), so with probability 1 - delta no stratum loses more than alpha of its
good documents to the learned rules together. Of the cutoffs so certified, the one with the best
balance of caught bad and lost good documents is used, or none.

Defined results: null and empty texts have no words and fail the base rules; ``lang`` outside ``strata``, null
too, is the stratum "other"; rows with the same id are judged one by one, and a label with several
rows counts once for each; null labels are ignored; without labels only the base rules act; all other columns
of the input stay as they are under ``with_verdict``.
"""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from .common import computed_once, cut_lineage, free_name, text_or_empty

SPACE = r"[\x20\x09-\x0D]+"
WINDOW = 8
BASE = ("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words")


@dataclass(frozen=True)
class RiskControl:
    """alpha: share of good documents of a stratum that the learned rules may reject; delta: how often this may fail."""

    alpha: float = 0.02
    delta: float = 0.05
    loss_weight: int = 10
    strata: tuple[str, ...] = ("en", "fr", "de", "es")
    grid: dict[str, tuple[float, ...]] = field(
        default_factory=lambda: {
            "symbol_rate": (0.5, 0.4, 0.3, 0.25, 0.2, 0.15, 0.12, 0.1, 0.08, 0.06, 0.05, 0.04, 0.03),
            "upper_rate": (0.9, 0.8, 0.7, 0.6, 0.5, 0.4, 0.35, 0.3, 0.25, 0.2, 0.15),
            "mark_rate": (0.9, 0.8, 0.7, 0.6, 0.5, 0.4, 0.3, 0.25, 0.2, 0.15, 0.1),
            "dup_line_rate": (0.9, 0.8, 0.7, 0.6, 0.5, 0.4, 0.3, 0.2, 0.15, 0.1),
        }
    )

    @property
    def rule_alpha(self) -> float:
        return self.alpha / len(self.grid)

    @property
    def rule_delta(self) -> float:
        return self.delta / (len(self.grid) * (len(self.strata) + 1))


def _ratio(a: Column, b: Column) -> Column:
    return F.when(b > 0, a.cast("double") / b.cast("double")).otherwise(F.lit(0.0))


def with_counts(docs: DataFrame, text_col: str = "text") -> tuple[DataFrame, dict[str, str]]:
    """docs with the counts that rules use, and the columns in which they are."""
    own = {n: free_name(docs, n) for n in ("text_", "words_", "lines_", "hashes_", "windows_", "sorted_", "twice_", *BASE, "n_lines", "n_upper", "n_marks")}
    c = {k: F.col(v) for k, v in own.items()}
    out = docs.withColumn(own["text_"], text_or_empty(text_col))
    out = out.withColumn(own["words_"], F.array_remove(F.split(c["text_"], SPACE, -1), ""))
    out = out.withColumn(own["lines_"], F.filter(F.split(c["text_"], "\n", -1), lambda x: x.rlike(r"[^\x20\x09-\x0D]")))
    out = out.withColumns(
        {
            own["n_words"]: F.size(c["words_"]).cast("long"),
            own["word_chars"]: F.length(F.array_join(c["words_"], "")).cast("long"),
            own["n_symbols"]: F.regexp_count(c["text_"], F.lit("[#*$%&|<>]")).cast("long"),
            own["n_upper"]: F.regexp_count(c["text_"], F.lit(r"\p{Lu}")).cast("long"),
            own["n_marks"]: F.regexp_count(c["text_"], F.lit("!")).cast("long"),
            own["n_lines"]: F.size(c["lines_"]).cast("long"),
            own["n_dup_lines"]: (F.size(c["lines_"]) - F.size(F.array_distinct(c["lines_"]))).cast("long"),
            own["hashes_"]: F.transform(c["words_"], lambda w: F.xxhash64(w)),
        }
    )
    # Windows of words as hashes, those that repeat in order of their hash, their positions, and the words these cover.
    out = out.withColumn(own["windows_"], F.when(c["n_words"] >= WINDOW, F.transform(F.sequence(F.lit(1), c["n_words"].cast("int") - WINDOW + 1), lambda i: F.xxhash64(F.slice(c["hashes_"], i, WINDOW)))))
    repeats = F.size(F.array_distinct(c["windows_"])) < F.size(c["windows_"])
    out = out.withColumn(own["sorted_"], F.when(repeats, F.sort_array(F.transform(c["windows_"], lambda h, i: F.struct(h.alias("h"), i.alias("i"))))))
    s = c["sorted_"]
    again = lambda x, k: F.when((F.get(s, k - 1)["h"] == x["h"]) | (F.get(s, k + 1)["h"] == x["h"]), x["i"])
    out = out.withColumn(own["twice_"], F.sort_array(F.filter(F.transform(s, again), lambda x: x.isNotNull())))
    t = c["twice_"]
    covered = F.aggregate(F.transform(t, lambda p, k: F.least(F.lit(WINDOW), F.coalesce(F.get(t, k + 1) - p, F.lit(WINDOW)))), F.lit(0).cast("long"), lambda a, x: a + x)
    zero = F.lit(0).cast("long")
    out = out.withColumn(own["n_repeat_words"], computed_once(F.coalesce(covered, zero), zero))
    return out.drop(*(own[n] for n in ("text_", "words_", "lines_", "hashes_", "windows_", "sorted_", "twice_"))), own


def rates(own: dict[str, str]) -> dict[str, Column]:
    """The values that learned rules compare with their cutoffs."""
    c = {k: F.col(v) for k, v in own.items()}
    return {
        "symbol_rate": _ratio(c["n_symbols"], c["word_chars"]),
        "upper_rate": _ratio(c["n_upper"], c["word_chars"]),
        "mark_rate": _ratio(c["n_marks"], c["n_words"]),
        "dup_line_rate": _ratio(c["n_dup_lines"], c["n_lines"]),
    }


def stratum(control: RiskControl, lang: Column) -> Column:
    return F.when(lang.isin(*control.strata), lang).otherwise(F.lit("other"))


def base_failed(own: dict[str, str]) -> Column:
    n = F.col(own["n_words"])
    return (n < 20) | (100 * F.col(own["n_repeat_words"]) > 30 * n)


def binomial_tail(k: Column, n: Column, p: float) -> Column:
    """P(Bin(n, p) <= k), summed in logarithms; 1 from the mean on, where no test can pass."""
    start = F.struct((n * F.log(F.lit(1 - p))).alias("term"), F.lit(0.0).alias("total"))
    odds = F.log(F.lit(p / (1 - p)))
    step = lambda a, i: F.struct((a["term"] + F.when(n > i, F.log((n - i) / (i + 1))).otherwise(F.lit(0.0)) + odds).alias("term"), (a["total"] + F.exp(a["term"])).alias("total"))
    return F.when(k >= n * p, F.lit(1.0)).otherwise(F.aggregate(F.sequence(F.lit(0).cast("long"), k), start, step, lambda a: a["total"]))


def choose_cutoffs(labelled: DataFrame, control: RiskControl) -> DataFrame:
    """(stratum, rule, cutoff) from columns stratum, good and one for each rate; cutoff is null where none is of use."""
    cases = F.array(*(F.struct(F.lit(rule).alias("rule"), F.lit(k).alias("step"), F.lit(float(cutoff)).alias("cutoff"), (F.col(rule) > cutoff).alias("over")) for rule, cuts in control.grid.items() for k, cutoff in enumerate(cuts)))
    counted = (
        labelled.select("stratum", "good", F.explode(cases).alias("x"))
        .groupBy("stratum", "x.rule", "x.step", "x.cutoff")
        .agg(F.count_if("good").alias("n"), F.count_if(F.col("good") & F.col("x.over")).alias("lost"), F.count_if(~F.col("good") & F.col("x.over")).alias("caught"))
    )
    tested = counted.withColumn("passed", binomial_tail(F.col("lost"), F.col("n"), control.rule_alpha) <= control.rule_delta)
    down = Window.partitionBy("stratum", "rule").orderBy("step")
    certified = tested.withColumn("certified", F.min("passed").over(down)).withColumn("gain", F.col("caught") - control.loss_weight * F.col("lost"))
    useful = F.col("certified") & (F.col("gain") > 0)
    best = F.max_by(F.when(useful, F.col("cutoff")), F.when(useful, F.struct(F.col("gain"), -F.col("step"))))
    return certified.groupBy("stratum", "rule").agg(best.alias("cutoff"))


def cutoff_table(labelled: DataFrame, control: RiskControl) -> DataFrame:
    """One row for each declared stratum with a cutoff column for each rule: at most len(strata) + 1 rows, whatever the data."""
    chosen = choose_cutoffs(labelled, control)
    wide = chosen.groupBy(F.col("stratum").alias("cut_stratum")).agg(*(F.max(F.when(F.col("rule") == r, F.col("cutoff"))).alias(f"cut_{r}") for r in control.grid))
    return cut_lineage(wide)


def labelled_rates(docs: DataFrame, labels: DataFrame, control: RiskControl, id_col: str = "doc_id", text_col: str = "text", lang_col: str = "lang") -> DataFrame:
    """stratum, good and the rates of labelled documents; texts are reduced to rates before the join."""
    slim = docs.select(F.col(id_col).alias("doc_id"), F.col(lang_col).alias("lang"), F.col(text_col).alias("text"))
    counted, own = with_counts(slim)
    small = counted.select("doc_id", stratum(control, F.col("lang")).alias("stratum"), *(v.alias(k) for k, v in rates(own).items()))
    return _with_labels(small, labels)


def _with_labels(small: DataFrame, labels: DataFrame) -> DataFrame:
    outcome = labels.where("doc_id IS NOT NULL AND quality IS NOT NULL").select(F.col("doc_id").alias("labelled_id"), (F.col("quality") == 1).alias("good"))
    return small.join(outcome, F.col("doc_id") == F.col("labelled_id")).drop("doc_id", "labelled_id")


def verdict(counted: DataFrame, own: dict[str, str], cutoffs: DataFrame, control: RiskControl, lang_col: str = "lang", kept_col: str = "kept") -> DataFrame:
    """counted with base_failed and kept; the cutoffs have a bounded number of rows, so they are broadcast."""
    free = {c: free_name(counted, c) for c in cutoffs.columns}
    cutoffs = cutoffs.select(*(F.col(c).alias(x) for c, x in free.items()))
    joined = counted.join(F.broadcast(cutoffs), stratum(control, F.col(lang_col)) == F.col(free["cut_stratum"]), "left")
    over = F.lit(False)
    for rule, value in rates(own).items():
        over = over | F.coalesce(value > F.col(free[f"cut_{rule}"]), F.lit(False))
    failed = free_name(counted, "base_failed")
    return joined.withColumn(failed, base_failed(own)).withColumn(kept_col, ~(F.col(failed) | over)).drop(*cutoffs.columns)


def judge(docs: DataFrame, labels: DataFrame, control: RiskControl | None = None) -> DataFrame:
    """doc_id, the base counts, base_failed and kept for every document; counts are made once."""
    control = control or RiskControl()
    counted, own = with_counts(docs.select("doc_id", "lang", "text"))
    counted = cut_lineage(counted.drop("text"))
    small = counted.select("doc_id", stratum(control, F.col("lang")).alias("stratum"), *(v.alias(k) for k, v in rates(own).items()))
    judged = verdict(counted, own, cutoff_table(_with_labels(small, labels), control), control)
    return judged.select("doc_id", *BASE, "base_failed", "kept")


def keep_good(docs: DataFrame, labels: DataFrame, control: RiskControl | None = None) -> DataFrame:
    """The documents that pass, with the columns they came with; no text is shuffled."""
    control = control or RiskControl()
    cutoffs = cutoff_table(labelled_rates(docs, labels, control), control)
    counted, own = with_counts(docs)
    kept = free_name(counted, "kept")
    return verdict(counted, own, cutoffs, control, kept_col=kept).where(F.col(kept)).select(*docs.columns)
