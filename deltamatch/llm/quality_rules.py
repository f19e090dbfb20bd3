"""Quality rules with adaptive thresholds, in DataFrame functions only.

Counts are exact over the whole text. Thresholds aren't fixed: for each language and
source a mergeable quantile sketch (Greenwald-Khanna, as percentile_approx has it) gives
the quartiles of each measure, and a document is rejected where it lies far outside
(Tukey fences, widened by an absolute slack so that near-constant groups keep their
documents). Sketches are merged per task before the shuffle, so a source with a third of
all rows costs one sketch per task.

Null texts count as empty: no words, so the base rule fails. Null languages and sources
form groups of their own. Repeated rows are judged alike. An empty table gives an empty
result. Extra columns are ignored or, in `filter_documents`, passed on.
"""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import cut

_SPACES = "\t\n\x0b\x0c\r"
_SYMBOLS = "#*$%&|<>"

#: measure -> (slack below or None, slack above or None): absolute room beyond the fences
SLACK = {"symbol_ratio": (None, 0.15), "word_length": (1.5, 3.0), "dup_line_share": (None, 0.3), "repeat_share": (None, 0.25)}
COUNTS = ("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words")


def word_array(text: Column) -> Column:
    """Words between ASCII white space, in order."""
    flat = reduce(lambda t, c: F.replace(t, F.lit(c), F.lit(" ")), _SPACES, text)
    return F.array_remove(F.split(flat, " "), "")


def with_counts(docs: DataFrame, text_col: str = "text") -> DataFrame:
    """docs with the counts and `q_lines` (lines that hold a word); helper columns are dropped again.

    Each step is a column of its own that later steps use more than once, so the planner
    keeps it evaluated once instead of inlining it into lambdas.
    """
    kept = [F.col(f"`{c}`") for c in docs.columns]
    text = F.coalesce(F.col(text_col), F.lit(""))
    out = docs.select(*kept, text.alias("__text")).select("*", word_array(F.col("__text")).alias("__words"))
    has_word = lambda line: F.length(F.btrim(line, F.lit(" " + _SPACES))) > 0
    out = out.select(
        "*",
        F.size("__words").cast("bigint").alias("n_words"),
        F.transform("__words", lambda w, i: F.concat_ws(" ", w, F.get("__words", i + 1), F.get("__words", i + 2))).alias("__tri"),
        F.filter(F.split("__text", "\n"), has_word).alias("__lines"),
    )
    n = F.size("__words")
    # The last two have fewer than three words and can't equal a whole window.
    repeats = (n >= 4) & (F.size(F.array_distinct("__tri")) < n)
    out = out.select("*", F.when(repeats, F.sort_array(F.transform(F.slice("__tri", 1, n - 2), lambda t, i: F.struct(t.alias("t"), i.alias("i"))))).alias("__sorted"))
    m = F.size("__sorted")
    covered = F.zip_with(
        F.slice("__sorted", 1, m - 1), F.slice("__sorted", 2, m - 1),
        lambda a, b: F.when(a["t"] == b["t"], F.array(a["i"], a["i"] + 1, a["i"] + 2, b["i"], b["i"] + 1, b["i"] + 2)).otherwise(F.array().cast("array<int>")),
    )
    bare = reduce(lambda t, c: F.replace(t, F.lit(c), F.lit("")), _SYMBOLS, F.col("__text"))
    return out.select(
        *kept,
        "n_words",
        F.length(F.array_join("__words", "")).cast("bigint").alias("word_chars"),
        (F.octet_length("__text") - F.octet_length(bare)).cast("bigint").alias("n_symbols"),
        (F.size("__lines") - F.size(F.array_distinct("__lines"))).cast("bigint").alias("n_dup_lines"),
        F.coalesce(F.when(m >= 2, F.size(F.array_distinct(F.flatten(covered)))), F.lit(0)).cast("bigint").alias("n_repeat_words"),
        # Adds zero, but keeps the planner from moving filters, and with them copies of all the above, below this step.
        (F.size("__lines") + F.least(F.monotonically_increasing_id(), F.lit(0))).cast("bigint").alias("q_lines"),
    )


def base_failed() -> Column:
    return (F.col("n_words") < 50) | (100 * F.col("n_repeat_words") > 50 * F.col("n_words"))


def _measures() -> dict[str, Column]:
    n = F.greatest(F.col("n_words"), F.lit(1)).cast("double")
    return {
        "symbol_ratio": F.col("n_symbols") / n,
        "word_length": F.col("word_chars") / n,
        "dup_line_share": F.col("n_dup_lines") / F.greatest(F.col("q_lines"), F.lit(1)).cast("double"),
        "repeat_share": F.col("n_repeat_words") / n,
    }


def thresholds(counted: DataFrame, *, reach: float = 6.0, accuracy: int = 10_000) -> DataFrame:
    """One row per (t_lang, t_source) with low_/high_ limits of each measure (null: none); base failures don't shape them."""
    quartiles = [F.percentile_approx(c, [0.25, 0.75], accuracy).alias(f"q_{k}") for k, c in _measures().items()]
    out = counted.where(~base_failed()).groupBy(F.col("lang").alias("t_lang"), F.col("source").alias("t_source")).agg(*quartiles)
    limits = []
    for k, (below, above) in SLACK.items():
        q = F.col(f"q_{k}")
        spread = reach * (q[1] - q[0])
        limits += [(q[0] - spread - below if below is not None else F.lit(None).cast("double")).alias(f"low_{k}"), (q[1] + spread + above if above is not None else F.lit(None).cast("double")).alias(f"high_{k}")]
    return out.select("t_lang", "t_source", *limits)


def sized(limits: DataFrame, most: int = 20_000) -> DataFrame:
    """Limits in the shared folder; broadcast only if there are at most `most` groups, else joined by key."""
    limits = cut(limits)
    return F.broadcast(limits) if limits.limit(most + 1).count() <= most else limits


def judged(counted: DataFrame, limits: DataFrame) -> DataFrame:
    """counted with base_failed and kept."""
    met = counted.join(limits, F.col("lang").eqNullSafe(F.col("t_lang")) & F.col("source").eqNullSafe(F.col("t_source")), "left")
    fine = F.lit(True)
    for k, c in _measures().items():
        fine = fine & F.coalesce(c >= F.col(f"low_{k}"), F.lit(True)) & F.coalesce(c <= F.col(f"high_{k}"), F.lit(True))
    return met.select(*[counted[f"`{c}`"] for c in counted.columns], base_failed().alias("base_failed"), (~base_failed() & fine).alias("kept"))


def quality_verdicts(docs: DataFrame) -> DataFrame:
    """doc_id, the counts, base_failed and kept for every document. Texts are read once; only counts are kept for the second step."""
    counted = cut(with_counts(docs.select("doc_id", "lang", "source", "text")).drop("text"))
    out = judged(counted, sized(thresholds(counted)))
    return out.select("doc_id", *COUNTS, "base_failed", "kept")


def filter_documents(docs: DataFrame) -> DataFrame:
    """The rows of docs that the rules keep, with their own columns. No text is shuffled: counts are taken again in the second pass."""
    limits = sized(thresholds(with_counts(docs.select("lang", "source", "text")).drop("text")))
    hidden = docs.select(F.struct(*[F.col(f"`{c}`") for c in docs.columns]).alias("__row"), "lang", "source", "text")
    return judged(with_counts(hidden), limits).where("kept").select("__row.*")
