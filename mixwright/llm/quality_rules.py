"""Quality rules: a threshold table compiled into one native Spark projection.

Every measure is a column expression over built-in functions, so the filter runs inside the JVM next to the
Parquet scan; there is no shuffle and no state, and a document costs the same whatever the corpus size.

Defined results: a null text counts as an empty one (no words, every count 0, rejected by the length rule); null
values in other columns pass through untouched; repeated rows are judged separately and alike; an empty table
gives an empty result; columns of the input whose names clash with measures are kept, since the measures live in
one struct column whose name is a parameter.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .shared import free_names as _free

SPACE = r"[\x20\x09-\x0D]+"
SYMBOLS = "[#*$%&|<>]"
REPEAT_WIDTH = 8

# Frequent function words of the four languages of the corpus.
STOP_WORDS = {
    "en": ["a", "an", "and", "are", "as", "at", "be", "by", "for", "from", "he", "in", "is", "it", "of", "on", "or", "that", "the", "this", "to", "was", "with"],
    "fr": ["au", "avec", "dans", "de", "des", "du", "elle", "en", "est", "et", "il", "la", "le", "les", "ou", "par", "pas", "pour", "que", "qui", "sur", "un", "une"],
    "de": ["als", "auf", "das", "dem", "den", "der", "des", "die", "ein", "eine", "einen", "für", "im", "in", "ist", "mit", "nicht", "sich", "und", "von", "zu"],
    "es": ["con", "de", "del", "el", "en", "es", "la", "las", "lo", "los", "no", "para", "por", "que", "se", "su", "un", "una", "y"],
}


@dataclass(frozen=True)
class Rule:
    """Keep a document while ``low <= measure <= high``; a missing bound is open."""

    name: str
    measure: str
    low: float | None = None
    high: float | None = None


@dataclass(frozen=True)
class RuleSet:
    rules: tuple[Rule, ...]
    stop_words: tuple[str, ...]


def default_rules() -> RuleSet:
    """Production thresholds (a parameter of every entry point)."""
    return RuleSet(
        (
            Rule("length", "n_words", low=20),
            Rule("mean_word", "mean_word_chars", low=1.5, high=20.0),
            Rule("symbols", "symbols_per_word", high=0.25),
            Rule("shouting", "upper_share", high=0.4),
            Rule("exclamations", "bangs_per_word", high=0.5),
            Rule("stop_words", "stop_share", low=0.02),
            Rule("repeat", "repeat_share", high=0.3),
            Rule("lines", "dup_line_share", high=0.5),
            Rule("bullets", "bullet_line_share", high=0.9),
            Rule("ellipsis", "ellipsis_line_share", high=0.5),
        ),
        tuple(sorted({w for ws in STOP_WORDS.values() for w in ws})),
    )


def _repeat_cover(hashes: Column, marks: Column) -> Column:
    """Words inside windows that occur twice or more; ``marks`` are the (hash, position) pairs sorted by hash."""
    last = F.size(marks) - 1
    twin = F.filter(
        F.sequence(F.lit(0), last),
        lambda j: ((j > 0) & (F.get(marks, j - 1)["h"] == F.get(marks, j)["h"])) | ((j < last) & (F.get(marks, j + 1)["h"] == F.get(marks, j)["h"])),
    )
    starts = F.array_sort(F.transform(twin, lambda j: F.get(marks, j)["i"]))
    width = F.lit(REPEAT_WIDTH)
    total = F.aggregate(
        starts,
        F.struct(F.lit(0).alias("upto"), F.lit(0).alias("words")),
        lambda acc, p: F.struct((p + width).alias("upto"), (acc["words"] + p + width - F.greatest(acc["upto"], p)).alias("words")),
        lambda acc: acc["words"],
    )
    return F.when(marks.isNull(), F.lit(0)).otherwise(total)


def measure(df: DataFrame, text: str = "text", out: str = "measures", rules: RuleSet | None = None) -> DataFrame:
    """Append one struct of counts and ratios per row; see the module text for null and empty inputs."""
    rules = rules or default_rules()
    t, words, lines, hashed, pairs, fours, grams, marks = _free(df, "_q_text", "_q_words", "_q_lines", "_q_hash", "_q_pairs", "_q_fours", "_q_grams", "_q_marks")
    col, n = F.col, F.size(F.col(words))
    joined = lambda of, step: F.transform(col(of), lambda h, i: F.xxhash64(h, F.get(col(of), i + step)))  # noqa: E731  doubling; a slice in a lambda would copy the whole array for each window
    staged = (
        df.withColumn(t, F.coalesce(col(text), F.lit("")))
        .withColumn(words, F.array_remove(F.split(col(t), SPACE), ""))
        .withColumn(lines, F.filter(F.split(col(t), "\n"), lambda x: x.rlike(r"[^\x20\x09-\x0D]")))
        .withColumn(hashed, F.transform(col(words), lambda w: F.xxhash64(w)))
        .withColumn(pairs, joined(hashed, 1))
        .withColumn(fours, joined(pairs, 2))
        .withColumn(grams, F.slice(joined(fours, 4), F.lit(1), F.greatest(F.lit(0), F.size(hashed) - (REPEAT_WIDTH - 1))))
        .withColumn(
            marks,
            F.when(F.size(F.array_distinct(grams)) < F.size(grams), F.sort_array(F.transform(col(grams), lambda h, i: F.struct(h.alias("h"), i.alias("i"))))),
        )
    )
    size = F.length(col(t))
    counts = {
        "n_words": F.size(col(words)),
        "word_chars": F.length(F.array_join(col(words), "")),
        "n_symbols": size - F.length(F.regexp_replace(col(t), SYMBOLS + "+", "")),
        "n_dup_lines": F.size(col(lines)) - F.size(F.array_distinct(lines)),
        "n_repeat_words": _repeat_cover(col(grams), col(marks)),
        "n_bangs": size - F.length(F.regexp_replace(col(t), "!+", "")),
        "n_upper": F.length(F.regexp_replace(col(t), r"\P{Lu}+", "")),
        "n_stops": F.size(F.filter(col(words), lambda w: F.lower(w).isin(list(rules.stop_words)))),
        "n_lines": F.size(col(lines)),
        "n_bullets": F.size(F.filter(col(lines), lambda x: x.rlike(r"^\s*[-*•‣]"))),
        "n_dots": F.size(F.filter(col(lines), lambda x: x.rlike(r"(\.\.\.|…)\s*$"))),
    }
    names = dict(zip(counts, _free(df, *[f"_q_{c}" for c in counts]), strict=True))
    staged = staged.select(*[F.col(f"`{c}`") for c in df.columns], *[e.cast("long").alias(names[c]) for c, e in counts.items()])
    c = {k: F.col(v) for k, v in names.items()}
    per = lambda a, b: F.when(c[b] > 0, c[a] / c[b]).otherwise(F.lit(0.0))
    struct = F.struct(
        *[c[k].alias(k) for k in ("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words")],
        per("word_chars", "n_words").alias("mean_word_chars"),
        per("n_symbols", "n_words").alias("symbols_per_word"),
        per("n_bangs", "n_words").alias("bangs_per_word"),
        per("n_upper", "word_chars").alias("upper_share"),
        per("n_stops", "n_words").alias("stop_share"),
        per("n_repeat_words", "n_words").alias("repeat_share"),
        per("n_dup_lines", "n_lines").alias("dup_line_share"),
        per("n_bullets", "n_lines").alias("bullet_line_share"),
        per("n_dots", "n_lines").alias("ellipsis_line_share"),
    )
    # The struct passes a generator, below which no filter is pushed: pushed down, a rule would repeat the expressions of its measure.
    kept = [F.col(f"`{x}`") for x in df.columns if x.lower() != out.lower()]
    return staged.select(*kept, F.explode(F.array(struct)).alias(out))


def passes(measures: Column, rules: RuleSet | None = None) -> Column:
    """The conjunction of all rules over a measures struct."""
    verdict = F.lit(True)
    for r in (rules or default_rules()).rules:
        if r.low is not None:
            verdict = verdict & (measures[r.measure] >= r.low)
        if r.high is not None:
            verdict = verdict & (measures[r.measure] <= r.high)
    return verdict


def broken_rules(measures: Column, rules: RuleSet | None = None) -> Column:
    """Names of the rules that a document breaks, in table order."""
    names = []
    for r in (rules or default_rules()).rules:
        bad = F.lit(False)
        if r.low is not None:
            bad = bad | (measures[r.measure] < r.low)
        if r.high is not None:
            bad = bad | (measures[r.measure] > r.high)
        names.append(F.when(bad, F.lit(r.name)))
    return F.array_compact(F.array(*names))


def keep_good(df: DataFrame, text: str = "text", rules: RuleSet | None = None) -> DataFrame:
    """The rows whose text passes every rule, with the input's columns."""
    (m,) = _free(df, "_q_measures")
    return measure(df, text, m, rules).filter(passes(F.col(m), rules)).drop(m)
