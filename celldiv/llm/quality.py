"""Quality rules: a threshold table compiled into one Spark projection.

Every measure is a built-in expression over the whole text; the verdict of each rule is a
comparison of two of them in whole numbers, so no division can round a document in or out.

Defined results: a null text has no words and fails the base rules; an empty text likewise.
Repeated rows are judged each for itself; columns of the input other than the text are kept,
and those that clash with an output name are replaced by the output.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from celldiv.llm.common import SPACE, let, space_words

SYMBOLS = "[#*$%&|<>]"
#: Very frequent words of the languages served; a text in prose has some of them.
STOP_WORDS = (
    "the of and to in is that for with on as are this by an be at or from it was "  # English
    "der die das und in den von zu mit sich des auf ist im dem nicht ein eine für "  # German
    "le la les de des un une et en que qui dans du pour par au est pas ce "  # French
    "el la los de y en que un una del se por con para las es su no"  # Spanish
).split()


@dataclass(frozen=True)
class Rule:
    """Fails if scale * measure `of` exceeds (side 'max') or is below ('min') limit * measure `per`.

    per None compares the measure itself.
    """

    name: str
    of: str
    side: str
    limit: int
    per: str | None = None
    scale: int = 1

    def failed(self) -> Column:
        left = F.lit(self.scale) * F.col(self.of)
        right = F.lit(self.limit) * (F.col(self.per) if self.per else F.lit(1))
        return left > right if self.side == "max" else left < right

    def sql(self) -> str:
        return f"{self.scale} * {self.of} {'>' if self.side == 'max' else '<'} {self.limit}" + (f" * {self.per}" if self.per else "")


#: Rules whose failure the contract calls base.
BASE_RULES = (
    Rule("few_words", "n_words", "min", 20),
    Rule("repeated_words", "n_repeat_words", "max", 30, "n_words", 100),
)
RULES = (
    Rule("many_words", "n_words", "max", 10_000_000),
    Rule("short_words", "word_chars", "min", 2, "n_words"),
    Rule("long_words", "word_chars", "max", 20, "n_words"),
    Rule("symbols", "n_symbols", "max", 10, "n_words", 100),
    Rule("shouting", "n_exclaims", "max", 10, "n_words", 100),
    Rule("bar_words", "n_bar_words", "max", 10, "n_words", 100),
    Rule("stop_words", "n_stop_words", "min", 2, "n_words", 100),
    Rule("duplicate_lines", "n_dup_lines", "max", 50, "n_lines", 100),
    Rule("echoed_words", "n_echo_words", "max", 20, "n_words", 100),
)
MEASURES = ("n_words", "word_chars", "n_symbols", "n_lines", "n_dup_lines", "n_repeat_words", "n_exclaims", "n_bar_words", "n_stop_words", "n_echo_words")


def _repeated(words: Column, width: int) -> Column:
    """Words inside windows of `width` words that occur at least twice in the text.

    A window is known by the XXH64 of its words' XXH64. Only texts with a repeated window pay for
    the sort that finds where: equal hashes stand side by side, and the places, in order, are
    covered from each to the next or to the window's end.
    """
    def covered(places: Column) -> Column:
        steps = F.transform(places, lambda p, j: F.least(F.lit(width), F.coalesce(F.get(places, j + 1) - p, F.lit(width))))
        return F.aggregate(steps, F.lit(0).cast("long"), lambda s, x: s + x)

    def twice(ranked: Column) -> Column:
        same = lambda j, k: F.coalesce(F.get(ranked, j)["h"] == F.get(ranked, k)["h"], F.lit(False))
        marked = F.transform(ranked, lambda x, j: F.when((j > 0) & same(j, j - 1) | same(j, j + 1), x["i"]))
        return F.array_sort(F.filter(marked, lambda i: i.isNotNull()))

    def of_windows(h: Column) -> Column:
        ranked = F.array_sort(F.transform(h, lambda x, i: F.struct(x.alias("h"), i.alias("i"))))
        return F.when(F.size(F.array_distinct(h)) == F.size(h), F.lit(0).cast("long")).otherwise(let(ranked, lambda r: let(twice(r), covered)))

    def of_hashes(h: Column) -> Column:
        starts = F.sequence(F.lit(0), F.size(h) - width)
        return let(F.transform(starts, lambda i: F.xxhash64(*[F.get(h, i + k) for k in range(width)])), of_windows)

    return F.when(F.size(words) < width, F.lit(0).cast("long")).otherwise(let(F.transform(words, lambda w: F.xxhash64(w)), of_hashes))


def measures(text: Column, width: int = 8) -> Column:
    """All measures of a text as one struct; nulls count as empty."""
    whole = F.coalesce(text, F.lit(""))
    stop = F.array(*[F.lit(w) for w in dict.fromkeys(STOP_WORDS)])

    def of_words(words: Column) -> Column:
        return F.struct(
            F.size(words).cast("long").alias("n_words"),
            F.aggregate(words, F.lit(0).cast("long"), lambda s, w: s + F.char_length(w)).alias("word_chars"),
            _repeated(words, width).alias("n_repeat_words"),
            F.size(F.filter(words, lambda w: (F.char_length(w) <= 4) & F.array_contains(stop, F.lower(w)))).cast("long").alias("n_stop_words"),
            # words equal to the word before them
            F.size(F.filter(words, lambda w, i: F.coalesce(w == F.get(words, i - 1), F.lit(False)))).cast("long").alias("n_echo_words"),
        )

    def of_lines(lines: Column) -> Column:
        return F.struct(
            F.size(lines).cast("long").alias("n_lines"),
            (F.size(lines) - F.size(F.array_distinct(lines))).cast("long").alias("n_dup_lines"),
        )

    lines = F.filter(F.split(whole, "\n"), lambda line: line.rlike(f"[^{SPACE}]"))
    return F.struct(
        let(space_words(whole), of_words).alias("words"),
        let(lines, of_lines).alias("lines"),
        F.regexp_count(whole, F.lit(SYMBOLS)).cast("long").alias("n_symbols"),
        F.regexp_count(whole, F.lit("!")).cast("long").alias("n_exclaims"),
        F.regexp_count(whole, F.lit(r"\|")).cast("long").alias("n_bar_words"),
    )


def judge(docs: DataFrame, text: str = "text", base: tuple[Rule, ...] = BASE_RULES, rules: tuple[Rule, ...] = RULES, width: int = 8) -> DataFrame:
    """docs with the measures, base_failed, kept and the names of all failed rules."""
    made = {*MEASURES, "base_failed", "kept", "failed_rules"}
    kept = [F.col(c) for c in docs.columns if c.lower() not in made]
    got = docs.select(*kept, measures(F.col(text), width).alias("__m"))
    parts = {"n_words": "words", "word_chars": "words", "n_repeat_words": "words", "n_stop_words": "words", "n_echo_words": "words", "n_lines": "lines", "n_dup_lines": "lines"}
    flat = got.select(*[c for c in got.columns if c != "__m"], *[F.col(f"__m.{parts[m]}.{m}" if m in parts else f"__m.{m}").alias(m) for m in MEASURES])
    any_of = lambda some: F.greatest(F.lit(False), F.lit(False), *[r.failed() for r in some])
    return flat.select(
        "*",
        any_of(base).alias("base_failed"),
        (~any_of((*base, *rules))).alias("kept"),
        F.filter(F.array(*[F.when(r.failed(), F.lit(r.name)) for r in (*base, *rules)]), lambda x: x.isNotNull()).alias("failed_rules"),
    )
