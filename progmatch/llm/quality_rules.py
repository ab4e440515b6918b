"""Quality rules: one table of thresholds compiled into one Spark projection, no user functions.

Measures are counts over the whole text: words (runs without white space), their code points, symbols, lines that repeat
an earlier line, words inside five-word windows that occur twice or more, words in capitals, stop words, words with a
letter, words with a Latin one. The list of stop words is of languages in Latin script: its rule asks Latin words only. A rule bounds a ratio of two of them, and may apply from a number of words on. Null and empty texts have counts
of 0 and fail the base rule; repeated rows give repeated results; further columns are kept, but those with the names of
measures and verdicts are replaced.
"""

from __future__ import annotations

from dataclasses import dataclass
from functools import reduce

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from progmatch.llm.common import SHINGLE_WORDS, table
from progmatch.llm.native_text import with_shingle_hashes, words

#: Symbols that the contract counts; white space characters; frequent function words of four languages.
SYMBOLS = "#*$%&|<>"
BLANKS = " \t\n\x0b\x0c\r"
LATIN = r"[A-Za-z\x{C0}-\x{24F}]"
STOP_WORDS = (
    "a an and are as at be by for from in is it not of on or that the this to was were with "
    "au aux avec ce dans de des du elle en est et il la le les ou par pas pour que qui sur un une "
    "al como con del el es esta las lo los mas no para por se sin su y "
    "als auf das dem den der die ein eine ist mit nicht sich und von zu"
).split()


@dataclass(frozen=True)
class Rule:
    """Keep a document whose `measure / per` lies in [least, most]; short documents, below from_words, are not judged."""

    name: str
    measure: str
    per: str
    least: float | None = None
    most: float | None = None
    from_words: int = 0

    def holds(self) -> Column:
        ratio = F.try_divide(F.col(self.measure).cast("double"), F.col(self.per).cast("double"))
        bounds = [ratio >= self.least] if self.least is not None else []
        bounds += [ratio <= self.most] if self.most is not None else []
        inside = F.coalesce(reduce(Column.__and__, bounds), F.lit(True))
        return inside | (F.col("n_words") < self.from_words) if self.from_words else inside


RULES = (
    Rule("word length", "word_chars", "n_words", least=1.5, most=20.0),
    Rule("symbols", "n_symbols", "n_words", most=0.25),
    Rule("capitals", "n_capital_words", "n_words", most=0.5, from_words=20),
    Rule("stop words", "n_stop_words", "n_latin_words", least=0.01, from_words=50),
    Rule("words with a letter", "n_letter_words", "n_words", least=0.6),
    Rule("repeated lines", "n_dup_lines", "n_lines", most=0.4),
)
LEAST_WORDS, MOST_REPEATED_PERCENT = 10, 20


def with_measures(docs: DataFrame, text: str = "text", size: int = SHINGLE_WORDS) -> DataFrame:
    """Adds the counts that rules refer to."""
    df = docs.withColumn("__t", F.coalesce(F.col(text), F.lit(""))).withColumn("__w", words(F.col("__t")))
    df = df.withColumn("__h", F.transform("__w", lambda w: F.xxhash64(w)))
    df = with_shingle_hashes(df, "__h", "__g", size)
    repeats = F.size(F.array_distinct("__g")) < F.size("__g")
    empty = F.array().cast("array<struct<g:bigint,i:int>>")
    df = df.withColumn("__s", F.when(repeats, F.sort_array(F.transform("__g", lambda g, i: F.struct(g.alias("g"), i.alias("i"))))).otherwise(empty))
    s = F.col("__s")

    def twice(x: Column, i: Column) -> Column:
        same = lambda j: F.coalesce(F.get(s, j)["g"] == x["g"], F.lit(False))
        return same(i - 1) | same(i + 1)

    df = df.withColumn("__p", F.sort_array(F.transform(F.filter("__s", twice), lambda x: x["i"])))
    after = F.slice(F.col("__p"), 2, F.greatest(F.size("__p"), F.lit(1)))
    covered = F.zip_with("__p", after, lambda a, b: F.least(F.coalesce(b - a, F.lit(size)), F.lit(size)))
    lines = F.filter(F.split("__t", "\n"), lambda x: F.trim(x, F.lit(BLANKS)) != "")
    count = lambda f: F.size(F.filter("__w", f)).cast("long")
    df = df.withColumn("__l", lines).withColumns(
        {
            "n_words": F.size("__w").cast("long"),
            "word_chars": F.length(F.translate("__t", BLANKS, "")).cast("long"),
            "n_symbols": (F.length("__t") - F.length(F.translate("__t", SYMBOLS, ""))).cast("long"),
            "n_lines": F.size("__l").cast("long"),
            "n_dup_lines": (F.size("__l") - F.size(F.array_distinct("__l"))).cast("long"),
            "n_repeat_words": F.aggregate(covered, F.lit(0), lambda a, x: a + x).cast("long"),
            "n_capital_words": count(lambda w: (F.upper(w) == w) & (F.lower(w) != w) & (F.length(w) > 1)),
            "n_stop_words": count(lambda w: F.lower(w).isin(STOP_WORDS)),
            "n_latin_words": count(lambda w: F.rlike(w, F.lit(LATIN))),
            "n_letter_words": count(lambda w: F.rlike(w, F.lit(r"\p{L}"))),
        }
    )
    return df.drop("__t", "__w", "__h", "__g", "__s", "__p", "__l")


def judged(docs: DataFrame, text: str = "text", rules: tuple[Rule, ...] = RULES) -> DataFrame:
    """Adds the counts, base_failed, failed_rules (names) and kept."""
    df = with_measures(docs, text)
    base = (F.col("n_words") < LEAST_WORDS) | (100 * F.col("n_repeat_words") > MOST_REPEATED_PERCENT * F.col("n_words"))
    failed = F.array_compact(F.array(*[F.when(~r.holds(), F.lit(r.name)) for r in rules])) if rules else F.array().cast("array<string>")
    df = df.withColumn("base_failed", base).withColumn("failed_rules", failed)
    return df.withColumn("kept", ~F.col("base_failed") & (F.size("failed_rules") == 0))


def op10_quality_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    made = judged(table(spark, sf_dir, "documents").select("doc_id", "text"))
    return made.select("doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "kept", "n_lines", "n_capital_words", "n_stop_words", "n_latin_words", "n_letter_words")


_WORDS = r"regexp_extract_all(t, '[^\x20\x09-\x0D]+')"
_STOP = ", ".join(f"'{w}'" for w in STOP_WORDS)
OP10_SQL = rf"""
WITH d AS (SELECT doc_id, coalesce(text, '') AS t FROM documents),
w AS (SELECT doc_id, t, {_WORDS} AS w, list_filter(string_split(t, chr(10)), lambda x: regexp_matches(x, '[^\x20\x09-\x0D]')) AS l FROM d),
g AS (SELECT *, list_transform(range(1, len(w) - 3), lambda i: array_to_string(w[i:i+4], ' ')) AS g FROM w),
runs AS (SELECT doc_id, unnest(g) AS g, unnest(range(len(g))) AS i FROM g),
again AS (SELECT doc_id, i FROM runs QUALIFY count(*) OVER (PARTITION BY doc_id, g) > 1),
gaps AS (SELECT doc_id, least(coalesce(lead(i) OVER (PARTITION BY doc_id ORDER BY i) - i, 5), 5) AS n FROM again),
covered AS (SELECT doc_id, sum(n)::BIGINT AS n FROM gaps GROUP BY doc_id),
m AS (SELECT g.doc_id, len(w)::BIGINT AS n_words, length(regexp_replace(t, '[\x20\x09-\x0D]', '', 'g'))::BIGINT AS word_chars,
  (length(t) - length(translate(t, '#*$%&|<>', '')))::BIGINT AS n_symbols, (len(l) - len(list_distinct(l)))::BIGINT AS n_dup_lines,
  coalesce(c.n, 0)::BIGINT AS n_repeat_words, len(l)::BIGINT AS n_lines,
  len(list_filter(w, lambda x: upper(x) = x AND lower(x) <> x AND length(x) > 1))::BIGINT AS n_capital_words,
  len(list_filter(w, lambda x: lower(x) IN ({_STOP})))::BIGINT AS n_stop_words,
  len(list_filter(w, lambda x: regexp_matches(x, '{LATIN}')))::BIGINT AS n_latin_words,
  len(list_filter(w, lambda x: regexp_matches(x, '\p{{L}}')))::BIGINT AS n_letter_words
  FROM g LEFT JOIN covered c USING (doc_id)),
b AS (SELECT *, n_words < 10 OR 100 * n_repeat_words > 20 * n_words AS base_failed FROM m)
SELECT doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, base_failed,
  NOT base_failed AND coalesce(word_chars / n_words BETWEEN 1.5 AND 20, true) AND coalesce(n_symbols / n_words <= 0.25, true)
  AND (coalesce(n_capital_words / n_words <= 0.5, true) OR n_words < 20) AND (coalesce(n_stop_words / nullif(n_latin_words, 0) >= 0.01, true) OR n_words < 50)
  AND coalesce(n_letter_words / n_words >= 0.6, true) AND coalesce(n_dup_lines / nullif(n_lines, 0) <= 0.4, true) AS kept,
  n_lines, n_capital_words, n_stop_words, n_latin_words, n_letter_words FROM b
"""
