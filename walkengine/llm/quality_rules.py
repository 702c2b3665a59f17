"""Quality rules: a threshold table compiled into one projection, evaluated inside Spark without user functions.

Words are runs of characters that are not ASCII white space.  Edge cases: a null text counts as empty; an empty
text has no words and fails the base rule; ratios over nothing are 0.  Rows are judged one by one, so repeated
rows, ties and skew do not matter, and further columns pass through ``filter_documents`` untouched.
"""

from __future__ import annotations

from functools import reduce
from typing import NamedTuple

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from walkengine.llm.common import BLANKS, let, only, read_table, whole_text, words_of

#: Characters counted as symbols.
SYMBOLS = "#*$%&|<>"
#: Frequent function words of four languages.
STOP_WORDS = (
    "the of and to in that is was for on with as by at be this are or from an it not have which "
    "de la le les des et en un une du que pour dans qui sur par au est il plus avec "
    "el los las del por una con para su se es al lo como más "
    "der die das und den von zu mit sich auf für ist im dem nicht ein eine als auch"
).split()


class Rule(NamedTuple):
    """A document fails where ``metric`` is below ``least`` or above ``most``."""

    name: str
    metric: str
    least: float | None
    most: float | None


#: The threshold table.
RULES = (
    Rule("word_length", "mean_word_chars", 2.0, 15.0),
    Rule("symbols", "symbols_per_word", None, 0.1),
    Rule("stop_words", "stop_word_ratio", 0.02, None),
    Rule("duplicate_lines", "dup_line_ratio", None, 0.6),
    Rule("bullets", "bullet_line_ratio", None, 0.9),
    Rule("ellipses", "ellipsis_line_ratio", None, 0.3),
    Rule("shouting", "upper_word_ratio", None, 0.5),
)


#: Low bits of a sort key that hold a window's place; the other bits hold the begin of its hash.
_PLACE = 24


def _covered(starts: Column) -> Column:
    """Words in windows of three at ``starts`` (ascending)."""
    begin = F.struct(F.lit(0).cast("long").alias("n"), F.lit(-3).cast("long").alias("at"))
    add = lambda acc, s: F.struct((acc["n"] + F.least(F.lit(3), s - acc["at"])).alias("n"), s.alias("at"))
    return F.aggregate(starts, begin, add, lambda acc: acc["n"])


def _exact_starts(words: Column) -> Column:
    """Places of repeated windows by a sort of the windows themselves."""

    def of(ordered: Column) -> Column:
        last = F.size(ordered) - 1
        same = lambda j, k: ordered[j]["w"] == ordered[k]["w"]
        near = lambda j: (F.when(j > 0, same(j, j - 1)).otherwise(False)) | F.when(j < last, same(j, j + 1)).otherwise(False)
        repeated = F.filter(F.sequence(F.lit(0), last), near)
        return F.array_sort(F.transform(repeated, lambda j: ordered[j]["i"]))

    window = lambda i: F.struct(F.concat_ws(" ", words[i], words[i + 1], words[i + 2]).alias("w"), i.cast("long").alias("i"))
    return let(F.array_sort(F.transform(F.sequence(F.lit(0), F.size(words) - 3), window)), of)


def measured(docs: DataFrame, rest: str | None = None, more: dict[str, Column] | None = None) -> DataFrame:
    """doc_id and the counts of every whole text (and the column ``rest``, untouched, and the columns ``more``, which may
    use ``text`` and ``words``).

    Each step is a projection whose columns the next one uses several times, so Spark computes them once.  Windows are
    compared by one primitive sort of (40 bits of the hash, place); where two neighbours share these bits but not their
    words, the text's windows are sorted as words instead.  The counts leave by a generator of one row: a filter on them
    can't be pushed below it, where Spark would compute every step again for each use.
    """
    none = F.array().cast("array<long>")
    place = (1 << _PLACE) - 1
    through = (rest,) if rest else ()
    rows = docs.select("doc_id", *through, whole_text().alias("text"))
    gone = lambda chars: F.length("text") - F.length(F.translate("text", chars, ""))
    rows = rows.select(
        "doc_id", *through, *(["text"] if more else []), gone(SYMBOLS).cast("long").alias("n_symbols"), words_of(F.col("text")).alias("words"),
        F.filter(F.split("text", "\n"), lambda x: x.rlike(r"[^\x20\x09-\x0D]")).alias("lines"),
    )
    word, lines = F.col("words"), F.col("lines")
    rows = rows.select(
        "doc_id", *through, "n_symbols", "words",
        F.size(lines).cast("long").alias("n_lines"),
        (F.size(lines) - F.size(F.array_distinct(lines))).cast("long").alias("n_dup_lines"),
        F.size(F.filter(lines, lambda x: x.rlike(r"^\s*[-*•]"))).alias("n_bullet_lines"),
        F.size(F.filter(lines, lambda x: x.rlike(r"(\.\.\.|…)\s*$"))).alias("n_ellipsis_lines"),
        F.size(F.filter(word, lambda w: w.isin(STOP_WORDS))).alias("n_stop_words"),
        F.size(F.filter(word, lambda w: (F.upper(w) == w) & (F.lower(w) != w))).alias("n_upper_words"),
        F.length(F.array_join(word, "")).cast("long").alias("word_chars"),
        F.size(word).cast("long").alias("n_words"),
        *(c.alias(n) for n, c in (more or {}).items()),
    )
    done = [*(more or {}), "n_symbols", "n_lines", "n_dup_lines", "n_bullet_lines", "n_ellipsis_lines", "n_stop_words", "n_upper_words", "word_chars", "n_words"]
    key = lambda i: F.xxhash64(word[i], word[i + 1], word[i + 2]).bitwiseAND(F.lit(~place)).bitwiseOR(i.cast("long"))
    windows = F.sort_array(F.transform(F.sequence(F.lit(0), F.size(word) - 3), key))
    rows = rows.select("doc_id", *through, *done, "words", F.when(F.size(word) >= 3, windows).otherwise(none).alias("keys"))
    keys = F.col("keys")
    begin = lambda k: F.shiftright(k, _PLACE)
    at = lambda k: k.bitwiseAND(F.lit(place)).cast("int")
    before = lambda k, j: F.when(j > 0, begin(keys[j - 1]) == begin(k)).otherwise(False)
    after = lambda k, j: F.when(j < F.size(keys) - 1, begin(keys[j + 1]) == begin(k)).otherwise(False)
    rows = rows.select("doc_id", *through, *done, "words", F.filter(keys, lambda k, j: before(k, j) | after(k, j)).alias("repeats"))
    repeats = F.col("repeats")

    def differs(k: Column, j: Column) -> Column:
        last = repeats[F.greatest(j - 1, F.lit(0))]
        other = reduce(lambda x, y: x | y, (word[at(k) + d] != word[at(last) + d] for d in range(3)))
        return F.when((j > 0) & (begin(last) == begin(k)), other).otherwise(False)

    rows = rows.select("doc_id", *through, *done, "words", "repeats", F.exists(F.transform(repeats, differs), lambda x: x).alias("mixed"))
    starts = F.when(F.col("mixed") | (F.size(word) > place), _exact_starts(word)).otherwise(
        F.sort_array(F.transform(repeats, lambda k: k.bitwiseAND(F.lit(place))))
    )
    repeated = F.when(F.size(repeats) > 0, _covered(starts)).otherwise(F.lit(0).cast("long"))
    counts = F.struct("doc_id", *through, *done, repeated.alias("n_repeat_words"))
    return rows.select(F.inline(F.array(counts)))


def ratios() -> dict[str, Column]:
    over = lambda a, b: F.when(F.col(b) > 0, F.col(a) / F.col(b)).otherwise(0.0)
    return {
        "mean_word_chars": over("word_chars", "n_words"),
        "symbols_per_word": over("n_symbols", "n_words"),
        "stop_word_ratio": over("n_stop_words", "n_words"),
        "upper_word_ratio": over("n_upper_words", "n_words"),
        "dup_line_ratio": over("n_dup_lines", "n_lines"),
        "bullet_line_ratio": over("n_bullet_lines", "n_lines"),
        "ellipsis_line_ratio": over("n_ellipsis_lines", "n_lines"),
    }


def compile_rules(rules: tuple[Rule, ...]) -> tuple[Column, Column]:
    """(fails any rule, names of the failed rules)."""
    no = F.lit(False)
    tests = {
        r.name: (F.col(r.metric) < r.least if r.least is not None else no)
        | (F.col(r.metric) > r.most if r.most is not None else no)
        for r in rules
    }
    names = F.concat_ws(",", *(F.when(test, F.lit(name)) for name, test in tests.items())) if tests else F.lit("")
    return reduce(lambda a, b: a | b, tests.values(), no), names


def _judged(rows: DataFrame, rules: tuple[Rule, ...], *columns: str) -> DataFrame:
    fails, names = compile_rules(rules)
    base = (F.col("n_words") < 50) | (100 * F.col("n_repeat_words") > 50 * F.col("n_words"))
    return rows.select("*", *(c.alias(n) for n, c in ratios().items())).select(
        *columns, base.alias("base_failed"), names.alias("failed_rules"), (~base & ~fails).alias("kept")
    )


def judge(docs: DataFrame, rules: tuple[Rule, ...] = RULES) -> DataFrame:
    """One row per document: counts, ratios, base_failed, failed rules and the verdict ``kept``."""
    return _judged(measured(only(docs, "doc_id", "text")), rules, "*")


def filter_documents(docs: DataFrame, rules: tuple[Rule, ...] = RULES) -> DataFrame:
    """The documents that pass, with their own columns; no shuffle, as the verdict is computed in the scan."""
    bound = docs.select("doc_id", "text", F.struct("*").alias("_row"))
    return _judged(measured(bound, "_row"), rules, "_row").where("kept").select("_row.*")


def op3_quality_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    return judge(read_table(spark, sf_dir, "documents")).select(
        "doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "kept", "failed_rules"
    )


def _sql() -> str:
    stop = ", ".join(f"'{w}'" for w in STOP_WORDS)
    blanks = r"' ' || chr(9) || chr(10) || chr(11) || chr(12) || chr(13)"
    ratio = lambda a, b: f"(CASE WHEN {b} > 0 THEN {a} / {b}::DOUBLE ELSE 0 END)"
    of = {
        "mean_word_chars": ratio("word_chars", "n_words"), "symbols_per_word": ratio("n_symbols", "n_words"),
        "stop_word_ratio": ratio("n_stop", "n_words"), "upper_word_ratio": ratio("n_upper", "n_words"),
        "dup_line_ratio": ratio("n_dup_lines", "n_lines"),
        "bullet_line_ratio": ratio("n_bullet", "n_lines"), "ellipsis_line_ratio": ratio("n_ellipsis", "n_lines"),
    }
    test = lambda r: " OR ".join(
        [f"{of[r.metric]} < {r.least}"] * (r.least is not None) + [f"{of[r.metric]} > {r.most}"] * (r.most is not None)
    )
    names = ", ".join(f"CASE WHEN {test(r)} THEN '{r.name}' END" for r in RULES)
    return f"""
WITH base AS (
  SELECT doc_id, coalesce(text, '') AS t,
         list_filter(regexp_split_to_array(coalesce(text, ''), '[ \\x09-\\x0D]+'), lambda w: w <> '') AS words,
         list_filter(string_split(coalesce(text, ''), chr(10)), lambda x: translate(x, {blanks}, '') <> '') AS lines
  FROM documents),
windows AS (
  SELECT doc_id, i, words[i] || ' ' || words[i + 1] || ' ' || words[i + 2] AS w
  FROM (SELECT doc_id, words, unnest(range(1, len(words) - 1)) AS i FROM base WHERE len(words) >= 3)),
repeated AS (
  SELECT doc_id, i FROM windows
  QUALIFY count(*) OVER (PARTITION BY doc_id, w) > 1),
covered AS (
  SELECT doc_id, count(DISTINCT i + k) AS n FROM repeated, (VALUES (0), (1), (2)) AS s(k) GROUP BY doc_id),
counts AS (
  SELECT base.doc_id, len(words)::BIGINT AS n_words, length(translate(t, {blanks}, ''))::BIGINT AS word_chars,
         (length(t) - length(translate(t, '{SYMBOLS}', '')))::BIGINT AS n_symbols,
         len(lines)::BIGINT AS n_lines, (len(lines) - len(list_distinct(lines)))::BIGINT AS n_dup_lines,
         coalesce(covered.n, 0)::BIGINT AS n_repeat_words,
         len(list_filter(words, lambda w: w IN ({stop}))) AS n_stop,
         len(list_filter(words, lambda w: upper(w) = w AND lower(w) <> w)) AS n_upper,
         len(list_filter(lines, lambda x: regexp_matches(x, '^\\s*[-*•]'))) AS n_bullet,
         len(list_filter(lines, lambda x: regexp_matches(x, '(\\.\\.\\.|…)\\s*$'))) AS n_ellipsis
  FROM base LEFT JOIN covered USING (doc_id)),
judged AS (
  SELECT *, n_words < 50 OR 100 * n_repeat_words > 50 * n_words AS base_failed, concat_ws(',', {names}) AS failed_rules
  FROM counts)
SELECT doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, base_failed,
       NOT base_failed AND failed_rules = '' AS kept, failed_rules
FROM judged"""


QUERIES = {"op3_quality_rules": op3_quality_rules}
ORACLES = {"op3_quality_rules": _sql()}
