"""Quality rules: a threshold table compiled into one projection of built-in functions."""

from __future__ import annotations

from typing import NamedTuple

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

_SPACES = " \t\n\x0b\f\r"
#: Function words of the four languages that the rules are set for.
STOP_WORDS = {
    "en": "the of and to a in that is was he for it with as his on be at by i this had not are but from or have an they which one you were her all she there would their we him been has when who will more no if out so what up said",
    "de": "der die das und in zu den von mit ist auf für im dem nicht ein eine als auch es an werden aus er hat dass sie nach wird bei einer um am sind noch wie einem über so zum war haben nur oder aber vor zur bis mehr durch man sein",
    "fr": "le la les de des du et en un une est que qui dans pour sur pas au aux par avec ce il elle se ne plus ont ou son sa ses mais comme nous vous leur y été cette sont tout je on",
    "es": "el la los las de del y en un una que es por con para se no su al lo como más pero sus le ya o este sí porque esta entre cuando muy sin sobre también me hasta hay donde quien desde todo nos",
}


class Rule(NamedTuple):
    """Keep a document only while low <= metric <= high (None: no bound)."""

    metric: str
    low: float | None = None
    high: float | None = None


#: The verdict's thresholds. Ratios are per word or per line and null-free.
RULES = (
    Rule("n_words", 50, 10_000_000),
    Rule("mean_word_chars", 2.0, 15.0),
    Rule("symbol_ratio", None, 0.10),
    Rule("shout_ratio", None, 0.10),
    Rule("stop_ratio", 0.02, None),
    Rule("dup_line_ratio", None, 0.50),
)


def _measured(docs: DataFrame) -> DataFrame:
    """One row a document with the base counts; each layer reads the columns of the one below."""
    text = F.coalesce("text", F.lit(""))
    trimmed = F.btrim(text, F.lit(_SPACES))
    stop = "|".join(sorted({w for ws in STOP_WORDS.values() for w in ws.split()}))
    first = docs.select(
        "doc_id",
        F.when(trimmed == "", F.array().cast("array<string>")).otherwise(F.split(trimmed, r"[\x20\x09-\x0D]+")).alias("w"),
        F.filter(F.split(text, "\n"), lambda x: x.rlike(r"[^\x20\x09-\x0D]")).alias("lines"),
        F.length(F.regexp_replace(text, r"[^#*$%&|<>]+", "")).cast("long").alias("n_symbols"),
        F.length(F.regexp_replace(text, r"[^!]+", "")).cast("long").alias("n_shouts"),
        F.regexp_count(F.lower(text), F.lit(rf"(?<![^\x20\x09-\x0D])(?:{stop})(?![^\x20\x09-\x0D.,;:!?])")).cast("long").alias("n_stops"),
    )
    hashed = first.select(
        "doc_id", "n_symbols", "n_shouts", "n_stops",
        F.size("w").cast("long").alias("n_words"),
        F.length(F.array_join("w", "")).cast("long").alias("word_chars"),
        F.size("lines").cast("long").alias("n_lines"),
        (F.size("lines") - F.size(F.array_distinct("lines"))).cast("long").alias("n_dup_lines"),
        F.expr("transform(w, (x, i) -> IF(i + 2 < size(w), xxhash64(x, w[i + 1], w[i + 2]), 0))").alias("g"),
    )
    grams = hashed.withColumn("g", F.expr("IF(n_words < 3, CAST(array() AS array<bigint>), slice(g, 1, greatest(CAST(n_words AS int) - 2, 1)))"))
    ordered = grams.withColumn("s", F.expr("IF(size(array_distinct(g)) = size(g), CAST(array() AS array<struct<h:bigint,i:int>>), sort_array(transform(g, (h, i) -> named_struct('h', h, 'i', i))))")).drop("g")
    again = ordered.withColumn("p", F.expr("transform(filter(s, (x, i) -> x.h = get(s, i - 1).h OR x.h = get(s, i + 1).h), x -> x.i)")).drop("s")
    # No filter is pushed below a projection that is not deterministic. Pushed down, a condition on this count would hold every
    # expression above in place of its column, and sort the windows again for each word. The ids are never negative.
    return again.withColumn("n_repeat_words", F.expr("IF(size(p) = 0 OR monotonically_increasing_id() < 0, 0L, CAST(size(array_distinct(concat(p, transform(p, x -> x + 1), transform(p, x -> x + 2)))) AS bigint))")).drop("p")


def _metrics() -> dict[str, Column]:
    per = lambda a, b: F.col(a) / F.greatest(F.col(b), F.lit(1))
    return {
        "n_words": F.col("n_words"), "mean_word_chars": per("word_chars", "n_words"), "symbol_ratio": per("n_symbols", "n_words"),
        "shout_ratio": per("n_shouts", "n_words"), "stop_ratio": per("n_stops", "n_words"), "dup_line_ratio": per("n_dup_lines", "n_lines"),
    }


def verdict(rules: tuple[Rule, ...] = RULES) -> Column:
    """The threshold table as one boolean expression over the measured columns."""
    out = F.lit(True)
    for r in rules:
        value = _metrics()[r.metric]
        if r.low is not None:
            out = out & (value >= r.low)
        if r.high is not None:
            out = out & (value <= r.high)
    return out


def quality_rules(docs: DataFrame, rules: tuple[Rule, ...] = RULES) -> DataFrame:
    """Base counts and verdict for each row of ``docs`` (doc_id, text; others are not read).

    Words are runs without ASCII white space. Returns doc_id, n_words, word_chars (code points
    in words), n_symbols, n_dup_lines (lines with a word that equal an earlier line),
    n_repeat_words (words in 3-word windows that occur again), n_lines, n_stops, n_shouts,
    base_failed and kept. Null and empty texts have no words, so they fail the base. All is one
    narrow projection: no shuffle, no Python, a row's memory in proportion to its text.
    Equal windows are found by sorting hashes with their positions, so a text's cost is n log n.
    """
    base = (F.col("n_words") < 50) | (F.col("n_repeat_words") * 100 > F.col("n_words") * 50)
    out = _measured(docs).withColumn("base_failed", base)
    return out.select(
        "doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "n_lines", "n_stops", "n_shouts", "base_failed",
        (~F.col("base_failed") & verdict(rules)).alias("kept"),
    )


def passing(docs: DataFrame, rules: tuple[Rule, ...] = RULES) -> DataFrame:
    """The rows of ``docs`` that the rules keep, with their columns."""
    carried = docs.select(F.struct(*[docs[c] for c in docs.columns]).alias("doc_id"), docs["text"].alias("text"))
    return quality_rules(carried, rules).where("kept").select("doc_id.*")
