"""Quality rules: a threshold table compiled into one projection (native, no user function, no shuffle).

The base measures are exact counts over the whole text; the rules are rows (measure, lower bound, upper bound) and the
compiled verdict is their conjunction.  Stop words come from four languages, matched after lower-casing and stripping
the marks .,;: - a text that shouts or hangs symbols on its words therefore has none.

Repeated three-word windows are found inside the row: window hashes with their starts are sorted, equal neighbours mark
their three words, and marked words are counted once (64-bit hashes within one document: a false match in 20,000 words has
odds below 1e-10).

Defined results: a null text has no words (all counts 0, base_failed, not kept); long texts are read whole; extra columns
are ignored by the query and kept by `quality_rules`; an empty table gives no rows.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import let, safe_prefix, table, whole_text, words_of

#: Characters counted as symbols.
SYMBOLS = "#*$%&|<>"
#: Frequent function words of English, German, French and Spanish.
STOP_WORDS = (
    "the of and to in a is that it for on as with was by at be this are from or an "
    "der die das und zu den mit von für auf ist im dem nicht ein eine des auch "
    "le la les de et un une du en que qui dans pour pas sur au par est avec "
    "el los las y se del al no una su con lo como más"
).split()

#: measure, least, most.  Bounds are inclusive; None means unbounded.
RULES = (
    ("mean_word_length", 2.0, 30.0),
    ("symbol_ratio", None, 0.05),
    ("stop_ratio", 0.04, None),
    ("dup_line_ratio", None, 0.5),
    ("repeat_ratio", None, 0.5),
)


def base_measures(text: Column) -> dict[str, Column]:
    """n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words and n_stop, n_lines of a text column (null: no words)."""
    chars = F.length(F.translate(text, " \t\n\x0b\f\r", ""))
    symbols = F.length(text) - F.length(F.translate(text, SYMBOLS, ""))
    lines = F.filter(F.split(text, "\n", -1), lambda x: F.length(F.translate(x, " \t\n\x0b\f\r", "")) > 0)
    dup = let(lines, lambda x: F.struct(F.size(x).cast("long").alias("n_lines"), (F.size(x) - F.size(F.array_distinct(x))).cast("long").alias("n_dup_lines")))

    def repeats(ws: Column) -> Column:
        hashes = F.transform(F.sequence(F.lit(0), F.size(ws) - 3), lambda i: F.xxhash64(F.get(ws, i), F.get(ws, i + 1), F.get(ws, i + 2)))

        def marked(s: Column) -> Column:
            again = F.transform(s, lambda x, k: F.when(F.get(s, k - 1)["h"].eqNullSafe(x["h"]) | F.get(s, k + 1)["h"].eqNullSafe(x["h"]), x["i"]))
            return F.size(F.array_distinct(F.flatten(F.transform(F.filter(again, lambda i: i.isNotNull()), lambda i: F.array(i, i + 1, i + 2)))))

        def only_if_any(hs: Column) -> Column:
            windows = F.sort_array(F.transform(hs, lambda h, i: F.struct(h.alias("h"), i.alias("i"))))
            return F.when(F.size(F.array_distinct(hs)) == F.size(hs), F.lit(0)).otherwise(let(windows, marked))

        return F.when(F.size(ws) < 4, F.lit(0)).otherwise(let(hashes, only_if_any))

    strip = lambda w: F.lower(F.rtrim(w, F.lit(".,;:")))
    per_word = let(words_of(text), lambda ws: F.struct(F.size(ws).cast("long").alias("n_words"), repeats(ws).cast("long").alias("n_repeat_words"), F.size(F.filter(ws, lambda w: strip(w).isin(STOP_WORDS))).cast("long").alias("n_stop")))
    return {"chars": chars.cast("long"), "symbols": symbols.cast("long"), "lines": dup, "per_word": per_word}


def compile_rules(rules, prefix: str = "") -> Column:
    """The conjunction of a threshold table over measure columns."""
    verdict = F.lit(True)
    for measure, least, most in rules:
        c = F.col(f"{prefix}{measure}")
        if least is not None:
            verdict = verdict & (c >= least)
        if most is not None:
            verdict = verdict & (c <= most)
    return F.coalesce(verdict, F.lit(False))


def quality_rules(docs: DataFrame, text: str = "text", rules=RULES, min_words: int = 50, max_repeat_percent: int = 50) -> tuple[DataFrame, str]:
    """docs with helper columns <p>n_words ... <p>base_failed, <p>kept; returns the frame and the prefix p."""
    p = safe_prefix(docs, "qr")
    m = base_measures(whole_text(text))
    out = docs.withColumns({f"{p}per_word": m["per_word"], f"{p}lines": m["lines"], f"{p}word_chars": m["chars"], f"{p}n_symbols": m["symbols"]})
    names = {"n_words": "per_word", "n_repeat_words": "per_word", "n_stop": "per_word", "n_lines": "lines", "n_dup_lines": "lines"}
    out = out.withColumns({f"{p}{k}": F.col(f"{p}{v}.{k}") for k, v in names.items()}).drop(f"{p}per_word", f"{p}lines")
    c = lambda k: F.col(f"{p}{k}")
    safe = lambda a, b: F.try_divide(c(a).cast("double"), c(b).cast("double"))
    out = out.withColumns({
        f"{p}mean_word_length": safe("word_chars", "n_words"), f"{p}symbol_ratio": safe("n_symbols", "word_chars"), f"{p}stop_ratio": safe("n_stop", "n_words"),
        f"{p}dup_line_ratio": safe("n_dup_lines", "n_lines"), f"{p}repeat_ratio": safe("n_repeat_words", "n_words"),
        f"{p}base_failed": (c("n_words") < min_words) | (100 * c("n_repeat_words") > max_repeat_percent * c("n_words")),
    })
    return out.withColumn(f"{p}kept", ~c("base_failed") & compile_rules(rules, p)), p


def op5_quality_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    out, p = quality_rules(table(spark, sf_dir, "documents").select("doc_id", "text"))
    return out.select("doc_id", *[F.col(f"{p}{k}").alias(k) for k in ("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "kept", "n_stop")])


def oracle(docs: str = "documents") -> str:
    """The same rows in DuckDB, repeated windows counted by grouping instead of sorting inside the row."""
    stops = ", ".join("'" + w + "'" for w in STOP_WORDS)
    cond = {"mean_word_length": "word_chars::DOUBLE / n_words", "symbol_ratio": "n_symbols::DOUBLE / nullif(word_chars, 0)", "stop_ratio": "n_stop::DOUBLE / nullif(n_words, 0)", "dup_line_ratio": "n_dup_lines::DOUBLE / nullif(n_lines, 0)", "repeat_ratio": "n_repeat_words::DOUBLE / nullif(n_words, 0)"}
    parts = []
    for measure, least, most in RULES:
        parts += [f"{cond[measure]} >= {least}"] if least is not None else []
        parts += [f"{cond[measure]} <= {most}"] if most is not None else []
    return f"""
    WITH base AS (SELECT row_number() OVER () AS rid, doc_id, coalesce(text, '') AS t FROM {docs}),
    w AS (SELECT *, regexp_extract_all(t, '[^\\x20\\x09-\\x0D]+') AS ws, list_filter(string_split(t, chr(10)), lambda x: regexp_matches(x, '[^\\x20\\x09-\\x0D]')) AS ls FROM base),
    win AS (SELECT rid, i, struct_pack(a := ws[i], b := ws[i + 1], c := ws[i + 2]) AS g FROM (SELECT rid, ws, unnest(range(1, len(ws) - 1)) AS i FROM w)),
    dup AS (SELECT rid, i FROM (SELECT rid, i, count(*) OVER (PARTITION BY rid, g) AS n FROM win) WHERE n > 1),
    rep AS (SELECT rid, count(DISTINCT i + k) AS n FROM dup, (VALUES (0), (1), (2)) v(k) GROUP BY rid),
    m AS (SELECT w.doc_id, len(ws)::BIGINT AS n_words, length(regexp_replace(t, '[\\x20\\x09-\\x0D]+', '', 'g'))::BIGINT AS word_chars,
        (length(t) - length(regexp_replace(t, '[#*$%&|<>]', '', 'g')))::BIGINT AS n_symbols, (len(ls) - len(list_distinct(ls)))::BIGINT AS n_dup_lines, len(ls)::BIGINT AS n_lines,
        coalesce(rep.n, 0)::BIGINT AS n_repeat_words, len(list_filter(ws, lambda x: lower(rtrim(x, '.,;:')) IN ({stops})))::BIGINT AS n_stop
        FROM w LEFT JOIN rep USING (rid))
    SELECT doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, n_words < 50 OR 100 * n_repeat_words > 50 * n_words AS base_failed,
        coalesce(NOT (n_words < 50 OR 100 * n_repeat_words > 50 * n_words) AND {' AND '.join(parts)}, FALSE) AS kept, n_stop FROM m"""
