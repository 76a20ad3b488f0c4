"""Line-first quality rules, in DataFrame functions only.

Each line is tested by itself: punctuation (ends in a terminal mark), navigation (two or more menu separators), boilerplate (a line of at
most ``SHORT`` characters with one of the fixed phrases, in the four languages of the documents). Failing lines go; a document that
keeps less than ``min_kept`` of its word characters is rejected, as is one that fails the base rules.

Null or empty text: no words, so the base rules reject it. Rows are judged one by one: repeated rows and ids, and rows without doc_id,
give repeated results. Whole texts are judged, however long; memory is some 200 bytes per word of the longest text. Other input
columns are neither read nor changed, whatever their names.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

BLANK = r"[\x20\x09-\x0D]"
PUNCTUATED = r"[.!?:;…。]['\"”’)\]]*[\x20\x09-\x0D]*\z"
NAVIGATION = r"[|»>].*[|»>]"
SHORT = 200
#: Phrases of page furniture, in lower case (English, German, French, Spanish).
PHRASES = (
    "cookie policy", "privacy policy", "terms of use", "terms of service", "lorem ipsum", "enable javascript", "click here", "subscribe to our",
    "all rights reserved", "sign up for our", "read more", "share this", "back to top", "skip to content",
    "datenschutzerklärung", "nutzungsbedingungen", "alle rechte vorbehalten", "hier klicken", "javascript aktivieren", "newsletter abonnieren", "weiterlesen", "zum inhalt springen",
    "politique de confidentialité", "conditions d'utilisation", "tous droits réservés", "cliquez ici", "activer javascript", "abonnez-vous", "lire la suite", "mentions légales",
    "política de privacidad", "condiciones de uso", "todos los derechos reservados", "haga clic aquí", "activar javascript", "suscríbase", "leer más", "aviso legal",
)
BOILERPLATE = "(" + "|".join(PHRASES) + ")"
MIN_KEPT = 0.5


def _let(value: Column, body) -> Column:
    """Evaluate ``value`` once and use it many times inside ``body``."""
    return F.transform(F.array(value), body)[0]


def _word_chars(text: Column) -> Column:
    return F.length(F.regexp_replace(text, BLANK + "+", "")).cast("long")


def _repeat_words(words: Column) -> Column:
    def windows(w):
        return F.when(F.size(w) < 5, F.array().cast("array<string>")).otherwise(
            F.transform(F.sequence(F.lit(1), F.greatest(F.size(w) - 4, F.lit(1))), lambda i: F.array_join(F.slice(w, i, 5), " ")))

    def covered(starts):
        return F.aggregate(starts, F.struct(F.lit(0).cast("long").alias("n"), F.lit(-5).alias("last")),
                           lambda acc, s: F.struct((acc["n"] + F.least(F.lit(5), s - acc["last"])).cast("long").alias("n"), s.alias("last")))["n"]

    def repeated(wins):
        pairs = F.array_sort(F.transform(wins, lambda x, i: F.struct(x.alias("w"), i.alias("p"))))
        starts = _let(pairs, lambda s: F.array_sort(F.transform(F.filter(s, lambda x, i: 
                      (F.coalesce(F.get(s, i - 1)["w"] == x["w"], F.lit(False)) | F.coalesce(F.get(s, i + 1)["w"] == x["w"], F.lit(False)))), lambda x: x["p"])))
        return F.when(F.size(F.array_distinct(wins)) == F.size(wins), F.lit(0).cast("long")).otherwise(covered(starts))

    return _let(words, lambda w: _let(windows(w), repeated))


def _judged(rows: DataFrame, min_kept: float) -> DataFrame:
    """``rows`` (whole_row, text) with the measures, ``clean_text`` (kept lines) and ``kept``."""
    text = F.coalesce(F.col("text"), F.lit(""))
    words = F.filter(F.split(text, BLANK + "+"), lambda w: w != "")
    lines = F.split(text, "\n")
    full = F.filter(lines, lambda x: x.rlike(r"[^\x20\x09-\x0D]"))
    good = F.filter(lines, lambda x: x.rlike(PUNCTUATED) & ~x.rlike(NAVIGATION) & ~((F.length(x) <= SHORT) & F.lower(x).rlike(BOILERPLATE)))
    out = rows.withColumns({
        "n_words": F.size(words).cast("long"),
        "word_chars": _word_chars(text),
        "n_symbols": (F.length(text) - F.length(F.translate(text, "#*$%&|<>", ""))).cast("long"),
        "n_dup_lines": _let(full, lambda x: F.size(x) - F.size(F.array_distinct(x))).cast("long"),
        "n_repeat_words": _repeat_words(words),
        "clean_text": F.array_join(good, "\n"),
    })
    failed = (F.col("n_words") < 10) | (100 * F.col("n_repeat_words") > 20 * F.col("n_words"))
    out = out.withColumn("base_failed", failed).withColumn("kept_chars", _word_chars(F.col("clean_text")))
    return out.withColumn("kept", ~F.col("base_failed") & (F.col("kept_chars") >= min_kept * F.col("word_chars")))


def quality_measures(docs: DataFrame, min_kept: float = MIN_KEPT) -> DataFrame:
    """doc_id, the measures, ``clean_text`` and ``kept``, one row per row of ``docs``."""
    return _judged(docs.select(F.col("doc_id").alias("whole_row"), "text"), min_kept).drop("text").withColumnRenamed("whole_row", "doc_id")


def clean_documents(docs: DataFrame, min_kept: float = MIN_KEPT) -> DataFrame:
    """The kept rows of ``docs`` with the kept lines as their ``text``."""
    rows = docs.select(F.struct(*(F.col(f"`{c}`") for c in docs.columns)).alias("whole_row"), F.col("text"))
    kept = _judged(rows, min_kept).where("kept").select("whole_row", "clean_text")
    return kept.select(*(F.col("clean_text").alias(c) if c == "text" else F.col(f"whole_row.`{c}`").alias(c) for c in docs.columns))


COLUMNS = ["doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "kept"]

_BLANKS = "[\\x20\\x09-\\x0D]"
#: The query's rows in DuckDB: words and lines with their places, windows of five words counted per document.
SQL = f"""with d as (select row_number() over () r, doc_id, coalesce(text, '') t from documents),
w as (select r, unnest(ws) w, generate_subscripts(ws, 1) p from (select r, regexp_extract_all(t, '[^\\x20\\x09-\\x0D]+') ws from d)),
g as (select r, p, w || ' ' || lead(w, 1) over o || ' ' || lead(w, 2) over o || ' ' || lead(w, 3) over o || ' ' || lead(w, 4) over o five from w window o as (partition by r order by p)),
twice as (select r, p from (select r, p, count(*) over (partition by r, five) c from g where five is not null) where c > 1),
repeated as (select r, count(distinct p + k) n from twice, range(5) s(k) group by r),
words as (select r, count(*) n from w group by r),
l as (select r, unnest(ls) l, generate_subscripts(ls, 1) p from (select r, string_split(t, chr(10)) ls from d)),
dup as (select r, count(*) - count(distinct l) n from l where regexp_matches(l, '[^\\x20\\x09-\\x0D]') group by r),
good as (select r, sum(length(regexp_replace(l, '{_BLANKS}+', '', 'g'))) n from l where regexp_matches(l, '{PUNCTUATED.replace("'", "''")}') and not regexp_matches(l, '{NAVIGATION}')
  and not (length(l) <= {SHORT} and regexp_matches(lower(l), '{BOILERPLATE.replace("'", "''")}')) group by r),
m as (select doc_id, coalesce(words.n, 0) n_words, length(regexp_replace(t, '{_BLANKS}+', '', 'g')) word_chars, length(t) - length(regexp_replace(t, '[#*$%&|<>]', '', 'g')) n_symbols,
  coalesce(dup.n, 0) n_dup_lines, coalesce(repeated.n, 0) n_repeat_words, coalesce(good.n, 0) kept_chars
  from d left join words using (r) left join dup using (r) left join repeated using (r) left join good using (r)),
f as (select *, n_words < 10 or 100 * n_repeat_words > 20 * n_words base_failed from m)
select doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, base_failed, not base_failed and kept_chars >= {MIN_KEPT} * word_chars kept from f"""
