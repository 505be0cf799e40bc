"""Line-first quality rules, in DataFrame functions only.

Each line of a text is judged by itself: does it end and read like prose (punctuation), is it a
row of links (navigation), is it page furniture or one phrase over and over (boilerplate)? Lines
that fail are removed; a document that loses too many of its words by that is rejected. Rules on
the whole document (length, repeated words) come first and can only reject.

Nothing is shuffled: every figure of a document is worked out in its own row.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import WORD, free_name, words

# Page furniture by language, lower case.
BOILERPLATE = {
    "en": (
        "accept cookies",
        "all rights reserved",
        "back to top",
        "click here",
        "cookie policy",
        "enable javascript",
        "follow us on",
        "log in to",
        "lorem ipsum",
        "powered by",
        "privacy policy",
        "read more",
        "share this",
        "sign up for",
        "skip to content",
        "subscribe to",
        "terms of service",
        "terms of use",
    ),
    "de": (
        "alle rechte vorbehalten",
        "cookies akzeptieren",
        "datenschutzerklärung",
        "folgen sie uns",
        "hier klicken",
        "jetzt anmelden",
        "mehr lesen",
        "nach oben",
        "newsletter abonnieren",
        "nutzungsbedingungen",
        "zum inhalt springen",
    ),
    "es": (
        "aceptar cookies",
        "haga clic aquí",
        "ir al contenido",
        "leer más",
        "política de cookies",
        "política de privacidad",
        "síguenos en",
        "suscríbete a",
        "todos los derechos reservados",
        "términos de uso",
        "volver arriba",
    ),
    "fr": (
        "accepter les cookies",
        "aller au contenu",
        "cliquez ici",
        "conditions d'utilisation",
        "haut de page",
        "inscrivez-vous à",
        "lire la suite",
        "politique de confidentialité",
        "suivez-nous sur",
        "tous droits réservés",
    ),
}
BOILERPLATE_PHRASES = tuple(x for phrases in BOILERPLATE.values() for x in phrases)


@dataclass(frozen=True)
class LineRules:
    """Shares are per cent of the words of a line or document."""

    min_words: int = 50
    max_repeat_pct: int = 50
    max_lost_pct: int = 50
    max_symbols_pct: int = 50
    max_shout_pct: int = 30
    min_separators: int = 3
    max_separators_pct: int = 20
    repeat_min_words: int = 8
    min_distinct_pct: int = 30
    boilerplate_max_words: int = 25


#: Ends of a line of prose: closing marks, then quotes or brackets.
_ENDS = r"""[.!?:;,\x{2026}\x{3002}\x{061F}\x{0964}]["'\x{2019}\x{201D}\x{00BB})\]]*[\x20\x09-\x0D]*$"""
#: A sentence that ends within the line: such a line is prose even if its own end was cut off.
_ENDS_WITHIN = r"""[.!?\x{2026}\x{3002}\x{061F}\x{0964}]["'\x{2019}\x{201D}\x{00BB})\]]*[\x20\x09]"""


def _line_failure(line: Column, n: Column, rules: LineRules) -> Column:
    """Name of the first rule that a line fails, or null. ``n``: its words."""
    symbols = F.regexp_count(line, F.lit(r"[#*$%&<>~^=_\\]"))
    shouts = F.regexp_count(line, F.lit(r"[!?]{2,}"))
    bars = F.regexp_count(line, F.lit(r"(?:^|[\x20\x09-\x0D])(?:[|\x{00BB}\x{203A}\x{2022}\x{00B7}>/-])(?=[\x20\x09-\x0D]|$)"))
    distinct = F.size(F.array_distinct(F.regexp_extract_all(line, F.lit(WORD), F.lit(0))))
    phrases = F.lit("(?iu)(?:" + "|".join(BOILERPLATE_PHRASES) + ")")
    return (
        F.when(n == 0, F.lit(None).cast("string"))
        .when((bars >= rules.min_separators) & (bars * 100 > n * rules.max_separators_pct), F.lit("navigation"))
        .when(
            (symbols * 100 > n * rules.max_symbols_pct) | (shouts * 100 > n * rules.max_shout_pct) | ~(F.rlike(line, F.lit(_ENDS)) | F.rlike(line, F.lit(_ENDS_WITHIN))),
            F.lit("punctuation"),
        )
        .when((n <= rules.boilerplate_max_words) & F.rlike(line, phrases), F.lit("boilerplate"))
        .when((n >= rules.repeat_min_words) & (distinct * 100 < n * rules.min_distinct_pct), F.lit("boilerplate"))
    )


def _repeat_words(df: DataFrame, w: str, out: str) -> DataFrame:
    """Adds ``out``: words in three-word windows that stand twice or more in the word list ``w``.

    Window hashes are compared by hash set first; only texts with a repeat sort (hash, place) pairs
    in their own row, so the work is n log n and never a pair of places."""
    n, g, s, p = (free_name(df, f"{w}_{x}") for x in "ngsp")
    at = lambda k: F.element_at(F.col(w), k)
    df = df.withColumn(n, F.size(w))
    df = df.withColumn(
        g,
        F.when(F.col(n) < 3, F.array().cast("array<bigint>")).otherwise(
            F.transform(F.sequence(F.lit(1), F.col(n) - 2), lambda i: F.xxhash64(at(i), at(i + 1), at(i + 2)))
        ),
    )
    none = F.array().cast("array<struct<h:bigint,i:int>>")
    df = df.withColumn(
        s,
        F.when(F.size(F.array_distinct(g)) == F.size(g), none).otherwise(
            F.sort_array(F.transform(g, lambda h, i: F.struct(h.alias("h"), i.alias("i"))))
        ),
    )
    hash_at = lambda j: F.get(F.col(s), j)["h"]  # noqa: E731  null beyond either end
    again = F.filter(s, lambda x, j: F.coalesce(hash_at(j - 1) == x["h"], F.lit(False)) | F.coalesce(hash_at(j + 1) == x["h"], F.lit(False)))
    df = df.withColumn(p, F.sort_array(F.transform(again, lambda x: x["i"])))
    start = F.struct(F.lit(-3).alias("last"), F.lit(0).alias("sum"))
    covered = F.aggregate(
        p, start, lambda a, x: F.struct(x.alias("last"), (a["sum"] + F.least(F.lit(3), x - a["last"])).alias("sum")), lambda a: a["sum"]
    )
    return df.withColumn(out, covered.cast("long")).drop(n, g, s, p)


def clean_lines(docs: DataFrame, text: str = "text", rules: LineRules = LineRules()) -> DataFrame:
    """``docs`` with the figures, the verdicts and the cleaned text of each row added.

    Added: n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words (long); base_failed;
    lost_words (words of removed lines), failed_lines (map from rule to removed lines); kept;
    clean_text (the lines that passed, blank ones stay).

    Null text: no words, so base_failed; clean_text is empty. Empty text and text of white space:
    the same. Whole texts are judged, of any length. Columns of ``docs`` by these names, in any case, are
    replaced. Null ids are carried. Repeated rows are judged alike, an empty table gives an empty table."""
    keep = [c for c in docs.columns if c.lower() not in {"n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "lost_words", "failed_lines", "kept", "clean_text"}]
    docs = docs.select(*(F.col(f"`{c}`") for c in keep))
    t, w, j = (free_name(docs, x) for x in ("_t", "_w", "_j"))
    df = docs.withColumn(t, F.coalesce(F.col(text), F.lit("")))
    df = df.withColumn(w, words(F.col(t)))
    df = df.withColumn("n_words", F.size(w).cast("long"))
    df = df.withColumn("word_chars", F.length(F.translate(F.col(t), " \t\n\x0b\x0c\r", "")).cast("long"))
    df = df.withColumn("n_symbols", F.regexp_count(F.col(t), F.lit("[#*$%&|<>]")).cast("long"))
    df = _repeat_words(df, w, "n_repeat_words").drop(w)
    judged = F.transform(
        F.split(F.col(t), "\n", -1),
        lambda line: F.struct(line.alias("line"), F.regexp_count(line, F.lit(WORD)).alias("n")),
    )
    df = df.withColumn(j, judged)
    df = df.withColumn(
        j, F.transform(j, lambda x: F.struct(x["line"].alias("line"), x["n"].alias("n"), _line_failure(x["line"], x["n"], rules).alias("rule")))
    )
    worded = F.transform(F.filter(j, lambda x: x["n"] > 0), lambda x: x["line"])
    df = df.withColumn(f"{j}l", worded)
    df = df.withColumn("n_dup_lines", (F.size(f"{j}l") - F.size(F.array_distinct(f"{j}l"))).cast("long")).drop(f"{j}l")
    df = df.withColumn("lost_words", F.aggregate(F.filter(j, lambda x: x["rule"].isNotNull()), F.lit(0).cast("bigint"), lambda a, x: a + x["n"]))
    count = lambda name: F.size(F.filter(j, lambda x: x["rule"] == name))
    names = ("punctuation", "navigation", "boilerplate")
    df = df.withColumn("failed_lines", F.create_map(*(e for k in names for e in (F.lit(k), count(k)))))
    df = df.withColumn("clean_text", F.array_join(F.transform(F.filter(j, lambda x: x["rule"].isNull()), lambda x: x["line"]), "\n")).drop(j, t)
    df = df.withColumn(
        "base_failed", (F.col("n_words") < rules.min_words) | (F.col("n_repeat_words") * 100 > F.col("n_words") * rules.max_repeat_pct)
    )
    return df.withColumn("kept", ~F.col("base_failed") & (F.col("lost_words") * 100 <= F.col("n_words") * rules.max_lost_pct))
