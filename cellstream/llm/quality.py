r"""Line-first cleaning with built-in functions only.

Every line is judged by itself, by four rules in this order: boilerplate (phrases of page furniture, as whole words, make
up a third of the line or more), navigation (two separator bars or more, in a line that ends no sentence or has a bar for every
16 characters), symbols (over a fifth of the characters), punctuation (fewer than ``short`` = 12 words and no final mark:
a heading, menu entry or fragment). Failing lines go; a document is rejected if it fails the base rules or if its failing lines hold
more than ``max_loss`` of its characters. Everything is an expression over one row: no shuffle, no join.

Null and empty texts have no words and are rejected. Words are runs outside space and \x09-\x0D; lines end at \n; blank lines
never fail. Texts of any length are judged whole, repeated rows one by one; an empty table gives an empty result; other
columns are kept by ``clean``, whatever their names, and ignored by ``measures``.
"""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import bound

# Phrases of page furniture by language, lower case.
BOILERPLATE = {
    "en": ["all rights reserved", "click here", "cookie policy", "enable javascript", "privacy policy", "terms of service", "terms of use", "subscribe to our newsletter", "lorem ipsum", "back to top", "sign up", "log in", "read more", "share this"],
    "de": ["alle rechte vorbehalten", "hier klicken", "cookie richtlinie", "datenschutzerklärung", "nutzungsbedingungen", "newsletter abonnieren", "nach oben", "jetzt anmelden", "weiterlesen", "impressum"],
    "fr": ["tous droits réservés", "cliquez ici", "politique de confidentialité", "conditions d utilisation", "abonnez vous à notre newsletter", "haut de page", "se connecter", "lire la suite", "mentions légales"],
    "es": ["todos los derechos reservados", "haga clic aquí", "política de privacidad", "términos de uso", "suscríbase a nuestro boletín", "volver arriba", "iniciar sesión", "leer más", "aviso legal"],
}
# Separators of navigation bars, and marks that end a line of prose.
NAVIGATION = [" | ", " » ", " > ", " · "]
ENDS = list(".!?:;,\"'”’»)]…。！？؟।")
SYMBOLS = "#*$%&|<>"
SPACE = "[ \\t-\\r]+"
PHRASES = [p for ps in BOILERPLATE.values() for p in ps]
RULES = ["boilerplate", "navigation", "symbols", "punctuation"]


def words(text: Column) -> Column:
    return F.filter(F.split(text, SPACE), lambda w: w != "")


def _without(text: Column, marks: str) -> Column:
    return reduce(lambda t, m: F.replace(t, F.lit(m), F.lit("")), marks, text)


def _repeated_words(w: Column, window: int) -> Column:
    """Words that lie in windows found twice or more; sorts only where some window repeats."""
    starts = F.sequence(F.lit(1), F.size(w) - (window - 1))
    hashes = F.transform(starts, lambda i: F.xxhash64(F.slice(w, i, window)))

    def covered(g):
        tagged = F.array_sort(F.transform(g, lambda h, i: F.struct(h.alias("h"), i.alias("i"))))
        n = F.size(g)

        def twins(s):
            ahead = F.concat(F.slice(s, 2, n), F.array(F.lit(None).cast("struct<h:bigint,i:int>")))
            behind = F.concat(F.array(F.lit(None).cast("struct<h:bigint,i:int>")), F.slice(s, 1, n - 1))
            flagged = F.zip_with(F.zip_with(behind, s, lambda a, b: F.struct(b.alias("x"), F.coalesce(a["h"] == b["h"], F.lit(False)).alias("p"))), ahead, lambda b, c: F.when(b["p"] | F.coalesce(b["x"]["h"] == c["h"], F.lit(False)), b["x"]["i"]))
            places = F.array_sort(F.filter(flagged, lambda i: i.isNotNull()))
            start = F.struct(F.lit(-window).alias("last"), F.lit(0).cast("long").alias("sum"))
            return F.aggregate(places, start, lambda acc, i: F.struct(i.alias("last"), (acc["sum"] + F.least(F.lit(window), i - acc["last"])).alias("sum")), lambda acc: acc["sum"])

        return F.when(F.size(F.array_distinct(g)) == n, F.lit(0).cast("long")).otherwise(bound(tagged, twins))

    return F.when(F.size(w) < window + 1, F.lit(0).cast("long")).otherwise(bound(hashes, covered))


def _mentions(text: Column) -> Column:
    """Whether the longest word of some phrase is in the text: without it no line has the phrase."""
    low = F.lower(text)
    return bound(low, lambda t: reduce(lambda a, w: a | F.contains(t, F.lit(w)), sorted({max(p.split(), key=len) for p in PHRASES}), F.lit(False)))


def _furniture(line: Column) -> Column:
    plain = F.concat(F.lit(" "), F.btrim(F.regexp_replace(F.lower(line), "[^\\p{L}\\p{N}]+", " "), F.lit(" ")), F.lit(" "))

    def share(t):
        held = reduce(lambda a, p: a + F.length(t) - F.length(F.replace(t, F.lit(f" {p} "), F.lit(" "))), PHRASES, F.lit(0))
        return 3 * held >= F.length(t)

    return bound(plain, share)


def _has_word(line: Column) -> Column:
    return line.rlike("[^ \\t-\\r]")


def _last(line: Column) -> Column:
    """Last character but blanks; most lines end with none."""
    end = F.substring(line, -1, 1)
    return bound(end, lambda e: F.when(e.isin(" ", "\t", "\r"), F.substring(F.rtrim(line, F.lit(" \t\r")), -1, 1)).otherwise(e))


def _signs(text: Column, symbols: Column | None = None) -> Column:
    """What a text must have for its lines to fail a rule: phrases, separators, symbols."""
    marks = F.length(text) > F.length(_without(text, SYMBOLS)) if symbols is None else symbols > 0
    bars = reduce(lambda a, p: a | F.contains(text, F.lit(p)), NAVIGATION, F.lit(False))
    return F.struct(_mentions(text).alias("phrases"), bars.alias("bars"), marks.alias("marks"))


def line_rule(line: Column, signs: Column, short: int = 12) -> Column:
    """Number of the first rule that the line fails, from 1 in the order of RULES; 0 if it passes or has no word."""
    bars = reduce(lambda a, p: a + F.floor((F.length(line) - F.length(F.replace(line, F.lit(p), F.lit("")))) / len(p)), NAVIGATION, F.lit(0))
    ends = _last(line).isin(ENDS)
    walk = bound(bars, lambda n: (n >= 2) & (~ends | (16 * n >= F.length(line))))
    marks = (F.length(line) - F.length(_without(line, SYMBOLS))) * 5 > F.length(line)
    size = bound(F.size(words(line)), lambda n: (n > 0) & (n < short))
    return F.when(signs["phrases"] & _has_word(line) & _furniture(line), 1).when(signs["bars"] & walk, 2).when(signs["marks"] & marks, 3).when(~ends & size, 4).otherwise(0)


def _judged(text: Column, max_loss: float, window: int, min_words: int, max_repeat_percent: int, short: int) -> Column:
    def all_of(t):
        lines = F.split(t, "\n", -1)
        full = F.filter(lines, _has_word)

        def from_words(w):
            return F.struct(
                F.size(w).cast("long").alias("n_words"),
                F.length(F.array_join(w, "")).cast("long").alias("word_chars"),
                (F.length(t) - F.length(_without(t, SYMBOLS))).cast("long").alias("n_symbols"),
                bound(full, lambda x: F.size(x) - F.size(F.array_distinct(x))).cast("long").alias("n_dup_lines"),
                _repeated_words(w, window).alias("n_repeat_words"),
                bound(F.struct(full.alias("x"), _signs(t).alias("m")), lambda f: F.transform(f["x"], lambda x: F.struct(line_rule(x, f["m"], short).alias("r"), F.length(x).alias("n")))).alias("lines"),
                F.length(t).cast("long").alias("n_chars_seen"),
            )

        return bound(words(t), from_words)

    def verdict(m):
        failed = (m["n_words"] < min_words) | (100 * m["n_repeat_words"] > max_repeat_percent * m["n_words"])
        lost = F.aggregate(m["lines"], F.lit(0).cast("long"), lambda a, x: a + F.when(x["r"] > 0, x["n"]).otherwise(0))
        names = ("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words")
        count = lambda k: F.size(F.filter(m["lines"], lambda x: x["r"] == k)).cast("long")
        counts = [count(k).alias(f"lines_{r}") for k, r in enumerate(RULES, 1)]
        kept = ~failed & (lost <= max_loss * m["n_chars_seen"])
        return F.struct(*[m[n].alias(n) for n in names], lost.alias("chars_lost"), *counts, failed.alias("base_failed"), kept.alias("kept"))

    return bound(bound(F.coalesce(text, F.lit("")), all_of), verdict)


def measures(docs: DataFrame, max_loss: float = 0.5, window: int = 5, min_words: int = 10, max_repeat_percent: int = 20, short: int = 12) -> DataFrame:
    """(doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, chars_lost, lines_<rule>.., base_failed, kept)."""
    return docs.select("doc_id", _judged(F.col("text"), max_loss, window, min_words, max_repeat_percent, short).alias("m")).select("doc_id", "m.*")


def clean(docs: DataFrame, max_loss: float = 0.5, window: int = 5, min_words: int = 10, max_repeat_percent: int = 20, short: int = 12) -> DataFrame:
    """Kept documents without their failing lines; columns as they came."""

    def left(t):
        return bound(_signs(t), lambda m: F.array_join(F.filter(F.split(t, "\n", -1), lambda x: line_rule(x, m, short) == 0), "\n"))

    # Under coalesce the planner infers no null check of the verdict, which would judge each text once more.
    kept = docs.where(F.coalesce(_judged(F.col("text"), max_loss, window, min_words, max_repeat_percent, short)["kept"], F.lit(False)))
    return kept.select(*[bound(F.col("text"), left).alias("text") if c == "text" else F.col(f"`{c}`") for c in docs.columns])
