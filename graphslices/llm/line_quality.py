"""Quality rules, line first: failing lines go, then documents that lost too much of their text.

Every expression is a DataFrame function over one row: no shuffle, no Python worker. A document of any length is judged
in its own task, in time that grows with n log n of its words.

Edge cases: a null or empty text has no words, fails the word-count rule and is not kept; ties and repeated rows are judged
alike, row by row; an empty table gives an empty table; other columns are carried through `clean` untouched (columns that
bear the names of the added ones are replaced).
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from graphslices.llm.common import NOT_WHITE, WHITE, let, words_of

SYMBOLS = "[#*$%&|<>]"
# Phrases of lines that belong to a page rather than to its text.
BOILERPLATE = (
    "lorem ipsum", "enable javascript", "javascript is disabled", "accept cookies", "use of cookies", "cookie policy",
    "privacy policy", "terms of use", "terms of service", "all rights reserved", "powered by", "copyright ©", "subscribe to our newsletter",
    "alle rechte vorbehalten", "datenschutzerklärung", "cookies akzeptieren", "nutzungsbedingungen", "newsletter abonnieren",
    "tous droits réservés", "politique de confidentialité", "accepter les cookies", "conditions d'utilisation", "abonnez-vous à notre",
    "todos los derechos reservados", "política de privacidad", "aceptar cookies", "condiciones de uso", "suscríbete a nuestr",
)
NAVIGATION = (
    "home", "menu", "login", "log in", "sign in", "sign up", "register", "next", "previous", "back to top", "read more",
    "click here", "share", "print", "search", "skip to content", "site map", "sitemap",
    "startseite", "menü", "anmelden", "abmelden", "registrieren", "weiter", "zurück", "nach oben", "weiterlesen", "mehr lesen", "teilen", "drucken", "suche", "zum inhalt springen", "impressum",
    "accueil", "connexion", "se connecter", "s'inscrire", "suivant", "précédent", "retour en haut", "lire la suite", "partager", "imprimer", "rechercher", "aller au contenu", "plan du site",
    "inicio", "menú", "iniciar sesión", "registrarse", "siguiente", "anterior", "volver arriba", "leer más", "compartir", "imprimir", "buscar", "saltar al contenido", "mapa del sitio",
)
UNLETTERED = r"[^\p{L}\x20\x09-\x0D]+"


@dataclass(frozen=True)
class LineRules:
    """Limits of the line rules and of the verdict.

    symbol_share: a line with a larger share of symbol characters fails. sign_share: so does one of `sign_chars` characters at least in which a larger share is neither letters nor white space. shout_share: so does one with more '!!' per word.
    bars: and one with so many ' | ', ' » ' or ' · ' separators. open_words: and one with at least so many words without any sentence punctuation.
    short_chars: boilerplate phrases are sought only in lines up to this length. lost_share: a document that loses a larger share of its characters is rejected.
    """

    symbol_share: float = 0.1
    sign_share: float = 0.5
    sign_chars: int = 12
    shout_share: float = 0.3
    bars: int = 2
    open_words: int = 40
    short_chars: int = 200
    lost_share: float = 0.5
    min_words: int = 10
    max_repeat_percent: int = 20


def _chars_without(text: Column, pattern: str) -> Column:
    return F.length(F.regexp_replace(text, pattern, ""))


def line_fails(line: Column, rules: LineRules = LineRules()) -> Column:
    """Whether a line breaks a punctuation, navigation or boilerplate rule. Blank lines never do."""
    n = F.length(line)
    symbols = n - _chars_without(line, SYMBOLS + "+")
    shouts = (n - _chars_without(line, "!!+")) > 0
    words = F.size(words_of(line))
    phrase = F.lower(line)
    punctuation = (symbols > rules.symbol_share * n) | (
        shouts & (F.size(F.split(line, "!!+")) - 1 > rules.shout_share * words)
    )
    signs = (n >= rules.sign_chars) & (n - _chars_without(line, UNLETTERED) > rules.sign_share * n)
    open_ended = (words >= rules.open_words) & ~line.rlike(r"[.!?;:…。！？؟।]")
    navigation = F.size(F.split(line, r"\s[|»·>]\s")) - 1 >= rules.bars
    named = phrase.rlike(rf"^\W*(?:{'|'.join(NAVIGATION)})\W*$")
    boilerplate = (n <= rules.short_chars) & (named | phrase.rlike("|".join(BOILERPLATE)))
    return line.rlike(NOT_WHITE) & (punctuation | signs | navigation | boilerplate | open_ended)


def kept_lines(text: Column, rules: LineRules = LineRules()) -> Column:
    return F.filter(F.split(F.coalesce(text, F.lit("")), "\n"), lambda x: ~line_fails(x, rules))


def repeated_words(words: Column) -> Column:
    """Words that stand in a window of five words found twice or more, counted once each.

    The windows' 64-bit hashes are compared; only a text with equal ones pays for sorting (hash, place) pairs.
    """
    n = F.size(words)

    def covered(hashes: Column) -> Column:
        pairs = F.array_sort(F.transform(hashes, lambda h, i: F.struct(h.alias("h"), i.alias("i"))))

        def places(p: Column) -> Column:
            marked = F.transform(
                p, lambda x, k: F.when(F.equal_null(x["h"], F.get(p, k - 1)["h"]) | F.equal_null(x["h"], F.get(p, k + 1)["h"]), x["i"])
            )
            return F.array_sort(F.filter(marked, lambda x: x.isNotNull()))

        zero = F.struct(F.lit(0).alias("n"), F.lit(0).alias("end"))
        step = lambda a, i: F.struct((a["n"] + i + 5 - F.greatest(i, a["end"])).alias("n"), (i + 5).alias("end"))
        return F.aggregate(let(pairs, places), zero, step, lambda a: a["n"])

    def of(hashes: Column) -> Column:
        return F.when(F.size(F.array_distinct(hashes)) < F.size(hashes), covered(hashes)).otherwise(0)

    by_word = F.transform(words, lambda w: F.xxhash64(w))
    windows = let(by_word, lambda h: F.transform(F.sequence(F.lit(1), n - 4), lambda i: F.xxhash64(F.slice(h, i, 5))))
    return F.when(n < 6, 0).otherwise(let(windows, of)).cast("long")


def measures(df: DataFrame, rules: LineRules = LineRules(), text: str = "text") -> DataFrame:
    """df with n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, clean_chars, base_failed and kept."""
    return _judged(df, rules, text).drop("__clean")


def _judged(df: DataFrame, rules: LineRules, text: str) -> DataFrame:
    """measures and __clean, the lines that do not fail."""
    words, lines = "__words", "__lines"
    staged = df.withColumns({words: words_of(F.col(text)), lines: F.split(F.coalesce(F.col(text), F.lit("")), "\n"), "__clean": kept_lines(F.col(text), rules)})
    spoken = F.filter(F.col(lines), lambda x: x.rlike(NOT_WHITE))
    clean = F.col("__clean")
    n = F.col("n_words")
    staged = staged.withColumns(
        {
            "n_words": F.size(words).cast("long"),
            "word_chars": F.length(F.array_join(words, "")).cast("long"),
            "n_symbols": (F.length(F.coalesce(F.col(text), F.lit(""))) - _chars_without(F.coalesce(F.col(text), F.lit("")), SYMBOLS + "+")).cast("long"),
            "n_dup_lines": let(spoken, lambda x: F.size(x) - F.size(F.array_distinct(x))).cast("long"),
            "n_repeat_words": repeated_words(F.col(words)),
            "clean_chars": F.length(F.regexp_replace(F.array_join(clean, ""), f"{WHITE}+", "")).cast("long"),
        }
    )
    failed = (n < rules.min_words) | (100 * F.col("n_repeat_words") > rules.max_repeat_percent * n)
    staged = staged.withColumn("base_failed", failed)
    enough = F.col("clean_chars") >= (1 - rules.lost_share) * F.col("word_chars")
    return staged.withColumn("kept", ~F.col("base_failed") & enough).drop(words, lines)


def clean(df: DataFrame, rules: LineRules = LineRules(), text: str = "text") -> DataFrame:
    """The documents that pass, without their failing lines, in df's columns."""
    judged, rest = _judged(df, rules, text), [c for c in df.columns if c != text]
    # A filter would be pushed below the measures and have them computed again; a generator passes each row or none.
    passed = F.when(F.col("kept"), F.array(F.array_join("__clean", "\n"))).otherwise(F.array().cast("array<string>"))
    return judged.select(*rest, F.explode(passed).alias(text)).select(*df.columns)
