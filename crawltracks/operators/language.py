"""Language identification by frequent words and marker letters, all native."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

UNKNOWN = "un"
#: Frequent words of each language, those it shares with no other here.
STOP_WORDS = {
    "ca": ["amb", "aquest", "dels", "els", "fins", "hem", "més", "però", "també"],
    "cs": ["jako", "jsme", "jsou", "které", "nebo", "podle", "při", "také", "že"],
    "de": ["als", "auf", "auch", "das", "der", "die", "ein", "eine", "ist", "mit", "nicht", "sich", "und", "von"],
    "en": ["and", "for", "from", "here", "of", "on", "that", "the", "this", "to", "was", "what", "with"],
    "es": ["del", "el", "los", "las", "para", "por", "se", "su", "una", "y"],
    "fr": ["au", "dans", "des", "du", "est", "et", "les", "par", "pour", "que", "sur", "une"],
    "it": ["anche", "che", "dalla", "degli", "della", "delle", "gli", "il", "nella", "sono"],
    "nl": ["bij", "een", "het", "naar", "niet", "ook", "van", "voor", "wordt", "zijn"],
    "pl": ["jest", "jak", "lub", "oraz", "przez", "się", "tym", "który", "więc"],
    "pt": ["ao", "com", "dos", "em", "foi", "mais", "não", "pela", "pelo", "uma"],
    "sv": ["att", "av", "efter", "från", "inte", "och", "som", "till", "är"],
}
#: Letters that mark a language.
LETTERS = {
    "ca": "·ïò",
    "cs": "ěřůčšž",
    "de": "äöüß",
    "en": "",
    "es": "ñíóú",
    "fr": "èêçà",
    "it": "ìò",
    "nl": "",
    "pl": "ąćęłńśźż",
    "pt": "ãõ",
    "sv": "åäö",
}
MIN_LETTERS, MIN_SHARE = 20, 0.5


def tokens(text: Column) -> Column:
    return F.split(F.lower(text), r"[^\p{L}]+")


def detect_language(rows: DataFrame, text: str, name: str = "desc_lang") -> DataFrame:
    """Adds the code of the language with the greatest score (ties: first by code); 'un' for few letters, no score or no text.

    One expression, in which a text's words and marker letters are bound once by a lambda: filters on the result, which
    the optimiser pushes down by copying the expression, then do not multiply the work. Words and letters are thinned to
    those that some language counts before each language counts in what is left.
    """
    letters = F.length(F.regexp_replace(text, r"[^\p{L}]", ""))
    known, marked = sorted({w for x in STOP_WORDS.values() for w in x}), "".join(sorted(set("".join(LETTERS.values()))))
    low = f"lower(`{text}`)"
    held = f"named_struct('words', filter(split({low}, r'[^\\p{{L}}]+'), w -> w IN ({_list(known)})), 'marks', regexp_replace({low}, '[^{marked}]+', ''))"
    entries = [f"named_struct('n', 0, 'order', 1, 'code', '{UNKNOWN}')"]
    for i, x in enumerate(sorted(STOP_WORDS)):
        marks = f" + length(h.marks) - length(translate(h.marks, '{LETTERS[x]}', ''))" if LETTERS[x] else ""
        entries.append(f"named_struct('n', size(filter(h.words, w -> w IN ({_list(STOP_WORDS[x])}))){marks}, 'order', {-i}, 'code', '{x}')")
    found = F.expr(f"get(transform(array({held}), h -> array_max(array({', '.join(entries)}))), 0).code")
    sure = (letters >= MIN_LETTERS) & (letters >= MIN_SHARE * F.length(text))
    return rows.withColumn(name, F.when(sure, found).otherwise(UNKNOWN))


def _list(words: list[str]) -> str:
    return ", ".join(f"'{w}'" for w in words)


def gate_known(rows: DataFrame, lang: str = "lang") -> DataFrame:
    return rows.where(F.col(lang).isNotNull() & (F.col(lang) != UNKNOWN))
