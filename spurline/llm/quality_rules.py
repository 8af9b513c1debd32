"""Line-first cleaning: rules judge each line, failed lines go, then documents that lose too much text go."""

from __future__ import annotations

import re
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from spurline.llm.arrow import map_rows

#: Phrases of page furniture in four languages, matched in lower case anywhere in a line of at most BOILER_WORDS words.
BOILERPLATE = {
    "en": ("all rights reserved", "accept cookies", "cookie policy", "privacy policy", "terms of use", "terms of service", "enable javascript", "click here", "read more", "sign up", "log in", "subscribe to our newsletter", "share this", "skip to content", "back to top"),
    "de": ("alle rechte vorbehalten", "cookies akzeptieren", "cookie-richtlinie", "datenschutzerklärung", "nutzungsbedingungen", "allgemeine geschäftsbedingungen", "javascript aktivieren", "hier klicken", "klicken sie hier", "weiterlesen", "mehr erfahren", "jetzt registrieren", "newsletter abonnieren", "artikel teilen", "zum inhalt springen", "nach oben"),
    "fr": ("tous droits réservés", "accepter les cookies", "politique de cookies", "politique de confidentialité", "conditions d'utilisation", "mentions légales", "activer javascript", "cliquez ici", "lire la suite", "en savoir plus", "se connecter", "créer un compte", "abonnez-vous à notre newsletter", "partager cet article", "aller au contenu", "haut de page"),
    "es": ("todos los derechos reservados", "aceptar cookies", "política de cookies", "política de privacidad", "términos de uso", "condiciones de uso", "aviso legal", "activar javascript", "haga clic aquí", "haz clic aquí", "leer más", "iniciar sesión", "crear una cuenta", "suscríbete a nuestro boletín", "compartir este artículo", "saltar al contenido", "volver arriba"),
}
BOILER_WORDS = 12
#: Share of a text's word characters that its failed lines may hold.
MAX_LOST = 0.3
SYMBOLS = "#*$%&|<>"
SPACES = " \t\n\x0b\x0c\r"
_phrases = tuple(p for group in BOILERPLATE.values() for p in group)
_sentence = re.compile(r"[.!?…:;,。！？،।\"')\]]").search
_symbol = re.compile(r"[#*$%&|<>]").search


def line_fails(line: str, words: list[bytes] | None = None) -> str | None:
    """The rule that a line with words breaks, or None.

    Of lines of three words or more: ``navigation`` (two bars or arrows, at least one for three words), ``symbols`` (over half of the
    words have one), ``numbers`` (over half of the word characters are digits), ``shouting`` (capitals only, with ``!!`` or eight words), ``repetition`` (eight words, under a quarter of them
    distinct). Of twelve words or more: ``punctuation`` (none at all). Of BOILER_WORDS or fewer: ``boilerplate``. Only the last knows words of a language.
    """
    words = line.split() if words is None else words
    n = len(words)
    if n >= 3:
        bars = line.count("|") + line.count("»") + line.count(" > ")
        if bars >= 2 and 3 * bars >= n:
            return "navigation"
        if any(c in line for c in SYMBOLS) and 2 * sum(bool(_symbol(w)) for w in line.split()) > n:
            return "symbols"
        if 2 * sum(map(line.count, "0123456789")) > len(line) - sum(map(line.count, SPACES)):
            return "numbers"
        if line.isupper() and ("!!" in line or n >= 8):
            return "shouting"
        if n >= 8 and 4 * len(set(words)) < n:
            return "repetition"
    if n >= 12 and not _sentence(line):
        return "punctuation"
    if n <= BOILER_WORDS:
        low = line.lower()
        if any(p in low for p in _phrases):
            return "boilerplate"
    return None


def count_repeated(words: list[bytes], width: int = 5) -> int:
    """Words inside windows of ``width`` words that occur twice or more, the first occurrence included."""
    n = len(words) - width + 1
    if n < 2:
        return 0
    windows = list(zip(*(words[i:] for i in range(width)), strict=False))
    seen: set = set()
    twice: set = set()
    if len(seen := set(windows)) == n:
        return 0
    seen = set()
    for w in windows:
        (twice if w in seen else seen).add(w)
    covered = total = 0  # covered: the end of what is counted so far
    for i, w in enumerate(windows):
        if w in twice:
            total += i + width - max(i, covered)
            covered = i + width
    return total


def judge(text: str | None) -> tuple:
    """``(n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, base_failed, kept, lost, cleaned)`` of a text; null: empty."""
    text = text or ""
    words = text.encode("utf-8", "surrogatepass").split()
    n = len(words)
    chars = len(text) - sum(map(text.count, SPACES))
    repeated = count_repeated(words)
    base = n < 10 or 100 * repeated > 20 * n
    seen: set[str] = set()
    twice, lost, good = 0, 0, []
    for line in text.split("\n"):
        if parts := line.encode("utf-8", "surrogatepass").split():
            twice += line in seen
            seen.add(line)
            if line_fails(line, parts):
                lost += len(line) - sum(map(line.count, SPACES))
                continue
        good.append(line)
    return n, chars, sum(map(text.count, SYMBOLS)), twice, repeated, base, not base and lost <= MAX_LOST * chars, lost, text if len(good) == text.count("\n") + 1 else "\n".join(good)


def judge_documents(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """A row for every row of ``docs``: id, the counts of :func:`judge`, verdict, characters lost, and the cleaned text.

    Words are runs without ASCII white space; lines are split at newlines only. Null text: no words, rejected by the base
    rule. Null ids and repeated rows stay. Other columns are ignored.
    """
    def make():
        return lambda doc, text: ((doc, *judge(text)),)

    return map_rows(docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("string").alias("text")), ["doc_id", "text"], make, "doc_id long, n_words long, word_chars long, n_symbols long, n_dup_lines long, n_repeat_words long, base_failed boolean, kept boolean, lost_chars long, cleaned string")


def keep_clean(docs: DataFrame) -> DataFrame:
    """The documents that pass, with their failed lines taken out (and ``n_chars`` recounted where that changed the text)."""
    names = docs.columns
    text = names.index("text")
    size = names.index("n_chars") if "n_chars" in names else None

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for at in range(0, batch.num_rows, 512):
                part = batch.slice(at, 512)
                old = part.column(text).to_pylist()
                found = [judge(t) for t in old]
                new = [f[-1] if t is not None else None for f, t in zip(found, old, strict=True)]
                columns = list(part.columns)
                columns[text] = pa.array(new, part.schema.field(text).type)
                if size is not None:
                    columns[size] = pa.array([k if a == b else len(b) for k, a, b in zip(part.column(size).to_pylist(), old, new, strict=True)], part.schema.field(size).type)
                yield pa.RecordBatch.from_arrays(columns, schema=part.schema).filter(pa.array([f[6] for f in found]))

    return docs.mapInArrow(run, docs.schema)
