"""Quality rules, lines first.

Each line is judged on its own: navigation (a run of short items between bars or arrows), boilerplate (site phrases),
punctuation (no letter or digit, mostly symbols, shouting, or a short line that ends in no terminal mark). Failing
lines are removed; a document that loses more than `max_lost_percent` of its word characters is rejected. The base
measures of the contract are taken on the whole text beforehand.

Documents are independent of each other: no shuffle, an Arrow batch at a time.

Defined cases: a null text counts as empty (0 words, base_failed); lines without a word are neither judged nor removed;
repeated rows get equal results; extra columns pass through `clean_documents` untouched.
"""

from __future__ import annotations

import re
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from lakeadapt.llm.common import of_type, sliced

#: ASCII white space, symbols of the contract, marks that end a sentence or a quotation, site phrases in English,
#: German, French and Spanish.
SPACES = b" \t\n\x0b\x0c\r"
ASCII_SPACES = SPACES.decode()
SYMBOLS = b"#*$%&|<>"
TERMINAL = tuple(".!?:;…\"'”’»)]}。！？।؟")
SEPARATORS = frozenset(["|", "»", "›", "·", "•", ">", ">>", "/"])
PHRASES = (
    "all rights reserved", "terms of use", "terms of service", "privacy policy", "cookie policy", "use cookies",
    "enable javascript", "lorem ipsum", "powered by", "click here", "sign up for", "subscribe to our", "skip to content",
    "back to top",
    "alle rechte vorbehalten", "nutzungsbedingungen", "datenschutzerklärung", "cookie-richtlinie", "verwendet cookies", "javascript aktivieren",
    "hier klicken", "newsletter abonnieren", "zum inhalt springen", "nach oben",
    "tous droits réservés", "conditions d'utilisation", "politique de confidentialité", "utilise des cookies", "activer javascript",
    "cliquez ici", "abonnez-vous à", "aller au contenu", "haut de page",
    "todos los derechos reservados", "términos de uso", "política de privacidad", "utiliza cookies", "activar javascript", "haga clic aquí",
    "suscríbase a", "saltar al contenido", "volver arriba",
)


@dataclass(frozen=True)
class Rules:
    min_words: int = 10
    max_repeat_percent: int = 20
    min_separators: int = 3
    words_per_separator: int = 4
    symbol_percent: int = 10
    shout_percent: int = 50
    short_line_words: int = 4
    max_lost_percent: int = 50


PRODUCTION = Rules()
_PHRASE = re.compile("|".join(map(re.escape, PHRASES)))
_ALNUM = re.compile(r"[^\W_]")
_ODD = np.array([0x9E3779B97F4A7C15, 0xC2B2AE3D27D4EB4F, 0x165667B19E3779F9, 0xD6E8FEB86659FD93, 0xA0761D6478BD642F], np.uint64)


def repeated_words(words: list[bytes], window: int = 5) -> int:
    """Words that lie in a window of five found twice or more."""
    n = len(words)
    if n <= window:
        return 0
    codes = np.fromiter(map(hash, words), np.int64, n).view(np.uint64)
    grams = np.zeros(n - window + 1, np.uint64)
    for k in range(window):
        grams += (codes[k : n - window + 1 + k] ^ (codes[k : n - window + 1 + k] >> np.uint64(29))) * _ODD[k]
    order = np.argsort(grams, kind="stable")
    ordered = grams[order]
    same = ordered[1:] == ordered[:-1]
    if not same.any():
        return 0
    twice = np.zeros(len(grams), bool)
    twice[order[1:][same]] = True
    twice[order[:-1][same]] = True
    covered = np.zeros(n, bool)
    for k in range(window):
        covered[k : k + len(twice)] |= twice
    return int(covered.sum())


def line_fails(line: str, words: list[str], rules: Rules) -> bool:
    """Whether a line with words goes."""
    n = len(words)
    bars = sum(w in SEPARATORS for w in words)
    if bars >= rules.min_separators and bars * rules.words_per_separator >= n:
        return True
    if not _ALNUM.search(line):
        return True
    raw = line.encode("utf-8", "surrogatepass")
    chars = len(line) - (len(raw) - len(raw.translate(None, SPACES)))
    if (len(raw) - len(raw.translate(None, SYMBOLS))) * 100 > rules.symbol_percent * chars:
        return True
    marked = sum(w.endswith(("!!", "??", "!?")) for w in words)
    if marked >= 3 and marked * 100 > rules.shout_percent * n:
        return True
    if n <= rules.short_line_words and not line.rstrip().endswith(TERMINAL):
        return True
    return n <= 40 and bool(_PHRASE.search(line.lower()))


def judge_text(text: str | None, rules: Rules = PRODUCTION) -> tuple:
    """n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, base_failed, kept, n_lines_removed, cleaned text."""
    text = text or ""
    raw = text.encode("utf-8", "surrogatepass")
    words = raw.split()
    n = len(words)
    bare = raw.translate(None, SPACES)
    word_chars = len(text) - (len(raw) - len(bare))
    symbols = len(bare) - len(bare.translate(None, SYMBOLS))
    lines = text.split("\n")
    seen: set[str] = set()
    dup = removed = lost = 0
    left = []
    for line in lines:
        if not line.strip(ASCII_SPACES):
            left.append(line)
            continue
        own = line.split() or [line]
        if line in seen:
            dup += 1
        seen.add(line)
        if line_fails(line, own, rules):
            removed += 1
            lost += sum(map(len, own))
        else:
            left.append(line)
    repeat = repeated_words(words)
    failed = n < rules.min_words or 100 * repeat > rules.max_repeat_percent * n
    kept = not failed and 100 * lost <= rules.max_lost_percent * word_chars
    return n, word_chars, symbols, dup, repeat, failed, kept, removed, "\n".join(left) if removed else text


FIELDS = "n_words long, word_chars long, n_symbols long, n_dup_lines long, n_repeat_words long, base_failed boolean, kept boolean, lines_removed long, clean_text string"


def judge_documents(docs: DataFrame, rules: Rules = PRODUCTION, with_text: bool = False) -> DataFrame:
    """documents -> doc_id and the fields above (the cleaned text only if asked for)."""
    names = [x.split()[0] for x in FIELDS.split(", ")]
    out = names if with_text else names[:-1]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in sliced(batches):
            rows = [judge_text(t, rules) for t in batch.column("text").to_pylist()]
            cols = list(zip(*rows)) if rows else [[] for _ in names]
            kinds = [pa.int64()] * 5 + [pa.bool_()] * 2 + [pa.int64(), pa.string()]
            arrays = [pa.array(c, t) for c, t in zip(cols, kinds)][: len(out)]
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), *arrays], ["doc_id", *out])

    schema = "doc_id long, " + ", ".join(FIELDS.split(", ")[: len(out)])
    return of_type(docs, {"doc_id": "long", "text": "string"}).mapInArrow(run, schema)


def clean_documents(docs: DataFrame, rules: Rules = PRODUCTION) -> DataFrame:
    """The documents kept, with the columns of docs; failing lines are out of their text and n_chars follows."""
    spec = docs.select(F.col("text").cast("string").alias("text"), *[F.col(f"`{c}`") for c in docs.columns if c != "text"]).schema

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in sliced(batches):
            rows = [judge_text(t, rules) for t in batch.column("text").to_pylist()]
            keep = pa.array([r[6] for r in rows], pa.bool_())
            at = batch.schema.get_field_index("text")
            out = batch.set_column(at, batch.schema.field(at), pa.array([r[8] for r in rows], batch.schema.field(at).type))
            at = batch.schema.get_field_index("n_chars")
            if at >= 0:
                out = out.set_column(at, batch.schema.field(at), pa.array([len(r[8]) for r in rows], pa.int64()).cast(batch.schema.field(at).type))
            yield out.filter(keep)

    return docs.select(*spec.names).mapInArrow(run, spec).select(*docs.columns)


def op9_line_first_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    return judge_documents(spark.read.parquet(f"{sf_dir}/documents.parquet"))
