"""Line-first cleaning: rules for each line, then a verdict on what is left.

A line fails if it is *badly punctuated* (it has ``min_line_words`` words or more
and does not end like a sentence, or marks and symbols outnumber half its words), *navigation* (separators between short entries), or
*boilerplate* (signs of rights in any language, and notices, cookie and script messages in four).  Failing lines go; a
document that loses more than ``max_lost`` of its non-blank bytes is rejected.

Null text is a text without words; such documents are rejected (under 20 words).
Lines that are blank are neither judged nor removed.  Repeated rows are judged
each on its own, a null doc_id stays null, empty tables give no rows.  Texts are
taken whole, one in memory at a time with a few numbers for each word.  Other
columns are not looked at; those that ``keep`` names come back, under ``in_`` and
their name where the operator has a column of that name.
"""

from __future__ import annotations

import re

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from .common import HashCache, covered, handed_on, slices

SPACE = b" \t\n\r\x0b\x0c"
#: fixed values: endings of a sentence, as UTF-8
ENDINGS = tuple(x.encode() for x in (".", "!", "?", "…", '"', "'", "”", "’", "»", ")", ":", ";", "。", "！", "？"))
#: fixed values: separators of navigation
BARS = (b"|", "»".encode(), "›".encode(), "·".encode(), "•".encode())
#: fixed values: signs of rights, and what notices say in English, German, French and Spanish
NOTICES = (
    "©|℗|[(]c[)] *(19|20)[0-9][0-9]|spdx-license-identifier|https?://[^ ]*(license|privacy|cookie|terms)|all rights reserved|cookie policy|privacy policy|terms of use|terms of service|use cookies|enable javascript|licensed under|released under|click here to|sign up for|subscribe to our|lorem ipsum"
    "|alle rechte vorbehalten|cookie-richtlinie|datenschutzerklärung|nutzungsbedingungen|verwendet cookies|verwenden cookies|javascript aktivieren|klicken sie hier|newsletter abonnieren|lizenziert unter"
    "|tous droits réservés|politique de confidentialité|conditions d'utilisation|utilise des cookies|utilisons des cookies|activer javascript|cliquez ici|abonnez-vous|sous licence"
    "|todos los derechos reservados|política de privacidad|términos de uso|condiciones de uso|utiliza cookies|utilizamos cookies|habilite javascript|activar javascript|haga clic aquí|suscríbase|bajo la licencia"
)
NOTICE = re.compile(NOTICES.encode())
SYMBOLS = re.compile(rb"[#*$%&|<>]")
MARKS = re.compile(rb"[!?#*$%&<>]")
MIN_LINE_WORDS, MAX_LOST = 4, 0.5
REPEAT_WORDS, MIN_WORDS, REPEAT_PERCENT = 8, 20, 30


def line_fails(line: bytes) -> str:
    """The name of the rule that the line breaks, or an empty string."""
    words = line.split()
    if not words:
        return ""
    bars = sum(1 for w in words if w in BARS)
    if bars >= 2 and 8 * bars >= len(words):
        return "navigation"
    if NOTICE.search(line.lower()):
        return "boilerplate"
    if len(words) >= MIN_LINE_WORDS and (not words[-1].endswith(ENDINGS) or 2 * len(MARKS.findall(line)) > len(words)):
        return "punctuation"
    return ""


_hash: HashCache | None = None


def repeat_words(words: list[bytes], window: int = REPEAT_WORDS) -> int:
    """Words that lie in a window of ``window`` words found twice or more."""
    global _hash
    if _hash is None:
        from xxhash import xxh3_64_intdigest

        _hash = HashCache(xxh3_64_intdigest)
    n = len(words) - window + 1
    if n < 2:
        return 0
    h = np.fromiter(map(_hash.__getitem__, words), dtype=np.uint64, count=len(words))
    key, factor = np.zeros(n, np.uint64), np.uint64(0x9E3779B97F4A7C15)
    for k in range(window):
        key = key * factor + h[k : k + n]
    order = np.sort(key)
    if not (order[1:] == order[:-1]).any():
        return 0
    again = np.isin(key, order[1:][order[1:] == order[:-1]])
    seen: dict[tuple, list[int]] = {}
    for i in np.flatnonzero(again).tolist():  # the hash only proposes; words decide
        seen.setdefault(tuple(words[i : i + window]), []).append(i)
    starts = np.array([i for at in seen.values() if len(at) > 1 for i in at], dtype=np.int64)
    return int(covered(len(words), starts, window).sum())


def judge(text: bytes, max_lost: float = MAX_LOST) -> tuple:
    """Base measures, verdict, and the text without failing lines."""
    words = text.split()
    chars = sum(len(w) for w in words) if text.isascii() else len(b"".join(words).decode("utf-8", "replace"))
    lines, seen, dup, lost, size, kept, failed = text.split(b"\n"), set(), 0, 0, 0, [], []
    for line in lines:
        bare = len(b"".join(line.split()))
        if bare:
            dup += line in seen
            seen.add(line)
        rule = line_fails(line) if bare else ""
        size += bare
        if rule:
            failed.append(rule)
            lost += bare
        else:
            kept.append(line)
    repeated = repeat_words(words)
    base_failed = len(words) < MIN_WORDS or 100 * repeated > REPEAT_PERCENT * len(words)
    verdict = not base_failed and lost <= max_lost * size
    return (len(words), chars, len(SYMBOLS.findall(text)), dup, repeated, base_failed, verdict, len(failed), lost, b"\n".join(kept) if failed else None)


COLUMNS = ("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "kept", "n_failed_lines", "n_lost_bytes")


def clean(docs: DataFrame, max_lost: float = MAX_LOST, keep: tuple[str, ...] = ()) -> DataFrame:
    """doc_id, the measures and verdict, and ``clean_text`` (text without failing lines).

    ``keep`` names further columns of ``docs`` to hand on unchanged.
    """
    from pyspark.sql import functions as F

    names = handed_on(tuple(c for c in keep if c != "doc_id"), ("doc_id", *COLUMNS, "clean_text"))
    source = docs.select(F.coalesce(F.col("text").cast("binary"), F.lit(b"")).alias("_text"), F.col("doc_id").cast("long").alias("doc_id"), *[F.col(f"`{c}`").alias(f"_keep{i}") for i, c in enumerate(names)])
    kinds = {f.name: f.dataType.simpleString() for f in source.schema}

    def run(batches):
        for batch in slices(batches):
            texts = batch.column(0).to_pylist()
            found = [judge(t, max_lost) for t in texts]
            cols = list(zip(*found, strict=True)) if found else [()] * 10
            types = [pa.int64()] * 5 + [pa.bool_()] * 2 + [pa.int64()] * 2
            arrays = [pa.array(c, t) for c, t in zip(cols, types, strict=False)]
            texts = pa.array([t if c is None else c for t, c in zip(texts, cols[9], strict=True)], pa.binary())
            yield pa.RecordBatch.from_arrays([*batch.columns[1:], *arrays, texts], [*batch.schema.names[1:], *COLUMNS, "clean_text"])

    schema = ", ".join([*(f"`{c}` {t}" for c, t in kinds.items() if c != "_text"), *(f"{c} {'boolean' if c in ('base_failed', 'kept') else 'long'}" for c in COLUMNS), "clean_text binary"])
    out = source.mapInArrow(run, schema)
    return out.select("doc_id", *[F.col(f"_keep{i}").alias(n) for i, n in enumerate(names.values())], *COLUMNS, F.col("clean_text").cast("string").alias("clean_text"))
