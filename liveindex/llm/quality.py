"""Quality rules on repetition: how much of a text lies inside repeated n-grams and lines.

Word and line hashes come from running polynomial sums in numpy, n-gram hashes from sums of word hashes; an
n-gram is repeated if its text holds its hash twice. Characters are code points.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import types as T

from liveindex.llm import common as C

# Widely published limits of repetition in web text. Share of a text's characters in words of
# repeats (after the first) of n-grams, share in occurrences of the most frequent n-gram, share of repeated
# lines by number and by characters.
REPEATED = {5: 0.15, 6: 0.14, 7: 0.13, 8: 0.12, 9: 0.11, 10: 0.10}
MOST_FREQUENT = {2: 0.20, 3: 0.18, 4: 0.16}
LINES, LINE_CHARS = 0.30, 0.20
#: Lines that a text must have for the share of repeated lines by number to count: in a text of three lines, one
#: heading that is said again is no repetition.
LEAST_LINES = 10
#: Times an n-gram must occur to count as a most frequent one: one long word pair is no repetition.
LEAST_TIMES = 3

SYMBOL = np.zeros(256, bool)
SYMBOL[list(b"#*$%&|<>")] = True

COLUMNS = [("n_words", T.LongType()), ("word_chars", T.LongType()), ("n_symbols", T.LongType()), ("n_dup_lines", T.LongType()), ("n_repeat_words", T.LongType()),
           ("base_failed", T.BooleanType()), ("kept", T.BooleanType()), *[(f"repeated_{n}", T.DoubleType()) for n in REPEATED], *[(f"top_{n}", T.DoubleType()) for n in MOST_FREQUENT],
           ("dup_lines", T.DoubleType()), ("dup_line_chars", T.DoubleType())]


def _classes(hashes: np.ndarray, doc: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Of each item, how often its text holds it, and whether an earlier item of the text equals it."""
    if not hashes.size:
        return np.zeros(0, np.int64), np.zeros(0, bool)
    key = C.mix(hashes ^ C.mix(doc.astype(np.uint64) + np.uint64(1)))  # one sort key for (text, item)
    order = np.argsort(key, kind="stable")
    sorted_ = key[order]
    new = np.ones(key.size, bool)
    new[1:] = sorted_[1:] != sorted_[:-1]
    heads = np.flatnonzero(new)
    sizes = np.diff(np.append(heads, key.size))
    times, again = np.empty(key.size, np.int64), np.empty(key.size, bool)
    times[order], again[order] = np.repeat(sizes, sizes), ~new
    return times, again


def _covered(at: np.ndarray, n: int, words: int) -> np.ndarray:
    """Words inside the n-grams that begin at the given words."""
    step = np.zeros(words + 1, np.int64)
    np.add.at(step, at, 1)
    np.add.at(step, np.minimum(at + n, words), -1)
    return np.cumsum(step)[:-1] > 0


def measures(texts: pa.Array) -> dict[str, np.ndarray]:
    """The columns of COLUMNS for an array of texts; a null text has the measures of an empty one."""
    raw, off = C.flat(texts)
    starts, ends, first = C.spans(C.IS_WORD[raw], off)
    doc = C.owner(first)
    words = C.span_hashes(raw, starts, ends)
    points = np.zeros(raw.size + 1, np.int64)
    np.cumsum((raw & 0xC0) != 0x80, out=points[1:])
    chars = points[ends] - points[starts]
    n_words, all_chars = np.diff(first), C.per_text(chars, first)
    share = lambda x: x / np.maximum(all_chars, 1)
    out = {"n_words": n_words, "word_chars": all_chars, "n_symbols": C.per_text(SYMBOL[raw], off)}

    line_starts, line_ends, line_first = C.spans(raw != 10, off)
    in_word = np.zeros(raw.size + 1, np.int64)
    np.cumsum(C.IS_WORD[raw], out=in_word[1:])
    worded = in_word[line_ends] > in_word[line_starts]
    lines, line_doc = C.span_hashes(raw, line_starts, line_ends)[worded], C.owner(line_first)[worded]
    line_chars = (points[line_ends] - points[line_starts])[worded]
    _, again = _classes(lines, line_doc)
    count = lambda d, w=None: np.bincount(d, w, minlength=len(n_words))
    out["n_dup_lines"] = count(line_doc[again])
    out["dup_lines"] = out["n_dup_lines"] / np.maximum(count(line_doc), 1)
    out["dup_line_chars"] = count(line_doc[again], line_chars[again]) / np.maximum(count(line_doc, line_chars), 1)

    bad = ((out["dup_lines"] > LINES) & (count(line_doc) >= LEAST_LINES)) | (out["dup_line_chars"] > LINE_CHARS)
    width = np.concatenate(([0], np.cumsum(chars)))
    for limits, least in ((MOST_FREQUENT, LEAST_TIMES), (REPEATED, 2)):
        alive = None  # where an n-gram may begin that occurs often enough: only where a shorter one did
        for n, most in limits.items():
            grams, at = C.grams(words, first, n, alive)
            times, again = _classes(grams, doc[at])
            alive = at[times >= least]
            if limits is MOST_FREQUENT:
                name, top = f"top_{n}", np.zeros(len(n_words), np.int64)
                often = times >= least
                np.maximum.at(top, doc[alive], times[often] * (width[alive + n] - width[alive]))
                out[name] = np.minimum(share(top), 1.0)
            else:
                name = f"repeated_{n}"
                out[name] = share(C.per_text(chars * _covered(at[again], n, words.size), first))
                if n == 5:
                    out["n_repeat_words"] = C.per_text(_covered(alive, n, words.size), first)
            bad |= out[name] > most
    out["base_failed"] = (n_words < 10) | (100 * out["n_repeat_words"] > 20 * n_words)
    out["kept"] = ~out["base_failed"] & ~bad
    return out


def repetition(df: DataFrame, text: str = "text") -> DataFrame:
    """df with the measures, the base rule and the verdict `kept` of each text.

    Null and empty texts have no words, so the base rule fails them. Every row is judged alone: repeated rows get
    equal verdicts, an empty table gives an empty result, and columns named like a measure are replaced.
    """
    names = {n for n, _ in COLUMNS}
    df = df.drop(*[c for c in df.columns if c.lower() in names and c != text])
    schema = T.StructType([*df.schema, *[T.StructField(n, t) for n, t in COLUMNS]])
    fields = [pa.field(n, {T.LongType: pa.int64(), T.DoubleType: pa.float64(), T.BooleanType: pa.bool_()}[type(t)]) for n, t in COLUMNS]

    def judged(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for part in C.pieces(batch, text):
                found = measures(part.column(text))
                yield pa.RecordBatch.from_arrays([*part.columns, *[pa.array(found[f.name].astype(f.type.to_pandas_dtype())) for f in fields]], schema=pa.schema([*part.schema, *fields]))

    return df.mapInArrow(judged, schema)
