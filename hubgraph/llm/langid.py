"""Language identification by cross-parsing entropy.

For each language a suffix automaton over a bounded sample of its labelled text gives longest-match lengths. A text
is parsed greedily into phrases, each the longest string that occurs in the sample; the number of phrases, times the
bits to point into the sample, per character is the cross-parsing entropy. The language with the least one wins.
A phrase also ends where a unit of PIECE signs does, for every language alike.

Signs are a blank for all that is no letter, one sign for each of the letters that are frequent in the samples, and
DIGITS signs for any other letter, from a band of their own, so that no two letters are ever taken for one.
"""

from __future__ import annotations

import hashlib
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from hubgraph.llm.common import id_crc, in_arrow, slices

UNKNOWN = "und"
#: Bounds of the labelled sample: distinct documents a language, characters taken from each, and of all languages.
SAMPLE_DOCS, DOC_CHARS, ALL_CHARS = 96, 160, 122_880
PIECE = 512  # signs parsed as one unit, so that a text is scanned by many lanes at once
FREQUENT, BAND, DIGITS = 92, 34, 4  # BAND ** DIGITS is more than there are code points


@lru_cache(1)
def _letters() -> tuple[np.ndarray, np.ndarray]:
    """For every code point: is it a letter, and its lower case where that is one code point."""
    letter, lower = np.zeros(0x110000, bool), np.arange(0x110000, dtype=np.uint32)
    for i in range(0x110000):
        c = chr(i)
        if c.isalpha():
            letter[i] = True
            if len(low := c.lower()) == 1:
                lower[i] = ord(low)
    return letter, lower


def _points(text: str) -> np.ndarray:
    return np.frombuffer(text.encode("utf-32-le", "surrogatepass"), np.uint32)


class SuffixAutomaton:
    """All substrings of a sequence of small integers, as a dense table for greedy parsing.

    parse[s, c] is twice the next state, plus one if a phrase begins with c, that is, no occurrence goes on with c and
    the parse starts again at the root.
    """

    def __init__(self, sequence: list[int], alphabet: int):
        step, link, size, last = [{}], [-1], [0], 0
        for c in sequence:
            cur = len(step)
            step.append({})
            size.append(size[last] + 1)
            link.append(0)
            p = last
            while p >= 0 and c not in step[p]:
                step[p][c] = cur
                p = link[p]
            if p >= 0:
                q = step[p][c]
                if size[q] == size[p] + 1:
                    link[cur] = q
                else:
                    twin = len(step)
                    step.append(dict(step[q]))
                    size.append(size[p] + 1)
                    link.append(link[q])
                    while p >= 0 and step[p].get(c) == q:
                        step[p][c] = twin
                        p = link[p]
                    link[q] = link[cur] = twin
            last = cur
        self.parse = np.zeros((len(step), alphabet), np.int32)
        root = np.zeros(alphabet, np.int32)
        for c, to in step[0].items():
            root[c] = to
        self.parse[:] = 2 * root + 1
        for s, steps in enumerate(step):
            for c, to in steps.items():
                self.parse[s, c] = 2 * to
        self.parse[0] = 2 * root + 1  # at the root a phrase begins; a sign that never occurs is one by itself
        self.length = max(2, len(sequence))


class LanguageModel:
    """One automaton a language over a common alphabet."""

    def __init__(self, samples: dict[str, str]):
        self.names = sorted(samples)
        letter, lower = _letters()
        points = {k: lower[_points(samples[k])] for k in self.names}
        seen, n = np.unique(np.concatenate([p[letter[p]] for p in points.values()] or [np.zeros(0, np.uint32)]), return_counts=True)
        seen = seen[np.argsort(-n, kind="stable")[:FREQUENT]]
        code = np.zeros(0x110000, np.uint8)
        code[letter] = FREQUENT + 1
        code[seen] = np.arange(1, len(seen) + 1)
        self.code = code[lower]  # upper case has the code of its lower case
        self.letter, self.lower, self.alphabet = letter, lower, FREQUENT + 1 + BAND
        self.automata = [SuffixAutomaton(self.signs(points[k])[0].tolist(), self.alphabet) for k in self.names]

    def signs(self, points: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """The signs of code points, and where each one's begin (with the total)."""
        code = self.code[points]
        rare = code > FREQUENT
        at = np.r_[0, np.cumsum(np.where(rare, DIGITS, 1))]
        out = np.repeat(code, np.diff(at))
        own, low = at[:-1][rare], self.lower[points[rare]]
        for k in range(DIGITS):
            out[own + k] = FREQUENT + 1 + low // BAND**k % BAND
        return out, at

    def entropies(self, texts: list[str]) -> tuple[np.ndarray, np.ndarray]:
        """Bits a character of each text for each language, and whether it has a letter."""
        chars = np.array([len(t) for t in texts], np.int64)
        points = _points("".join(texts))
        off = np.r_[0, np.cumsum(chars)]
        has = np.r_[0, np.cumsum(self.letter[points])]
        lettered = has[off[1:]] > has[off[:-1]]
        codes, at = self.signs(points)
        off = at[off]
        size = np.diff(off)
        pieces = -(-size // PIECE)
        doc = np.repeat(np.arange(len(texts)), pieces)
        at = off[:-1][doc] + PIECE * (np.arange(len(doc)) - np.repeat(np.cumsum(pieces) - pieces, pieces))
        length = np.minimum(PIECE, off[1:][doc] - at)
        order = np.argsort(-length, kind="stable")
        doc, at, length = doc[order], at[order], length[order]
        live = len(length) - np.searchsorted(length[::-1], np.arange(PIECE), side="right")  # lanes longer than the step
        bits = np.zeros((len(texts), len(self.names)))
        lanes = np.zeros((int(length.max(initial=0)), len(doc)), np.uint8)
        for t in range(len(lanes)):
            lanes[t, : live[t]] = codes[at[: live[t]] + t]
        for k, automaton in enumerate(self.automata):
            table, wide = automaton.parse.ravel(), self.alphabet
            state, phrases = np.zeros(len(doc), np.int64), np.zeros(len(doc), np.int64)
            for t in range(len(lanes)):
                n = live[t]
                got = table[state[:n] * wide + lanes[t, :n]]
                phrases[:n] += got & 1
                state[:n] = got >> 1
            bits[:, k] = np.bincount(doc, phrases, len(texts)) * np.log2(automaton.length)
        return bits / np.maximum(chars, 1)[:, None], lettered

    def predict(self, texts: list[str]) -> tuple[list[str], np.ndarray]:
        bits, lettered = self.entropies(texts)
        if not self.names:
            return [UNKNOWN] * len(texts), np.zeros(len(texts))
        share = np.exp2(-4 * (bits - bits.min(1, keepdims=True)))
        score = share.max(1) / share.sum(1)
        best = bits.argmin(1)
        return [self.names[b] if ok else UNKNOWN for b, ok in zip(best, lettered, strict=True)], np.where(lettered, score, 0.0)


def sample_languages(labelled: DataFrame) -> dict[str, str]:
    """A bounded sample of each language of (text, lang): from the SAMPLE_DOCS distinct texts with the smallest hash,
    DOC_CHARS characters each, at a place in the text that the hash draws too. With many languages each document gives
    fewer, so that all samples together stay within ALL_CHARS (16 characters a document at least)."""
    known = labelled.where("lang is not null and text is not null").withColumn("h", F.xxhash64("text"))
    # Hashes above what some four samples of a language need are passed over before any rows are ranked.
    low = F.col("h").bitwiseAND((1 << 63) - 1)
    found = known.groupBy("lang").agg(F.approx_count_distinct("h").alias("n")).collect()
    most = labelled.sparkSession.createDataFrame([(r.lang, min((1 << 63) - 1, 4 * SAMPLE_DOCS * (1 << 63) // max(1, r.n))) for r in found], "lang string, most long")
    some = known.join(F.broadcast(most), "lang").where(low <= F.col("most")).select("lang", "h").distinct()
    ranked = some.withColumn("r", F.row_number().over(Window.partitionBy("lang").orderBy(low, "h")))
    drawn = ranked.where(F.col("r") <= SAMPLE_DOCS).collect()
    if not drawn:
        return {}
    chars = max(16, min(DOC_CHARS, ALL_CHARS // (SAMPLE_DOCS * len({r.lang for r in drawn}))))
    wanted = labelled.sparkSession.createDataFrame(drawn, "lang string, h long, r int")
    place = F.pmod("h", F.greatest(F.length("text") - chars + 1, F.lit(1)).cast("long")).cast("int") + 1
    rows = known.join(F.broadcast(wanted), ["lang", "h"]).select("lang", "r", F.substring("text", place, F.lit(chars)).alias("t"))
    held: dict[str, dict[int, str]] = {}
    for r in rows.dropDuplicates(["lang", "r"]).collect():
        held.setdefault(r.lang, {})[r.r] = r.t
    return {k: " ".join(v[r] for r in sorted(v)) for k, v in held.items()}


@lru_cache(1)
def _model(key: str, samples: tuple) -> LanguageModel:
    return LanguageModel(dict(samples))


def predict_languages(docs: DataFrame, samples: dict[str, str]) -> DataFrame:
    """docs with lang_pred and score (0 to 1, the winner's share of the languages' likelihoods).

    Whole texts are parsed, very long ones too. A null text, or one without a letter, has lang_pred "und" and score 0;
    so has every text if nothing was learned. Ties go to the first name. Repeated rows each get their row, an empty
    table gives an empty result, and all columns of docs are kept but those two names.
    """
    kept = [c for c in docs.columns if c not in ("lang_pred", "score")]
    docs = docs.select(*kept)
    items = tuple(sorted(samples.items()))
    key = hashlib.sha256(repr(items).encode()).hexdigest()
    schema = f"{', '.join(f'`{f.name}` {f.dataType.simpleString()}' for f in docs.schema)}, lang_pred string, score double"

    def run(batches):
        model = _model(key, items)
        for b in slices(batches, "text", 1_000_000):
            names, score = model.predict([t or "" for t in b.column("text").to_pylist()])
            yield pa.RecordBatch.from_arrays([*b.columns, pa.array(names, pa.string()), pa.array(score, pa.float64())], [*kept, "lang_pred", "score"])

    return docs.transform(in_arrow, run, schema)


def language_report(docs: DataFrame) -> DataFrame:
    """The digest of query op2: three folds of four are learned from, all documents are predicted."""
    fold = id_crc("doc_id") % 4
    samples = sample_languages(docs.where(fold != 2))
    return predict_languages(docs.select("doc_id", "text"), samples).select("doc_id", (id_crc("doc_id") % 4 == 2).alias("held_out"), "lang_pred", "score")
