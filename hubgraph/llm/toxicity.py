"""Toxicity by a learned lexicon, matched through Levenshtein automata over its trie.

Stems of words that mark toxic documents are learned from labelled rows. The trie of the stems is intersected with
the Levenshtein automata of distance 1 and made deterministic, so that all words of a block run through one table in
step and misspelled stems are caught, wherever the error is. Hits inside quotation marks and open ones are features of
their own, so how much a quotation counts is learned. A logistic model over what the hits of a document come to gives
the score.
"""

from __future__ import annotations

import re
from collections import Counter

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from hubgraph.llm.common import id_crc, slices
from hubgraph.llm.langid import _letters

#: Bounds of the labelled sample that stems and weights are learned from, by label; STEMS bounds the lexicon.
SAMPLE = {1: 1500, 0: 3000}
STEMS, SHORTEST, LONGEST, FUZZY_FROM = 160, 4, 24, 5
QUOTES = '"“”«»„‟'
FEW = 3  # documents
SURE = 1.64  # standard errors that are taken off the log odds of a stem before it has any worth
QUOTE_WINDOW = 60  # characters: the most between a quoted hit and either quotation mark
WORD = re.compile(r"[^\W_]+")
QUOTED = re.compile(f"[{QUOTES}][^{QUOTES}]{{0,{2 * QUOTE_WINDOW}}}[{QUOTES}]")


def learn_stems(docs: list[tuple[str, int]]) -> list[str]:
    """Prefixes of words that many toxic documents and hardly any clean ones hold outside of quotation marks; none is
    the prefix of another."""
    n = Counter(y for _, y in docs)
    seen = {0: Counter(), 1: Counter()}
    for text, y in docs:
        words = {w[:LONGEST] for w in WORD.findall(QUOTED.sub(" ", text.lower()))}
        seen[y].update({w[:k] for w in words for k in range(SHORTEST, len(w) + 1)})
    found = []
    for stem, hit in seen[1].items():
        odds = np.log((hit + 0.5) / (n[1] + 1)) - np.log((seen[0][stem] + 0.5) / (n[0] + 1))
        if hit >= 4 and odds >= 2.5:
            found.append((hit * odds, len(stem), stem))  # of prefixes with the same documents the longest
    stems: list[str] = []
    for _, _, stem in sorted(found, reverse=True):
        if len(stems) < STEMS and not any(stem.startswith(s) or s.startswith(stem) for s in stems):
            stems.append(stem)
    return stems


class FuzzyTrie:
    """Deterministic automaton of all words that begin with a stem, or with a string at distance 1 from one.

    table[state, code] is the next state; 0 is dead. accept[state] is -1, or 2 * stem + errors of the best stem that
    has been matched. Codes: 0 for no letter, then the letters of the stems, then one for all others.
    """

    def __init__(self, stems: list[str]):
        self.stems = stems
        letters = sorted(set("".join(stems)))
        self.code = {c: i + 1 for i, c in enumerate(letters)}
        self.width = len(letters) + 2
        child, final = [{}], [-1]
        for k, stem in enumerate(stems):
            at = 0
            for c in stem:
                if self.code[c] not in child[at]:
                    child[at][self.code[c]] = len(child)
                    child.append({})
                    final.append(-1)
                at = child[at][self.code[c]]
            final[at] = k
        fuzzy = [len(s) >= FUZZY_FROM for s in stems]
        # Nodes below which some stem is long enough to be misspelled.
        open_to = [False] * len(child)
        for k, stem in enumerate(stems):
            at = 0
            open_to[0] |= fuzzy[k]
            for c in stem:
                at = child[at][self.code[c]]
                open_to[at] |= fuzzy[k]

        def close(items):
            out = set(items)
            for node, e in items:
                if e == 0:  # a letter of the stem left out
                    out |= {(to, 1) for to in child[node].values() if open_to[to]}
            return frozenset(x for x in out if not (x[1] == 1 and (x[0], 0) in out))

        def best(state):
            hits = [(e, final[node]) for node, e in state if final[node] >= 0 and (e == 0 or fuzzy[final[node]])]
            return 2 * min(hits)[1] + min(hits)[0] if hits else -1

        start = close({(0, 0)})
        number, todo, rows, accept = {frozenset(): 0, start: 1}, [start], [[0] * self.width, None], [-1, -1]
        while todo:
            state = todo.pop()
            row = [0] * self.width
            for c in range(1, self.width):
                to = set()
                for node, e in state:
                    if c in child[node]:
                        to.add((child[node][c], e))
                    if e == 0:
                        to.add((node, 1))
                        to |= {(x, 1) for x in child[node].values()}
                to = close({x for x in to if x[1] == 0 or open_to[x[0]]})
                if to not in number:
                    number[to] = len(rows)
                    rows.append(None)
                    accept.append(best(to))
                    todo.append(to)
                row[c] = number[to]
            rows[number[state]] = row
        self.table, self.accept = np.array(rows, np.int32), np.array(accept, np.int32)

    def codes(self) -> np.ndarray:
        """The code of every code point; digits and signs that stand for letters count as other letters."""
        letter, lower = _letters()
        code = np.zeros(0x110000, np.uint8)
        code[letter] = self.width - 1
        code[[ord(c) for c in "0123456789@$"]] = self.width - 1
        for c, k in self.code.items():
            code[ord(c)] = k
        code[letter] = code[lower[letter]]
        return code


class ToxicityModel:
    def __init__(self, labelled: list[tuple[str, int]]):
        half = len(labelled) // 2
        self.stems = learn_stems(labelled[:half]) if labelled else []
        self.trie, self.code = FuzzyTrie(self.stems), None
        texts, y = [t for t, _ in labelled], np.array([y for _, y in labelled], float)
        hits = self.hits(texts)
        # The worth of each stem, matched exactly or nearly, from the documents that it was not chosen on.
        held = (np.arange(len(labelled)) >= half)[:, None] & (hits[0] > 0)
        n1, n0 = max(1, y[half:].sum()), max(1, (1 - y[half:]).sum())
        one, none = (held * y[:, None]).sum(0), (held * (1 - y[:, None])).sum(0)

        def worth(one, none):
            odds = np.log((one + 0.5) / (n1 + 1)) - np.log((none + 0.5) / (n0 + 1))
            return np.maximum(0, odds - SURE * np.sqrt(1 / (one + 0.5) + 1 / (none + 0.5)))

        self.worth = worth(one, none)
        # Misspellings that were hardly seen are worth what their stem is, but no more than all misspellings together.
        near = (one + none)[1::2]
        together = worth(one[1::2].sum(), none[1::2].sum()) if near.sum() >= FEW else np.inf
        self.worth[1::2] = np.where(near < FEW, np.minimum(self.worth[::2], together), self.worth[1::2])
        x = self.features(hits)
        self.coef = np.zeros(x.shape[1])
        weight = np.where(y == 1, 0.5 / max(y.mean() if len(y) else 0.5, 1e-3), 0.5 / max(1 - y.mean() if len(y) else 0.5, 1e-3))
        for _ in range(25):  # Newton steps on the penalised likelihood
            if not len(y):
                break
            p = 1 / (1 + np.exp(-np.clip(x @ self.coef, -30, 30)))
            slope = x.T @ (weight * (y - p)) - 0.1 * self.coef
            bend = (x * (weight * p * (1 - p))[:, None]).T @ x + 0.1 * np.eye(x.shape[1])
            self.coef += np.linalg.solve(bend, slope)

    def features(self, hits: np.ndarray) -> np.ndarray:
        """A constant, then for open and for quoted hits: is there a stem of worth, the greatest worth, and the sum."""
        out = [np.ones(hits.shape[1])]
        for kind in hits:
            worth = (kind > 0) * self.worth
            out += [worth.sum(1) > 0, worth.max(1, initial=0), np.log1p((kind * self.worth).sum(1))]
        return np.stack(out, 1)

    def hits(self, texts: list[str]) -> np.ndarray:
        """For each text the hits of each stem, open ones [0] and quoted ones [1]: even columns exact, odd ones with an error."""
        if self.code is None:
            self.code = self.trie.codes()
        off = np.r_[0, np.cumsum([len(t) for t in texts])].astype(np.int64)
        points = np.frombuffer("".join(texts).encode("utf-32-le", "surrogatepass"), np.uint32)
        code = self.code[points]
        out = np.zeros((2, len(texts), 2 * len(self.stems)))
        word = code > 0
        edge = np.zeros(len(code) + 1, bool)
        edge[off] = True
        at = np.nonzero(word & (~np.r_[False, word[:-1]] | edge[:-1]))[0]
        begin, state = at, np.ones(len(at), np.int64)
        stop = np.r_[code, np.uint8(0)]
        quotes = np.nonzero(np.isin(points, [ord(c) for c in QUOTES]))[0]
        table = self.trie.table.ravel()
        best = np.full(len(begin), -1, np.int64)
        live, place = np.arange(len(begin)), at.copy()
        while len(live):
            state = table[state * self.trie.width + stop[place]]
            alive = state > 0
            live, place, state = live[alive], place[alive] + 1, state[alive].astype(np.int64)
            got = self.trie.accept[state]
            hit = got >= 0
            # An exact match is final; a match with an error may still become an exact one.
            old = best[live]
            better = hit & ((old < 0) | (got % 2 < old % 2))
            best[live[better]] = got[better]
            ended = edge[np.minimum(place, len(code))] | (place >= len(code))
            go = ~ended & ~(hit & (got % 2 == 0))
            live, place, state = live[go], place[go], state[go]
        found = np.nonzero(best >= 0)[0]
        where = begin[found]
        doc = np.searchsorted(off, where, side="right") - 1
        quoted = np.zeros(len(found), np.int64)
        if len(quotes) and len(found):
            k = np.searchsorted(quotes, where)
            before = np.where(k > 0, where - quotes[np.maximum(k - 1, 0)], 1 << 40)
            after = np.where(k < len(quotes), quotes[np.minimum(k, len(quotes) - 1)] - where, 1 << 40)
            same = (k > 0) & (k < len(quotes)) & (quotes[np.maximum(k - 1, 0)] >= off[doc]) & (quotes[np.minimum(k, len(quotes) - 1)] < off[doc + 1])
            inside = (k - np.searchsorted(quotes, off[doc])) % 2 == 1
            quoted[same & inside & (before <= QUOTE_WINDOW) & (after <= QUOTE_WINDOW)] = 1
        np.add.at(out, (quoted, doc, best[found]), 1)
        return out

    def score(self, texts: list[str]) -> np.ndarray:
        return 1 / (1 + np.exp(-np.clip(self.features(self.hits(texts)) @ self.coef, -30, 30)))

    def __getstate__(self):
        return {k: v for k, v in self.__dict__.items() if k != "code"} | {"code": None}


def labelled_sample(docs: DataFrame, labels: DataFrame) -> list[tuple[str, int]]:
    """A bounded sample of (text, toxic), the rows of each label with the smallest hash of their text."""
    # The sample is drawn on ids and hashes; only its texts are fetched, by ids whose number SAMPLE bounds.
    known = labels.select("doc_id", "toxic").where("toxic in (0, 1)").dropDuplicates(["doc_id"])
    hashed = docs.select("doc_id", F.xxhash64(F.coalesce("text", F.lit(""))).alias("h")).join(known, "doc_id")
    drawn = [(r.doc_id, y) for y, n in SAMPLE.items() for r in hashed.where(F.col("toxic") == y).orderBy("h", "doc_id").limit(n).collect()]
    ids = docs.sparkSession.createDataFrame(drawn, "doc_id long, toxic int").dropDuplicates(["doc_id"])
    rows = docs.select("doc_id", F.coalesce("text", F.lit("")).alias("text")).join(F.broadcast(ids), "doc_id")
    held = {(r.h, r.text, r.toxic) for r in rows.select(F.xxhash64("text").alias("h"), "text", "toxic").collect()}
    return [(t, y) for _, t, y in sorted(held)]


def score_toxicity(docs: DataFrame, model: ToxicityModel) -> DataFrame:
    """(doc_id, score, predicted, n_hits) of docs (doc_id, text, ...).

    Whole texts are scanned, very long ones too. Null and empty texts have no hits and the score of a text without
    hits. Repeated rows each get their row; an empty table gives an empty result; with no labels every score is 0.5.
    Other columns of docs are ignored.
    """
    shared = docs.sparkSession.sparkContext.broadcast(model)

    def run(batches):
        for b in slices(batches, "text", 4_000_000):
            m = shared.value
            hits = m.hits([t or "" for t in b.column("text").to_pylist()])
            score = 1 / (1 + np.exp(-np.clip(m.features(hits) @ m.coef, -30, 30)))
            yield pa.RecordBatch.from_arrays([b.column("doc_id"), pa.array(score), pa.array((score >= 0.7).astype(np.int32)), pa.array(hits.sum((0, 2)))], ["doc_id", "score", "predicted", "n_hits"])

    return docs.select("doc_id", "text").mapInArrow(run, "doc_id long, score double, predicted int, n_hits double")


def toxicity_report(docs: DataFrame, labels: DataFrame) -> DataFrame:
    """The digest of query op10: two folds of three are learned from, all documents are scored."""
    fold = id_crc("doc_id") % 3
    model = ToxicityModel(labelled_sample(docs.where(fold != 1), labels))
    return score_toxicity(docs, model).select("doc_id", (id_crc("doc_id") % 3 == 1).alias("held_out"), "score", "predicted", "n_hits")
