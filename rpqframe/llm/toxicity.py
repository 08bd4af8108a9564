"""Toxicity scores from a learned lexicon, Levenshtein automata and context windows.

The lexicon is learned from labelled training rows: words and word stems whose presence in a
document goes with the toxic label (log-likelihood ratio). All entries sit in one trie; the
Levenshtein automata of its entries are intersected with it and made deterministic lazily, so a
word is read once, whatever the lexicon's size, and misspelled terms are found with their
edit count. A window around each hit tells quotation from abuse. A logistic model over the counts of
exact, misspelled, quoted and unquoted hits gives the score; it is fitted on the same training rows.

Bounds: at most ``max_train`` labelled rows (those of least hash) fit the lexicon and the model. Everything
else covers all rows and whole texts.

Defined results: null and empty texts score as texts without hits; a null id is never held out;
a row repeated in the input is repeated in the result; a null label does not train; without
any labels every score is 0; extra columns are ignored.
"""

from __future__ import annotations

import math
import re
from bisect import bisect_left
from collections import Counter
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from rpqframe.llm.common import fresh, pick, text_slices

WORD = re.compile(r"[^\W\d_]+")
#: Words that report what someone else said.
REPORTING = frozenset("called quote quoted quotes reads said saying says term word words wrote".split())
OPEN, CLOSE = "“«", "”»"
STEM_LENGTHS = range(4, 9)
THRESHOLD = 0.3
CLEAN_WORDS = 600_000
FLUSH_TERMS = 300_000
#: States of an automaton that are kept between words.
MAX_STATES = 200_000


class FuzzyTrie:
    """Levenshtein automata of all entries intersected with their trie, determinised lazily.

    An entry is (term, is_stem); a stem accepts any continuation. Terms of under five characters
    allow no edit, of under ten one, others two; stems of under seven none, others one.
    """

    def __init__(self, entries: list[tuple[str, bool]]):
        self.entries = entries
        self.kids: list[dict[str, int]] = [{}]
        self.ends: list[list[int]] = [[]]
        self.slack = [-1]
        for k, (term, stem) in enumerate(entries):
            node, most = 0, self.edits(term, stem)
            self.slack[0] = max(self.slack[0], most)
            for ch in term:
                if ch not in self.kids[node]:
                    self.kids[node][ch] = len(self.kids)
                    self.kids.append({})
                    self.ends.append([])
                    self.slack.append(-1)
                node = self.kids[node][ch]
                self.slack[node] = max(self.slack[node], most)
            self.ends[node].append(k)
        self.alphabet = {ch for kids in self.kids for ch in kids}
        self._restart()

    def _restart(self) -> None:
        """Forget all states but the first two; they are made again as words need them."""
        self.states: dict[frozenset, int] = {}
        self.members: list[frozenset] = []
        self.accepts: list[tuple[tuple[int, int] | None, tuple[int, int] | None]] = []
        self.moves: list[dict[str, int]] = []
        self.dead = self._state(frozenset())
        self.start = self._state(self._closed({(0, 0)}))

    @staticmethod
    def edits(term: str, stem: bool) -> int:
        return int(len(term) >= 7) if stem else (len(term) >= 5) + (len(term) >= 10)

    def _closed(self, pairs: set[tuple[int, int]]) -> frozenset:
        todo, seen = list(pairs), set()
        while todo:
            node, e = todo.pop()
            if (node, e) in seen or e > self.slack[node]:
                continue
            seen.add((node, e))
            todo += [(kid, e + 1) for kid in self.kids[node].values()]
        least: dict[int, int] = {}
        for node, e in seen:
            least[node] = min(e, least.get(node, e))
        return frozenset(least.items())

    def _state(self, pairs: frozenset) -> int:
        if pairs not in self.states:
            self.states[pairs] = len(self.members)
            self.members.append(pairs)
            found = [(e, k) for node, e in pairs for k in self.ends[node] if e <= self.edits(*self.entries[k])]
            self.accepts.append((min((x for x in found if self.entries[x[1]][1]), default=None), min(found, default=None)))
            self.moves.append({})
        return self.states[pairs]

    def _move(self, state: int, ch: str) -> int:
        if ch and ch not in self.alphabet:
            got = self.moves[state].get("")
            got = self._move(state, "") if got is None else got
            self.moves[state][ch] = got
            return got
        to: set[tuple[int, int]] = set()
        for node, e in self.members[state]:
            to.add((node, e + 1))
            for label, kid in self.kids[node].items():
                to.add((kid, e if label == ch else e + 1))
        self.moves[state][ch] = got = self._state(self._closed(to))
        return got

    def look(self, word: str) -> tuple[int, int] | None:
        """(edits, entry) of the nearest entry, or None."""
        if len(self.members) > MAX_STATES:
            self._restart()
        state, best, moves, accepts = self.start, None, self.moves, self.accepts
        for ch in word:
            nxt = moves[state].get(ch)
            state = self._move(state, ch) if nxt is None else nxt
            if not state:  # the dead state is the first
                return best
            stem = accepts[state][0]
            if stem is not None and (best is None or stem < best):
                best = stem
        whole = self.accepts[state][1]
        return whole if whole is not None and (best is None or whole < best) else best


def quoted(text: str, spans: list[tuple[int, int]], window: int = 80) -> list[bool]:
    """For each span, in order, whether it stands inside quotation marks of its line, in a quoted line or after a reporting word.

    Marks are counted from the line's start, however long the line is, and each character once.
    """
    out, line, seen, marks, nxt = [], 0, 0, {}, -1
    for at, end in spans:
        start = text.rfind("\n", seen, at) + 1
        if start or not out:
            line = seen = start or 0
            marks = dict.fromkeys('"' + OPEN + CLOSE, 0)
        for ch in marks:
            marks[ch] += text.count(ch, seen, at)
        seen = at
        inside = any(marks[o] > marks[c] for o, c in zip(OPEN, CLOSE))
        if not inside and marks['"'] % 2:
            if nxt < end:
                nxt = text.find('"', end)
                nxt = len(text) if nxt < 0 else nxt
            stop = text.find("\n", end, nxt)
            inside = nxt < len(text) and stop < 0
        before = text[max(line, at - window) : at]
        out.append(inside or text.startswith(">", line) or not REPORTING.isdisjoint(WORD.findall(before)[-4:]))
    return out


FEATURES = 6


class Scorer:
    def __init__(self, entries: list[tuple[str, bool, float]]):
        self.trie = FuzzyTrie([(t, s) for t, s, _ in entries])
        self.weights = [w for _, _, w in entries]
        self.clean: set[str] = set()

    def hits(self, text: str) -> list[tuple[int, int, int, int, bool]]:
        """(start, end, entry, edits, quoted) of each hit, in the lower-cased text."""
        low = text.lower()
        new = set(WORD.findall(low)) - self.clean
        found = {}
        for w in new:
            got = self.trie.look(w)
            if got is not None:
                found[w] = got
        if len(self.clean) > CLEAN_WORDS:
            self.clean.clear()
        self.clean |= new - found.keys()
        if not found:
            return []
        places = [m for m in WORD.finditer(low) if m[0] in found]
        flags = quoted(low, [m.span() for m in places])
        return [(*m.span(), found[m[0]][1], found[m[0]][0], q) for m, q in zip(places, flags)]

    def features(self, hits: list[tuple[int, int, int, int, bool]]) -> list[float]:
        counts = Counter((e > 0, q) for _, _, _, e, q in hits)
        most = max((self.weights[k] / (1 + e) for _, _, k, e, _ in hits), default=0.0)
        return [1.0, *(math.log1p(counts[key]) for key in ((False, False), (False, True), (True, False), (True, True))), most]


def held_out(id_col: str):
    return F.coalesce(F.crc32(F.col(id_col).cast("string")) % 4 == 2, F.lit(False))


def training_rows(docs: DataFrame, labels: DataFrame, id_col: str, text_col: str, label_col: str, max_train: int) -> DataFrame:
    """text, label of at most ``max_train`` labelled rows outside the held-out part."""
    own = pick(labels, id_col, label_col).toDF("id", "label").where("id is not null and label is not null").where(~held_out("id"))
    own = own.groupBy("id").agg(F.max("label").alias("label")).orderBy(F.xxhash64("id"), "id").limit(max_train)
    return pick(docs, id_col, text_col).toDF("id", "text").join(F.broadcast(own), "id").select("text", "label")


def _term_counts(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Documents by label that hold each word ("w") or stem ("w*"), summed over what was read so far."""
    counts: tuple[Counter, Counter] = (Counter(), Counter())

    def flush() -> pa.RecordBatch:
        terms = list(counts[0].keys() | counts[1].keys())
        out = pa.RecordBatch.from_arrays(
            [pa.array(terms, pa.string()), pa.array([counts[1][t] for t in terms], pa.int64()), pa.array([counts[0][t] for t in terms], pa.int64())],
            names=["term", "pos", "neg"],
        )
        counts[0].clear()
        counts[1].clear()
        return out

    for batch in batches:
        for rows, texts in text_slices(batch):
            for raw, label in zip(texts, rows.column(1).to_pylist()):
                words = set(WORD.findall((raw or b"").decode("utf-8", "replace").lower()))
                stems = {w[:n] + "*" for w in words for n in STEM_LENGTHS if len(w) >= n}
                counts[int(label > 0)].update(words | stems)
                if len(counts[0]) + len(counts[1]) > FLUSH_TERMS:
                    yield flush()
    yield flush()


def learn_lexicon(train: DataFrame, least_llr: float = 22.0, least_precision: float = 0.8) -> list[tuple[str, bool, float]]:
    """(term, is_stem, weight): the terms whose presence goes with the toxic label."""
    sizes = {r.label: r["count"] for r in train.groupBy((F.col("label") > 0).cast("int").alias("label")).count().collect()}
    n1, n0 = sizes.get(1, 0), sizes.get(0, 0)
    if not n1 or not n0:
        return []
    terms = train.mapInArrow(_term_counts, "term string, pos bigint, neg bigint").groupBy("term").agg(F.sum("pos").alias("pos"), F.sum("neg").alias("neg"))
    part = lambda k, e: F.when(k > 0, k * F.log(k / e)).otherwise(0.0)
    p, q, seen = F.col("pos"), F.col("neg"), F.col("pos") + F.col("neg")
    llr = 2 * sum(part(k, e) for k, e in ((p, seen * n1 / (n1 + n0)), (q, seen * n0 / (n1 + n0)), (n1 - p, (n1 + n0 - seen) * n1 / (n1 + n0)), (n0 - q, (n1 + n0 - seen) * n0 / (n1 + n0))))
    good = terms.where((p >= 4) & (p >= least_precision * seen)).withColumn("llr", llr).where(F.col("llr") >= least_llr)
    rows = good.collect()  # terms of at most max_train texts that pass both thresholds
    by_term = {r.term: r for r in rows}
    names = sorted(by_term)
    entries: list[tuple[str, bool, float]] = []
    for r in sorted(rows, key=lambda r: (-r.pos, r.term)):
        stem = r.term.removesuffix("*")
        if any(stem.startswith(t) if s else stem == t for t, s, _ in entries):
            continue
        same = [t for t in names[bisect_left(names, stem) : bisect_left(names, stem + "\U0010ffff")] if by_term[t].pos >= 0.97 * r.pos]
        best = max(same, key=lambda t: (not t.endswith("*"), len(t), t))
        b = best.removesuffix("*")
        if any((b.startswith(t) if s else b == t) or t.startswith(stem) and s is False and by_term[r.term].pos < 1.5 * by_term[t].pos for t, s, _ in entries):
            continue
        pos, neg = by_term[best].pos, by_term[best].neg
        entries.append((b, best.endswith("*"), math.log((pos + 0.5) / (n1 + 1)) - math.log((neg + 0.5) / (n0 + 1))))
    return entries


def fit_logistic(x: np.ndarray, y: np.ndarray, ridge: float = 1.0, rounds: int = 40) -> np.ndarray:
    beta = np.zeros(x.shape[1])
    penalty = np.diag([1e-6] + [ridge] * (x.shape[1] - 1))
    for _ in range(rounds):
        p = 1 / (1 + np.exp(-np.clip(x @ beta, -30, 30)))
        grad = x.T @ (y - p) - penalty @ beta
        step = np.linalg.solve((x * (p * (1 - p))[:, None]).T @ x + penalty + 1e-9 * np.eye(x.shape[1]), grad)
        beta = beta + np.clip(step, -4, 4)
        if np.abs(step).max() < 1e-8:
            break
    return beta


class Model:
    """A lexicon and the weights of its features; small, so it is shipped with the tasks."""

    def __init__(self, entries: list[tuple[str, bool, float]], beta: np.ndarray | None):
        self.entries, self.beta = entries, beta

    def score(self, features: list[list[float]]) -> np.ndarray:
        if self.beta is None:
            return np.zeros(len(features))
        return 1 / (1 + np.exp(-np.clip(np.array(features).reshape(-1, FEATURES) @ self.beta, -30, 30)))


def train_model(docs: DataFrame, labels: DataFrame, id_col: str = "doc_id", text_col: str = "text", label_col: str = "toxic", max_train: int = 20_000) -> Model:
    train = training_rows(docs, labels, id_col, text_col, label_col, max_train)
    entries = learn_lexicon(train)

    def features(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        scorer = Scorer(entries)
        for batch in batches:
            for rows, texts in text_slices(batch):
                x = [scorer.features(scorer.hits((t or b"").decode("utf-8", "replace"))) for t in texts]
                yield pa.RecordBatch.from_arrays([pa.array(x, pa.list_(pa.float64())), rows.column(1).cast(pa.int32())], names=["x", "label"])

    distinct = train.mapInArrow(features, "x array<double>, label int").groupBy("x", "label").count().collect()
    if len({r.label for r in distinct}) < 2:
        return Model(entries, None)
    x = np.repeat([r.x for r in distinct], [r["count"] for r in distinct], axis=0)
    y = np.repeat([float(r.label > 0) for r in distinct], [r["count"] for r in distinct])
    return Model(entries, fit_logistic(x, y))


def score(docs: DataFrame, model: Model, id_col: str = "doc_id", text_col: str = "text", threshold: float = THRESHOLD) -> DataFrame:
    """id_col, held_out, score, predicted, n_hits, n_misspelled, n_quoted; one row per input row."""
    flagged, tox = with_score(pick(docs, id_col, text_col), model, text_col)
    return flagged.select(
        id_col, held_out(f"`{id_col}`").alias("held_out"), F.col(f"{tox}.score").alias("score"), (F.col(f"{tox}.score") >= threshold).cast("int").alias("predicted"),
        F.col(f"{tox}.n_hits").alias("n_hits"), F.col(f"{tox}.n_misspelled").alias("n_misspelled"), F.col(f"{tox}.n_quoted").alias("n_quoted"),
    )


def with_score(docs: DataFrame, model: Model, text_col: str = "text") -> tuple[DataFrame, str]:
    """The documents with a struct column (score, n_hits, n_misspelled, n_quoted), and its name, which is new to them."""
    tox = fresh("tox", docs)
    kind = "struct<score:double,n_hits:int,n_misspelled:int,n_quoted:int>"
    src = docs.withColumn(tox, F.lit(None).cast(kind))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        scorer = Scorer(model.entries)
        for batch in batches:
            for rows, texts in text_slices(batch, text_col):
                x, more = [], []
                for t in texts:
                    hits = scorer.hits((t or b"").decode("utf-8", "replace"))
                    x.append(scorer.features(hits))
                    more.append((len(hits), sum(h[3] > 0 for h in hits), sum(h[4] for h in hits)))
                out = [{"score": p, "n_hits": a, "n_misspelled": b, "n_quoted": c} for p, (a, b, c) in zip(model.score(x).tolist(), more)]
                kinds = pa.struct([("score", pa.float64()), ("n_hits", pa.int32()), ("n_misspelled", pa.int32()), ("n_quoted", pa.int32())])
                yield pa.RecordBatch.from_arrays([*rows.columns[:-1], pa.array(out, kinds)], names=rows.schema.names)

    return src.mapInArrow(run, src.schema), tox


def drop_toxic(docs: DataFrame, model: Model, text_col: str = "text", threshold: float = THRESHOLD) -> DataFrame:
    """The documents of a lower score than the threshold, with all their columns."""
    flagged, tox = with_score(docs, model, text_col)
    return flagged.where(F.col(f"{tox}.score") < threshold).drop(tox)
