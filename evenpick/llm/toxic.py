"""Toxicity: a Levenshtein automaton intersected with a lexicon trie, and context windows around its hits.

The lexicon is learnt from labelled documents (terms that toxic documents hold far more often, counted over distinct near-copy groups).
Every distinct word is run as an automaton against one trie of all terms, with the edits that a term's length allows (``EDITS_FROM``: an edit
in a short word makes another word). Words that no term can be near are not run; that loses none: an edit changes the length by one at most
and the set of ASCII letters and digits by two, and one edit leaves the first or the last half of a term as it is. A window around each hit
tells quoted from plain use, and a logistic model over exact, misspelled and quoted evidence gives the score.

Defined results: null and empty texts hold no term and get the score of a text without evidence; without any usable label the score
is 0.5 for all; repeated rows repeat; an empty table gives no rows; whole texts are read, in bounded slices.
"""

from __future__ import annotations

from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from evenpick.llm.labelled import TRAIN_ROWS, held_out, training_documents
from evenpick.llm.textbits import MEMORIES, U, bounded_slices, lowered, prefix_hash, span_hash, utf8_buffer
from evenpick.plans.durable import ship_package, staged

#: Letters from which a term is met with one edit (a second entry: with two).
EDITS_FROM = (4,)
WINDOW_BYTES = 60
#: Marks and words that open or report a quotation (fixed values).
QUOTE_MARKS = ('"', "“", "”", "„", "«", "»")
QUOTE_CUES = ("said", "says", "quoted", "quote", "wrote", "called", "term", "word", "dit", "mot", "sagte", "wort", "dijo", "palabra")
FEATURES = ("exact_sum", "exact_best", "exact_terms", "exact_rate", "fuzzy_sum", "fuzzy_best", "quoted_sum", "quoted_only")

_TOKEN = np.zeros(256, bool)
_TOKEN[[*range(48, 58), *range(65, 91), *range(97, 123), *range(128, 256)]] = True


#: One bit for every ASCII letter and digit of a lowered text.
_BIT = np.zeros(256, U)
_BIT[[*range(48, 58), *range(97, 123)]] = U(1) << np.arange(36, dtype=U)


def allowed_edits(letters: int) -> int:
    return sum(letters >= n for n in EDITS_FROM)


def _lower_utf8(buf: np.ndarray) -> np.ndarray:
    """ASCII and Latin-1 letters in lower case, byte by byte."""
    out = lowered(buf)
    after = np.zeros(len(buf), bool)
    after[1:] = buf[:-1] == 0xC3
    wide = after & (buf >= 0x80) & (buf <= 0x9E) & (buf != 0x97)
    if wide.any():
        out = out.copy()
        out[wide] += 0x20
    return out


def tokens(buf: np.ndarray, off: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(start, end, document) of the runs of letters and digits."""
    solid = _TOKEN[buf]
    begin, stop = solid.copy(), solid.copy()
    begin[1:] &= ~solid[:-1]
    stop[:-1] &= ~solid[1:]
    inner = off[(off > 0) & (off < len(buf))]
    begin[inner] = solid[inner]
    stop[inner - 1] = solid[inner - 1]
    start = np.flatnonzero(begin)
    return start, np.flatnonzero(stop) + 1, np.searchsorted(off, start, "right") - 1


class Trie:
    """A lexicon as flat arrays: the children of a node are a range of (node, letter); ``term`` is the number of the term that ends at a node, or -1."""

    def __init__(self, terms: list[str]):
        nodes: list[dict[str, int]] = [{}]
        ends = {}
        for i, term in enumerate(terms):
            at = 0
            for c in term:
                if c not in nodes[at]:
                    nodes[at][c] = len(nodes)
                    nodes.append({})
                at = nodes[at][c]
            ends[at] = i
        self.letters = np.array(sorted({ord(c) for n in nodes for c in n}), np.uint32)
        place = {int(c): i for i, c in enumerate(self.letters)}
        self.count = np.array([len(n) for n in nodes], np.int64)
        self.first = np.cumsum(self.count) - self.count
        self.child = np.array([x for n in nodes for x in n.values()], np.int64)
        self.letter = np.array([place[ord(c)] for n in nodes for c in n], np.int64)
        self.term = np.array([ends.get(i, -1) for i in range(len(nodes))], np.int64)
        self.longest = max(map(len, terms), default=0)

    def within(self, words: list[str], edits: int = 1, chunk: int = 4096) -> list[list[tuple[int, int]]]:
        """For each word the (term, edits) of all terms at most ``edits`` away: the words' automata walk the trie together, level by level.

        A state holds one bit set per number of edits; bit i means that i characters of the word are consumed. Words that are too long
        for any term have no hits.
        """
        out: list[list[tuple[int, int]]] = [[] for _ in words]
        short = [i for i, w in enumerate(words) if len(w) <= min(self.longest + edits, 62)]
        for a in range(0, len(short), chunk):
            part = short[a : a + chunk]
            for w, t, e in zip(*self._walk([words[i] for i in part], edits)):
                out[part[w]].append((t, e))
        return out

    def _walk(self, words: list[str], edits: int):
        one = U(1)
        size = np.array([len(w) for w in words], np.int64)
        codes = np.frombuffer("".join(words).encode("utf-32-le", "surrogatepass"), np.uint32)
        owner = np.repeat(np.arange(len(words)), size)
        position = np.arange(len(codes)) - np.repeat(np.cumsum(size) - size, size)
        at = np.minimum(np.searchsorted(self.letters, codes), len(self.letters) - 1)
        known = self.letters[at] == codes if len(self.letters) else np.zeros(len(codes), bool)
        marks = np.zeros((len(words), max(1, len(self.letters))), U)
        np.bitwise_or.at(marks, (owner[known], at[known]), one << position[known].astype(U))
        accept = one << size.astype(U)
        full = (accept << one) - one
        word, node = np.arange(len(words)), np.zeros(len(words), np.int64)
        state = [np.ones(len(words), U)]
        for _ in range(edits):
            state.append((state[-1] | state[-1] << one) & full)
        found: list[tuple[np.ndarray, np.ndarray, np.ndarray]] = []
        while len(word):
            many = self.count[node]
            up = np.repeat(np.arange(len(word)), many)
            edge = np.repeat(self.first[node] - (np.cumsum(many) - many), many) + np.arange(len(up))
            word, node = word[up], self.child[edge]
            m, limit, after = marks[word, self.letter[edge]], full[word], []
            alive = np.zeros(len(word), U)
            for e, s in enumerate(state):
                s = s[up]
                now = (s & m) << one
                if e:
                    now |= before | before << one | after[-1] << one
                after.append(now & limit)
                alive |= after[-1]
                before = s
            live = np.flatnonzero(alive)
            word, node, state = word[live], node[live], [x[live] for x in after]
            ends = np.flatnonzero(self.term[node] >= 0)
            least = np.full(len(ends), -1)
            for e in reversed(range(edits + 1)):
                least[(state[e][ends] & accept[word[ends]]) != 0] = e
            hit = least >= 0
            found.append((word[ends[hit]], self.term[node[ends[hit]]], least[hit]))
        return [np.concatenate(x).tolist() for x in zip(*found)] if found else ([], [], [])


@dataclass
class Lexicon:
    """Terms with their evidence (log odds), and ordinary words that look like misspelled terms."""

    terms: list[str] = field(default_factory=list)
    weights: list[float] = field(default_factory=list)
    ordinary: frozenset[str] = frozenset()


#: What this worker has found about words, by lexicon: word -> (term, edits) or None.
_KNOWN: dict[int, dict[bytes, tuple[int, int] | None]] = {}
KNOWN_WORDS = 300_000


class Matcher:
    """Hits of a lexicon in a slice of texts."""

    def __init__(self, lexicon: Lexicon):
        self.lexicon = lexicon
        self.weights = np.array(lexicon.weights)
        MEMORIES["toxic"] = _KNOWN.clear
        self.known = _KNOWN.setdefault(hash((*lexicon.terms, *lexicon.weights, *EDITS_FROM)), {})
        data = [t.encode() for t in lexicon.terms]
        hashes = self._hashes(data)
        self.exact_term = np.argsort(hashes)
        self.exact = hashes[self.exact_term]
        self.trie = Trie(lexicon.terms)
        self.edits = [allowed_edits(len(t)) for t in lexicon.terms]
        #: Length, allowed edits and letters of the terms that are met with edits.
        self.halves: dict[tuple[int, int, int], np.ndarray] = {}
        for t, d, e in zip(lexicon.terms, data, self.edits):
            if e == 1:
                cut = len(t[: len(t) // 2].encode())
                for key, half in (((0, cut, len(t)), d[:cut]), ((1, len(d) - cut, len(t)), d[cut:])):
                    self.halves.setdefault(key, set()).add(half)
        self.halves = {k: np.sort(self._hashes(sorted(v))) for k, v in sorted(self.halves.items())}
        self.shapes = sorted({(len(t), e, int(np.bitwise_or.reduce(_BIT[np.frombuffer(d, np.uint8)]))) for t, d, e in zip(lexicon.terms, data, self.edits) if e})

    @staticmethod
    def _hashes(items) -> np.ndarray:
        items = list(items)
        buf = np.frombuffer(b"".join(items), np.uint8)
        end = np.cumsum([len(x) for x in items]).astype(np.int64)
        return span_hash(prefix_hash(buf), end - [len(x) for x in items], end) if items else np.zeros(0, U)

    def nearest(self, data: list[bytes]) -> list[tuple[int, int] | None]:
        """For each word the (term, edits) of the nearest term that allows so many edits, the weightiest of equals, or None."""
        fresh = [d for d in data if d not in self.known]
        if len(self.known) + len(fresh) > KNOWN_WORDS:
            self.known.clear()
            fresh = data
        for d, hits in zip(fresh, self.trie.within([d.decode("utf-8", "ignore") for d in fresh], max(self.edits, default=0)) if fresh else ()):
            found = [(e, -self.lexicon.weights[t], t) for t, e in hits if 0 < e <= self.edits[t]]
            self.known[d] = (min(found)[2], min(found)[0]) if found else None
        return [None if (got := self.known[d]) is None or d.decode("utf-8", "ignore") in self.lexicon.ordinary else got for d in data]

    def near(self, low: np.ndarray, prefix: np.ndarray, start: np.ndarray, end: np.ndarray) -> np.ndarray:
        """Which words (in order of place) could be within the allowed edits of a term, by their length, letters and halves."""
        out = np.zeros(len(start), bool)
        if not len(start) or not self.shapes:
            return out
        whole = np.zeros(len(low) + 1, np.int64)
        np.cumsum((low & 0xC0) != 0x80, out=whole[1:])
        letters = np.bitwise_or.reduceat(np.append(_BIT[low], U(0)), np.stack([start, end], 1).ravel())[::2]
        size = whole[end] - whole[start]
        order = np.argsort(size, kind="stable")
        sizes, letters = size[order], letters[order]
        once = out.copy()
        for n, e, mask in self.shapes:
            a, b = np.searchsorted(sizes, n - e), np.searchsorted(sizes, n + e, "right")
            (once if e == 1 else out)[order[a:b]] |= np.bitwise_count(letters[a:b] ^ U(mask)) <= 2 * e
        lengths = {}
        for n in {k[2] for k in self.halves}:
            a, b = np.searchsorted(sizes, n - 1), np.searchsorted(sizes, n + 1, "right")
            lengths[n] = order[a:b][once[order[a:b]]]
        for (side, n, letters_), held in self.halves.items():
            i = lengths[letters_]
            i = i[~out[i] & (end[i] - start[i] >= n)]
            h = span_hash(prefix, end[i] - n, end[i]) if side else span_hash(prefix, start[i], start[i] + n)
            out[i] = held[np.minimum(np.searchsorted(held, h), len(held) - 1)] == h
        return out

    def hits(self, buf: np.ndarray, off: np.ndarray):
        """(document, term, edits, start, end) of every hit, and the number of tokens of each document."""
        low = _lower_utf8(buf)
        start, end, doc = tokens(low, off)
        count = np.bincount(doc, minlength=len(off) - 1)
        if not len(start) or not self.lexicon.terms:
            none = np.zeros(0, np.int64)
            return (none, none, none, none, none), count
        prefix = prefix_hash(low)
        words, one, word = np.unique(span_hash(prefix, start, end), return_index=True, return_inverse=True)
        at = np.minimum(np.searchsorted(self.exact, words), len(self.exact) - 1)
        exact = self.exact[at] == words
        term, edits = np.where(exact, self.exact_term[at], -1), np.zeros(len(words), np.int64)
        rest = np.flatnonzero(~exact)
        rest = rest[np.argsort(one[rest])]
        rest = rest[self.near(low, prefix, start[one[rest]], end[one[rest]])].tolist()
        for i, got in zip(rest, self.nearest([low[start[one[i]] : end[one[i]]].tobytes() for i in rest])):
            if got:
                term[i], edits[i] = got
        where = np.flatnonzero(term[word] >= 0)
        return (doc[where], term[word][where], edits[word][where], start[where], end[where]), count

    @staticmethod
    def quoted(window_before: str, window_after: str) -> bool:
        """A hit counts as quoted if marks stand on both sides of it, or a reporting word right before it."""
        if any(q in window_before for q in QUOTE_MARKS) and any(q in window_after for q in QUOTE_MARKS):
            return True
        return any(w.strip(".,:;'\"") in QUOTE_CUES for w in window_before.lower().split()[-3:])

    def features(self, array: pa.Array) -> tuple[np.ndarray, list[tuple[int, str]]]:
        """One row of ``FEATURES`` per text, and the misspelled words found (document, word)."""
        buf, off = utf8_buffer(array)
        (doc, term, edits, start, end), count = self.hits(buf, off)
        out = np.zeros((len(off) - 1, len(FEATURES)))
        seen: dict[int, list] = {}
        forms = []
        for d, t, e, a, b in zip(doc.tolist(), term.tolist(), edits.tolist(), start.tolist(), end.tolist()):
            lo, hi = max(off[d], a - WINDOW_BYTES), min(off[d + 1], b + WINDOW_BYTES)
            quoted = self.quoted(buf[lo:a].tobytes().decode("utf-8", "ignore"), buf[b:hi].tobytes().decode("utf-8", "ignore"))
            seen.setdefault(d, []).append((t, e, quoted))
            if e:
                forms.append((d, _lower_utf8(buf[a:b]).tobytes().decode("utf-8", "ignore")))
        for d, got in seen.items():
            plain = {t for t, e, q in got if not e and not q}
            spelt = {t for t, e, q in got if e and not q} - plain
            quoted = {t for t, _, q in got if q} - plain - spelt
            w = self.weights
            out[d] = (
                min(sum(w[t] for t in plain), 20), max((w[t] for t in plain), default=0), np.log1p(len(plain)),
                min(1.0, 20 * sum(1 for _, e, q in got if not e and not q) / max(count[d], 1)),
                min(sum(w[t] for t in spelt), 20), max((w[t] for t in spelt), default=0),
                min(sum(w[t] for t in quoted), 20), float(bool(quoted) and not plain and not spelt),
            )
        return out, forms


@dataclass
class ToxicityModel:
    lexicon: Lexicon
    bias: float = 0.0
    coef: np.ndarray = field(default_factory=lambda: np.zeros(len(FEATURES)))

    def score(self, x: np.ndarray) -> np.ndarray:
        return 1 / (1 + np.exp(-np.clip(self.bias + x @ self.coef, -30, 30)))


#: Prior means of the coefficients: evidence counts, misspelled evidence less, quoted evidence hardly (fixed values).
PRIOR = np.array([0.3, 0.5, 0.5, 0.5, 0.2, 0.3, 0.05, 0.0])


def fit_logistic(x: np.ndarray, y: np.ndarray, strength: float = 2.0) -> tuple[float, np.ndarray]:
    """Ridge towards ``PRIOR`` by Newton steps; the bias is free."""
    if not len(y) or y.min() == y.max():
        share = (y.sum() + 0.5) / (len(y) + 1)
        return float(np.log(share / (1 - share))), np.zeros(x.shape[1])
    a = np.column_stack([np.ones(len(x)), x])
    mean, weight = np.concatenate([[0], PRIOR]), np.concatenate([[1e-6], np.full(x.shape[1], strength)])
    beta = mean.copy()
    beta[0] = np.log(y.mean() / (1 - y.mean()))
    for _ in range(50):
        p = 1 / (1 + np.exp(-np.clip(a @ beta, -30, 30)))
        grad = a.T @ (y - p) - weight * (beta - mean)
        step = np.linalg.solve((a * (p * (1 - p))[:, None]).T @ a + np.diag(weight), grad)
        beta += np.clip(step, -2, 2)
        if np.abs(step).max() < 1e-8:
            break
    return float(beta[0]), beta[1:]


def _token_rows(batches):
    """(group, label, token) once per document; ``group`` is the least hash of five tokens in a row, shared by most near copies."""
    for b in bounded_slices(batches, owner="toxic"):
        buf, off = utf8_buffer(b.column(0))
        low = _lower_utf8(buf)
        start, end, doc = tokens(low, off)
        if not len(start):
            continue
        prefix = prefix_hash(low)
        last = np.minimum(np.arange(len(start)) + 4, len(start) - 1)
        last = np.minimum(last, np.searchsorted(doc, doc, "right") - 1)
        run = span_hash(prefix, start, end[last])
        group = np.full(b.num_rows, np.iinfo(np.uint64).max, U)
        np.minimum.at(group, doc, run)
        h = span_hash(prefix, start, end)
        order = np.lexsort((h, doc))
        fresh = np.ones(len(order), bool)
        fresh[1:] = (h[order][1:] != h[order][:-1]) | (doc[order][1:] != doc[order][:-1])
        keep = order[fresh]
        size = (end - start)[keep]
        keep = keep[(size >= 3) & (size <= 40)]
        label = b.column(1).to_numpy(zero_copy_only=False)
        said = [low[a:e].tobytes().decode("utf-8", "ignore") for a, e in zip(start[keep], end[keep])]
        yield pa.RecordBatch.from_arrays([pa.array(group[doc[keep]].astype(np.int64)), pa.array(label[doc[keep]].astype(np.int32)), pa.array(said, pa.string())], names=["grp", "label", "token"])


def learn_lexicon(sample: DataFrame) -> Lexicon:
    """All terms of toxic documents by log odds, each supported by at least three near-copy groups and significant at three deviations."""
    rows = sample.select("text", "label").mapInArrow(_token_rows, "grp long, label int, token string")
    groups = rows.select("grp", "label").distinct().groupBy().agg(F.coalesce(F.sum("label"), F.lit(0)).alias("t"), F.count("*").alias("n")).first()
    toxic_groups, clean_groups = int(groups.t), int(groups.n - groups.t)
    counts = rows.distinct().groupBy("token").agg(F.sum("label").alias("t"), F.sum(1 - F.col("label")).alias("c"))
    odds = F.log((F.col("t") + 0.5) / (toxic_groups + 1)) - F.log((F.col("c") + 0.5) / (clean_groups + 1))
    sure = odds / F.sqrt(1 / (F.col("t") + 0.5) + 1 / (F.col("c") + 0.5))
    kept = counts.where("t >= 3").withColumn("odds", odds).withColumn("sure", sure).where("odds >= 1.4 and sure >= 3")
    top = kept.orderBy(F.col("sure").desc(), "token").collect()
    return Lexicon([r.token for r in top], [float(r.odds) for r in top])


def _feature_rows(lexicon: Lexicon):
    def run(batches):
        matcher = Matcher(lexicon)
        for b in bounded_slices(batches, owner="toxic"):
            x, forms = matcher.features(b.column(0))
            said: dict[int, set] = {}
            for d, w in forms:
                said.setdefault(d, set()).add(w)
            yield pa.RecordBatch.from_arrays(
                [b.column(1), b.column(2), pa.array(x.tolist(), pa.list_(pa.float64())), pa.array([sorted(said.get(i, ())) for i in range(b.num_rows)], pa.list_(pa.string()))],
                names=["doc_id", "label", "features", "forms"],
            )

    return run


def train_toxicity(docs: DataFrame, labels: DataFrame, rows: int = TRAIN_ROWS) -> ToxicityModel:
    """Lexicon and logistic model from at most ``rows`` labelled documents outside the held-out fold.

    What reaches the driver comes from the sample alone: significant terms, clean words that look like them, and one feature row per document.
    """
    ship_package(docs.sparkSession)
    sample = staged(training_documents(docs, labels, "toxic", rows), "toxic-sample")
    lexicon = learn_lexicon(sample)
    schema = "doc_id long, label int, features array<double>, forms array<string>"
    first = sample.select("text", "doc_id", "label").mapInArrow(_feature_rows(lexicon), schema)
    forms = first.select(F.explode("forms").alias("form"), "label").groupBy("form").agg(F.sum(1 - F.col("label")).alias("c"), F.sum("label").alias("t"))
    clean = forms.where("c > 0 and 3 * c >= t").orderBy("form").collect()
    lexicon.ordinary = frozenset(r.form for r in clean)
    got = sample.select("text", "doc_id", "label").mapInArrow(_feature_rows(lexicon), schema).select("doc_id", "label", "features").orderBy("doc_id").limit(rows).toPandas()
    x = np.array(got.features.tolist(), float).reshape(-1, len(FEATURES))
    return ToxicityModel(lexicon, *fit_logistic(x, got.label.to_numpy(float) if len(got) else np.zeros(0)))


def score_toxicity(docs: DataFrame, model: ToxicityModel, threshold: float = 0.5) -> DataFrame:
    """Per document: fold, score and decision; texts stay in the worker."""
    ship_package(docs.sparkSession)

    def run(batches):
        matcher = Matcher(model.lexicon)
        for b in bounded_slices(batches, owner="toxic"):
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(model.score(matcher.features(b.column(1))[0]))], names=["doc_id", "score"])

    scored = docs.select("doc_id", "text").mapInArrow(run, "doc_id long, score double")
    return scored.select("doc_id", held_out(F.col("doc_id")).alias("held_out"), "score", (F.col("score") >= threshold).cast("int").alias("predicted"))
