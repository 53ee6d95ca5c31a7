"""Toxicity: a weighted finite-state pattern grammar that scores clauses.

Words become symbols: insult, threat, target (who is addressed), negation, reported speech, other. Three
transducers run over the symbols of a clause and are composed into one table beforehand:

* negation weakens insults and threats for the next three words;
* reported speech weakens what follows it in the clause;
* a target in the clause strengthens what stands with it.

A clause scores the sum of its hits' weights, each times the factor that the table gives it there. A text
becomes four numbers (strongest clause, all clauses, all per hundred words, number of hits), which a
logistic curve turns into a score from 0 to 1.

Insult stems and their weights (log odds) and the curve are learned from labelled texts: at most
``TOXIC_ROWS`` toxic and ``CLEAN_ROWS`` clean ones, those with the smallest hashes, and none of the fold
that is held out (crc32 of the id modulo 5 is 0). Words of the other classes are fixed lists. Everything else
covers whole texts: all of them are scored.

Null and empty texts get the curve's value for no hits. Null ids are held out. Repeated labels of an id
count as toxic if one is; null labels are ignored. Extra columns are ignored.
"""

from __future__ import annotations

import math
from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ripplegraph.llm import kernel as K
from ripplegraph.llm.store import table, text_of

TOXIC_ROWS = 1_500
CLEAN_ROWS = 4_500
OTHER, INSULT, THREAT, TARGET, NEGATION, REPORT = range(6)
#: Fixed word lists of the grammar, in the languages of the corpus.
WORDS = {
    THREAT: "kill hurt destroy beat punish burn tuer frapper töten schlagen matar golpear",
    TARGET: "you your yours yourself u tu toi vous ton ta du dich dir ihr euch tú usted ustedes vosotros",
    NEGATION: "not never no nobody isn't aren't wasn't don't doesn't pas jamais nicht kein keine niemals nunca ningún",
    REPORT: "said says say wrote quoted reported claimed called dit écrit sagte schrieb dijo escribió",
}
THREAT_WEIGHT = 1.0
NEGATED, REPORTED, TARGETED = 0.3, 0.5, 1.5
SCOPE = 3
MIN_EVIDENCE = 11.0
_PUNCTUATION = np.zeros(256, dtype=bool)
_PUNCTUATION[[b for b in range(33, 127) if not chr(b).isalnum()]] = True
_ENDS = np.zeros(256, dtype=bool)
_ENDS[[ord(c) for c in ".!?;:"]] = True


@dataclass(frozen=True)
class Transducer:
    """A deterministic transducer over symbols: (state, symbol) to (state, factor on hits)."""

    states: int
    step: tuple[tuple[tuple[int, float], ...], ...]

    def then(self, other: Transducer) -> Transducer:
        """Both at once: states are pairs, factors multiply."""
        rows = []
        for a in range(self.states):
            for b in range(other.states):
                row = []
                for symbol in range(6):
                    (na, fa), (nb, fb) = self.step[a][symbol], other.step[b][symbol]
                    row.append((na * other.states + nb, fa * fb))
                rows.append(tuple(row))
        return Transducer(self.states * other.states, tuple(rows))


def negation() -> Transducer:
    """State: words left in the scope of a negation."""
    return Transducer(SCOPE + 1, tuple(tuple((SCOPE, 1.0) if s == NEGATION else (max(left - 1, 0), NEGATED if left and s in (INSULT, THREAT) else 1.0) for s in range(6)) for left in range(SCOPE + 1)))


def reported() -> Transducer:
    return Transducer(2, tuple(tuple((1 if told or s == REPORT else 0, REPORTED if told and s in (INSULT, THREAT) else 1.0) for s in range(6)) for told in range(2)))


def targeted() -> Transducer:
    return Transducer(2, tuple(tuple((1 if seen or s == TARGET else 0, TARGETED if seen and s in (INSULT, THREAT) else 1.0) for s in range(6)) for seen in range(2)))


GRAMMAR = negation().then(reported()).then(targeted())


def clause_score(symbols: list[int], weights: list[float]) -> float:
    """Run the composed grammar over one clause. A target counts wherever it stands, so it is read first."""
    state = 1 if TARGET in symbols else 0
    total = 0.0
    for symbol, weight in zip(symbols, weights, strict=True):
        state, factor = GRAMMAR.step[state][symbol]
        total += factor * weight
    return total


@dataclass
class Lexicon:
    """Hashed stems: whole words and word beginnings by their number of bytes."""

    whole: dict[int, tuple[int, float]]
    starts: dict[int, dict[int, float]]

    @classmethod
    def of(cls, stems: dict[str, float]) -> Lexicon:
        """Stems that end in ``$`` are whole words, others are beginnings."""
        whole = {}
        for symbol, words in WORDS.items():
            for w, h in zip(words.split(), _hash_words(words.split()), strict=True):
                whole[h] = (symbol, THREAT_WEIGHT if symbol == THREAT else 0.0)
        entire = [s for s in stems if s.endswith("$")]
        for s, h in zip(entire, _hash_words([s[:-1] for s in entire]), strict=True):
            whole[h] = (INSULT, stems[s])
        starts: dict[int, dict[int, float]] = {}
        begun = [s for s in stems if not s.endswith("$")]
        for s, h in zip(begun, _hash_words(begun), strict=True):
            starts.setdefault(len(s.encode()), {})[h] = stems[s]
        return cls(whole, starts)


def _hash_words(words: list[str]) -> list[int]:
    out: list[int] = []
    for w in K.slices(pa.array([" ".join(words)])):
        out += w.hashes().tolist()
    return out


def _bare(w: K.Words) -> K.Words:
    """Words without the ASCII punctuation around them."""
    begin, end = w.begin.copy(), w.end.copy()
    for _ in range(4):
        begin += (begin < end - 1) & _PUNCTUATION[w.data[begin]]
        end -= (end > begin + 1) & _PUNCTUATION[w.data[end - 1]]
    return K.Words(w.first, w.n_docs, w.data, begin, end, w.doc, w.start)


def _lookup(values: np.ndarray, known: dict[int, float]) -> np.ndarray:
    keys = np.array(sorted(known), dtype=np.uint64)
    weights = np.array([known[k] for k in sorted(known)])
    at = np.minimum(np.searchsorted(keys, values), len(keys) - 1)
    return np.where(keys[at] == values, weights[at], 0.0)


def features(texts: pa.Array, lexicon: Lexicon) -> np.ndarray:
    """Strongest clause, all clauses, all per hundred words and number of hits, of each text."""
    out = []
    lowered = pc.utf8_lower(texts)
    for w in K.slices(lowered):
        found = np.zeros((w.n_docs, 4))
        out.append(found)
        if not len(w.begin):
            continue
        bare = _bare(w)
        hashed = bare.hashes()
        weight = np.zeros(len(hashed))
        symbol = np.zeros(len(hashed), dtype=np.int8)
        kinds = {h: float(s) for h, (s, _) in lexicon.whole.items()}
        symbol[:] = _lookup(hashed, kinds).astype(np.int8)
        weight[:] = _lookup(hashed, {h: v for h, (_, v) in lexicon.whole.items()})
        for length, known in lexicon.starts.items():
            fits = np.flatnonzero(bare.end - bare.begin >= length)
            begun = K.Words(w.first, w.n_docs, w.data, bare.begin[fits], bare.begin[fits] + length, w.doc, w.start)
            own = _lookup(begun.hashes(), known)
            better = own > weight[fits]
            weight[fits[better]] = own[better]
            symbol[fits[better]] = INSULT
        hits = np.flatnonzero((symbol == INSULT) | (symbol == THREAT))
        if not len(hits):
            continue
        lines = np.concatenate(([0], np.cumsum(w.data == 10)))
        new = np.ones(len(hashed), dtype=bool)
        new[1:] = _ENDS[w.data[w.end[:-1] - 1]] | (lines[w.begin[1:]] > lines[w.end[:-1]]) | (w.doc[1:] != w.doc[:-1])
        clause = np.cumsum(new) - 1
        heads = np.append(np.flatnonzero(new), len(hashed))
        for c in np.unique(clause[hits]).tolist():
            a, b = heads[c], heads[c + 1]
            score = clause_score(symbol[a:b].tolist(), weight[a:b].tolist())
            k = w.doc[a]
            found[k, 0] = max(found[k, 0], score)
            found[k, 1] += score
        np.add.at(found[:, 3], w.doc[hits], 1)
        found[:, 2] = 100 * found[:, 1] / np.maximum(np.diff(w.start), 1)
    return np.log1p(np.concatenate(out)) if out else np.zeros((0, 4))


def _stems_of(text: str) -> set[str]:
    out = set()
    for word in set(text.lower().split()):
        word = word.strip("!\"#$%&'()*+,-./:;<=>?@[\\]^_`{|}~")
        if len(word) > 2:
            out.add(word + "$")
            out.update(word[:n] for n in range(3, min(len(word), 12) + 1))
    return out


def learn_stems(texts: list[str], toxic: np.ndarray) -> dict[str, float]:
    """Stems that occur in toxic texts far more than in others, and their log odds."""
    bad = Counter(s for t, x in zip(texts, toxic, strict=True) if x for s in _stems_of(t))
    bad = Counter({s: n for s, n in bad.items() if n >= 4})
    good: Counter = Counter()
    for t, x in zip(texts, toxic, strict=True):
        if not x:
            good.update(s for s in _stems_of(t) if s in bad)
    n_bad = int(toxic.sum())
    n_good = len(texts) - n_bad
    share = n_bad / len(texts)

    def evidence(a: int, b: int) -> float:
        rate = a / (a + b)
        return a * math.log(rate / share) + (b * math.log((1 - rate) / (1 - share)) if b else 0.0)

    odds = {s: math.log((a + 0.5) / (n_bad + 1)) - math.log((good[s] + 0.5) / (n_good + 1)) for s, a in bad.items()}
    strong = {s for s, a in bad.items() if odds[s] > 2.5 and evidence(a, good[s]) >= MIN_EVIDENCE}
    kept: dict[str, float] = {}
    for s in sorted(strong, key=lambda s: (len(s), s)):
        longer = any(t in strong and bad[t] == bad[s] for t in {s + c for c in {t[len(s)] for t in strong if len(t) > len(s) and t.startswith(s)}})
        if not longer and not any(s[:n] in kept for n in range(3, len(s))):
            kept[s] = odds[s]
    return kept


def fit_curve(x: np.ndarray, y: np.ndarray, ridge: float = 1.0) -> np.ndarray:
    """Logistic regression by Newton steps."""
    x = np.column_stack((np.ones(len(x)), x))
    w = np.zeros(x.shape[1])
    hold = np.full(x.shape[1], ridge)
    hold[0] = 1e-6
    for _ in range(30):
        p = 1 / (1 + np.exp(-np.clip(x @ w, -30, 30)))
        step = np.linalg.solve((x * (p * (1 - p))[:, None]).T @ x + np.diag(hold), x.T @ (y - p) - hold * w)
        w += step
        if np.abs(step).max() < 1e-8:
            break
    return w


def held_out(doc_id: str = "doc_id") -> Column:
    return F.crc32(F.coalesce(F.col(doc_id).cast("string"), F.lit("")).cast("binary")) % 5 == 0


def train(docs: DataFrame, labels: DataFrame, toxic_rows: int = TOXIC_ROWS, clean_rows: int = CLEAN_ROWS) -> tuple[dict[str, float], np.ndarray]:
    """Stems and curve from a bounded sample of labelled texts outside the held-out fold."""
    known = labels.where("doc_id is not null and toxic is not null").where(~held_out()).groupBy("doc_id").agg(F.max("toxic").alias("toxic"))
    pick = lambda value, n: known.where(F.col("toxic") == value).orderBy(F.xxhash64("doc_id"), "doc_id").limit(n)
    chosen = pick(1, toxic_rows).unionByName(pick(0, clean_rows))  # bounded by its limits
    rows = docs.select(F.col("doc_id").cast("long"), text_of("text").alias("text")).join(F.broadcast(chosen), "doc_id").dropDuplicates(["doc_id"]).toArrow()
    if not rows.num_rows:
        return {}, np.array([-3.0, 0, 0, 0, 0])
    rows = rows.sort_by("doc_id")
    toxic = np.asarray(rows["toxic"].to_numpy()).astype(int)
    if toxic.min() == toxic.max():
        return {}, np.array([3.0 if toxic[0] else -3.0, 0, 0, 0, 0])
    stems = learn_stems(rows["text"].to_pylist(), toxic)
    return stems, fit_curve(features(rows["text"].combine_chunks(), Lexicon.of(stems)), toxic)


def _scored(stems: dict[str, float], curve: np.ndarray):
    def rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        lexicon = Lexicon.of(stems)
        for batch in batches:
            x = features(batch.column("text"), lexicon)
            score = 1 / (1 + np.exp(-np.clip(curve[0] + x @ curve[1:], -30, 30)))
            names = [n for n in batch.schema.names if n != "text"]
            yield pa.RecordBatch.from_arrays([*(batch.column(n) for n in names), pa.array(score)], [*names, "score"])

    return rows


def _passed(stems: dict[str, float], curve: np.ndarray, text: int):
    def rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        lexicon = Lexicon.of(stems)
        for batch in batches:
            x = features(pc.fill_null(batch.column(text), ""), lexicon)
            score = 1 / (1 + np.exp(-np.clip(curve[0] + x @ curve[1:], -30, 30)))
            yield batch.filter(pa.array(score < 0.5))

    return rows


def without_toxic(docs: DataFrame, labels: DataFrame) -> DataFrame:
    """The rows of ``docs`` that are not predicted toxic, whole and in one pass without a shuffle."""
    return docs.mapInArrow(_passed(*train(docs, labels), docs.columns.index("text")), docs.schema)


def toxicity(spark: SparkSession, docs: DataFrame, labels: DataFrame) -> DataFrame:
    """One row per input row: doc_id, th (a hash of its text), held_out, score, predicted."""
    stems, curve = train(docs, labels)
    rows = docs.select(F.col("doc_id").cast("long"), text_of("text").alias("text")).withColumn("th", F.xxhash64("text")).withColumn("held_out", held_out())
    scored = rows.select("doc_id", "th", "held_out", "text").mapInArrow(_scored(stems, curve), "doc_id long, th long, held_out boolean, score double")
    return scored.withColumn("predicted", (F.col("score") >= 0.5).cast("int"))


def op7_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    return toxicity(spark, table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels")).drop("th")
