"""Toxicity by a weighted finite-state pattern grammar.

Five transducers read the words of a clause as classes. The insult transducer weighs how an insult is put (said of
somebody with a copula, called after somebody, or by itself), the threat transducer whether a verb of violence is intended,
the target transducer whether somebody is near, before or after; the negation and reported-speech transducers keep the scopes
that weaken a match; targets and reports count on either side of it. Each is a table of moves with factors; their composition multiplies the factors over the
product of their states. What depends on words to the left is composed into one machine, what depends on words to the right
into one that reads backwards, and a match weighs its rating times both factors. A clause's score is the
sum of its matches, so no word counts apart from what stands around it.

Insults are a short list and what labelled training rows teach: words and word beginnings, rated by the lower end of the
confidence interval of their log odds. A logistic curve over the clause scores turns them to a probability. It is fitted
on scores that either half of the training rows gets from the lexicon of the other half.

The lexicon and the curve are fitted on at most ``sample`` labelled rows (the first by a hash of the id); all
documents are scored whole, in time linear in their length. Repeated texts count once in training; of rows that share
a text, one that is toxic makes it toxic.

A very long text takes memory of a small multiple of its longest clause that matches. Null and empty texts and texts without a match get the curve's value at zero. Labels of ids without a text are ignored; a
null label is no label. Rows with null ids are scored, never trained on. Repeated rows get equal scores. Words that tie in
weight enter the lexicon by length, then by code point. Without toxic or without clean training rows the score is 1 - exp(-sum). Extra columns,
whatever their names, are ignored by scores() and kept by keep_clean().
"""

from __future__ import annotations

import math
import re
from collections import Counter
from collections.abc import Iterator

import ahocorasick
import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from embedvocab.llm.common import columns, crc_remainder, held_out, per_document, trimmed, written

#: Lexemes of the grammar in English, German, French and Spanish, by the class that the transducers read.
INSULTS = "idiot idiots moron morons stupid scum trash clown loser losers pathetic worthless disgusting imbecile vermin filth subhuman garbage abschaum dummkopf imbécile ordure basura imbécil".split()
LEXEMES = {
    "threat": "kill hurt destroy beat burn shoot stab hang strangle exterminate töten umbringen erschießen verbrennen tuer frapper brûler matar golpear quemar".split(),
    "target": "you your you're he she they them him her their people those these everyone du dich dir euch ihr sie tu toi te vous ils elles tú ti vosotros ellos ellas ustedes".split(),
    "negation": "not no never neither nor isn't aren't wasn't don't doesn't without nobody nicht kein keine nie niemals ohne pas jamais sans ni nunca sin".split(),
    "report": "said says say called calls wrote writes claimed claims reported quoted according accused sagte sagt schrieb behauptet dit écrit affirme dijo dice escribió afirma".split(),
    "copula": "am is are was were be being bist seid ist sind es êtes est sont eres sois son".split(),
    "intent": "will shall should must gonna going want let's werde werden will sollte vais va vont veux voy vamos quiero".split(),
    "filler": "a an the such so very really total complete utter fucking bloody ein eine so total un une si très una muy tan".split(),
}
CLASSES = ["other", "insult", *LEXEMES]

#: How many words on a target, a negation and an intent reach; what each does to a match.
REACH, NEGATION_REACH, INTENT_REACH = 4, 3, 3
NEGATED, REPORTED, TARGETED = 0.35, 0.6, 1.5
PREDICATED, VOCATIVE = 1.4, 1.25
INTENDED, BARE_THREAT, THREAT = 1.0, 0.2, 2.0

_WORD = re.compile(r"[^\W\d_]+(?:'[^\W\d_]+)*")
_ENDS = ".!?;:,\n"
_CLAUSE = re.compile(r"[^.!?;:,\n]+")


class Transducer:
    """A start state and moves: (state, class) -> (state, factor of a match of that class read in that state)."""

    def __init__(self, start: int, moves: dict[tuple[int, str], tuple[int, float]]):
        self.start, self.moves = start, moves


def countdown(trigger: str, reach: int, inside: float, outside: float, matches: tuple[str, ...]) -> Transducer:
    """A scope that a trigger opens for so many words."""
    return Transducer(0, {(s, c): (reach if c == trigger else max(0, s - 1), (inside if s else outside) if c in matches else 1.0) for s in range(reach + 1) for c in CLASSES})


def latch(trigger: str, factor: float, matches: tuple[str, ...]) -> Transducer:
    """A scope that a trigger opens to the clause's end."""
    return Transducer(0, {(s, c): (int(s or c == trigger), factor if s and c in matches else 1.0) for s in (0, 1) for c in CLASSES})


def insults() -> Transducer:
    """State 1 follows a target, 2 a copula after a target; fillers keep the state, and so does a negation ("you are not")."""
    moves = {}
    for s, factor in enumerate((1.0, VOCATIVE, PREDICATED)):
        for c in CLASSES:
            to = 1 if c == "target" else 2 if c == "copula" and s else s if c in ("filler", "insult", "negation") else 0
            moves[s, c] = to, factor if c == "insult" else 1.0
    return Transducer(0, moves)


def compose(machines: list[Transducer]) -> list[list[tuple[int, float]]]:
    """One deterministic machine over the product of the states reached from the start, row 0; factors multiply. Columns are CLASSES."""
    first = tuple(m.start for m in machines)
    names, todo, table = {first: 0}, [first], [[]]
    while todo:
        state = todo.pop()
        row = []
        for c in CLASSES:
            steps = [m.moves[s, c] for m, s in zip(machines, state, strict=True)]
            to = tuple(t for t, _ in steps)
            if to not in names:
                names[to] = len(names)
                table.append([])
                todo.append(to)
            row.append((names[to], math.prod(f for _, f in steps)))
        table[names[state]] = row
    return table


_BOTH = ("insult", "threat")
#: Reading forwards: insult, threat, negation and reported speech before the match; the target before it as state only.
FORWARD = compose([insults(), countdown("intent", INTENT_REACH, INTENDED, BARE_THREAT, ("threat",)), countdown("negation", NEGATION_REACH, NEGATED, 1.0, _BOTH), latch("report", REPORTED, _BOTH),
                   countdown("target", REACH, TARGETED, 1.0, _BOTH)])
#: Reading backwards: a target or a report after the match.
BACKWARD = compose([countdown("target", REACH, TARGETED, 1.0, _BOTH), latch("report", REPORTED, _BOTH)])

#: Lengths of the word beginnings that may be learned as stems, written with a star.
STEMS = range(4, 9)


def lexemes(word: str) -> list[str]:
    """The word and its beginnings, as they may be in the lexicon."""
    return [word, *(word[:n] + "*" for n in STEMS if len(word) >= n)]


class Model:
    """The lexicon with its weights, and the curve from a document's clause scores to a probability."""

    def __init__(self, learned: dict[str, float], curve: list[float]):
        self.weights = dict.fromkeys(INSULTS, 2.0) | learned
        self.classes = {w: CLASSES.index(c) for c, words in LEXEMES.items() for w in words}
        self.curve = curve
        self._finder = None

    def __getstate__(self) -> dict:
        return self.__dict__ | {"_finder": None}

    def finder(self) -> ahocorasick.Automaton:
        if self._finder is None:
            self._finder = ahocorasick.Automaton()
            for w in [*self.weights, *LEXEMES["threat"]]:
                self._finder.add_word(w.rstrip("*"), len(w.rstrip("*")))
            self._finder.make_automaton()
        return self._finder

    def rated(self, word: str) -> tuple[int, float]:
        """The word's class and its weight, zero if it is no match."""
        weight = max((self.weights[x] for x in lexemes(word) if x in self.weights), default=0.0)
        if weight:
            return 1, weight
        c = self.classes.get(word, 0)
        return c, THREAT if CLASSES[c] == "threat" else 0.0

    def clause(self, words: list[str]) -> float:
        read = [self.rated(w) for w in words]
        if not any(weight for _, weight in read):
            return 0.0
        state, after = 0, [1.0] * len(read)
        for i in range(len(read) - 1, -1, -1):
            state, after[i] = BACKWARD[state][read[i][0]]
        state, total = 0, 0.0
        for (c, weight), behind in zip(read, after, strict=True):
            state, factor = FORWARD[state][c]
            if weight:
                total += weight * factor * behind
        return total

    def clauses(self, text: str) -> list[float]:
        """The scores of the clauses in which a lexeme begins a word; the search leaves all other clauses unread."""
        low = text.lower()
        out, done = [], 0
        for end, size in self.finder().iter(low):
            begin = end - size + 1
            if begin < done or (begin and low[begin - 1].isalpha()):
                continue
            # no clause begins before the end of the one read last, so each character is searched once
            start = max(max(low.rfind(c, done, begin) for c in _ENDS) + 1, done)
            found = _CLAUSE.match(low, start)
            done = found.end() if found else end + 1
            out.append(self.clause(_WORD.findall(low, start, done)))
        return out

    def features(self, text: str) -> tuple[float, float]:
        """The sum of the clause scores, and the sum for each thousand characters, damped."""
        total = sum(self.clauses(text))
        return math.log1p(total), math.log1p(1000 * total / (len(text) + 200))

    def score(self, text: str) -> float:
        x = self.features(text)
        if not self.curve:
            return -math.expm1(-math.expm1(x[0]))
        z = self.curve[0] + sum(b * v for b, v in zip(self.curve[1:], x, strict=True))
        return 1 / (1 + math.exp(-max(-40.0, min(40.0, z))))


def training_rows(docs: DataFrame, labels: DataFrame, label: str, modulus: int, remainder: int, sample: int) -> DataFrame:
    """(text, label): labelled rows outside the held-out remainder, at most ``sample`` by a hash of the id, each text once."""
    known = (columns(labels, doc_id="long", **{label: "int"}).filter(F.col(label).isNotNull() & F.col("doc_id").isNotNull() & (crc_remainder(F.col("doc_id"), modulus) != remainder))
             .groupBy("doc_id").agg(F.max(label).alias("label")).orderBy(F.xxhash64("doc_id"), "doc_id").limit(sample))
    return columns(docs, doc_id="long", text="string").filter(F.col("text").isNotNull()).join(F.broadcast(known), "doc_id").groupBy("text").agg(F.max("label").alias("label"))


def lexicon_of(toxic: dict[str, int], clean: dict[str, int], n1: int, n0: int, most: int, least_weight: float) -> dict[str, float]:
    """Lexemes and weights from how many of n1 toxic and n0 clean texts have each."""
    weights = {}
    for w, a in toxic.items():
        b = clean.get(w, 0)
        odds = math.log((a + 0.5) / (n1 + 1)) - math.log((b + 0.5) / (n0 + 1))
        weights[w] = odds - 1.64 * math.sqrt(1 / (a + 0.5) + 1 / (b + 0.5))
    learned: dict[str, float] = {}
    for w in sorted(weights, key=lambda w: (-weights[w], len(w), w)):
        if weights[w] < least_weight or len(learned) == most:
            break
        if w not in _FUNCTION and not any(x in learned for x in lexemes(w.rstrip("*"))):
            learned[w] = weights[w]
    return learned


_FUNCTION = {w for c, words in LEXEMES.items() if c != "threat" for w in words}


def curve_of(x: np.ndarray, y: np.ndarray, ridge: float = 1.0) -> list[float]:
    """Intercept and coefficients of a logistic regression, by Newton's method; the ridge leaves the intercept free."""
    rows = np.column_stack([np.ones(len(x)), x])
    penalty, beta = np.diag([1e-6] + [ridge] * x.shape[1]), np.zeros(x.shape[1] + 1)
    for _ in range(30):
        p = 1 / (1 + np.exp(-np.clip(rows @ beta, -30, 30)))
        step = np.linalg.solve(rows.T @ (rows * (p * (1 - p) + 1e-9)[:, None]) + penalty, rows.T @ (y - p) - penalty @ beta)
        beta += step
        if np.abs(step).max() < 1e-9:
            break
    return [float(b) for b in beta]


def fit(docs: DataFrame, labels: DataFrame, modulus: int = 4, remainder: int = 2, sample: int = 20_000, lexicon: int = 1024, candidates: int = 20_000, least_weight: float = 1.0) -> Model:
    """The model that the labelled rows teach; the driver gets counts of at most ``candidates`` lexemes and two numbers a training row."""
    fold = F.pmod(F.xxhash64("text"), F.lit(2)).cast("int").alias("fold")
    rows = written(training_rows(docs, labels, "toxic", modulus, remainder, sample).select("text", F.col("label").cast("int").alias("label"), fold))  # a bounded table, read several times
    sizes = {(r.label, r.fold): r.n for r in rows.groupBy("label", "fold").agg(F.count(F.lit(1)).alias("n")).collect()}
    n1, n0 = (sizes.get((y, 0), 0) + sizes.get((y, 1), 0) for y in (1, 0))
    if not n1 or not n0:
        return Model({}, [])

    def counted(label: int, among: set[str] | None) -> DataFrame:
        """(w, a, b): in how many rows of either half each lexeme occurs."""

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            seen: tuple[Counter[str], Counter[str]] = Counter(), Counter()
            for batch in batches:
                for text, half in zip(batch.column(0), batch.column(1).to_pylist(), strict=True):
                    own = {x for w in set(_WORD.findall(text.as_py().lower())) for x in lexemes(w)}
                    seen[half].update(own if among is None else own & among)
            found = list(seen[0] | seen[1])
            yield pa.record_batch([pa.array(found, pa.string()), *(pa.array([s[w] for w in found], pa.int64()) for s in seen)], names=["w", "a", "b"])
            trimmed()

        return rows.filter(F.col("label") == label).select("text", "fold").mapInArrow(run, "w string, a long, b long").groupBy("w").agg(F.sum("a").alias("a"), F.sum("b").alias("b"))

    # chance makes lexemes of very few rows
    often = counted(1, None).filter(F.col("a") + F.col("b") >= max(3.0, n1 / 200)).orderBy(F.desc(F.col("a") + F.col("b")), "w").limit(candidates)
    toxic = {r.w: (r.a, r.b) for r in often.collect()}
    clean = {r.w: (r.a, r.b) for r in counted(0, set(toxic)).collect()}

    def learned(halves: tuple[int, ...]) -> dict[str, float]:
        both = [{w: sum(n[h] for h in halves) for w, n in counts.items()} for counts in (toxic, clean)]
        totals = [sum(sizes.get((y, h), 0) for h in halves) for y in (1, 0)]
        least = max(3.0, totals[0] / 200)
        return lexicon_of({w: n for w, n in both[0].items() if n >= least}, both[1], *totals, lexicon, least_weight)

    across = [Model(learned((1,)), []), Model(learned((0,)), [])]

    def measured(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            found = [across[half].features(t.as_py()) for t, half in zip(batch.column(0), batch.column(2).to_pylist(), strict=True)]
            yield pa.record_batch([*(pa.array([x[i] for x in found], pa.float64()) for i in range(2)), batch.column(1).cast(pa.int32())], names=["total", "density", "label"])
        trimmed()

    seen = rows.select("text", "label", "fold").mapInArrow(measured, "total double, density double, label int").toPandas().sort_values(["total", "density", "label"])
    return Model(learned((0, 1)), curve_of(seen[["total", "density"]].to_numpy(float), seen["label"].to_numpy(float)))


def scores(docs: DataFrame, model: Model, modulus: int = 4, remainder: int = 2, threshold: float = 0.3) -> DataFrame:
    """(doc_id, held_out, score, predicted) of every row."""
    schema = pa.schema([("doc_id", pa.int64()), ("held_out", pa.bool_()), ("score", pa.float64()), ("predicted", pa.int32())])

    def run(ids: list, texts: list[bytes]) -> Iterator[tuple]:
        for i, t in zip(ids, texts, strict=True):
            s = model.score(t.decode())
            yield i, held_out(i, modulus, remainder), s, int(s >= threshold)

    return per_document(docs, run, schema, "doc_id long, held_out boolean, score double, predicted int")


def keep_clean(docs: DataFrame, model: Model, threshold: float = 0.3) -> DataFrame:
    """The documents that score below the threshold, all columns kept; workers hold one Arrow batch and one text at a time."""
    place = docs.columns.index("text")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            clean = [model.score(t.as_py() or "") < threshold for t in batch.column(place)]
            yield batch.filter(pa.array(clean, pa.bool_()))
        trimmed()

    return docs.mapInArrow(run, docs.schema)


def brute_force(words: list[str], model: Model) -> float:
    """A clause's score by the definition, plainly, for tests: each match against the words around it."""
    kind = [CLASSES[model.rated(w)[0]] for w in words]
    total = 0.0
    for i, w in enumerate(words):
        weight = model.rated(w)[1]
        if not weight:
            continue
        weight *= NEGATED if "negation" in kind[max(0, i - NEGATION_REACH):i] else 1.0
        weight *= REPORTED ** (("report" in kind[:i]) + ("report" in kind[i + 1:]))
        weight *= TARGETED ** (("target" in kind[max(0, i - REACH):i]) + ("target" in kind[i + 1:i + 1 + REACH]))
        if kind[i] == "threat":
            weight *= INTENDED if "intent" in kind[max(0, i - INTENT_REACH):i] else BARE_THREAT
        else:
            # back over fillers, insults and negations to a copula, which must follow a target, or to a target
            j, copula = i - 1, False
            while j >= 0 and (kind[j] in ("filler", "insult", "negation") or kind[j] == "copula"):
                copula = copula or kind[j] == "copula"
                j -= 1
            if j >= 0 and kind[j] == "target":
                weight *= PREDICATED if copula else VOCATIVE
        total += weight
    return total
