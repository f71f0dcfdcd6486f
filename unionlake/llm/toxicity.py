"""Toxicity by a weighted finite-state grammar over clauses.

Words become classes: insult, threat, target, negation, reported speech, other. Small transducers
each rewrite the class string of a clause - one marks what stands under reported speech, one what
stands under a negation, one what is aimed at a target before it - and their composition is one
deterministic transducer, whose outputs carry weights. What is aimed at a target behind it is
marked by the last of them once more, run from the clause's end over the outputs. A text's score is the logistic of a bias and
the weights of its matched clauses, so a word counts by the clause it stands in.

The insult lexicon starts from common words and is widened from labelled texts: whole words and
word beginnings that cover toxic texts and hardly occur in clean ones, chosen greedily so that only
what explains further toxic texts is taken. Words weigh by log ratios,
patterns by how the odds of their texts compare, and a line through the sums is fitted to the same texts. Labels are learned from a bounded sample; language, source and id are never looked at.

Defined results: null and empty texts have no clause and get the base rate as score; labels that
contradict each other count as toxic; with no labelled row the weights given here hold; repeated
rows give a row each; an empty table gives an empty result; extra columns are ignored.
"""

from __future__ import annotations

import math
import re
from collections import defaultdict
from dataclasses import dataclass, field

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from unionlake.llm.common import checkpointed, id_remainder, light, portions

SCHEMA = "doc_id bigint, held_out boolean, score double, predicted int, clauses int"

#: Common words of each class in English, German, Spanish and French.
SEEDS = {
    "I": "idiot idiots moron morons loser losers stupid scum trash pathetic worthless disgusting clown idiota imbécil estúpido basura trottel dummkopf abschaum arschloch crétin imbécile connard ordure",
    "T": "kill hurt destroy murder töten umbringen vernichten matar destruir tuer détruire",
    "Y": "you your yours he she they him her them du ihr dich euch dir er sie tú usted vosotros ustedes él ella ellos tu vous toi il elle ils elles",
    "N": "not no never neither nor nicht kein keine keinen niemals nie jamás nunca tampoco pas jamais aucun ni",
    "R": "said says wrote writes quoted quotes claimed claims called reported according sagte sagt schrieb behauptet zitiert laut dijo dice escribió según afirmó dit écrit selon affirme cité",
}

#: By what a word's weight counts in a clause before labels say otherwise, by the composed output:
#: plain, negated, reported and aimed insult; plain, negated, reported and aimed threat.
FACTORS = {"I": 1.0, "j": 0.3, "i": 0.3, "A": 1.2, "T": 0.3, "u": 0.0, "t": 0.0, "B": 1.0}
SEED_WEIGHT = 4.0

_CLAUSE = re.compile(r"[.,;:!?\n]+")
#: Bytes of UTF-8 texts that are neither ASCII letters nor beyond ASCII end a word.
_FOLD = bytes(b if 97 <= b <= 122 or b >= 128 else b + 32 if 65 <= b <= 90 else 32 for b in range(256))


@dataclass
class Transducer:
    """arcs: (state, symbol) -> (next state, output). A symbol without an arc keeps the state `loop` says, and is put out as it is."""

    arcs: dict[tuple[int, str], tuple[int, str]]
    loop: dict[int, int] = field(default_factory=dict)

    def step(self, state: int, symbol: str) -> tuple[int, str]:
        return self.arcs.get((state, symbol)) or (self.loop.get(state, state), symbol)


def compose(first: Transducer, second: Transducer, alphabet: str) -> Transducer:
    """The transducer that hands first's output to second; states are numbered as they are reached from (0, 0)."""
    number, arcs, todo = {(0, 0): 0}, {}, [(0, 0)]
    while todo:
        a, b = todo.pop()
        for x in alphabet:
            a2, y = first.step(a, x)
            b2, z = second.step(b, y)
            if (a2, b2) not in number:
                number[a2, b2] = len(number)
                todo.append((a2, b2))
            arcs[number[a, b], x] = (number[a2, b2], z)
    return Transducer(arcs)


def within(trigger: str, reach: int | None, rewrite: dict[str, str]) -> Transducer:
    """After `trigger`, for the next `reach` words (None: to the end of the clause), symbols are rewritten."""
    arcs, loop = {(0, trigger): (1, trigger)}, {0: 0}
    for s in range(1, (reach or 1) + 1):
        after = 1 if reach is None else (s + 1 if s < reach else 0)
        arcs[s, trigger] = (1, trigger)
        loop[s] = after
        for x, y in rewrite.items():
            arcs[s, x] = (after, y)
    return Transducer(arcs, loop)


CLASSES = "OITYNR"


def aimed(scope: int = 3) -> Transducer:
    return within("Y", scope, {"I": "A", "T": "B"})


def grammar(scope: int = 3) -> Transducer:
    reported = within("R", None, {"I": "i", "T": "t"})
    negated = within("N", scope, {"I": "j", "T": "u"})
    return compose(compose(reported, negated, CLASSES), aimed(scope), CLASSES)


class Scorer:
    """words: class and weight of each word; stems: weight of each beginning of insults; a text's sum z of its clauses
    scores the logistic of slope * z + bias."""

    def __init__(self, words: dict[str, tuple[str, float]], stems: dict[str, float], factors: dict[str, float], slope: float = 1.0, bias: float = -3.0, remembered: int = 60_000):
        self.words = {w.encode(): x for w, x in words.items()}
        self.stems = {w.encode(): ("I", x) for w, x in stems.items()}
        self.lengths = sorted({len(w) for w in self.stems}, reverse=True)
        self.factors, self.slope, self.bias, self.remembered = factors, slope, bias, remembered
        self.machine, self.back = grammar(), aimed()
        self.plain: set[bytes] = set()

    def kind(self, word: bytes) -> tuple[str, float]:
        got = self.words.get(word)
        if got is None:
            for n in self.lengths:
                if len(word) > n and (got := self.stems.get(word[:n])):
                    return got
            return ("O", 0.0)
        return got

    def clauses(self, text: str | None) -> list[tuple[str, float]]:
        """(pattern, weight of the word) of the heaviest match of each clause that has one."""
        if not text:
            return []
        raw = text.lower().encode("utf-8", "replace")
        if len(self.plain) > self.remembered:
            self.plain.clear()
        marked = False
        for w in set(raw.translate(_FOLD).split()).difference(self.plain):
            if self.kind(w)[0] in "IT":
                marked = True
            else:
                self.plain.add(w)
        if not marked:
            return []
        out = []
        for clause in _CLAUSE.split(raw.decode()):
            kinds = [self.kind(w) for w in clause.encode().translate(_FOLD).split()]
            if not any(k in "IT" for k, _ in kinds):
                continue
            state, best, marks = 0, None, []
            for x, _ in kinds:
                state, y = self.machine.step(state, x)
                marks.append(y)
            state = 0
            for i in range(len(marks) - 1, -1, -1):
                state, marks[i] = self.back.step(state, marks[i])
            for y, (_, weight) in zip(marks, kinds, strict=True):
                if y in self.factors and (best is None or self.factors[y] * weight > self.factors[best[0]] * best[1]):
                    best = (y, weight)
            if best:
                out.append(best)
        return out

    def sum(self, clauses: list[tuple[str, float]]) -> float:
        return sum(self.factors[p] * w for p, w in clauses)

    def score(self, text: str | None) -> tuple[float, int]:
        found = self.clauses(text)
        return logistic(self.slope * self.sum(found) + self.bias), len(found)


def logistic(z: float) -> float:
    return 1 / (1 + math.exp(-max(-30.0, min(30.0, z))))


def fit_line(points: list[tuple[float, int, float]], rounds: int = 50) -> tuple[float, float]:
    """slope and bias of the logistic curve through (z, label, weight), by Newton steps with a small ridge."""
    a, b = 1.0, -3.0
    for _ in range(rounds):
        ga, gb, haa, hab, hbb = 0.1 * (a - 1.0), 0.01 * (b + 3.0), 0.1, 0.0, 0.01
        for z, y, w in points:
            p = logistic(a * z + b)
            v = w * p * (1 - p)
            ga += w * (p - y) * z
            gb += w * (p - y)
            haa += v * z * z
            hab += v * z
            hbb += v
        det = haa * hbb - hab * hab
        da, db = (hbb * ga - hab * gb) / det, (haa * gb - hab * ga) / det
        da, db = max(-2.0, min(2.0, da)), max(-2.0, min(2.0, db))
        a, b = a - da, b - db
        if abs(da) + abs(db) < 1e-6:
            break
    return max(a, 0.05), b


def labelled(docs: DataFrame, labels: DataFrame, most_per_label: int = 6000) -> tuple[DataFrame, dict[int, int]]:
    """(text, toxic) of at most about most_per_label labelled documents of each kind, and how many labels of each kind there are.

    A document is toxic if any label of it says so. The sample is drawn from the labels by a hash of
    the id, so it is small before it meets the documents, and goes to their scan as a broadcast.
    """
    marks = labels.where("doc_id is not null and toxic is not null").groupBy("doc_id").agg(F.max(F.col("toxic").cast("int")).alias("toxic"))
    sizes = {r["toxic"]: r["n"] for r in marks.groupBy("toxic").agg(F.count("*").alias("n")).collect()}
    share = F.pmod(F.xxhash64(F.lit(11), "doc_id"), F.lit(1_000_003)) / 1_000_003.0
    kept = F.lit(False)
    for kind, n in sizes.items():
        kept = kept | ((F.col("toxic") == kind) & (share < most_per_label / n))
    few = marks.where(kept).coalesce(1)
    return docs.select("doc_id", "text").join(F.broadcast(few), "doc_id").where("text is not null").select("text", "toxic"), sizes


def _terms(text: str, lengths: tuple[int, ...]) -> set[str]:
    words = {w for w in set(text.lower().encode("utf-8", "replace").translate(_FOLD).decode("utf-8", "replace").split()) if 3 <= len(w) <= 40}
    return words | {w[:n] + "*" for w in words for n in lengths if len(w) > n}


def train(spark: SparkSession, known: DataFrame, sizes: dict[int, int], stems: tuple[int, ...] = (4, 5, 6, 7, 8, 9), purity: float = 0.3) -> Scorer:
    """Fits lexicon and weights on `known` (text, toxic), a bounded sample of texts; sizes: how many of each kind it stands for.

    A term may enter if its share of clean texts is at most `purity` of its share of toxic ones. Its
    weight is the log ratio of the two shares.
    """
    rows = checkpointed(spark, known, "labelled")
    totals = {r["toxic"]: r["n"] for r in rows.groupBy("toxic").agg(F.count("*").alias("n")).collect()}
    words = {w: (c, SEED_WEIGHT if c in "IT" else 0.0) for c, line in SEEDS.items() for w in line.split()}
    n_toxic, n_clean = totals.get(1, 0), totals.get(0, 0)
    if not n_toxic or not n_clean:
        return Scorer(words, {}, dict(FACTORS))
    support = max(3, n_toxic // 300)

    def count(batches):
        seen: dict[str, list[int]] = defaultdict(lambda: [0, 0])
        for batch in batches:
            for text, toxic in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
                for t in _terms(text, stems):
                    seen[t][toxic] += 1
        yield pa.RecordBatch.from_pydict({"term": list(seen), "clean": [v[0] for v in seen.values()], "toxic": [v[1] for v in seen.values()]}, pa.schema([("term", pa.string()), ("clean", pa.int64()), ("toxic", pa.int64())]))

    terms = rows.mapInArrow(light(count), "term string, clean bigint, toxic bigint").groupBy("term").agg(F.sum("clean").alias("clean"), F.sum("toxic").alias("toxic"))
    pure = F.col("clean") / n_clean <= purity * F.col("toxic") / n_toxic
    seeds = [w for w, (c, _) in words.items() if c in "IT"]
    seen = {r["term"]: (r["clean"], r["toxic"]) for r in terms.where(((F.col("toxic") >= support) & pure) | F.col("term").isin(seeds)).collect()}  # bounded by the sample
    found = {t: n for t, n in seen.items() if n[1] >= support and n[0] / n_clean <= purity * n[1] / n_toxic}
    shared = spark.sparkContext.broadcast(frozenset(found))

    def cover(batches):
        for batch in batches:
            yield pa.RecordBatch.from_pydict({"terms": [sorted(_terms(t, stems) & shared.value) for t in batch.column(0).to_pylist()]}, pa.schema([("terms", pa.list_(pa.string()))]))

    holds: dict[str, set[int]] = defaultdict(set)
    for i, r in enumerate(rows.where("toxic = 1").select("text").mapInArrow(light(cover), "terms array<string>").collect()):  # bounded by the sample
        for t in r["terms"]:
            holds[t].add(i)
    chosen, open_ = [], set().union(*holds.values()) if holds else set()
    dear = n_toxic / n_clean / purity  # what a clean text that holds a term costs, in toxic ones
    while holds:
        rank = lambda t: (len(holds[t] & open_) - found[t][0] * dear, not t.endswith("*"), len(t), t)
        best = max(holds, key=rank)
        if rank(best)[0] < support:
            break
        chosen.append(best)
        open_ -= holds.pop(best)
        holds = {t: x for t, x in holds.items() if len(x & open_) >= support}
    ratio = lambda t: math.log((seen[t][1] + 0.5) / (n_toxic + 1)) - math.log((seen[t][0] + 0.5) / (n_clean + 1))
    for w in seeds:  # a common insult that clean texts use as often is none here
        if w in seen:
            words[w] = (words[w][0], max(0.0, ratio(w)))
    words |= {t: ("I", ratio(t)) for t in chosen if not t.endswith("*")}
    begins = {t[:-1]: ratio(t) for t in chosen if t.endswith("*")}
    fitted = spark.sparkContext.broadcast(Scorer(words, begins, dict(FACTORS)))

    def match(batches):
        for batch in batches:
            got = [fitted.value.clauses(t) for t in batch.column(0).to_pylist()]
            yield pa.RecordBatch.from_arrays([pa.array([[p for p, _ in g] for g in got], pa.list_(pa.string())), pa.array([[w for _, w in g] for g in got], pa.list_(pa.float64())), batch.column(1)], ["patterns", "weights", "toxic"])

    tried = [(list(zip(r["patterns"], r["weights"], strict=True)), r["toxic"]) for r in rows.mapInArrow(light(match), "patterns array<string>, weights array<double>, toxic int").collect()]  # bounded by the sample
    # a pattern's factor: how the odds of texts with one clause, of that pattern, compare with those of plain insults; few texts change little
    tally: dict[str, list[int]] = defaultdict(lambda: [0, 0])
    for g, y in tried:
        if len(g) == 1:
            tally[g[0][0]][y] += 1
    odds = lambda p: math.log((tally[p][1] + 0.5) / (n_toxic + 1)) - math.log((tally[p][0] + 0.5) / (n_clean + 1))
    factors = dict(FACTORS)
    if odds("I") > 0.5:
        for p, f in FACTORS.items():
            n = sum(tally[p])
            factors[p] = (f * 4 + max(0.0, min(1.5, odds(p) / odds("I"))) * n) / (4 + n) if p != "I" else 1.0
    scorer = Scorer(words, begins, factors)
    weight = {y: sizes[y] / totals[y] for y in (0, 1)}
    scorer.slope, scorer.bias = fit_line([(scorer.sum(g), y, weight[y]) for g, y in tried])
    return scorer


def score(spark: SparkSession, docs: DataFrame, scorer: Scorer, held_out: Column) -> DataFrame:
    shared = spark.sparkContext.broadcast(scorer)

    def run(batches):
        s = shared.value
        for batch in (p for b in batches for p in portions(b, 2)):
            got = [s.score(t) for t in batch.column(2).to_pylist()]
            columns = [pa.array([g[0] for g in got], pa.float64()), pa.array([int(g[0] >= 0.5) for g in got], pa.int32()), pa.array([g[1] for g in got], pa.int32())]
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), *columns], ["doc_id", "held_out", "score", "predicted", "clauses"])

    return docs.select(F.col("doc_id").cast("bigint").alias("doc_id"), held_out.alias("held_out"), "text").mapInArrow(light(run), SCHEMA)


def classify(spark: SparkSession, docs: DataFrame, labels: DataFrame, modulus: int = 5, held: int = 0) -> DataFrame:
    """One row per document, learned from the labels of documents whose id's remainder is not `held`."""
    out = id_remainder("doc_id", modulus) == held
    return score(spark, docs, train(spark, *labelled(docs, labels.where(~out))), out)


def accept(spark: SparkSession, docs: DataFrame, labels: DataFrame, modulus: int = 5, held: int = 0, limit: float = 0.5) -> DataFrame:
    """The rows of docs, all columns, that score below the limit."""
    scorer = train(spark, *labelled(docs, labels.where(id_remainder("doc_id", modulus) != held)))
    shared, at = spark.sparkContext.broadcast(scorer), docs.columns.index("text")

    def run(batches):
        for batch in (p for b in batches for p in portions(b, at)):
            yield batch.filter(pa.array([shared.value.score(t)[0] < limit for t in batch.column(at).to_pylist()], pa.bool_()))

    return docs.mapInArrow(light(run), docs.schema)
