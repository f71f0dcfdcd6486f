"""Language identification by interpolated Kneser-Ney character models.

One model per language over lower-cased letters (anything else is one blank). The highest order
uses counts, the lower ones how many different characters stand before; every order is interpolated
with the next. The runs of all languages share one sorted hash array per order, whose rows hold the
log probability in each language and, for contexts, the log weight passed down. A text's language
is the one of the lowest cross-entropy per character. Calibration on training texts that were not
counted gives each language a limit above which a text is rejected as in none of the languages: the
mean of their cross-entropies and `slack` standard deviations, and for a text of n characters `sway`
standard deviations of one character's cost over the root of n, as short texts vary more.

Defined results: null texts and texts without a letter are `und` with score 0 and rejected; rows
without a language are not learned from; with no labelled row at all every text is `und`; repeated
rows give a row each; an empty table gives an empty result; extra columns are ignored.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from unionlake.llm.common import id_remainder, light, portions
from unionlake.llm.hash_arrays import HashArray

SCHEMA = "doc_id bigint, held_out boolean, lang_pred string, score double, cross_entropy double, rejected boolean"
PIECE = 1 << 18


class Alphabet:
    """Code points to small numbers: 0 for anything but letters, then the letters seen in training, then one for all others."""

    def __init__(self, letters: list[str]):
        self.letters = letters
        self.size = len(letters) + 2
        self.of = np.zeros(0x110000, np.uint8 if self.size < 256 else np.uint32)
        self.of[_letters()] = self.size - 1
        for i, c in enumerate(letters, 1):
            self.of[ord(c)] = i

    def codes(self, texts: list[str | None], order: int) -> tuple[np.ndarray, np.ndarray]:
        """The codes of all texts, runs of blanks as one, and where each text begins; blanks stand between texts."""
        gap = " " * order
        joined = np.frombuffer("".join(gap + (t or "") for t in texts).lower().encode("utf-32-le", "replace"), np.uint32)
        # lower() may lengthen a text, so places come from the lowered parts
        sizes = np.array([len((gap + (t or "")).lower()) for t in texts], np.int64)
        if sizes.sum() != len(joined):  # a final sigma depends on its neighbours; lengths then still agree part by part
            joined = np.concatenate([np.frombuffer((gap + (t or "")).lower().encode("utf-32-le", "replace"), np.uint32) for t in texts])
        code = self.of[joined]
        begins = np.cumsum(sizes) - sizes
        keep = code != 0
        keep[1:] |= code[:-1] != 0
        for i in range(order):
            keep[begins + i] = True
        at = np.cumsum(keep) - keep
        return code[keep], at[begins]


_LETTERS = None


def _letters() -> np.ndarray:
    global _LETTERS
    if _LETTERS is None:
        _LETTERS = np.array([i for i in range(0x110000) if chr(i).isalpha()], np.int64)
    return _LETTERS


def runs(codes: np.ndarray, begins: np.ndarray, order: int, base: int) -> tuple[np.ndarray, np.ndarray]:
    """Each place's last `order` codes as a number, and the places (the blanks before a text are context only)."""
    key = np.zeros(len(codes) - order + 1, np.uint64)
    for i in range(order):
        key *= np.uint64(base)
        key += codes[i : i + len(key)]
    real = np.ones(len(codes), bool)
    for i in range(order - 1):
        real[begins + i] = False
    places = np.flatnonzero(real)
    return key[places - order + 1], places


class Models:
    """counts: for each language the runs of `order` codes and how often each occurs."""

    def __init__(self, languages: list[str], letters: list[str], counts: list[tuple[np.ndarray, np.ndarray]], order: int, discount: float = 0.75):
        self.languages, self.order = languages, order
        self.alphabet = Alphabet(letters)
        base = np.uint64(self.alphabet.size)
        self.base = int(base)
        n_lang = len(languages)
        # order by order: keys of all languages together, each language's count (continuation count below the top)
        stacks = []
        current = counts
        for k in range(order, 0, -1):
            keys = np.unique(np.concatenate([c[0] for c in current])) if n_lang else np.zeros(0, np.uint64)
            table = np.zeros((len(keys), n_lang))
            for lang, (kk, nn) in enumerate(current):
                table[np.searchsorted(keys, kk), lang] = nn
            stacks.append((keys, table))
            current = [np.unique(c[0] % base ** np.uint64(k - 1), return_counts=True) for c in current]
        self.tables: list[tuple[HashArray, np.ndarray]] = [None] * (order + 1)  # of probabilities by order
        self.passed: list[tuple[HashArray, np.ndarray]] = [None] * (order + 1)  # of weights passed down from a context
        lower_keys, lower = np.zeros(1, np.uint64), np.full((1, n_lang), 1.0 / self.base)
        for k in range(1, order + 1):
            keys, n = stacks[order - k]
            context = keys // base
            own, back = np.unique(context, return_inverse=True)
            total = np.zeros((len(own), n_lang))
            np.add.at(total, back, n)
            kinds = np.zeros((len(own), n_lang))
            np.add.at(kinds, back, n > 0)
            weight = np.where(total > 0, discount * kinds / np.maximum(total, 1), 1.0)
            short = np.zeros(len(keys), np.int64) if k == 1 else np.searchsorted(lower_keys, keys % base ** np.uint64(k - 1))
            p = np.maximum(n - discount, 0) / np.maximum(total[back], 1) + weight[back] * lower[short]
            lower_keys, lower = keys, p
            t, c = HashArray(keys), HashArray(own)
            self.tables[k] = (t, np.log(p[t.order]).astype(np.float32))
            self.passed[k] = (c, np.log(weight[c.order]).astype(np.float32))
        self.limits, self.sways = np.full(n_lang, np.inf), np.zeros(n_lang)

    def cross_entropies(self, texts: list[str | None]) -> tuple[np.ndarray, np.ndarray]:
        """Nats per character of each text in each language, and how many characters were scored."""
        logs, starts, ends = self.costs(texts)
        sums = np.concatenate((np.zeros((1, logs.shape[1])), np.cumsum(logs, axis=0, dtype=np.float64)))
        n = ends - starts
        return (sums[ends] - sums[starts]) / np.maximum(n, 1)[:, None], n

    def costs(self, texts: list[str | None]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Nats of each character of all texts in each language, and where each text's begin and end."""
        order, base = self.order, np.uint64(self.base)
        codes, begins = self.alphabet.codes(texts, order - 1)
        key, places = runs(codes, begins, order, self.base)
        n_lang = len(self.languages)
        logs = np.zeros((len(key), n_lang), np.float32)
        todo = np.arange(len(key))
        for k in range(order, 0, -1):
            g = key[todo] % base ** np.uint64(k) if k < order else key
            t, values = self.tables[k]
            row = t.rows(g)
            hit = row >= 0
            if hit.all():
                logs[todo] += values[row]
                todo = todo[:0]
                break
            logs[todo[hit]] += values[row[hit]]
            todo, g = todo[~hit], g[~hit]
            c, weights = self.passed[k]
            at = c.rows(g // base)
            known = at >= 0
            logs[todo[known]] += weights[at[known]]
        logs[todo] -= np.float32(np.log(self.base))
        ends = np.append(np.searchsorted(places, begins[1:]), len(places))
        return -logs, np.searchsorted(places, begins), ends

    def predict(self, texts: list[str | None], sharpness: float = 12.0) -> list[tuple[str, float, float | None, bool]]:
        """(language, score, cross-entropy, rejected) of each text."""
        if not texts:
            return []
        lettered = [t is not None and any(map(str.isalpha, t)) for t in texts]
        if not self.languages:
            return [("und", 0.0, None, True)] * len(texts)
        h, n = self.cross_entropies(texts)
        best = h.argmin(1)
        odds = np.exp(-sharpness * (h - h.min(1, keepdims=True)))
        score = odds.max(1) / odds.sum(1)
        low = h[np.arange(len(h)), best]
        rejected = low > self.limits[best] + self.sways[best] / np.sqrt(np.maximum(n, 1))
        return [(self.languages[b], float(s), float(x), bool(r)) if ok else ("und", 0.0, None, True) for b, s, x, r, ok in zip(best, score, low, rejected, lettered, strict=True)]


def sample(docs: DataFrame, label: str, most: int, salt: int) -> DataFrame:
    """At most about `most` rows of each value of `label`, chosen by a hash of the text: a bounded sample to fit on.

    A value with fewer rows is used whole; of others the share most / rows is kept.
    """
    sizes = docs.groupBy(label).agg(F.count("*").alias("_n"))
    chosen = docs.join(F.broadcast(sizes), label)  # a row per label value
    share = F.pmod(F.xxhash64(F.lit(salt), "text"), F.lit(1_000_003)) / 1_000_003.0
    return chosen.where(share < F.lit(float(most)) / F.col("_n")).drop("_n")


def train(spark: SparkSession, docs: DataFrame, order: int = 4, most_per_language: int = 1500, most_languages: int = 500, slack: float = 12.0, sway: float = 5.0) -> Models:
    """Fits on at most about most_per_language texts of each language, whole; counting is distributed.

    Every tenth sampled text is not counted but used for the limits, if it has 50 characters; a language
    without such a text takes the widest limit of the others.
    """
    labelled = docs.where("lang is not null and text is not null").select("lang", "text")
    picked = sample(labelled, "lang", most_per_language, 3).cache()
    try:
        tenth = F.pmod(F.xxhash64(F.lit(5), "text"), F.lit(10)) == 0
        languages = sorted(r["lang"] for r in picked.select("lang").distinct().limit(most_languages + 1).collect())
        if len(languages) > most_languages:
            raise ValueError(f"more than {most_languages} languages")
        letters = picked.select(F.explode(F.array_distinct(F.split(F.lower("text"), ""))).alias("c")).where(r"c rlike '^\\p{L}$'")
        letters = letters.groupBy("c").count().orderBy(F.desc("count"), "c").limit(60_000).collect()
        letters = sorted(r["c"] for r in letters if len(r["c"]) == 1)

        def count(batches):
            alphabet = Alphabet(letters)
            for batch in batches:
                by: dict[str, list[str]] = {}
                for lang, text in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
                    by.setdefault(lang, []).append(text)
                for lang, texts in by.items():
                    codes, begins = alphabet.codes(texts, order - 1)
                    keys, n = np.unique(runs(codes, begins, order, alphabet.size)[0], return_counts=True)
                    yield pa.RecordBatch.from_arrays([pa.array([lang] * len(keys)), pa.array(keys.view(np.int64)), pa.array(n.astype(np.int64))], ["lang", "key", "n"])

        counted = picked.where(~tenth).mapInArrow(count, "lang string, key bigint, n bigint").groupBy("lang", "key").agg(F.sum("n").alias("n")).toPandas()  # bounded by the sample
        groups = dict(iter(counted.groupby("lang")))
        empty = (np.zeros(0, np.uint64), np.zeros(0, np.int64))
        per = [(g["key"].to_numpy().view(np.uint64), g["n"].to_numpy()) if (g := groups.get(x)) is not None else empty for x in languages]
        per = [(k[o], n[o]) for k, n in per for o in [np.argsort(k)]]
        models = Models(languages, letters, per, order)
        if languages:
            shared = spark.sparkContext.broadcast(models)

            def measure(batches):
                m = shared.value
                for part in (p for batch in batches for p in portions(batch, 1, PIECE)):
                    logs, starts, ends = m.costs(part.column(1).to_pylist())
                    own = [m.languages.index(x) for x in part.column(0).to_pylist()]
                    x = [logs[a:b, i].astype(np.float64) for a, b, i in zip(starts, ends, own, strict=True)]
                    mean, variance = ([float(f(c)) if len(c) else 0.0 for c in x] for f in (np.mean, np.var))
                    yield pa.RecordBatch.from_arrays([part.column(0), pa.array(mean), pa.array(variance), pa.array(list(map(len, x)), pa.int64())], ["lang", "h", "v", "n"])

            seen = picked.where(tenth).mapInArrow(light(measure), "lang string, h double, v double, n bigint").where("n >= 50")
            for r in seen.groupBy("lang").agg(F.avg("h").alias("m"), F.stddev("h").alias("s"), F.avg("v").alias("v")).collect():
                at = languages.index(r["lang"])
                models.limits[at], models.sways[at] = r["m"] + slack * (r["s"] or 0.0), sway * np.sqrt(r["v"])
            measured = np.isfinite(models.limits)
            if measured.any():
                models.limits[~measured], models.sways[~measured] = models.limits[measured].max(), models.sways[measured].max()
        return models
    finally:
        picked.unpersist()


def predict(spark: SparkSession, docs: DataFrame, models: Models, held_out) -> DataFrame:
    shared = spark.sparkContext.broadcast(models)

    def run(batches):
        m = shared.value
        for batch in (p for b in batches for p in portions(b, 2, PIECE)):
            out = m.predict(batch.column(2).to_pylist())
            kinds = [pa.string(), pa.float64(), pa.float64(), pa.bool_()]
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), *(pa.array([o[i] for o in out], k) for i, k in enumerate(kinds))], [f.split()[0] for f in SCHEMA.split(", ")])

    return docs.select(F.col("doc_id").cast("bigint").alias("doc_id"), held_out.alias("held_out"), "text").mapInArrow(light(run), SCHEMA)


def identify(spark: SparkSession, docs: DataFrame, order: int = 4, most_per_language: int = 1500, modulus: int = 4, held: int = 2) -> DataFrame:
    """One row per document, learned from the documents whose id's remainder is not `held`."""
    out = id_remainder("doc_id", modulus) == held
    return predict(spark, docs, train(spark, docs.where(~out), order, most_per_language), out)


def accept(spark: SparkSession, docs: DataFrame, order: int = 4, most_per_language: int = 1500) -> DataFrame:
    """The rows of docs, all columns, whose language is recognised."""
    models = train(spark, docs, order, most_per_language)
    shared, at = spark.sparkContext.broadcast(models), docs.columns.index("text")

    def run(batches):
        for part in (p for batch in batches for p in portions(batch, at, PIECE)):
            yield part.filter(pa.array([not r[3] for r in shared.value.predict(part.column(at).to_pylist())], pa.bool_()))

    return docs.mapInArrow(light(run), docs.schema)
