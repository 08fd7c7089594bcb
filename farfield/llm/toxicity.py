"""Toxicity of restored text: a noisy channel is decoded before the text is scored.

1. A character model: trigrams within words, counted over all documents. Letters fall into 48 classes (a to z, others
   by code point, everything else a boundary), so the table has at most 48^3 counts however large the corpus is.
2. Restoring: places where letters touch symbols, where a letter is repeated, or where single characters are
   spaced out become lattices. A symbol can stand for a letter, for itself or for nothing, a repeated letter can go, a
   spacer can be a space or nothing. Viterbi decoding takes the likeliest path under channel costs plus the character
   model. All other text has a lattice of one path: itself.
3. Scoring: words of the restored text and their beginnings are features. The `MAX_FEATURES` that tell toxic rows best
   are weighted by a logistic regression. It is fitted on at most `MAX_FIT` labelled rows, those of least hash
   among the rows whose crc32 fold is not 0. Labels, languages, sources and ids are no features.

Defined results: null and empty texts get the score of a text without any feature; without labelled rows of both kinds
all scores are the smoothed share of toxic rows; a null doc_id counts as not held out and is not learned from; repeated rows
each get a row; an empty table gives an empty table; extra columns are not read, or carried along by the stage.
"""

from __future__ import annotations

import re
from collections import Counter
from collections.abc import Iterator
from functools import lru_cache
from zlib import crc32

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from farfield.llm.common import DOCUMENT_COLUMNS, let_workers_import, slices, table, written

#: At most so many labelled rows are learned from, and so many candidates and features looked at.
MAX_FIT, MAX_CANDIDATES, MAX_FEATURES = 20_000, 50_000, 3_000
#: Least cautious share of toxic rows among those with a feature; least number of toxic rows with it (or 1 % of them, if
#: that is more); least bias, so that a feature that is sure by itself is enough.
LEAST_SHARE, LEAST_ROWS, LEAST_BIAS = 0.35, 4, -4.0
FOLDS = 5
BANDS, _PER_BAND = 8, 5
CLASSES = 48
STEMS = (4, 5, 6)

#: What a symbol can stand for.
STANDS_FOR = {
    "0": "o", "1": "il", "2": "z", "3": "e", "4": "a", "5": "s", "6": "gb", "7": "t", "8": "b", "9": "g",
    "@": "a", "$": "s", "!": "i", "|": "il", "+": "t", "(": "c", "€": "e", "£": "l", "¡": "i", "§": "s",
}
SPACERS = " .-_*~·"
INVISIBLE = re.compile("[\u200b\u200c\u200d\u2060\ufeff\u00ad]+")
_REST_OF_WORD = re.compile(r"\S*")

#: Costs of the channel, in nats.
STAND_IN, ITSELF, ITSELF_BEFORE_LETTER, SYMBOL_GONE, SPACER_GONE, SPACER_STAYS, THIRD_GONE, SECOND_GONE = 1.2, 1.0, 4.5, 6.0, 0.3, 2.5, 0.1, 4.0
#: After so many characters of a lattice, what all paths still open have in common is written out. It can't change any more, so the path stays the best one.
STRETCH = 512

_LETTER, _SYMBOL, _SPACER = r"[^\W\d_]", "[" + re.escape("".join(STANDS_FOR)) + "]", "[" + re.escape(SPACERS) + "]"
_ONE = f"(?:{_LETTER}|{_SYMBOL})"
#: Spaced characters, which may stand in quotes and before punctuation; symbols between, before and behind letters; repeated letters. What begins with a letter is one branch,
#: as most places are letters, and each branch would look at them again.
_NOISE = re.compile(
    rf"(?<![^\W_]){_ONE}(?:{_SPACER}{{1,3}}{_ONE}){{2,}}(?![^\W_])"
    rf"|({_LETTER})(?:[{re.escape(''.join(STANDS_FOR) + SPACERS[1:])}]+{_LETTER}|(?P<double>\1)|[0-9@$€£§|])|(?<!\S){_SYMBOL}{_LETTER}{{2}}|[0-9@$€£¡§|+]{_LETTER}"
)
_FACTORS, _TERMS = (np.random.default_rng(k).integers(1, 1 << 61, BANDS * _PER_BAND, dtype=np.uint64) for k in (7, 8))
_FACTORS |= np.uint64(1)
_LETTERS = re.compile(_LETTER + "+")


@lru_cache(1)
def _class_of() -> np.ndarray:
    c = np.zeros(0x10000, np.uint8)
    for p in range(0x10000):
        if chr(p).isalpha():
            c[p] = p - 96 if 97 <= p <= 122 else 27 + p % (CLASSES - 27)
    return c


def char_class(ch: str) -> int:
    return int(_class_of()[min(ord(ch), 0xFFFF)])


def trigram_counts(texts: Iterator[str | None]) -> np.ndarray:
    """Counts of class trigrams within words; a word has two boundaries before it and one behind."""
    total, some, size = np.zeros(CLASSES**3, np.int64), [], 0

    def count() -> None:
        cls = _class_of()[np.minimum(np.frombuffer("\n".join(some).lower().encode("utf-32-le"), np.uint32), 0xFFFF)]
        cls = np.concatenate([[0], cls, [0]])
        cls = cls[np.concatenate([[True], (cls[1:] != 0) | (cls[:-1] != 0)])]
        cls = np.repeat(cls, 1 + (cls == 0)).astype(np.int64)
        total[:] += np.bincount((cls[:-2] * CLASSES + cls[1:-1]) * CLASSES + cls[2:], minlength=CLASSES**3)
        some.clear()

    for t in texts:
        for at in range(0, len(t or ""), 1 << 20):
            some.append(t[at : at + (1 << 20)])
            size += len(some[-1])
            if size >= 1 << 20:
                count()
                size = 0
    if some:
        count()
    return total


def log_model(counts: np.ndarray) -> np.ndarray:
    """log P(c | a, b), each order smoothed by the one below."""
    n3 = counts.reshape(CLASSES, CLASSES, CLASSES).astype(np.float64)
    n2, n1 = n3.sum(axis=0), n3.sum(axis=(0, 1))
    p1 = (n1 + 1) / (n1.sum() + CLASSES)
    p2 = (n2 + 4 * p1) / (n2.sum(axis=1, keepdims=True) + 4)
    return np.log((n3 + 4 * p2) / (n3.sum(axis=2, keepdims=True) + 4)).astype(np.float32)


class Restorer:
    """Decodes noisy places of lower-cased text."""

    def __init__(self, model: np.ndarray):
        self.model = model.tolist()
        self.known: dict[str, str] = {}

    def decode(self, noisy: str) -> str:
        """The text of the likeliest path through the whole lattice."""
        out, states = [], {(0, 0): (0.0, None)}
        for at in range(0, len(noisy), STRETCH):
            if at:
                out.append(self._settled([path for _, path in states.values()]))
            states = self._stretch(noisy, at, min(len(noisy), at + STRETCH), states)
        best = max(states, key=lambda ab: states[ab][0] + (self.model[ab[0]][ab[1]][0] if ab[1] else 0.0))
        text, path = [], states[best][1]
        while path:
            path, part = path
            text.append(part)
        return "".join(out) + "".join(reversed(text))

    @staticmethod
    def _settled(paths: list) -> str:
        """Cuts off and returns what the paths have in common. A path is [path before, text written]."""
        chain, node = [], paths[0]
        while node is not None:
            chain.append(node)
            node = node[0]
        place, back = {id(x): k for k, x in enumerate(chain)}, 0
        for node in paths:
            while node is not None and id(node) not in place:
                node = node[0]
            if node is None:
                return ""
            back = max(back, place[id(node)])
        text = "".join(x[1] for x in reversed(chain[back:]))
        chain[back][:] = None, ""
        return text

    def _stretch(self, s: str, lo: int, hi: int, states: dict) -> dict:
        model, n = self.model, len(s)
        for i in range(lo, hi):
            ch, nxt = s[i], {}
            here = char_class(ch)
            options: list[tuple[str, int, float]]  # what is written, its class or -1 for nothing, the cost
            if here:
                options = [(ch, here, 0.0)]
                if i and s[i - 1] == ch:
                    third = (i > 1 and s[i - 2] == ch) or (i + 1 < n and s[i + 1] == ch)
                    options.append(("", -1, THIRD_GONE if third else SECOND_GONE))
            else:
                options = [(x, char_class(x), STAND_IN) for x in STANDS_FOR.get(ch, "")]
                if ch in SPACERS or ch.isspace():
                    options += [(" ", 0, SPACER_STAYS), ("", -1, SPACER_GONE)]
                else:
                    k = i + 1
                    while k < n and k < i + 4 and s[k] in SPACERS:
                        k += 1
                    before_letter = k < n and (char_class(s[k]) or (s[k] != ch and s[k] in STANDS_FOR))
                    options += [(ch, 0, ITSELF_BEFORE_LETTER if before_letter else ITSELF), ("", -1, SYMBOL_GONE)]
                if i and s[i - 1] == ch and ch in STANDS_FOR:
                    options.append(("", -1, THIRD_GONE))
            for (a, b), (score, path) in states.items():
                row = model[a][b]
                for text, c, cost in options:
                    if c < 0:
                        to, got = (a, b), score - cost
                    elif c:
                        to, got = (b, c), score - cost + row[c]
                    else:
                        to, got = (0, 0), score - cost + (row[0] if b else 0.0)
                    if to not in nxt or got > nxt[to][0]:
                        nxt[to] = (got, [path, text] if text else path)
            states = nxt
        return states

    def restore(self, text: str) -> tuple[str, int]:
        """The restored text in lower case, and how many places were decoded."""
        s, out, done, places = text.lower(), [], 0, 0
        if not s.isascii():
            s = INVISIBLE.sub("", s)
        for m in _NOISE.finditer(s):
            a, b = m.span()
            if a < done:
                continue
            while a > done and not s[a - 1].isspace():
                a -= 1
            b = _REST_OF_WORD.match(s, b).end()
            noisy = s[a:b]
            if (clean := self.known.get(noisy)) is None:
                clean = self.decode(noisy)
                if len(noisy) <= 64:
                    if len(self.known) >= 100_000:
                        self.known.clear()
                    self.known[noisy] = clean
            out += [s[done:a], clean]
            # most doubled letters are meant
            done, places = b, places + (m["double"] is None or clean != noisy)
        return "".join([*out, s[done:]]), places


def words_of(restored: str) -> set[str]:
    return set(_LETTERS.findall(restored))


def features_of(words: set[str]) -> set[str]:
    """Whole words, marked by a space behind, and beginnings of longer words."""
    return {w + " " for w in words}.union(*({w[:k] for w in words if len(w) > k} for k in STEMS))


def held_out(doc_id: Column) -> Column:
    """The fold that is never learned from."""
    return F.coalesce(F.crc32(F.encode(doc_id.cast("string"), "utf-8")) % FOLDS == 0, F.lit(False))


def character_model(docs: DataFrame) -> np.ndarray:
    """From all texts; what reaches the driver is one row per trigram of classes."""
    let_workers_import(docs.sparkSession)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = sum((trigram_counts(t.as_py() for t in b.column(0)) for b in slices(batches, 2048)), np.zeros(CLASSES**3, np.int64))
        seen = np.flatnonzero(total)
        yield pa.RecordBatch.from_arrays([pa.array(seen.astype(np.int32)), pa.array(total[seen])], names=["gram", "n"])

    counts = np.zeros(CLASSES**3, np.int64)
    for gram, n in docs.select(F.col("text").cast("string")).mapInArrow(run, "gram int, n long").groupBy("gram").agg(F.sum("n")).collect():
        counts[gram] = n
    return log_model(counts)


def _learned_rows(docs: DataFrame, labels: DataFrame, max_fit: int) -> DataFrame:
    """(text, toxic) of the labelled rows to learn from: at most max_fit, so the ids are broadcast."""
    ids = (
        labels.filter(F.col("doc_id").isNotNull() & F.col("toxic").isin(0, 1) & ~held_out(F.col("doc_id")))
        .groupBy("doc_id").agg(F.max("toxic").alias("toxic"))
        .orderBy(F.xxhash64("doc_id"), "doc_id").limit(max_fit)
    )
    return docs.select("doc_id", F.col("text").cast("string").alias("text")).join(F.broadcast(ids), "doc_id").select("text", "toxic")


def bands_of(words: list[str]) -> list[int]:
    """MinHash bands of the long words; near copies share one of them, other texts hardly any."""
    long = [w for w in words if len(w) >= 6] or words
    if not long:
        return []
    h = np.array([crc32(w.encode()) for w in long], np.uint64)
    mixed = (h[:, None] * _FACTORS[None] + _TERMS[None]) & np.uint64((1 << 61) - 1)
    return [hash(tuple(r)) for r in (mixed >> np.uint64(20)).min(axis=0).reshape(BANDS, -1).tolist()]


def _one_of_each(learned: DataFrame) -> DataFrame:
    """The rows without near copies, so that words of a text that was copied often don't pass for signs of what it is. Runs on the
    rows to learn from only, whose number is bounded."""
    rows = sorted((r["h"], r["bands"]) for r in learned.select(F.xxhash64("words").alias("h"), "bands").collect())
    above: dict[int, int] = {}

    def top(x: int) -> int:
        while above.setdefault(x, x) != x:
            above[x] = x = above[above[x]]
        return x

    first: dict[tuple[int, int], int] = {}
    for h, bands in rows:
        for k, b in enumerate(bands):
            x, y = top(h), top(first.setdefault((k, b), h))
            above[max(x, y)] = min(x, y)
    keep = learned.sparkSession.createDataFrame([(h,) for h, _ in rows if top(h) == h], "h long")
    return written(learned.withColumn("h", F.xxhash64("words")).join(F.broadcast(keep), "h").select("words", "toxic"), "learned")


class ToxicityModel:
    def __init__(self, chars: np.ndarray, weights: dict[str, float], bias: float):
        self.chars, self.weights, self.bias = chars, weights, bias

    def scorer(self):
        restorer, weights = Restorer(self.chars), self.weights
        known, words = set(weights), {w[:-1] for w in weights if w[-1] == " "}
        stems = {k: {w for w in known if len(w) == k and w[-1] != " "} for k in STEMS}

        def score(text: str | None) -> tuple[float, int]:
            restored, places = restorer.restore(text or "")
            own = words_of(restored)
            hits = {w + " " for w in own & words}
            for k, of in stems.items():
                if of:
                    hits |= {w[:k] for w in own if len(w) > k} & of
            z = self.bias + sum(map(weights.__getitem__, sorted(hits)))
            return 1 / (1 + np.exp(-min(max(z, -30.0), 30.0))), places

        return score


def _cautious(k: int, n: int, z: float = 2.5) -> float:
    """Lower end of the Wilson interval of k of n."""
    p = k / n
    return (p + z * z / (2 * n) - z * np.sqrt(p * (1 - p) / n + z * z / (4 * n * n))) / (1 + z * z / n)


def _logistic(rows: list[np.ndarray], y: np.ndarray, times: np.ndarray, n: int, bias: float, l2: float = 3e-5, steps: int = 400) -> np.ndarray:
    """Adam on the mean log loss of sparse 0/1 rows, each with the number of times that it occurs, under a given bias."""
    times = times / max(times.sum(), 1)
    doc, col = np.repeat(np.arange(len(rows)), [len(r) for r in rows]), np.concatenate([np.zeros(0, int), *rows])
    w, m, v = np.zeros(n), np.zeros(n), np.zeros(n)
    for t in range(1, steps + 1):
        z = bias + np.bincount(doc, w[col], len(y))
        err = times * (1 / (1 + np.exp(-np.clip(z, -30, 30))) - y)
        g = np.bincount(col, err[doc], n) + l2 * w
        m, v = 0.9 * m + 0.1 * g, 0.99 * v + 0.01 * g * g
        w -= 0.1 * (m / (1 - 0.9**t)) / (np.sqrt(v / (1 - 0.99**t)) + 1e-8)
    return w


def fit(docs: DataFrame, labels: DataFrame, max_fit: int = MAX_FIT) -> ToxicityModel:
    spark = docs.sparkSession
    let_workers_import(spark)
    chars = character_model(docs)
    shared = spark.sparkContext.broadcast(chars)

    def restored(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        restorer = Restorer(shared.value)
        for b in slices(batches):
            own = [sorted(words_of(restorer.restore(t.as_py() or "")[0])) for t in b.column(0)]
            yield pa.RecordBatch.from_arrays(
                [pa.array([" ".join(w) for w in own], pa.string()), b.column(1), pa.array([bands_of(w) for w in own], pa.list_(pa.int64()))], names=["words", "toxic", "bands"]
            )

    learned = written(_learned_rows(docs, labels, max_fit).select("text", F.col("toxic").cast("int").alias("toxic")).mapInArrow(restored, "words string, toxic int, bands array<long>").groupBy("words").agg(F.max("toxic").alias("toxic"), F.min("bands").alias("bands")), "learned")
    learned = _one_of_each(learned)
    n = {r["toxic"]: r["n"] for r in learned.groupBy("toxic").agg(F.count(F.lit(1)).alias("n")).collect()}
    n0, n1 = n.get(0, 0), n.get(1, 0)
    if not n0 or not n1:
        return ToxicityModel(chars, {}, float(np.log((n1 + 1) / (n0 + 9))))

    def counted(rows: DataFrame, among: set[str] | None) -> DataFrame:
        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            c: Counter[str] = Counter()
            for b in batches:
                for t in b.column(0):
                    own = features_of(set((t.as_py() or "").split()))
                    c.update(own if among is None else own & among)
            yield pa.RecordBatch.from_arrays([pa.array(list(c), pa.string()), pa.array(list(c.values()), pa.int64())], names=["f", "n"])

        return rows.select("words").mapInArrow(run, "f string, n long").groupBy("f").agg(F.sum("n").alias("n"))

    often = max(LEAST_ROWS, n1 // 100)
    a = {r["f"]: r["n"] for r in counted(learned.filter("toxic = 1"), None).filter(F.col("n") >= often).orderBy(F.desc("n"), "f").limit(MAX_CANDIDATES).collect()}
    b = {r["f"]: r["n"] for r in counted(learned.filter("toxic = 0"), set(a)).collect()}
    # A feature counts if a cautious (Wilson) bound of the toxic share of its rows is high, and not only in this sample.
    share = {f: _cautious(a[f], a[f] + b.get(f, 0)) for f in a}
    picked = sorted((f for f in a if share[f] > LEAST_SHARE), key=lambda f: (-a[f] * share[f], f))[:MAX_FEATURES]
    at = {f: k for k, f in enumerate(picked)}

    def hits(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        """A row for each document, and one for each of its words that has features: a single word has to tell by itself, too."""
        for x in batches:
            own, toxic = [], []
            for t, y in zip(x.column(0), x.column(1)):
                by_word = [h for w in (t.as_py() or "").split() if (h := sorted(at[f] for f in features_of({w}) & at.keys()))]
                own += [sorted(set().union(*by_word)), *by_word]
                toxic += [y.as_py()] * (1 + len(by_word))
            yield pa.RecordBatch.from_arrays([pa.array(own, pa.list_(pa.int32())), pa.array(toxic, pa.int32())], names=["hits", "toxic"])

    got = learned.mapInArrow(hits, "hits array<int>, toxic int").groupBy("hits", "toxic").count().collect()
    got = sorted(((tuple(r["hits"]), r["toxic"], r["count"]) for r in got))
    # rows without features set the bias, the others the weights over it
    bare = {y: k for h, y, k in got if not h}
    bias = max(LEAST_BIAS, float(np.log((bare.get(1, 0) + 0.5) / (bare.get(0, 0) + 5))))
    told = [g for g in got if g[0]]
    weights = _logistic([np.array(h, int) for h, _, _ in told], *(np.array([g[k] for g in told], float) for k in (1, 2)), len(picked), bias)
    return ToxicityModel(chars, {f: float(w) for f, w in zip(picked, weights) if abs(w) > 1e-4}, bias)


def score(docs: DataFrame, model: ToxicityModel, keep: tuple[str, ...] = ("doc_id",)) -> DataFrame:
    """The kept columns, __score and __restored (the number of decoded places)."""
    let_workers_import(docs.sparkSession)
    shared = docs.sparkSession.sparkContext.broadcast(model)
    place = len(keep)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        score = shared.value.scorer()
        for b in slices(batches):
            got = [score(t.as_py()) for t in b.column(place)]
            new = [pa.array([float(s) for s, _ in got], pa.float64()), pa.array([p for _, p in got], pa.int64())]
            yield pa.RecordBatch.from_arrays([*b.columns[:place], *new], names=[*keep, "__score", "__restored"])

    columns = docs.select(*keep, F.col("text").cast("string").alias("__text"))
    fields = [*columns.schema.fields[:-1], T.StructField("__score", T.DoubleType()), T.StructField("__restored", T.LongType())]
    return columns.mapInArrow(run, T.StructType(fields))


def op1_toxicity(docs: DataFrame, labels: DataFrame) -> DataFrame:
    """doc_id, held_out, score, predicted, n_restored."""
    return score(docs, fit(docs, labels)).select(
        "doc_id",
        held_out(F.col("doc_id")).alias("held_out"),
        F.col("__score").alias("score"),
        (F.col("__score") >= 0.5).cast("int").alias("predicted"),
        F.col("__restored").alias("n_restored"),
    )


def stage(spark, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Pipeline: documents that score 0.5 or more go."""
    scored = score(docs, fit(docs, table(spark, sf_dir, "labels")), DOCUMENT_COLUMNS)
    return scored.filter(F.col("__score") < 0.5).select(*DOCUMENT_COLUMNS)
