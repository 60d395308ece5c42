"""Toxicity scores from subword bags: character n-gram embeddings averaged to a document, then a linear softmax.

A word's vector is the weighted mean of the embeddings of its hashed character n-grams and of the word itself:
an n-gram weighs the square of its smoothed log odds between the classes, so what says nothing of them, or is
rare, hardly counts.  A document's vector is the weighted mean over its distinct words and 30 neutral ones; very
frequent words weigh less.  Embeddings and softmax are trained together in numpy, so a misspelling that was never
seen shares most n-gram vectors with the words it comes from.

Training uses at most ``max_train`` labelled documents and ``max_bytes`` of text (the documented bounds of the
sample; ids are chosen by a hash from the label table alone, up to a third of them toxic, with class weights that
restore the true share; in the same order the texts are taken whole as long as they fit; one row for an id).
Every word of a training text trains.  Scoring reads every whole text.

Defined cases: null and wordless texts score the bias alone; documents without labels are scored like others;
of several label rows for one id the highest counts; without labels of both classes every score is the share
of toxic labels (0 without any); held-out rows are those whose crc32(doc_id as text) mod 5 is 0, a null id
being the empty text.
"""

from __future__ import annotations

import re
import zlib
from collections import Counter

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from . import common

MAX_TRAIN, MAX_BYTES = 4000, 64 << 20
BUCKETS = 1 << 18
DIM = 8
EPOCHS, BATCH = 6, 64
RATE = 0.3
GAIN = 20.0
SMOOTHING = 30.0
COMMON = 1e-3
NEUTRAL = 30.0
GRAMS = (3, 4, 5)
CACHE, CACHED_CHARS = 60_000, 64
BATCH_WORDS, BATCH_CHARS = 20_000, 1 << 20


def words_of(text: str | None) -> list[str]:
    return re.findall(r"\w+", text.lower()) if text else []


def gram_table(words: list[str], buckets: int = BUCKETS):
    """(word number, bucket) of every hashed n-gram of ``<word>`` in UTF-8, and of every whole word."""
    import numpy as np

    raw = [f"<{w}>".encode("utf-8", "surrogatepass") for w in words]
    sizes = np.fromiter(map(len, raw), dtype=np.int64, count=len(raw))
    owner, ends = np.repeat(np.arange(len(raw)), sizes), np.repeat(np.cumsum(sizes), sizes)
    letters = np.frombuffer(b"".join(raw), dtype=np.uint8).astype(np.uint64)
    owners, grams = [np.arange(len(raw))], [np.fromiter((zlib.crc32(w) % buckets for w in raw), dtype=np.int64, count=len(raw))]
    with np.errstate(over="ignore"):
        for n in GRAMS:
            m = len(letters) - n + 1
            if m <= 0:
                continue
            h = np.full(m, n, dtype=np.uint64)
            for j in range(n):
                h = (h ^ letters[j : j + m]) * np.uint64(0x9E3779B97F4A7C15)
                h ^= h >> np.uint64(29)
            whole = np.arange(n, m + n) <= ends[:m]
            owners.append(owner[:m][whole])
            grams.append((h[whole] % np.uint64(buckets)).astype(np.int64))
    return np.concatenate(owners), np.concatenate(grams)


def ranges(first, count):
    """The integers first[i] .. first[i] + count[i] - 1 for all i, one after the other."""
    import numpy as np

    return np.repeat(first - (np.cumsum(count) - count), count) + np.arange(count.sum())


def gram_weights(docs, starts, counts, gram, labels, weights, buckets: int, smoothing: float = SMOOTHING):
    """For each bucket the square of its smoothed log odds: in how many documents of either class it occurs."""
    import numpy as np

    seen = np.zeros((2, buckets))
    for words, y, w in zip(docs, labels, weights):
        if len(words):
            seen[y, np.unique(gram[ranges(starts[words], counts[words])])] += w
    share = float((labels * weights).sum() / weights.sum())
    odds = np.log((seen[1] + smoothing * share) / (seen[0] + smoothing * (1 - share))) - np.log(share / (1 - share))
    return (odds * odds).astype(np.float32)


def train(bags: list[tuple[str, list[int]]], labels, weights, seed: int = 7, dim: int = DIM, epochs: int | None = None, buckets: int = BUCKETS) -> dict:
    """The trained model (from each document's distinct words, joined by spaces, and their counts), folded to one number for each n-gram bucket (its pull towards toxic) and a bias."""
    import numpy as np

    y, class_weight = np.asarray(labels, dtype=np.int64), np.asarray(weights, dtype=np.float64)
    if len(set(y.tolist())) < 2:
        share = float((y * class_weight).sum() / class_weight.sum()) if len(y) else 0.0
        return {"pull": np.zeros(buckets, dtype=np.float32), "bias": 0.0, "constant": share, "common": {}}
    said = Counter()
    for joined, counts in bags:
        said.update(dict(zip(joined.split(), counts)))
    mass = max(1, said.total())
    common_words = {t: COMMON / (COMMON + c / mass) for t, c in said.items() if c >= 1e-5 * mass}
    vocabulary = {t: i for i, t in enumerate(said)}
    del said
    docs, parts = [], []
    for joined, _ in bags:
        found = joined.split()
        part = np.array([common_words.get(t, 1.0) for t in found])
        docs.append(np.array([vocabulary[t] for t in found], dtype=np.int32))
        parts.append((part / (part.sum() + NEUTRAL)).astype(np.float32))
    grams, counts = [], []
    for part in batches(list(vocabulary)):  # a part at a time, as the driver's memory is bounded
        of, gram = gram_table(part, buckets)
        grams.append(gram[np.argsort(of, kind="stable")].astype(np.int32))
        counts.append(np.bincount(of, minlength=len(part)).astype(np.int32))
    gram, counts = np.concatenate(grams), np.concatenate(counts)
    starts = np.cumsum(counts, dtype=np.int64) - counts
    del of, vocabulary, grams
    scale = gram_weights(docs, starts, counts, gram, y, class_weight, buckets)
    rng = np.random.default_rng(seed)
    table, way, bias = rng.uniform(-0.01, 0.01, (buckets, dim)).astype(np.float32), rng.normal(0, 0.5, (dim, 2)).astype(np.float32), np.zeros(2, dtype=np.float32)
    past = [np.full_like(a, 1e-6) for a in (table, way, bias)]
    # what does not change from epoch to epoch: each batch's words; their n-grams are looked up anew, as the driver's memory is bounded
    order = [d for d in rng.permutation(len(docs)).tolist() if len(docs[d])]
    plans = []
    for at in range(0, len(order), BATCH):
        some = np.array(order[at : at + BATCH])
        sizes = np.array([len(docs[d]) for d in some])
        words, place = np.unique(np.concatenate([docs[d] for d in some]), return_inverse=True)
        plans.append((some, np.cumsum(sizes) - sizes, np.repeat(np.arange(len(some)), sizes), place.astype(np.int32), np.concatenate([parts[d] for d in some])[:, None], words))
    del docs, parts
    slot = np.zeros(buckets, dtype=np.int32)

    def grams_of(words):
        """(n-grams, each word's n-grams as places among them, where a word's begin, the word of each, share of each)."""
        count = counts[words]
        found = gram[ranges(starts[words], count)]
        seen = np.zeros(buckets, dtype=bool)
        seen[found] = True
        grams = np.flatnonzero(seen)
        slot[grams] = np.arange(len(grams), dtype=np.int32)
        return grams, slot[found], np.cumsum(count) - count, np.repeat(np.arange(len(words), dtype=np.int32), count), (1 / count).astype(np.float32)[:, None]

    class_weight = class_weight / class_weight.mean()
    by = lambda rows, keys, n: np.stack([np.bincount(keys, weights=rows[:, k], minlength=n) for k in range(dim)], axis=1).astype(np.float32)
    for _ in range(epochs or EPOCHS):
        for some, doc_at, doc, place, part, words in (plans[i] for i in rng.permutation(len(plans))):
            grams, local, word_at, word, share = grams_of(words)
            weight = scale[grams][:, None]
            vectors = np.add.reduceat((table[grams] * weight)[local], word_at, axis=0) * share
            mean = np.add.reduceat(vectors[place] * part, doc_at, axis=0) * GAIN
            logits = mean @ way + bias
            pull = np.exp(logits - logits.max(axis=1, keepdims=True))
            pull /= pull.sum(axis=1, keepdims=True)
            pull[np.arange(len(some)), y[some]] -= 1
            pull = (pull * (class_weight[some] / len(some))[:, None]).astype(np.float32)
            to_words = by((pull @ way.T * GAIN)[doc] * part, place, len(share)) * share
            steps = (by(to_words[word], local, len(grams)) * weight, mean.T @ pull, pull.sum(axis=0))
            past[0][grams] += steps[0] * steps[0]
            table[grams] -= RATE * steps[0] / np.sqrt(past[0][grams])
            for i, a, rate in ((1, way, RATE * 0.3), (2, bias, RATE)):
                past[i] += steps[i] * steps[i]
                a -= rate * steps[i] / np.sqrt(past[i])
    turn = way[:, 1] - way[:, 0]
    return {"pull": (table @ turn * GAIN * scale).astype(np.float32), "bias": float(bias[1] - bias[0]), "constant": None, "common": common_words}


def batches(words: list[str]):
    """The words in lists that are hashed at once, of bounded number and length; a longer word comes alone."""
    part, chars = [], 0
    for w in words:
        if part and (len(part) >= BATCH_WORDS or chars + len(w) > BATCH_CHARS):
            yield part
            part, chars = [], 0
        part.append(w)
        chars += len(w)
    if part:
        yield part


def score_texts(texts: list[str | None], model: dict, cache: dict[str, tuple[float, float]]) -> list[float]:
    """Scores of a batch; words that the cache lacks are hashed together."""
    import math

    import numpy as np

    if model["constant"] is not None:
        return [model["constant"]] * len(texts)
    pull, often = model["pull"], model["common"]
    found = [set(words_of(t)) for t in texts]
    if len(cache) > CACHE:
        cache.clear()
    fresh, long_words = list(set().union(*found) - cache.keys()), {}
    for part in batches(fresh):
        of, gram = gram_table(part, len(pull))
        means = np.bincount(of, weights=pull[gram], minlength=len(part)) / np.bincount(of, minlength=len(part))
        for t, m in zip(part, means.tolist()):
            weight = often.get(t, 1.0)
            (cache if len(t) <= CACHED_CHARS else long_words)[t] = (weight, weight * m)
    out = []
    for words in found:
        pairs = [cache.get(t) or long_words[t] for t in words]
        # exact sums: the order of a set does not matter
        z = model["bias"] + math.fsum(p[1] for p in pairs) / (math.fsum(p[0] for p in pairs) + NEUTRAL)
        out.append(1 / (1 + math.exp(-max(-60.0, min(60.0, z)))))
    return out


def held_out(doc_id) -> F.Column:
    return F.crc32(F.coalesce(doc_id.cast("string"), F.lit(""))) % 5 == 0


def fit(docs: DataFrame, labels: DataFrame, id_col: str = "doc_id", text: str = "text", label: str = "toxic", max_train: int = MAX_TRAIN, max_bytes: int = MAX_BYTES) -> dict:
    """Train on at most ``max_train`` labelled rows, and ``max_bytes`` of their texts, that are not held out."""
    known = labels.where(F.col(label).isNotNull() & F.col(id_col).isNotNull() & ~held_out(F.col(id_col))).groupBy(F.col(id_col).alias("id")).agg(F.max(F.col(label).cast("int")).alias("y"))
    sizes = {r["y"]: r["n"] for r in known.groupBy("y").agg(F.count("*").alias("n")).collect()}
    quota = {1: min(sizes.get(1, 0), max_train // 3)}
    quota[0] = min(sizes.get(0, 0), max_train - quota[1])
    spread = F.xxhash64("id"), F.col("id")
    chosen = [r for y in (0, 1) if quota[y] for r in known.where(F.col("y") == y).orderBy(*spread).limit(quota[y]).collect()]
    if not chosen:
        return train([], [], [])
    spark = docs.sparkSession
    sample = F.broadcast(spark.createDataFrame([(r["id"], r["y"]) for r in chosen], "id long, y int"))  # max_train rows at most
    # one row for an id, so repeated ids add nothing
    picked = docs.select(F.col(id_col).alias("id"), F.coalesce(F.col(text).cast("string"), F.lit("")).alias("body")).join(sample, "id").groupBy("id", "y").agg(F.min("body").alias("body"))
    picked = common.staged(picked, "toxicity-sample")
    total, fits = 0, []
    for r in picked.select("id", F.octet_length("body").alias("b")).orderBy(*spread).collect():
        if total + r["b"] <= max_bytes:
            total += r["b"]
            fits.append((r["id"],))
    held = F.broadcast(spark.createDataFrame(fits, "id long"))

    def bags(frames):
        import pandas as pd

        for f in frames:
            counts = [Counter(words_of(t)) for t in f["body"]]
            yield pd.DataFrame({"id": f["id"], "y": f["y"], "words": [" ".join(c) for c in counts], "counts": [list(c.values()) for c in counts]})

    rows = sorted(picked.join(held, "id").mapInPandas(bags, "id long, y int, words string, counts array<int>").collect(), key=lambda r: r["id"])
    weight = {y: sizes[y] / quota[y] for y in (0, 1) if quota[y]}
    model = train([(r["words"], r["counts"]) for r in rows], [r["y"] for r in rows], [weight[r["y"]] for r in rows])
    del rows
    common.give_back()
    return model


def score(docs: DataFrame, model: dict, text: str = "text") -> DataFrame:
    """Every row of ``docs`` with score (0 to 1) and predicted (0 or 1)."""
    shared = docs.sparkSession.sparkContext.broadcast(model)  # BUCKETS floats, whatever the data

    def compute():
        cache: dict[str, tuple[float, float]] = {}
        found = shared.value

        def work(texts):
            scores = score_texts(texts, found, cache)
            return scores, [int(s >= 0.5) for s in scores]

        return work

    return common.extend_rows(docs, [("score", T.DoubleType()), ("predicted", T.IntegerType())], compute, [text])


def drop_toxic(docs: DataFrame, labels: DataFrame, training: DataFrame | None = None, **options) -> DataFrame:
    """The rows of ``docs`` that are not predicted toxic, with their own columns."""
    model = fit(training if training is not None else docs, labels, **options)
    return score(docs, model).where("predicted = 0").select(*docs.columns)


def op9_toxicity(spark, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text")
    model = fit(docs, spark.read.parquet(f"{sf_dir}/labels.parquet"))
    return score(docs, model).select("doc_id", held_out(F.col("doc_id")).alias("held_out"), "score", "predicted")
