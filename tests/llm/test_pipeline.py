import random

import corpus_pipeline
from peakcover.llm import common, decontaminate, minhash, queries, toxicity
from pyspark.sql import functions as F

from .test_operators import brute_components, ids_of, word_sets


def test_pipeline_stages(spark):
    base = "/root/testdata/sf0.001"
    docs = spark.read.parquet(f"{base}/documents.parquet")
    columns, counts = docs.columns, [docs.count()]
    for name, stage in corpus_pipeline.STAGES[:-1]:
        docs = stage(spark, docs, base)
        assert docs.columns == columns, name
        counts.append(docs.count())
    assert counts == sorted(counts, reverse=True) and counts[-1] > 0.5 * counts[0]
    pieces = corpus_pipeline.run(spark, base)
    assert pieces.select("doc_id").distinct().count() == counts[-1]


def small_tables(spark, path):
    """A corpus with a case for every stage, odd rows, and columns whose names the operators add."""
    rng = random.Random(3)
    word = lambda: "".join(rng.choices("abcdefghijklmnop", k=rng.randrange(3, 9)))
    line = lambda: " ".join(word() for _ in range(10))
    text = lambda n: "\n".join(line() for _ in range(n))
    rows, labels = [], []
    for i in range(240):
        body = text(6).split(" ")
        if i % 4 == 0:
            for _ in range(6):
                body[rng.randrange(len(body))] = rng.choice(["vileword", "nastyword", "awfulword"])
        rows.append((i, " ".join(body)))
        labels.append((i, 1, int(i % 4 == 0)))
    item, passage = " ".join(word() for _ in range(20)), text(6)
    base = " ".join(word() for _ in range(200)).split(" ")
    near = base[:100] + ["changed"] + base[101:]
    crumbs = rows[5][1].rsplit(" ", 1)[0] + " other"
    rows += [(300, text(4) + "\n" + passage), (301, passage + "\n" + text(4)), (302, " ".join(base)), (303, " ".join(near)), (304, "so " + item + " it ends"), (305, None), (306, ""), (None, "no id here"), (307, rows[7][1]), (308, crumbs)]
    docs = spark.createDataFrame([(i, t, "en", "s", len(t or ""), "a", 1, "b", 2.0) for i, t in rows], "doc_id long, text string, lang string, source string, n_chars long, predicted string, n_removed int, bands string, score double")
    docs.write.mode("overwrite").parquet(f"{path}/documents.parquet")
    spark.createDataFrame(labels, "doc_id long, quality long, toxic long").write.mode("overwrite").parquet(f"{path}/labels.parquet")
    spark.createDataFrame([(1, item)], "item_id long, text string").write.mode("overwrite").parquet(f"{path}/benchmark.parquet")
    return dict(rows), passage


def test_pipeline_equals_brute_force(spark, tmp_path):
    path = str(tmp_path)
    rows, passage = small_tables(spark, path)
    seen = {}
    docs = spark.read.parquet(f"{path}/documents.parquet")
    for name, stage in corpus_pipeline.STAGES:
        seen[name] = docs
        docs = common.staged(stage(spark, docs, path), f"test-{name}")
        if name != "packing":
            assert docs.columns == seen[name].columns
    kept = lambda df: {r["doc_id"]: r["text"] for r in df.collect()}
    before, after_toxic, after_lines, after_near, after_clean = kept(seen["toxicity"]), kept(seen["line_dedup"]), kept(seen["minhash"]), kept(seen["decontaminate"]), kept(seen["packing"])
    model = toxicity.fit(seen["toxicity"].select("doc_id", "text"), spark.read.parquet(f"{path}/labels.parquet"))
    scores = dict(zip(before, toxicity.score_texts(list(before.values()), model, {})))
    assert after_toxic == {i: t for i, t in before.items() if scores[i] < 0.5}
    bad = {i for i in range(240) if i % 4 == 0}
    assert len(bad - set(after_toxic)) >= 0.95 * len(bad) and set(before) - bad <= set(after_toxic)
    # lines: the second occurrence of the passage and the crumbs of a copy go, nothing else
    want = dict(after_toxic) | {301: "\n".join(rows[301].split("\n")[6:])}
    del want[307], want[308]
    assert after_lines == want
    sets = word_sets({i: t for i, t in after_lines.items() if i is not None})
    comps = brute_components(sets, 80)
    assert after_near == {i: t for i, t in after_lines.items() if i is None or comps[i] == i} and 303 not in after_near and 302 in after_near
    windows = [w for r in spark.read.parquet(f"{path}/benchmark.parquet").collect() for w in decontaminate.windows_of(decontaminate.words_of(r["text"]), 13)]

    def dirty(t):
        w, hit = decontaminate.words_of(t), set()
        for q in windows:
            for k in range(len(w) - len(q) + 1):
                if tuple(w[k : k + len(q)]) == q:
                    hit |= set(range(k, k + len(q)))
        return bool(hit) and 20 * len(hit) >= len(w)

    assert after_clean == {i: t for i, t in after_near.items() if not dirty(t)} and 304 not in after_clean
    pieces = docs.groupBy("doc_id").agg(F.sum("length").alias("n"), F.max("doc_tokens").alias("m")).collect()
    assert {r["doc_id"]: (r["n"], r["m"]) for r in pieces} == {i: (len(ids_of(t)) + 1,) * 2 for i, t in after_clean.items()}


def test_pipeline_without_rows(spark, tmp_path):
    path, whole = str(tmp_path / "none"), str(tmp_path / "some")
    small_tables(spark, whole)
    for t in ("documents", "labels", "benchmark"):
        spark.read.parquet(f"{whole}/{t}.parquet").limit(0).write.parquet(f"{path}/{t}.parquet")
    assert corpus_pipeline.run(spark, path).count() == 0


def test_pipeline_drops_near_copies_of_four_fifths(spark):
    words = [f"w{i}" for i in range(200)]
    near = ["other" + w if i in (30, 70, 110, 150) else w for i, w in enumerate(words)]  # 176 of 216 shingles
    docs = spark.createDataFrame([(1, " ".join(words)), (2, " ".join(near))], "doc_id long, text string")
    assert [r["doc_id"] for r in dict(corpus_pipeline.STAGES)["minhash"](spark, docs, "").collect()] == [1]
    assert minhash.drop_near_duplicates(docs).count() == 2


def test_every_operator_has_a_query():
    assert [sorted(int(q[2:].split("_")[0]) for q in queries.QUERIES)] == [list(range(1, 11))]
