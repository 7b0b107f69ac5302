import re

import numpy as np
from pyspark.sql import functions as F

import corpus_pipeline
from pathwindow.llm import lines, shingles, toxicity

SF = "/root/testdata/sf0.001"


def test_pipeline_runs_and_packs_all_that_is_left(spark):
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    left = corpus_pipeline.drop_contaminated(spark, docs, SF)
    assert left.columns == docs.columns and 0 < left.count() < docs.count()
    first = corpus_pipeline.drop_near_copies(spark, docs.union(docs.limit(0)), SF)
    assert first.columns == docs.columns and first.count() == first.select("doc_id").distinct().count() < docs.count()
    rows = corpus_pipeline.run(spark, SF)
    assert {"doc_id", "piece", "sequence_id"} <= set(rows.columns) and rows.count() > 0


def test_near_dedup_links_by_the_similarity_of_shingle_sets(spark):
    rng = np.random.default_rng(5)
    words = lambda n: [f"w{k}" for k in rng.integers(0, 10**6, n)]
    texts = []
    for n in (60, 150, 400):
        for changes in (0, 1, 2, 3, 4, 5, 6, 8):
            base = words(n)
            for _ in range(6):
                other = list(base)
                for at in rng.choice(n, changes, False):
                    other[at] = "x" + other[at]
                texts += [" ".join(base), " ".join(other)]
    passage = words(200)
    texts += [" ".join(passage), " ".join(passage * 2), None, "", " ", "short one", "Short ONE", "a b c d e"]
    sets = [shingles.set_of(t or "") for t in texts]
    root = list(range(len(texts)))
    for i in range(len(texts)):
        for j in range(i):
            both = len(np.intersect1d(sets[i], sets[j]))
            if root[i] != root[j] and both >= 0.8 * (len(sets[i]) + len(sets[j]) - both):
                a, b = sorted((root[i], root[j]))
                root = [a if r == b else r for r in root]
    docs = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    left = {r.doc_id for r in corpus_pipeline.drop_near_copies(spark, docs, SF).collect()}
    assert left == set(root)


def test_near_dedup_drops_copies_only_never_by_id(spark):
    text = lambda k: " ".join(f"w{k}x{i}" for i in range(30))
    rows = [(None, text(k), k) for k in range(20)] + [(None, text(3), 99), (7, text(50), 0), (7, text(51), 0), (7, text(50), 0), (8, text(50), 1), (9, text(4), 2), (6, text(60), 0), (6, text(60), 0)]
    left = corpus_pipeline.drop_near_copies(spark, spark.createDataFrame(rows, "doc_id long, text string, other int"), SF).collect()
    assert len(left) == 23 and {r.text for r in left} == {r[1] for r in rows}
    assert {r.doc_id for r in left if r.text in (text(50), text(4))} == {7, 9} and sum(r.doc_id is None for r in left) == 19


def test_near_dedup_finds_copies_by_trees_over_fingerprints(spark):
    """Without any bucket the trees alone propose near copies; the sets still have to prove them."""
    text = lambda k, n=400: " ".join(f"w{k}x{i}" for i in range(n))
    texts = [t for k in range(30) for t in (text(k), text(k) + " end", text(k) + " end of it")] + [text(99, 40), text(98, 40), "", None]
    docs = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    sets = shingles._sets(docs, "doc_id", "text", 5)
    node = {r.doc_id: r.node for r in sets.collect()}
    found = {r.node: r.component for r in shingles._links(sets.withColumn("bands", F.array().cast("array<long>")), 0.8).collect()}
    together = [len({found.get(node[3 * k + i], node[3 * k + i]) for i in range(3)}) == 1 for k in range(30)]
    assert sum(together) >= 24 and len({found[node[3 * k]] for k in range(30) if together[k]}) == sum(together)
    assert not {node[90], node[91], node[92]} & set(found)


def _lines_left(rows):
    """(doc_id, text) without the lines that have an earlier line of a Jaccard similarity of 0.8 or more, by brute force."""
    seen, out = [], []
    for doc, text in rows:
        kept = []
        for line in (text or "").split("\n"):
            words = lines.words_of(line)
            if words and any(len(words & s) >= 0.8 * len(words | s) - 1e-9 for s in seen):
                seen.append(words)
                continue
            if words:
                seen.append(words)
            kept.append(line)
        out.append((doc, "\n".join(kept)))
    return out


def _contaminated(text, items):
    words = re.findall(r"[0-9a-z\x80-\U0010ffff]+", re.sub("[A-Z]", lambda m: m.group().lower(), text or ""))
    hit = set()
    for item in items:
        own = re.findall(r"[0-9a-z\x80-\U0010ffff]+", re.sub("[A-Z]", lambda m: m.group().lower(), item or ""))
        size = min(13, len(own))
        windows = {tuple(own[k : k + size]) for k in range(len(own) - size + 1)} if own else set()
        for k in range(len(words) - size + 1):
            if size and tuple(words[k : k + size]) in windows:
                hit.update(range(k, k + size))
    return bool(hit) and 20 * len(hit) >= len(words)


def test_stages_equal_brute_force(spark):
    docs = spark.read.parquet(f"{SF}/documents.parquet").orderBy("doc_id")
    rows = [(r.doc_id, r.text) for r in docs.collect()]
    got = corpus_pipeline.drop_lines(spark, docs, SF)
    assert got.columns == docs.columns
    assert {r.doc_id: r.text for r in got.collect()} == dict(_lines_left(rows))
    items = [r.text for r in spark.read.parquet(f"{SF}/benchmark.parquet").collect()]
    assert {r.doc_id for r in corpus_pipeline.drop_contaminated(spark, docs, SF).collect()} == {d for d, t in rows if not _contaminated(t, items)}
    packed = corpus_pipeline.pack(spark, docs, SF).collect()
    assert {r.doc_id for r in packed} == {d for d, _ in rows}
    left = corpus_pipeline.drop_toxic(spark, docs, SF)
    scored = toxicity.score(docs, toxicity.fit(docs, spark.read.parquet(f"{SF}/labels.parquet"), held_out=toxicity.held_out("doc_id")))
    assert {r.doc_id for r in left.collect()} == {r.doc_id for r in toxicity.digest(scored).collect() if not r.predicted}


def test_stages_take_empty_tables_and_nulls(spark):
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    odd = docs.limit(3).union(docs.limit(2).withColumn("text", F.lit(None).cast("string"))).union(docs.limit(1).withColumn("doc_id", F.lit(None).cast("long")))
    for name, stage in corpus_pipeline.STAGES:
        assert stage(spark, docs.limit(0), SF).count() == 0, name
        assert stage(spark, odd, SF).count() > 0, name
