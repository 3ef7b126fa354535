"""The whole pipeline against its stages composed in plain Python."""

import hashlib
import subprocess
import sys
from pathlib import Path

import brute
import corpus_pipeline
import numpy as np
import pyarrow as pa
from conftest import DATA
from pyspark.sql import functions as F

from colsketch import session
from colsketch.llm import mixing, near, registry, toxicity
from colsketch.llm.common import table

SF = f"{DATA}/sf0.001"


def mixed(docs):
    """{doc_id: copies} of docs {doc_id: (text, source)}."""
    size = {i: len(brute.WORDS.findall(t or "")) for i, (t, _) in docs.items()}
    sources = sorted({s for _, s in docs.values()}, key=lambda s: (s is None, s or ""))
    n = {s: sum(size[i] for i, (_, x) in docs.items() if x == s) for s in sources}
    w = {s: (5, 2, 1)[k % 3] for k, s in enumerate(sources)}
    capped, target = set(), {}
    while True:
        left, share = sum(n.values()) - sum(3 * n[s] for s in capped), sum(w[s] for s in sources if s not in capped)
        target = {s: 3 * n[s] if s in capped else left * w[s] / share for s in sources}
        above = {s for s in sources if target[s] > 3 * n[s]}
        if not above:
            break
        capped |= above
    out = {i: 1 for i in docs if not size[i]}
    for s in sources:
        whole, rest = divmod(int(target[s]), n[s]) if n[s] else (0, 0)
        mine = sorted((hashlib.md5(f"7:{i}".encode()).hexdigest(), i) for i, (_, x) in docs.items() if x == s and size[i])
        at = 0
        for _, i in mine:
            out[i] = whole + (at < rest)
            at += size[i]
    return {i: k for i, k in out.items() if k}


def sharded(sizes, limit=1 << 20):
    """{doc_id: prefix} of rows [(doc_id, bytes)], by splitting a bucket that is too large on its next bit."""
    bits = {i: bin(int(hashlib.md5(str(i).encode()).hexdigest()[:15], 16))[2:].zfill(60) for i, _ in sizes}
    out, todo = {}, [("", sizes)]
    while todo:
        prefix, rows = todo.pop()
        if sum(b for _, b in rows) <= limit:
            out |= {i: prefix for i, _ in rows}
        else:
            todo += [(prefix + x, [r for r in rows if bits[r[0]].startswith(prefix + x)]) for x in "01"]
    return out


def test_whole_pipeline(spark):
    docs = table(spark, SF, "documents")
    rows = {r.doc_id: (r.text, r.source) for r in docs.collect()}
    scores = {r.doc_id: r.predicted for r in registry.op2_toxicity(spark, SF).collect()}
    rows = {i: x for i, x in rows.items() if not scores[i]}
    near = brute.near({i: t for i, (t, _) in rows.items()})
    rows = {i: x for i, x in rows.items() if near[i][1] == i}
    items = {r.item_id: r.text for r in table(spark, SF, "benchmark").collect()}
    hit = brute.contaminated({i: t for i, (t, _) in rows.items()}, items)
    rows = {i: x for i, x in rows.items() if not hit[i][-1]}
    copies = mixed(rows)
    every = [(i, len((rows[i][0] or "").encode())) for i, k in copies.items() for _ in range(k)]
    place = sharded(every)
    got = sorted((r.doc_id, r.bytes, r.shard, r.depth) for r in corpus_pipeline.run(spark, SF).collect())
    assert got == sorted((i, b, place[i], len(place[i])) for i, b in every)
    assert 50 < len({g[0] for g in got}) < docs.count()


def test_pipeline_stages_on_empty_tables(spark):
    empty = table(spark, SF, "documents").where("false")
    for name, stage in corpus_pipeline.STAGES[1:4]:
        assert stage(spark, empty, SF).count() == 0, name
    assert toxicity.toxic_flags(empty, toxicity.Model()).count() == 0
    assert mixing.mixed_rows(empty.withColumn("whole", F.lit(1))).columns[-1] == "whole"


def test_batches_of_the_pipeline_are_bounded(spark):
    """Small batches go to Python, whatever the session's own bound; workers load no pandas; frequent shingles stay the same."""
    docs = spark.read.parquet(f"{SF}/documents.parquet").coalesce(1)
    docs = docs.unionByName(docs).unionByName(docs).coalesce(1)
    key, before = session._BATCH, spark.conf.get(session._BATCH)

    def sizes(batches):
        for b in batches:
            yield pa.RecordBatch.from_arrays([pa.array([b.num_rows]), pa.array([b.nbytes])], names=["n", "bytes"])

    try:
        spark.conf.set(key, "1g")
        corpus_pipeline.mix_sources(spark, docs, SF)
        assert 0 < int(spark.conf.get(key).removesuffix("b")) <= session.BATCH_BYTES
        spark.conf.set(key, str(1 << 16))
        corpus_pipeline.mix_sources(spark, docs, SF)
        assert int(spark.conf.get(key).removesuffix("b")) == 1 << 16
        rows = docs.mapInArrow(sizes, "n long, bytes long").collect()
        longest = docs.selectExpr("max(octet_length(text))").first()[0]
        assert len(rows) > 3 and sum(r.n for r in rows) == docs.count() and max(r.bytes for r in rows) < (1 << 17) + 2 * longest
    finally:
        spark.conf.set(key, before)
    code = "import sys; sys.path.insert(0, sys.argv[1]); import colsketch.llm.near, colsketch.llm.toxicity, colsketch.llm.mixing; print('pandas' in sys.modules)"
    found = subprocess.run([sys.executable, "-c", code, str(Path(corpus_pipeline.__file__).parent)], capture_output=True, text=True, check=True)
    assert found.stdout.strip() == "False"
    held = [np.array([1, 5, 9], np.uint64)] * near.OFTEN + [np.array([5, 7], np.uint64)]
    assert near._frequent(held).column("h1").to_pylist() == [1, 5, 9] and not held
