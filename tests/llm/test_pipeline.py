"""The pipeline against a version of its own: SQL of another engine, plain set and edit-distance loops, the piece library."""

import collections
import hashlib

import corpus_pipeline
import duckdb
import numpy as np
import pandas as pd
import public_tokenizers
import sentencepiece

from stratacore.llm import sqltext
from tests.llm.helpers import A
from tests.llm.test_operators import brute_components

NAMES = ["doc_id", "text", "lang", "source", "n_chars"]
sha = lambda s: hashlib.sha256(s.encode()).hexdigest()


def by_sql(text, rows):
    con = duckdb.connect()
    con.register("documents", pd.DataFrame(rows, columns=["doc_id", "text", "lang"]))
    return con.execute(text).fetchall()


def without_repeated_lines(rows):
    """Op 7's rule in plain loops."""
    key = lambda x: x.strip(" \t\n\x0b\x0c\r").translate(str.maketrans("ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"))
    held = collections.defaultdict(set)
    for i, t, _ in rows:
        for x in (t or "").split("\n"):
            if len(key(x)) >= 20:
                held[key(x)].add(i)
    gone = lambda x, i: len(held[key(x)]) >= 3 and max(held[key(x)]) != i
    return [(i, "\n".join(x for x in (t or "").split("\n") if not gone(x, i)), lang) for i, t, lang in rows]


def least_distance(item, text):
    """Least edit distance of item to a substring of text, row by row."""
    t = np.array([ord(c) for c in text])
    row, steps = np.zeros(len(t) + 1, int), np.arange(len(t) + 1)
    for i, c in enumerate(item, 1):
        new = np.append(i, np.minimum(row[1:] + 1, row[:-1] + (t != ord(c))))
        row = np.minimum.accumulate(new - steps) + steps
    return row.min()


def brute(rows, items):
    """(doc_id, n_tokens, ids_sha256, decoded_sha256) of what all stages leave."""
    kept = {r[0] for r in by_sql(sqltext.OP1, rows) if r[-1]}
    rows = without_repeated_lines([r for r in rows if r[0] in kept])
    classes, _ = brute_components([(i, t) for i, t, _ in rows])
    rows = [r for r in rows if classes[r[0]] == r[0]]
    norm = lambda t: " ".join(t.lower().split())
    items = [norm(x) for x in items]
    rows = [r for r in rows if not any(least_distance(x, norm(r[1])) <= int(0.08 * len(x)) for x in items)]
    sp = sentencepiece.SentencePieceProcessor(model_file=public_tokenizers.path("piece_bpe_32k.model"))
    out = set()
    for i, t, _ in rows:
        ids = sp.encode(t)
        out.add((i, len(ids), sha(",".join(map(str, ids))), sha(sp.decode(ids))))
    return out


def test_the_whole_pipeline(spark, sf_dir, tmp_path):
    given = spark.read.parquet(f"{sf_dir}/documents.parquet").limit(90).toPandas()[NAMES]
    items = spark.read.parquet(f"{sf_dir}/benchmark.parquet").limit(6)
    x = [r.text for r in items.collect()]
    base = " ".join(given.text[3].split()[:120])
    extra = [base, base + " and one more", "x " * 60, A + "\n" + x[0] + " " + A, x[1][:-2] + "zz and what follows it " + A, "A line that stands in many of the documents here\n" + given.text[5]]
    extra += [f"a line that stands in many of the documents here \n{given.text[k]}" for k in (6, 7)]
    more = pd.DataFrame({"doc_id": range(9000, 9000 + len(extra)), "text": extra, "lang": "en", "source": "s", "n_chars": 0})
    docs = pd.concat([given, more])
    spark.createDataFrame(docs).write.parquet(f"{tmp_path}/documents.parquet")
    items.write.parquet(f"{tmp_path}/benchmark.parquet")
    want = brute([tuple(r) for r in docs[["doc_id", "text", "lang"]].itertuples(index=False)], x)
    got = {tuple(r) for r in corpus_pipeline.run(spark, str(tmp_path)).collect()}
    assert got == want and 0 < len(got) < len(docs)


def test_stages_keep_odd_rows_and_clashing_columns(spark, sf_dir):
    assert [n for n, _ in corpus_pipeline.STAGES] == ["quality_rules", "line_dedup", "near_duplicates", "decontamination", "piece_encoding"]
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").limit(20)
    docs = docs.unionByName(spark.createDataFrame([(None, A, "en", None, None), (None, None, None, "s", 1), (7, A + " x", "en", "s", 1)], docs.schema))
    clash = docs.selectExpr("*", *[f"1 as {c}" for c in ("stays", "doc", "_dropped", "dropped", "key", "owner", "row", "kept", "carry", "item_ids", "distances", "component_id", "id", "n")])
    for name, stage in corpus_pipeline.STAGES[:-1]:
        out = stage(spark, clash, sf_dir)
        assert out.columns == clash.columns, name
        assert out.where("stays = 1 and key = 1 and item_ids = 1").count() == out.count() > 0, name
        assert stage(spark, clash.where("false"), sf_dir).count() == 0, name
