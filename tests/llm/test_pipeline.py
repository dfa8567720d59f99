"""The pipeline: stages in order, each on what its predecessor kept, each decision in effect."""

import re
from collections import Counter, defaultdict

from pyspark.sql import functions as F

import corpus_pipeline
from linkwalk.llm.storage import cut

WORD = re.compile("[^\\x20\\x09-\\x0D]+")
COLUMNS = ["doc_id", "text", "lang", "source", "n_chars"]


def test_stages(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    kept = [docs]
    for name, stage in corpus_pipeline.STAGES[:-1]:
        out = cut(stage(spark, kept[-1], sf))
        assert out.columns == COLUMNS, name
        kept.append(out)
    rows = [{r["doc_id"]: r["text"] for r in k.collect()} for k in kept]
    assert set(rows[1]) <= set(rows[0]) and set(rows[2]) <= set(rows[1])
    assert set(rows[2]) == set(rows[3]) == set(rows[4])
    sets = {}
    for i, t in rows[1].items():
        ws = WORD.findall(t.lower())
        sets[i] = {tuple(ws[k : k + 5]) for k in range(max(1, len(ws) - 4))} if ws else set()
    for i in rows[2]:  # no near-duplicates remain, and none but those went
        assert not any(j < i and sets[i] and 5 * len(sets[i] & sets[j]) >= 4 * len(sets[i] | sets[j]) for j in rows[2])
    gone = set(rows[1]) - set(rows[2])
    assert all(any(j != i and 5 * len(sets[i] & sets[j]) >= 4 * len(sets[i] | sets[j]) for j in rows[1]) for i in gone)
    seen = set()
    for i in sorted(rows[2]):
        ws = WORD.findall(rows[2][i])
        cover = [False] * len(ws)
        for k in range(len(ws) - 19):
            w = tuple(ws[k : k + 20])
            if w in seen:
                cover[k : k + 20] = [True] * 20
            seen.add(w)
        assert rows[3][i] == (" ".join(w for w, c in zip(ws, cover, strict=True) if not c) if any(cover) else rows[2][i])
    assert any("<EMAIL>" in t for t in rows[4].values()) or rows[3] == rows[4]
    assert kept[4].where(F.length("text") != F.col("n_chars")).count() == 0
    final = corpus_pipeline.STAGES[-1][1](spark, kept[-1], sf).collect()
    assert {r["doc_id"] for r in final} == set(rows[4])
    use = defaultdict(int)
    for r in final:
        use[r["sequence_id"]] += r["length"]
    assert max(use.values()) <= 1024


def test_odd_rows(spark, sf):
    rows = [(1, "one two three", "en", "a", 13), (1, "one two three", None, None, None), (None, "call +1 555 123 4567 now", "en", "a", 24), (2, None, None, None, None), (3, "", "en", "a", 0), (4, "x " * 30000, "en", "a", 60000)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long")
    for table, kept in ((docs, 5), (docs.limit(0), 0)):
        for name, stage in corpus_pipeline.STAGES[:-1]:
            table = cut(stage(spark, table, sf))
            assert table.columns == COLUMNS, name
        assert table.count() == kept
        out = corpus_pipeline.STAGES[-1][1](spark, table, sf).collect()
        assert Counter(r["doc_id"] for r in out if r["piece"] == 0) == Counter(r["doc_id"] for r in table.collect())


def test_later_stages_change_no_text_they_need_not(spark, sf):
    docs = spark.createDataFrame([(1, "version 10.20.30.40 of it", "en", "a", 25), (2, "server 10.20.30.40 there", "en", "a", 24)], "doc_id long, text string, lang string, source string, n_chars long")
    got = {r["doc_id"]: r["text"] for r in corpus_pipeline.mask_personal_data(spark, docs, sf).collect()}
    assert got == {1: "version 10.20.30.40 of it", 2: "server <IP> there"}
