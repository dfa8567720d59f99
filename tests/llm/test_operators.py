"""The ten operators against brute force, on the smallest tables and on a table of awkward rows."""

import base64
import hashlib
import re
import zlib
from collections import Counter, defaultdict

import numpy as np
import public_tokenizers
import pytest
from pyspark.sql import functions as F

from linkwalk.llm import bpe, fingerprints, neardup, packing, pii, secret_scan, sharding, substring, toxicity, vectors
from linkwalk.llm.components import connected_components
from linkwalk.llm.queries import QUERIES

WORD = re.compile("[^\\x20\\x09-\\x0D]+")
LOW = str.maketrans("ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")
PASSAGE = " ".join(f"w{i}x" for i in range(60))
ODD = [
    (1, PASSAGE + " tail one", "en", "a"),
    (2, "lead " + PASSAGE, "en", "a"),
    (3, None, None, None),
    (4, "", "en", None),
    (5, "  \t\n ", "en", "a"),
    (6, "one two", "en", "a"),
    (7, "one two", "en", "a"),
    (7, "one two", "en", "a"),
    (7, "other text " + PASSAGE, "en", "a"),
    (None, PASSAGE, "en", "a"),
    (None, "x" * 30000, "en", "a"),
    (8, "é" * 3000 + " 😀 token = \"abcdef12\" AKIA" + "A" * 16 + " +1 (555) 123-4567 a.b@c.de 4111 1111 1111 1111 10.0.0.256 10.0.0.7", "fr", "a"),
    (9, ("ab " * 5000) + PASSAGE + " " + PASSAGE, "fr", "a"),
    (10, "GB82WEST12345698765432 bank 12345678901234567890 password: token: abcdefg x@y z@@q.r.s+t@u.v", "en", "a"),
]


@pytest.fixture(scope="module")
def docs(spark, sf):
    return spark.read.parquet(f"{sf}/documents.parquet")


@pytest.fixture(scope="module")
def odd(spark):
    rows = [(i, t, a, b, len(t) if t else None, "clash", 1) for i, t, a, b in ODD]
    return spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long, uid string, n_shingles int").repartition(3)


def pairs(df):
    return [(r["doc_id"], r["text"] or "") for r in df.select("doc_id", "text").collect()]


def matches(text, pattern, keep=lambda m: True):
    return [(m.start(), m.end()) for m in re.finditer(pattern, text) if keep(m)]


def only_digits(s):
    return re.sub("[^0-9]", "", s)


def luhn(s):
    total = 0
    for i, c in enumerate(reversed(s)):
        x = int(c) * (1 + i % 2)
        total += x - 9 * (x > 9)
    return total % 10 == 0


def sha(s):
    return hashlib.sha256(s.encode()).hexdigest()


def secrets_of(text):
    found = [(a, k, b) for k, (a, b) in [(0, x) for x in matches(text, r"""((?a:(?i:password|passwd|secret|token|api_?key)))["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", lambda m: len(m[2]) >= 6 and m[1].isascii())] + [(1, x) for x in matches(text, "AKIA[A-Z0-9]+", lambda m: len(m[0]) >= 20)] + [(2, x) for x in matches(text, "[0-9a-f]+", lambda m: len(m[0]) >= 24)]]
    return sha(",".join(f"{('assign', 'access', 'hex')[k]}:{a}:{b}" for a, k, b in sorted(found)))


def private_of(text):
    kinds = {
        "email": (r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+", lambda m: True),
        "ip": (r"[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)", lambda m: all(int(x) <= 255 for x in m[0].split("."))),
        "card": (r"[0-9]([\x20-]?[0-9])+", lambda m: 13 <= len(only_digits(m[0])) <= 19 and luhn(only_digits(m[0]))),
        "phone": (r"\+[0-9][\x20().0-9-]+[0-9]", lambda m: 9 <= len(only_digits(m[0])) <= 15),
    }
    return sha(",".join(f"{k}:{a}:{b}" for k, (p, keep) in kinds.items() for a, b in matches(text, p, keep)))


@pytest.mark.parametrize("which", ["docs", "odd"])
def test_secrets(spark, which, request):
    df = request.getfixturevalue(which)
    from linkwalk.llm.spans import by_start, listed

    path = secret_scan.new_ledger(spark)
    found = secret_scan.scan_secrets(df, path)

    base = by_start(F.filter("spans", lambda s: s["kind"].isin(secret_scan.BASE)), secret_scan.BASE)
    got = Counter((r["text"] or "", r["h"]) for r in found.select("text", F.sha2(listed(base).cast("binary"), 256).alias("h")).collect())
    assert got == Counter((t, secrets_of(t)) for _, t in pairs(df))
    ledger = secret_scan.read_ledger(spark, path)
    assert ledger.count() == len({t for _, t in pairs(df)})
    again = secret_scan.scan_unseen(df.select(secret_scan.blob_name(F.col("text")).alias("blob"), "text"), ledger)
    assert again.count() == 0
    assert secret_scan.scan_unseen(df.select(secret_scan.blob_name(F.col("text")).alias("blob"), "text"), ledger, "next").count() == ledger.count()


def test_ledger_scans_only_what_it_lacks(spark):
    path = secret_scan.new_ledger(spark)
    old = [("a", "token = abcdefgh"), ("b", "nothing"), ("c", None)]
    new = [*old, ("d", "token = abcdefgh"), ("a", "secret: zyxwvuts")]
    of = lambda rows: spark.createDataFrame(rows, "path string, text string")
    assert secret_scan.read_ledger(spark, path).count() == 0
    first = secret_scan.scan_secrets(of(old), path)
    assert {r["path"]: len(r["spans"]) for r in first.collect()} == {"a": 1, "b": 0, "c": 0}
    assert secret_scan.read_ledger(spark, path).count() == 3
    # What is in the ledger is taken from it: a marked row shows that its blob was not scanned again.
    mark = secret_scan.read_ledger(spark, path).where(F.size("spans") > 0).select("blob").first()["blob"]
    got = Counter((r["path"], r["blob"] == mark, len(r["spans"])) for r in secret_scan.scan_secrets(of(new), path).collect())
    assert got == Counter([("a", True, 1), ("b", False, 0), ("c", False, 0), ("d", True, 1), ("a", False, 1)])
    assert secret_scan.read_ledger(spark, path).count() == 4
    secret_scan.scan_secrets(of(new), path)
    assert secret_scan.read_ledger(spark, path).count() == 4
    secret_scan.scan_secrets(of(new), path, rule_version="next")
    assert secret_scan.read_ledger(spark, path).groupBy("rule_version").count().count() == 2
    assert secret_scan.scan_secrets(of([]), path).count() == 0


@pytest.mark.parametrize("which", ["docs", "odd"])
def test_pii(which, request):
    from linkwalk.llm.spans import listed

    df = request.getfixturevalue(which)
    base = F.filter("pii", lambda s: s["kind"].isin(pii.BASE))
    got = Counter((r["text"] or "", r["h"]) for r in pii.find_pii(df).select("text", F.sha2(listed(base).cast("binary"), 256).alias("h")).collect())
    assert got == Counter((t, private_of(t)) for _, t in pairs(df))


def test_pii_values_and_redaction(spark):
    t = "call +1 (555) 123-4567 or a@b.cd; visa 4111 1111 1111 1111, IBAN GB82WEST12345698765432 end"
    row = pii.find_pii(spark.createDataFrame([(t,)], "text string")).select("pii", pii.redact(F.col("text"), F.col("pii")).alias("r")).first()
    assert [s["kind"] for s in row["pii"]] == ["email", "card", "phone", "iban"]
    assert all(t[s["start"] : s["end"]] == s["value"] for s in row["pii"])
    assert {s["kind"]: s["score"] for s in row["pii"]}["phone"] == 0.95
    assert row["r"] == "call <PHONE> or <EMAIL>; visa <CARD>, IBAN <IBAN> end"
    long_ = spark.createDataFrame([("1 " * 40000,), ("a" * 60000 + "@",), ("+1" + "-" * 60000,), ("4" * 60000,)], "text string")
    assert [len(r["pii"]) for r in pii.find_pii(long_).collect()] == [0, 0, 0, 0]


def test_context_decides_what_is_masked(spark):
    texts = ["version 10.20.30.40 of it", "the server version 10.20.30.40", "a ship 10.20.30.40 hotel", "ip 10.20.30.40", "w" * 30 + "x ip 1.2.3.4"]
    rows = pii.find_pii(spark.createDataFrame([(t,) for t in texts], "text string")).select("text", "pii", pii.redact(F.col("text"), F.col("pii")).alias("r")).collect()
    by = {r["text"]: (r["pii"][0]["score"], r["r"]) for r in rows}
    assert [by[t][0] for t in texts] == [0.3, 0.65, 0.6, 0.95, 0.95]
    assert by[texts[0]][1] == texts[0] and by[texts[2]][1] == "a ship <IP> hotel"
    # A word that the edge of the context cuts does not count.
    cut = "xship " + "." * 38 + "1.2.3.4"
    assert pii.find_pii(spark.createDataFrame([(cut,)], "text string")).first()["pii"][0]["score"] == 0.6
    over = spark.createDataFrame([("+4111111111111111 1.2.3.4.5.6.7.8 ß😀a@b.cd",)], "text string")
    assert pii.find_pii(over).select(pii.redact(F.col("text"), F.col("pii")).alias("r")).first()["r"].endswith("ß😀<EMAIL>")


def test_many_matches_stay_cheap(spark):
    import time

    n = 200_000
    rows = [(1, "12, " * n + "visa 4111 1111 1111 1111 end"), (2, "a@b.cd 10.0.0.1; " * (n // 4))]
    df = spark.createDataFrame(rows, "doc_id long, text string")
    began = time.time()
    got = {r["doc_id"]: r for r in pii.find_pii(df).select("doc_id", F.size("pii").alias("n"), F.element_at("pii", -1)["end"].alias("e"), pii.redact(F.col("text"), F.col("pii")).alias("r")).collect()}
    assert time.time() - began < 30
    assert got[1]["n"] == 1 and got[1]["r"].endswith("12, visa <CARD> end") and got[2]["n"] == n // 2 and got[2]["r"] == "<EMAIL> <IP>; " * (n // 4)
    began = time.time()
    found = secret_scan.scan_secrets(spark.createDataFrame([("token = abcdefgh12 " * n,)], "text string"), secret_scan.new_ledger(spark)).select(F.size("spans").alias("n"), F.element_at("spans", -1)["end"].alias("e")).first()
    assert time.time() - began < 30 and (found["n"], found["e"]) == (n, 19 * n - 1)


def removed(rows):
    seen, out = set(), []
    for _, text in rows:
        ws = WORD.findall(text)
        gone = [False] * len(ws)
        for k in range(len(ws) - 19):
            w = tuple(ws[k : k + 20])
            if w in seen:
                gone[k : k + 20] = [True] * 20
            seen.add(w)
        kept = " ".join(w for w, g in zip(ws, gone, strict=True) if not g)
        out.append((text, len(ws), sum(gone), kept))
    return out


def test_substring(docs):
    rows = sorted(pairs(docs))
    got = {r["doc_id"]: r for r in substring.remove_repeats(docs).collect()}
    words = {i: WORD.findall(t) for i, t in rows}
    for (i, _), (_, n, gone, kept) in zip(rows, removed(rows), strict=True):
        r = got[i]
        assert (r["n_words"], r["n_removed"], r["kept_text"], r["kept_sha256"]) == (n, gone, kept, sha(kept))
        for f in r["factors"]:
            assert f["words"] >= 20 and (f["ref_uid"], f["ref_start"]) < (i, f["start"])
            assert words[i][f["start"] : f["start"] + f["words"]] == words[f["ref_uid"]][f["ref_start"] : f["ref_start"] + f["words"]]


def test_substring_odd_rows(odd):
    out = substring.remove_repeats(odd)
    assert out.columns[:7] == odd.columns and out.count() == len(ODD)
    by = defaultdict(list)
    for r in out.collect():
        by[r["doc_id"]].append((r["text"], r["n_words"], r["n_removed"]))
    assert by[1] == [(PASSAGE + " tail one", 62, 0)]
    assert by[2] == [("lead " + PASSAGE, 61, 60)]
    assert by[3] == [(None, 0, 0)] and by[4] == [("", 0, 0)]
    assert ("other text " + PASSAGE, 62, 60) in by[7]
    assert (PASSAGE, 60, 60) in by[None]
    assert by[9][0][2] == 4999 + 120


def test_parse_joins_and_picks_longest():
    assert substring.parse([0, 1, 5], [1, 4, 2], [7, 7, 9], [10, 11, 0], 20) == [(0, 24, 7, 10), (5, 21, 9, 0)]
    assert substring.parse([0, 0, 9], [2, 6, 1], [3, 4, 5], [0, 0, 0], 20) == [(0, 25, 4, 0), (9, 20, 5, 0)]


def sets_of(rows):
    out = []
    for i, text in rows:
        ws = WORD.findall(text.translate(LOW))
        out.append((i, {tuple(ws[k : k + 5]) for k in range(len(ws) - 4)} if len(ws) >= 5 else ({tuple(ws)} if ws else set())))
    return out


def components_of(sets, percent):
    parent = list(range(len(sets)))

    def find(x):
        while parent[x] != x:
            x = parent[x] = parent[parent[x]]
        return x

    for a in range(len(sets)):
        for b in range(a):
            x, y = sets[a][1], sets[b][1]
            k = len(x & y)
            if k and 100 * k >= percent * (len(x) + len(y) - k):
                parent[max(find(a), find(b))] = min(find(a), find(b))
    return [sets[find(a)][0] for a in range(len(sets))]


@pytest.mark.parametrize("percent", [80, 85])
def test_near_duplicates(docs, percent):
    rows = sorted(pairs(docs))
    sets = sets_of(rows)
    want = {i: (len(s), c, c == i) for (i, s), c in zip(sets, components_of(sets, percent), strict=True)}
    got = {r["doc_id"]: (r["n_shingles"], r["component_id"], r["kept"]) for r in neardup.near_duplicates(docs, percent=percent).collect()}
    assert got == want


@pytest.mark.parametrize("side", [neardup.SIDE, 20])
def test_near_duplicates_dense_group(spark, monkeypatch, side):
    monkeypatch.setattr(neardup, "SIDE", side)
    r = np.random.default_rng(0)
    base = [f"t{i}" for i in range(120)]
    rows = []
    for i in range(300):
        ws = list(base)
        for k in r.choice(120, r.integers(0, 9), replace=False):
            ws[k] = f"e{i}_{k}"
        rows.append((i, " ".join(ws)))
    sets = sets_of(rows)
    want = dict(zip(range(300), components_of(sets, 85), strict=True))
    df = spark.createDataFrame(rows, "doc_id long, text string").repartition(4)
    assert {x["doc_id"]: x["component_id"] for x in neardup.near_duplicates(df, percent=85).collect()} == want


def test_near_duplicates_odd_rows(odd):
    out = neardup.near_duplicates(odd)
    assert out.columns == ["doc_id", "text", "lang", "source", "n_chars", "uid", "n_shingles_in", "n_shingles", "component_id", "kept"]
    assert out.count() == len(ODD)
    by = defaultdict(list)
    for r in out.collect():
        by[r["doc_id"]].append((r["text"], r["n_shingles"], r["component_id"], r["kept"]))
    assert by[3] == [(None, 0, 3, True)] and by[4] == [("", 0, 4, True)]
    assert by[6] == [("one two", 1, 6, True)]
    assert by[7].count(("one two", 1, 6, False)) == 2
    assert by[2][0][2] == 1 and not by[2][0][3]


def test_forest_joins_what_is_linked():
    r = np.random.default_rng(3)
    base = np.unique(r.integers(0, 1 << 60, 120, dtype=np.uint64))
    sets = []
    for i in range(150):
        if i % 3 == 2:
            sets.append(np.unique(r.integers(0, 1 << 60, 120, dtype=np.uint64)))
        else:
            v = base.copy() if i % 3 else np.sort(base ^ np.uint64(1 << 61))
            v[r.choice(len(v), r.integers(0, 8), replace=False)] = r.integers(0, 1 << 60)
            sets.append(np.unique(v))
    at = np.arange(150)
    needed = neardup.needed_matches(0.85, 1e-5)
    joined = components_of([(int(i), set(v.tolist())) for i, v in zip(at, sets, strict=True)], 85)
    label = at.copy()
    edges = neardup.forest(sets, at.copy(), at, at, needed, 85)
    assert len(edges) == 150 - len(set(joined))
    for i, j in edges:
        label[label == max(label[i], label[j])] = min(label[i], label[j])
    assert label.tolist() == joined
    # Members of one component are not compared.
    assert neardup.forest(sets, np.zeros(150, np.int64), at, at, needed, 85) == []


def test_components_raise_where_rounds_do_not_do(spark):
    chain = spark.createDataFrame([(i, i + 1) for i in range(200)], "u long, v long")
    with pytest.raises(RuntimeError, match="settle"):
        connected_components(chain, rounds=1)


def test_sequential_test_keeps_what_it_should():
    needed = neardup.needed_matches(0.8, 1e-5)
    r = np.random.default_rng(1)
    hits = r.random((20000, neardup.HASHES)) < 0.8
    a = np.zeros(hits.shape, np.uint32)
    assert len(neardup._survive(a, a + ~hits, needed)) >= 19990
    assert len(neardup._survive(a, a + (r.random(hits.shape) >= 0.4), needed)) == 0
    assert neardup.miss_chance(0.85) < 1e-6


def test_components(spark):
    edges = [(i, i + 1) for i in range(50)] + [(100, 101), (102, 101), (5, 5), (None, 3)] + [(200, 200 + k) for k in range(1, 40)]
    got = {r["node"]: r["component"] for r in connected_components(spark.createDataFrame(edges, "u long, v long")).collect()}
    assert got == {i: 0 for i in range(51)} | {100: 100, 101: 100, 102: 100} | {200 + k: 200 for k in range(40)}
    assert connected_components(spark.createDataFrame([], "u long, v long")).count() == 0


def test_bpe_matches_the_library():
    import tiktoken

    e = bpe.Encoder(public_tokenizers.path("byte_bpe_multi_50k.tiktoken"))
    lib = tiktoken.Encoding("own", pat_str=public_tokenizers.PATTERN, mergeable_ranks=e.vocabulary.ranks, special_tokens={})
    r = np.random.default_rng(3)
    parts = ["'", "s", "t", "re", "ve", "m", "ll", "d", " ", "  ", "\n", "a", "B", "é", "1", "½", "二", "!", "''", "'s", "\U0001f600", "\x1c", "́", "　", "\x85"]
    texts = ["", "x" * 5000, "ab" * 900, "!" * 900 + " " * 900] + ["".join(r.choice(parts, r.integers(1, 40))) for _ in range(1500)]
    for part in bpe.groups(texts, 3000):
        for text, (ids, back) in zip(part, e.encode(part), strict=True):
            got = [int(x) for x in ids.split(b",")[:-1]]
            assert got == lib.encode_ordinary(text) and back.decode() == text
    assert e.decode(e.ids("héllo wörld")) == "héllo wörld" and e.offsets(e.ids("abc"))[0] == 0


def test_bpe_query(spark, sf, docs, odd):
    import tiktoken

    with open(public_tokenizers.path("byte_bpe_multi_50k.tiktoken"), "rb") as f:
        ranks = {base64.b64decode(a): int(b) for a, b in map(bytes.split, f)}
    lib = tiktoken.Encoding("own", pat_str=public_tokenizers.PATTERN, mergeable_ranks=ranks, special_tokens={})
    got = {r["doc_id"]: r for r in QUERIES["op6_bpe"](spark, sf).collect()}
    for i, text in pairs(docs):
        ids = lib.encode_ordinary(text)
        assert (got[i]["n_tokens"], got[i]["ids_sha256"], got[i]["decoded_sha256"]) == (len(ids), sha(",".join(map(str, ids))), sha(text))
    out = bpe.encode_documents(odd, public_tokenizers.path("byte_bpe_multi_50k.tiktoken"))
    assert all(r["ids"] == lib.encode_ordinary(r["text"] or "") for r in out.collect())


def check_packing(rows, texts):
    from tokenizers import Tokenizer

    lib = Tokenizer.from_file(public_tokenizers.path("byte_bpe_50k.json"))
    want = Counter()
    for i, text in texts:
        ids = np.array([*lib.encode(text, add_special_tokens=False).ids, 2], "<u4")
        head = (len(ids) - 1) % 1024 + 1
        at = 0
        for k in range(-(-len(ids) // 1024)):
            n = head if k == 0 else 1024
            want[i, k, at, n, zlib.crc32(ids[at : at + n].tobytes())] += 1
            at += n
    assert Counter((r["doc_id"], r["piece"], r["start"], r["length"], r["ids_crc32"]) for r in rows) == want
    held = defaultdict(list)
    for r in rows:
        held[r["sequence_id"]].append((r["offset"], r["length"]))
    for got in held.values():
        at = 0
        for offset, n in sorted(got):
            assert offset == at
            at += n
        assert at <= 1024
    return len(held), sum(r["length"] for r in rows)


def test_packing(spark, sf, docs, odd):
    n, total = check_packing(QUERIES["op7_packing"](spark, sf).collect(), pairs(docs))
    assert n <= -(-total // 1024) * 1.02 + 1
    extra = spark.createDataFrame([(20, "a <|endoftext|> b" + " " * 6000 + "x")], "doc_id long, text string").unionByName(odd.select("doc_id", "text"))
    ranks = public_tokenizers.path("byte_bpe_50k.tiktoken")
    check_packing(packing.pack(packing.pieces(extra, ranks, public_tokenizers.PATTERN, packing.special_tokens(public_tokenizers.path("byte_bpe_50k.json")))).collect(), pairs(extra))


def test_plan_places_all():
    r = np.random.default_rng(4)
    for histogram in ({}, {1024: 3}, {600: 5, 424: 5}, {513: 7}, {int(x): int(n) for x, n in zip(r.integers(1, 1025, 300), r.integers(1, 50, 300), strict=True)}):
        plan = packing.plan(histogram)
        used = Counter()
        for content, n in plan:
            assert sum(content) <= 1024 and n > 0
            for x in content:
                used[x] += n
        assert used == Counter(histogram)
    assert sum(n for _, n in packing.plan({600: 5, 424: 5})) == 5


def least_bins(pieces, capacity):
    """The least number of bins, by trying all ways."""
    best = [len(pieces)]

    def go(i, rooms):
        if len(rooms) >= best[0]:
            return
        if i == len(pieces):
            best[0] = len(rooms)
            return
        for j, r in enumerate(rooms):
            if r >= pieces[i] and r not in rooms[:j]:
                go(i + 1, [*rooms[:j], r - pieces[i], *rooms[j + 1 :]])
        go(i + 1, [*rooms, capacity - pieces[i]])

    go(0, [])
    return best[0]


def test_plan_against_all_ways():
    r = np.random.default_rng(21)
    for _ in range(60):
        pieces = sorted(r.integers(1, 21, r.integers(1, 10)).tolist(), reverse=True)
        got = packing.report(Counter(pieces), 20)
        least = least_bins(pieces, 20)
        assert got["at_least"] <= least <= got["sequences"] <= least + 1
        assert sum(n for _, n in packing.plan(Counter(pieces), 20)) == got["sequences"]


def test_plan_is_near_the_dual_bound():
    r = np.random.default_rng(11)
    wide = {n: int(r.integers(20, 80)) for n in range(1, 1025)}
    thirds = {341: 1000, 342: 900, 512: 50, 683: 700, 700: 200, 30: 50}
    long_ = {700: 10, 600: 20, 513: 5, 100: 1}
    for histogram, most in ((wide, 1.01), ({n: 50_000 * k for n, k in wide.items()}, 1.01), (thirds, 1.15), (long_, 1.0)):
        used = Counter()
        for content, n in packing.plan(histogram):
            assert sum(content) <= 1024 and n > 0
            for x in content:
                used[x] += n
        assert used == Counter(histogram)
        got = packing.report(histogram)
        assert got["at_least"] <= got["sequences"] <= most * got["at_least"] and got["sequences"] <= got["best_fit"]
    # The dual bound sees what the sum of tokens does not: no two of these fit together.
    assert packing.report(long_)["at_least"] == 35
    assert packing.price(np.array([0.5, 0.1]), np.array([100, 300]), np.array([2, 1]), 1024).tolist() == [[2, 1], [2, 1]]


@pytest.mark.parametrize("size", ["sf0.001", "sf0.01", "sf0.1"])
def test_plan_on_the_tables(spark, size):
    path = public_tokenizers.path("byte_bpe_50k.tiktoken")
    docs = spark.read.parquet(f"/root/testdata/{size}/documents.parquet")
    parts = packing.pieces(docs, path, public_tokenizers.PATTERN)
    got = packing.report({r["length"]: r["count"] for r in parts.groupBy("length").count().collect()})
    assert got["sequences"] <= 1.01 * got["at_least"] and got["sequences"] <= got["best_fit"]


def test_sharding(spark, docs, odd):
    rows = sharding.shard_documents(docs).collect()
    texts = dict(pairs(docs))
    sizes, slots, groups = Counter(), defaultdict(list), defaultdict(Counter)
    for r in rows:
        b = texts[r["doc_id"]].encode()
        assert (r["size"], r["text_crc32"], r["law"], r["grown_shard"]) == (len(b) + 8, zlib.crc32(b), "rows", None)
        sizes[r["shard"]] += 1
        slots[r["shard"]].append(r["slot"])
        groups[texts[r["doc_id"]]][r["shard"]] += 1
    assert len(rows) == len(texts) and max(sizes.values()) - min(sizes[s] for s in range(24)) <= 1
    assert all(sorted(x) == list(range(len(x))) for x in slots.values())
    assert sum(len(g) > 1 for g in groups.values()) <= 1
    out = sharding.shard_documents(odd).collect()
    assert len(out) == len(ODD) and max(Counter(r["shard"] for r in out).values()) == 1
    assert [(r["size"], r["text_crc32"]) for r in out if r["doc_id"] == 3] == [(8, 0)]


def test_sharding_hot_group(spark):
    rows = [(i, "hot" if i % 3 == 0 else (f"pair {i // 6}" if i % 3 == 1 else f"single {i}")) for i in range(6000)]
    out = sharding.shard_documents(spark.createDataFrame(rows, "doc_id long, text string").repartition(4)).collect()
    assert sorted(Counter(r["shard"] for r in out).values()) == [250] * 24
    text = dict(rows)
    hot = Counter(r["shard"] for r in out if text[r["doc_id"]] == "hot")
    assert len(hot) <= 16  # twice the least number of shards that hold it


@pytest.mark.parametrize(("sizes", "most"), [({"a": 216, "b": 240, "c": 228}, 1), ({"a": 456}, 2), (dict.fromkeys(map(str, range(2880)), 2), 1)])
def test_sharding_keeps_groups_whole(spark, sizes, most):
    # 240 rows a shard: groups of 0.9 to 1.0 and 1.9 shards; and a table where every text has a copy.
    texts = [g for g, n in sizes.items() for _ in range(n)]
    rows = [(i, texts[i] if i < len(texts) else f"single {i}") for i in range(5760)]
    text = dict(rows)
    out = sharding.shard_documents(spark.createDataFrame(rows, "doc_id long, text string").repartition(4)).collect()
    assert sorted(Counter(r["shard"] for r in out).values()) == [240] * 24
    groups = defaultdict(set)
    for r in out:
        groups[text[r["doc_id"]]].add(r["shard"])
    assert max(map(len, groups.values())) == most


def test_fingerprints(spark, sf, docs):
    rows = sorted(pairs(docs))
    got = {r["doc_id"]: r for r in QUERIES["op5_fingerprints"](spark, sf).collect()}
    better = 0
    for (i, t), (_, after) in zip(rows, rows[1:] + rows[:1], strict=True):
        k = len(t) // 4
        edited = t[: len(t) - k] + after[:k]
        r = got[i]
        assert (r["n_chars"], r["edited_sha256"]) == (len(t), sha(edited))
        same = sum(a == b for a, b in zip(r["fingerprint"].split(","), r["edited_fingerprint"].split(","), strict=True)) / fingerprints.SKETCHES
        assert r["near_edited"] == same
        better += r["near_edited"] > r["near_next"]
    assert better >= 0.95 * len(rows)
    by = defaultdict(set)
    for i, t in rows:
        by[t].add(got[i]["fingerprint"])
    assert all(len(x) == 1 for x in by.values())


def test_fingerprints_follow_order_and_repeats(spark):
    base = " ".join(f"w{i}" for i in range(200))
    moved = " ".join([f"w{i}" for i in range(100, 200)] + [f"w{i}" for i in range(100)])
    twice = base + " " + base
    texts = [base, moved, twice, base.replace("w7 ", "v7 "), "", None, "  ", "a", "ab " * 3000]
    df = spark.createDataFrame([(i, t) for i, t in enumerate(texts)], "i int, text string")
    fp = [r["fingerprint"].split(",") for r in fingerprints.fingerprints(df, "i").orderBy("i").collect()]
    like = lambda a, b: sum(x == y for x, y in zip(fp[a], fp[b], strict=True)) / 32
    assert like(0, 3) > 0.85 > like(0, 1) and like(0, 2) < 0.9
    assert fp[4] == fp[5] == fp[6] != fp[7]


def shingled(text):
    """Units and occurrence-numbered k-mers with their places, by hand."""
    out = []
    for w in re.findall(r"[^ \t\n\x0b\f\r]+", text):
        out += [w] if len(w) <= fingerprints.LONG else [w[i : i + fingerprints.GRAM] for i in range(len(w) - fingerprints.GRAM + 1)]
    seen, kmers = Counter(), []
    for i in range(max(1, len(out) - 1)):
        k = tuple(out[i : i + 2])
        kmers.append((k, seen[k]))
        seen[k] += 1
    return kmers


def test_fingerprints_against_brute_force(spark):
    """The picks are the ends of each order over all k-mers: hashes come from Spark, the choice is made here."""
    r = np.random.default_rng(5)
    texts = [" ".join(r.choice(["ab", "cde", "f", "ghij", "k" * 40, "lm nop"], r.integers(1, 120))) for _ in range(12)] + ["", "one", "q" * 300, "é" * 17 + " 😀" * 30]
    got = {x["i"]: x["fingerprint"] for x in fingerprints.fingerprints(spark.createDataFrame(list(enumerate(texts)), "i int, text string"), "i").collect()}
    rows = []
    for i, t in enumerate(texts):
        for place, (k, o) in enumerate(shingled(t), 1):
            k = (*k, None, None)[:2]
            rows.append((i, place, *k, o))
    df = spark.createDataFrame(rows, "i int, place long, a string, b string, o int")
    top = lambda c: F.shiftleft(F.shiftrightunsigned(c, fingerprints.PLACE + 1), fingerprints.PLACE)
    kmer = F.shiftright(top(F.xxhash64(F.shiftright(top(F.xxhash64("a", "b")), fingerprints.PLACE), "o")), fingerprints.PLACE)
    ranks = df.select("i", "place", *[F.shiftright(F.xxhash64(kmer, F.lit(j)), fingerprints.PLACE).alias(f"r{j}") for j in range(fingerprints.SKETCHES)]).collect()
    pairs_ = []
    for i in range(len(texts)):
        own = [x for x in ranks if x["i"] == i]
        for j in range(fingerprints.SKETCHES):
            low, high = min((x[f"r{j}"], x["place"]) for x in own), max((x[f"r{j}"], x["place"]) for x in own)
            first, last = (low, high) if low[1] <= high[1] else (high, low)
            pairs_.append((i, j, first[0], last[0], low[1] <= high[1]))
    want = spark.createDataFrame(pairs_, "i int, j int, x long, y long, up boolean")
    h = F.when(F.col("up"), F.xxhash64("j", "x", "y")).otherwise(F.xxhash64("j", "x", "y", F.lit(1)))
    made = defaultdict(dict)
    for x in want.select("i", "j", F.substring(F.lower(F.lpad(F.hex(h), 16, "0")), 1, 8).alias("t")).collect():
        made[x["i"]][x["j"]] = x["t"]
    assert got == {i: ",".join(made[i][j] for j in range(fingerprints.SKETCHES)) for i in range(len(texts))}


def test_fingerprints_bear_shifts_in_long_runs(spark):
    r = np.random.default_rng(9)
    run = "".join(r.choice(list("abcdefghij0123456789"), 4000))
    other = "".join(r.choice(list("abcdefghij0123456789"), 4000))
    df = spark.createDataFrame(list(enumerate([run, "x" + run, run[:2000] + "y" + run[2000:], other])), "i int, text string")
    fp = [x["fingerprint"].split(",") for x in fingerprints.fingerprints(df, "i").orderBy("i").collect()]
    like = lambda a, b: sum(x == y for x, y in zip(fp[a], fp[b], strict=True)) / 32
    assert like(0, 1) > 0.9 and like(0, 2) > 0.9 and like(0, 3) < 0.1


def test_fingerprints_odd_rows(odd):
    assert fingerprints.edit_probe(odd).count() == len(ODD)
    assert fingerprints.edit_probe(odd.limit(0)).count() == 0


def test_toxicity(spark, sf):
    docs = spark.read.parquet("/root/testdata/sf0.01/documents.parquet")
    labels = spark.read.parquet("/root/testdata/sf0.01/labels.parquet")
    held = F.col("doc_id") % 4 == 0
    model = toxicity.fit(docs, labels.where(~held))
    assert (np.diff(model.thresholds) > 0).all()
    got = toxicity.score(docs, model).join(labels.where(held).select("doc_id", F.col("toxic").alias("y")), "doc_id").collect()
    right = sum(r["toxic"] == bool(r["y"]) for r in got)
    assert right >= 0.95 * len(got)
    assert all(0 <= r["severity"] <= 3 for r in got)


def test_toxicity_odd_rows(spark, odd):
    none = spark.createDataFrame([], "doc_id long, quality int, toxic int")
    out = toxicity.score(odd, toxicity.fit(odd, none))
    assert out.columns[:7] == odd.columns and out.count() == len(ODD) and out.where("toxic").count() == 0
    labels = spark.createDataFrame([(1, 1), (2, None), (None, 1), (6, 0), (7, 1), (7, 0)], "doc_id long, toxic int")
    assert toxicity.score(odd.limit(0), toxicity.fit(odd, labels)).count() == 0


def test_scores_against_brute_force(spark):
    toxic, fine = ["vile", "nasty", "awful", "rotten"], ["kindly", "garden", "morning", "river"]
    r = np.random.default_rng(4)
    rows = []
    for i in range(400):
        ws = list(r.choice(["the", "and", "house", "walk", "green"], 12)) + (list(r.choice(toxic, r.integers(1, 9))) if i % 2 else list(r.choice(fine, 3)))
        rows.append((i, " ".join(r.permutation(ws)), i % 2))
    df = spark.createDataFrame(rows, "doc_id long, text string, toxic int")
    model = toxicity.fit(df, df.select("doc_id", "toxic"))
    weight = dict(zip(model.keys.tolist(), model.weights.tolist(), strict=True))
    assert min(weight.values()) < 0 < max(weight.values())  # features of both signs
    hasher = toxicity._hasher()

    def hashes(word):
        b = np.frombuffer(word.encode(), np.uint8)
        one = lambda part, salt: int(hasher.words(b, np.array([0]), np.array([len(part)]))[0]) ^ salt
        return [one(word, 0)] + [one(word[:n], salt) for n, salt in ((4, 0x5851F42D4C957F2D), (5, 0x14057B7EF767814F)) if len(word) > n]

    for x in toxicity.score(df, model).collect():
        counts = Counter(h for word in x["text"].split() for h in hashes(word) if h in weight)
        z = sum(weight[h] * np.log1p(n) for h, n in counts.items())
        severity = sum(1 / (1 + np.exp(t - z)) for t in model.thresholds)
        assert abs(x["severity"] - severity) < 1e-5 and x["toxic_in"] == int(x["toxic"])
    graded = toxicity.fit(df, df.select("doc_id", (F.col("toxic") * (1 + F.col("doc_id") % 3)).alias("toxic")))
    assert len(graded.thresholds) == 3 and graded.rows == 400


def test_slopes_against_differences():
    r = np.random.default_rng(8)
    n, m = 40, 6
    row, place = np.nonzero(r.random((n, m)) < 0.5)
    x, grade, weight = r.random(len(row)), r.integers(0, 4, n), r.random(n) + 0.5
    w, raw = r.normal(0, 1, m), np.array([0.3, -0.2, 0.1])
    loss = lambda w, raw: toxicity.loss_and_slopes(row, place, x, grade, weight, w, raw, 0.01)[0]
    _, d_w, d_raw = toxicity.loss_and_slopes(row, place, x, grade, weight, w, raw, 0.01)
    step = 1e-6
    for k in range(m):
        assert abs((loss(w + step * np.eye(m)[k], raw) - loss(w - step * np.eye(m)[k], raw)) / (2 * step) - d_w[k]) < 1e-6
    for k in range(3):
        assert abs((loss(w, raw + step * np.eye(3)[k]) - loss(w, raw - step * np.eye(3)[k])) / (2 * step) - d_raw[k]) < 1e-6


def test_ordinal_fit_recovers_order():
    r = np.random.default_rng(2)
    n = 3000
    x = r.poisson(1.5, (n, 3))
    z = np.log1p(x) @ np.array([3.0, -2.0, 0.0]) + r.logistic(size=n)
    grade = np.digitize(z, [0, 1.5, 3])
    row, place = np.nonzero(x)
    w, theta = toxicity.fit_ordinal(row, place, x[row, place], grade, 3, ridge=1e-5)
    assert w[0] > 1 and w[1] < -0.7 and abs(w[2]) < 0.6 and (np.diff(theta) > 0).all()


def links_of(rows):
    x = {}
    for i, label, v in rows:
        if label is not None and v and all(a is not None and np.isfinite(a) for a in v) and any(v):
            a = np.array(v, float)
            x[i] = (label, a / np.linalg.norm(a))
    return {i: {j for j, (m, b) in x.items() if j != i and m == k and len(a) == len(b) and a @ b >= 0.93} for i, (k, a) in x.items()}


def test_vectors(spark):
    r = np.random.default_rng(6)
    rows = []
    for i in range(3000):
        if i < 1300:  # one large group, more than a unit of work holds
            v = np.ones(16) + r.normal(0, 0.08, 16)
        elif i < 1500:
            v = np.ones(16) + r.normal(0, 0.25, 16)
        else:
            v = r.normal(0, 1, 16) if i % 2 else np.array(rows[-1][2]) + r.normal(0, 0.1, 16)
        rows.append((i, 1 if i < 1500 else i % 4 // 2, [float(a) for a in v]))
    rows += [(5000, None, [1.0]), (5001, 1, None), (5002, 1, []), (5003, 1, [0.0] * 16), (5004, 1, [None] + [1.0] * 15), (5005, 1, [float("nan")] + [1.0] * 15), (5006, 1, [float("inf")] + [1.0] * 15)]
    rows += [(6000, 9, [1.0, 2.0]), (6001, 9, [1.0, 2.0]), (6002, 9, [2.0, 4.0]), (6003, 9, [-1.0, 5.0])]
    df = spark.createDataFrame(rows, "vec_id long, label int, embedding array<double>").repartition(5)
    got = {x["vec_id"]: x for x in vectors.near_vectors(df).collect()}
    assert len(got) == len(rows)
    want = links_of(rows)
    total = sum(map(len, want.values()))
    found = sum(x["n_links"] for x in got.values())
    assert 0.98 * total <= found <= total
    assert all(got[i]["n_links"] <= len(want.get(i, ())) for i in got)
    assert all((got[i]["n_links"], got[i]["component_id"], got[i]["kept"]) == (0, i, True) for i in range(5000, 5007))
    assert [(got[i]["n_links"], got[i]["component_id"]) for i in range(6000, 6004)] == [(2, 6000)] * 3 + [(0, 6003)]
    assert vectors.near_vectors(df.limit(0)).count() == 0


def test_vectors_compares_all_where_search_falls_short(spark, monkeypatch):
    r = np.random.default_rng(8)
    rows = [(i, i % 2, [float(a) for a in (np.ones(8) + r.normal(0, 0.3, 8))]) for i in range(1500)]
    df = spark.createDataFrame(rows, "vec_id long, label int, embedding array<double>").repartition(3)
    monkeypatch.setattr(vectors, "OVERLAP", vectors.MOST_OVERLAP)
    monkeypatch.setattr(vectors, "CAP", 256)
    true, seen = vectors.audit_recall, []

    def audit(*args):
        seen.append(true(*args))
        return 0.5 if len(seen) == 1 else seen[-1]

    monkeypatch.setattr(vectors, "audit_recall", audit)
    got = {x["vec_id"]: x["n_links"] for x in vectors.near_vectors(df).collect()}
    assert len(seen) == 2 and seen[1] == 1.0
    assert got == {i: len(x) for i, x in links_of(rows).items()}


def test_audit_counts_small_groups(spark):
    # One query with all of its 1000 links, nine with none of their two: by links alone this is a recall of 0.98.
    e = np.eye(10)
    reps = spark.createDataFrame([(i, "a", e[i].tobytes(), 1) for i in range(10)] + [(100 + i, "a", e[i].tobytes(), 1000 if i == 0 else 2) for i in range(10)], "rid long, label string, x binary, n long")
    counts = spark.createDataFrame([(0, 1000)] + [(100 + i, 1) for i in range(10)], "rid long, links long")
    assert vectors.audit_recall(reps, counts, 0.93) < 0.6


def test_robust_prune_spreads():
    x = np.array([[1, 0.0], [0.999, 0.04], [0.998, 0.06], [0, 1.0], [-1, 0.0]])
    x /= np.linalg.norm(x, axis=1, keepdims=True)
    out = vectors.robust_prune(x, np.array([0]), np.array([[1, 2, 3, 4, 4, 1, -1]]), degree=3)
    assert out[0].tolist() == [1, 3, 2]
    # What was pruned fills the places that stay free, nearest first.
    assert vectors.robust_prune(x, np.array([0]), np.array([[1, 2, 3, 4]]), degree=2)[0].tolist() == [1, 3]
    assert vectors.robust_prune(x, np.array([0]), np.array([[1, 2, 3, 4]]), degree=4)[0].tolist() == [1, 3, 2, 4]


def test_graph_search_walks_from_medoids():
    r = np.random.default_rng(14)
    dense = np.ones(32) + r.normal(0, 0.1, (400, 32))  # around one centre, which lies nearer to each than they to each other
    pairs_ = r.normal(0, 1, (300, 32))
    x = np.vstack([np.ones((1, 32)), dense, pairs_, pairs_ + r.normal(0, 0.1, (300, 32))])
    x /= np.linalg.norm(x, axis=1, keepdims=True)
    true = x @ x.T >= 0.93
    np.fill_diagonal(true, False)
    starts = vectors.medoids(x)
    found = vectors.search(x, vectors.build(x), starts, 0.93, vectors.BEAM)
    assert len(starts) <= 9 and not (found & ~true).any()
    share = (found & true).sum(1)[true.any(1)] / true.sum(1)[true.any(1)]
    assert share.mean() >= 0.98 and (found & true).sum() >= 0.99 * true.sum()
    # Without edges a search sees its starting points only.
    alone = vectors.search(x, np.full((len(x), 4), -1), starts, 0.93, vectors.BEAM)
    assert alone.sum() <= true[starts].sum() * 2


def test_vectors_odd_ids(spark):
    v = [1.0, 2.0, 3.0]
    rows = [(None, 1, v, 7), (None, 1, v, 7), (4, 1, v, 7), (4, 1, v, 7), (2, 1, [-1.0, 0.0, 0.0], 7), (3, None, v, 7)]
    df = spark.createDataFrame(rows, "vec_id long, label int, embedding array<double>, kept int")
    got = Counter((r["vec_id"], r["n_links"], r["component_id"], r["kept"]) for r in vectors.near_vectors(df).collect())
    assert got == Counter({(4, 3, 4, True): 1, (4, 3, 4, False): 1, (None, 3, 4, False): 2, (2, 0, 2, True): 1, (3, 0, 3, True): 1})


def applied(spark, odd, name):
    """Each operator on a table, as its callers use it."""
    ranks, multi = public_tokenizers.path("byte_bpe_50k.tiktoken"), public_tokenizers.path("byte_bpe_multi_50k.tiktoken")
    labels = spark.createDataFrame([(1, 1), (6, 0)], "doc_id long, toxic int")
    return {
        "toxicity": lambda d: toxicity.score(d, toxicity.fit(d, labels)),
        "sharding": sharding.shard_documents,
        "secrets": lambda d: secret_scan.scan_secrets(d, secret_scan.new_ledger(spark)),
        "substring": substring.remove_repeats,
        "fingerprints": fingerprints.edit_probe,
        "bpe": lambda d: bpe.encode_documents(d, multi),
        "packing": lambda d: packing.pack(packing.pieces(d, ranks, public_tokenizers.PATTERN)),
        "neardup": neardup.near_duplicates,
        "pii": pii.find_pii,
        "vectors": lambda d: vectors.near_vectors(d.selectExpr("doc_id AS vec_id", "1 AS label", "array(1.0D, 2.0D) AS embedding")),
    }[name](odd)


OPERATORS = ["toxicity", "sharding", "secrets", "substring", "fingerprints", "bpe", "packing", "neardup", "pii", "vectors"]


@pytest.mark.parametrize("name", OPERATORS)
def test_empty_tables(spark, odd, name):
    out = applied(spark, odd.limit(0), name)
    assert out.collect() == [] and len(set(out.columns)) == len(out.columns)


@pytest.mark.parametrize("name", ["toxicity", "secrets", "substring", "bpe", "neardup", "pii"])
def test_clashing_names(spark, odd, name):
    added = [c for c in applied(spark, odd.select("doc_id", "text").limit(0), name).columns if c not in ("doc_id", "text")]
    rows = odd.select("doc_id", "text", *[F.lit("own").alias(c) for c in added], F.lit("too").alias(added[0] + "_in"))
    out = applied(spark, rows, name)
    assert len(set(out.columns)) == len(out.columns) and set(added) <= set(out.columns)
    first = out.first()
    assert [first[c + "_in"] for c in added[1:]] == ["own"] * (len(added) - 1) and first[added[0] + "_in"] == "too" and first[added[0] + "_in_in"] == "own"
    assert out.count() == len(ODD)


OUTSIDE = """
import sys
sys.path.insert(0, {root!r})
from pyspark.sql import SparkSession
spark = SparkSession.builder.master("local[2]").config("spark.ui.enabled", "false").config("spark.sql.shuffle.partitions", "2").config("spark.checkpoint.dir", {shared!r}).getOrCreate()
import pyspark.sql.functions as F
import __spark_entry__
assert spark.range(1).mapInArrow(lambda bs: [b for b in bs if not __import__("importlib").util.find_spec("linkwalk")], "id long").count() == 1
for name in ("op1_toxicity", "op4_substring", "op6_bpe", "op7_packing", "op8_neardup", "op10_vectors", "similar_reach"):
    __spark_entry__.queries()[name](spark, {sf!r}).write.format("noop").mode("overwrite").save()
    print("ran", name, flush=True)
"""


def test_executors_need_no_copy_of_the_repository(sf, tmp_path):
    import os
    import subprocess
    import sys
    from pathlib import Path

    root = str(Path(__file__).resolve().parents[2])
    env = {k: v for k, v in os.environ.items() if k != "PYTHONPATH"}
    code = OUTSIDE.format(root=root, shared=str(tmp_path / "shared"), sf=sf)
    done = subprocess.run([sys.executable, "-c", code], cwd=tmp_path, env=env, capture_output=True, text=True, timeout=300, check=False)
    assert done.stdout.count("ran ") == 7, done.stderr[-3000:]
