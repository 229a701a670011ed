"""Operators of the llm subpackage against brute force, the public library, or planted cases, edge cases included."""

import hashlib
import re

import duckdb
import numpy as np
import pyarrow as pa
import pytest
from pyspark.sql import functions as F

from ordwork.llm import bpe_codec, decontaminate, embedding_dedup, html_extract, language_id, line_dedup, queries, simhash, suffix_dedup, token_count, url_filter
from ordwork.llm.bpe import Bpe
from ordwork.llm.components import components
from ordwork.llm.common import Scratch, table

DOCS = "doc_id long, text string, Ids string, n_words int, `N_Lines` int"


def docs_of(spark, rows):
    return spark.createDataFrame([(i, t, "x", 1, 2) for i, t in rows], DOCS).repartition(3)


@pytest.fixture(scope="module")
def documents(spark, sf):
    return table(spark, sf, "documents").select("doc_id", "text")


@pytest.fixture(scope="module")
def rows(documents):
    return [tuple(r) for r in documents.collect()]


@pytest.fixture(scope="module")
def bpe():
    return Bpe(queries.tokenizer_path())


@pytest.fixture(scope="module")
def library():
    from tokenizers import Tokenizer

    return Tokenizer.from_file(queries.tokenizer_path())


ODD = ["", None, "a", "aaaaaaa aaaa   \n\n  x<|endoftext|> y", "日本語のテキスト　全角", "꟏₁ 'S 's don't", "é" * 3000, "z\x00\x85\x1c ​﻿", "0x" * 5000, "𝔘𝔫𝔦 😀😀", "<|endoftext|><|endoftext|>", "A" * 4097]


# --- sql oracles ---


@pytest.mark.parametrize("name", ["op1_line_dedup", "op3_embedding_dedup", "op4_decontamination"])
def test_sql(spark, sf, name):
    con = duckdb.connect()
    for t in ("documents", "benchmark", "embeddings"):
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM '{sf}/{t}.parquet'")
    found = con.execute(queries.oracle_sql()[name])
    names = [x[0] for x in found.description]
    frame = queries.queries()[name](spark, sf)
    assert sorted(frame.columns) == sorted(names)
    assert sorted(map(tuple, frame.select(*names).collect())) == sorted(found.fetchall())


# --- 1 line dedup ---


def test_line_dedup_cases(spark):
    block = "one\ntwo\nthree"
    given = [(1, block), (2, f"intro\n{block}\n\nend"), (3, "one\ntwo"), (4, None), (5, ""), (None, block), (6, " one \n\ntwo\r\nthree\nfour"), (7, "a\n" * 6)]
    got = {r["doc_id"]: r for r in line_dedup.dedup_lines(docs_of(spark, given)).collect()}
    assert got[1]["text"] == block and got[2]["text"] == "intro\n\nend" and got[3]["text"] == "one\ntwo"
    assert got[4]["text"] is None and got[5]["text"] == "" and got[None]["text"] == block
    assert got[6]["text"] == "\nfour" and got[6]["n_removed"] == 3 and got[6]["n_lines"] == 4
    assert got[7]["text"] == "a\n"  # overlapping occurrences: all but the first line
    assert line_dedup.dedup_lines(docs_of(spark, given).limit(0)).count() == 0


def test_line_dedup_hot_window(spark):
    rows = [(i, f"head {i}\nx\ny\nz") for i in range(400)]
    got = line_dedup.dedup_lines(docs_of(spark, rows))
    assert got.where("n_removed = 3").count() == 399


def brute_lines(rows):
    """(id, text) -> places of the lines that go; documents are pairs of an id and a text, ordered by id, then by the hash of the text."""
    seen, out = {}, {}
    def windows(text):
        filled = [(i, x.strip(" \t\r")) for i, x in enumerate(text.split("\n")) if x.strip(" \t\r")]
        return [([i for i, _ in filled[k : k + 3]], tuple(x for _, x in filled[k : k + 3])) for k in range(len(filled) - 2)]

    for i, t, h in sorted({(i, t, h) for i, t, h in rows}, key=lambda r: (r[0], r[2])):
        gone = out.setdefault((i, t), set())
        for at, w in windows(t):
            if w in seen:
                gone.update(at)
            seen.setdefault(w, (i, h, at[0]))
    return out


def test_line_dedup_repeated_ids(spark):
    """Rows of one id with different texts lose their own lines only."""
    rows = [(1, "a\nb\nc"), (7, "zz"), (7, "x\na\nb\nc"), (7, "kd\nke\nkf\nkg"), (8, "kd\nke\nkf"), (7, "x\na\nb\nc"), (9, "p\nq\nr"), (9, "o\np\nq\nr")]
    docs = docs_of(spark, rows)
    hashed = [tuple(r) for r in docs.select("doc_id", "text", F.xxhash64("text")).collect()]
    want = brute_lines(hashed)
    expected = sorted((i, "\n".join(x for k, x in enumerate(t.split("\n")) if k not in want[i, t]), len(want[i, t])) for i, t in rows)
    got = line_dedup.dedup_lines(docs)
    assert sorted(tuple(r) for r in got.select("doc_id", "text", "n_removed").collect()) == expected
    assert got.where("n_removed > n_lines").count() == 0 and ("zz" in [r["text"] for r in got.collect()])


# --- 2 url filter ---


def expect_rule(host, path):
    best = (None, None)
    for text, verdict in queries.RULES:
        h, _, p = text.partition("/")
        if (host == h or host.endswith("." + h)) and path.startswith("/" + p) and (best[0] is None or len(text) > len(best[0])):
            best = (text, verdict)
    return best


def test_url_rules(spark, sf):
    got = queries.url_filter(spark, sf).collect()
    assert len(got) == table(spark, sf, "pages").count()
    for r in got:
        rule, verdict = expect_rule(r["host"], r["path"])
        assert r["rule"] == rule and (rule is None or r["verdict"] == verdict)


def test_url_query_follows_the_contract(spark, tmp_path):
    """Rules and words of the contract, written out here."""
    urls = ["http://a.com/en/1", "http://EXAMPLE.com/en/7", "http://b.net/de/1", "http://example.net/de/8/x", "http://c.org/es/", "http://c.org/x"]
    spark.createDataFrame(list(enumerate(urls)), "page_id long, url string").write.parquet(f"{tmp_path}/pages.parquet")
    spark.createDataFrame([], "doc_id long, quality int, toxic int").write.parquet(f"{tmp_path}/labels.parquet")
    got = sorted((r["page_id"], r["rule"], r["verdict"]) for r in queries.url_filter(spark, str(tmp_path)).collect())
    assert [x[1:] for x in got] == [("com/en/", "block"), ("example.com/en/7", "allow"), ("net/de/", "allow"), ("example.net/de/8", "block"), ("org/es/", "block"), (None, "allow")]


def brute_rules(baskets, least, confidence):
    """Token sets that say `bad` by support and confidence, without those that a smaller one is as good as."""
    from collections import Counter
    from itertools import combinations

    n, sets, bad = len(baskets), Counter(), Counter()
    for tokens, b in baskets:
        for size in range(1, len(tokens) + 1):
            for c in combinations(sorted(tokens), size):
                sets[c] += 1
                bad[c] += b
    good = {c: bad[c] / sets[c] for c in sets if bad[c] >= least * n - 1e-9 and bad[c] / sets[c] >= confidence}
    return {c for c, x in good.items() if not any(set(d) < set(c) and y >= x for d, y in good.items())}


def test_url_query_mines_planted_associations(spark, tmp_path):
    """The registered query at its own thresholds on tables with an association: rules and verdicts are those of brute force."""
    pages, labels = [], []
    for k in range(400):
        shop = k % 4 == 0
        pages.append((k, f"https://www.{'shop' if shop else 'news'}{k % 3}.info/{'deal' if shop else 'story'}/{k}" + ("?ref=1" if k % 8 == 0 else "")))
        if k % 2 == 0:
            labels.append((k, 0 if shop and k % 20 else 1, 0))
    spark.createDataFrame(pages, "page_id long, url string").write.parquet(f"{tmp_path}/pages.parquet")
    spark.createDataFrame(labels, "doc_id long, quality int, toxic int").write.parquet(f"{tmp_path}/labels.parquet")
    frame = spark.createDataFrame(pages, "page_id long, url string").select("page_id", url_filter.tokens_of(F.col("url")).alias("t"))
    tokens = {r["page_id"]: set(r["t"]) for r in frame.collect()}
    baskets = [(tokens[i], q == 0) for i, q, _ in labels]
    rules = brute_rules(baskets, max(url_filter.MIN_SUPPORT, url_filter.MIN_COUNT / len(baskets)), url_filter.MIN_CONFIDENCE)
    assert rules
    got = {r["page_id"]: r for r in queries.url_filter(spark, str(tmp_path)).collect()}
    assert {i: got[i]["mined"] for i in tokens} == {i: sum(set(c) <= t for c in rules) for i, t in tokens.items()}
    assert all((got[i]["verdict"] == "block") == (got[i]["mined"] > 0) for i in tokens if got[i]["rule"] is None)
    assert 0 < sum(r["verdict"] == "block" for r in got.values()) < len(got)


def test_url_parts_and_mining(spark):
    urls = [(f"http://bad.site{k % 3}.com/buy/{k}?ref=1", True) for k in range(60)] + [(f"https://good.site{k % 3}.com/read/{k}", False) for k in range(60)]
    labelled = spark.createDataFrame(urls, "url string, bad boolean")
    mined = url_filter.mine(labelled, "url", "bad")
    assert mined.count() > 0
    pages = spark.createDataFrame([(1, "HTTP://BAD.Site1.com/Buy/9#x"), (2, "https://good.site2.com/read/1"), (3, None), (4, "no-scheme.com/x"), (5, "http://a?b"), (6, "https://x.example.com/en/7/z")], "page_id long, url string")
    got = {r["page_id"]: r for r in url_filter.judge(pages, [url_filter.Rule(*r) for r in queries.RULES], mined).collect()}
    assert got[1]["verdict"] == "block" and got[1]["host"] == "bad.site1.com" and got[1]["path"] == "/Buy/9"
    assert got[2]["verdict"] == "allow" and got[3]["host"] == "" and got[4]["path"] == "" and got[5]["host"] == "a"
    assert (got[6]["rule"], got[6]["verdict"]) == ("example.com/en/7", "allow")
    # a rule fits exactly the urls that hold all its tokens
    rules = [set(r["tokens"]) for r in mined.collect()]
    held = {r["url"]: set(r["t"]) for r in pages.where("url is not null").select("url", url_filter.tokens_of(F.col("url")).alias("t")).collect()}
    found = {r["url"]: r["mined"] for r in url_filter.matching(pages, "url", mined).collect()}
    assert found == {u: n for u, t in held.items() if (n := sum(x <= t for x in rules))}
    assert url_filter.judge(pages.limit(0), [], mined).count() == 0
    assert url_filter.mine(labelled.limit(0), "url", "bad").count() == 0


# --- 3 embeddings ---


def brute_vectors(items, limit=0.9):
    ok = [(i, np.array(v, float)) for i, v in items if v is not None and None not in v and np.isfinite(np.array(v, float)).all() and np.any(np.array(v, float))]
    ids = [i for i, _ in ok]
    ok = [(i, v / np.abs(v).max()) for i, v in ok]
    x = np.stack([v / np.linalg.norm(v) for _, v in ok])
    link = x @ x.T >= limit
    n = {i: int(link[k].sum()) - 1 for k, i in enumerate(ids)}
    root = dict(zip(ids, ids, strict=True))
    for _ in ids:
        for a in range(len(ids)):
            root[ids[a]] = min(root[ids[b]] for b in np.flatnonzero(link[a]))
    return {i: (n.get(i, 0), root.get(i, i)) for i, _ in items}


@pytest.mark.parametrize("settings", [{}, {"block": 7}, {"leaf": 40}])
def test_embeddings(spark, settings):
    rng = np.random.default_rng(5)
    centers = rng.standard_normal((12, 16))
    items = [(i, [float(x) for x in centers[i % 12] + rng.standard_normal(16) * rng.choice([0.05, 0.5])]) for i in range(150)]
    items += [(200 + k, items[3][1]) for k in range(40)] + [(300, None), (301, [0.0] * 16), (302, [float("nan")] + [1.0] * 15), (303, [None] + [1.0] * 15), (304, [1e300] * 16)]
    frame = spark.createDataFrame([(i, v, 0) for i, v in items], "vec_id long, embedding array<double>, label int")
    got = {r["vec_id"]: (r["n_links"], r["component_id"]) for r in embedding_dedup.near_vectors(frame, **settings).collect()}
    want = brute_vectors(items)
    if "leaf" in settings:  # many leaves: links may be missed, but none is made up or counted twice
        found = sum(n for n, _ in got.values())
        assert 0.9 * sum(n for n, _ in want.values()) <= found and all(got[i][0] <= want[i][0] for i in want)
    else:
        assert got == want
    assert embedding_dedup.near_vectors(frame.limit(0)).count() == 0


def planted_vectors(n, pairs, dims, seed):
    """n random unit vectors; the first ``pairs`` have a partner at a cosine just above the limit; ids are shuffled."""
    rng = np.random.default_rng(seed)
    x = rng.standard_normal((n - pairs, dims))
    x /= np.linalg.norm(x, axis=1)[:, None]
    noise = rng.standard_normal((pairs, dims))
    noise -= (noise * x[:pairs]).sum(1)[:, None] * x[:pairs]
    noise /= np.linalg.norm(noise, axis=1)[:, None]
    cos = rng.uniform(0.901, 0.95, pairs)[:, None]
    ids = rng.permutation(n)
    return ids, np.concatenate([x, cos * x[:pairs] + np.sqrt(1 - cos**2) * noise]), {frozenset((int(ids[i]), int(ids[n - pairs + i]))) for i in range(pairs)}


@pytest.mark.parametrize(("n", "pairs", "settings"), [(50_000, 5_000, {}), (6_000, 600, {"sample": 300, "leaf": 40, "block": 100})])
def test_embeddings_recall(spark, tmp_path, n, pairs, settings):
    """Pairs close to the limit are found, none is made up; the second table overfills the leaves of its sample, which are split further."""
    import pandas as pd

    ids, x, planted = planted_vectors(n, pairs, 64, 3)
    pd.DataFrame({"vec_id": ids, "embedding": list(x)}).to_parquet(tmp_path / "v.parquet")
    rows = embedding_dedup.near_vectors(spark.read.parquet(str(tmp_path / "v.parquet")), **settings).where("n_links > 0 or vec_id <> component_id").collect()
    assert all(r["n_links"] == 1 for r in rows)
    found = {frozenset((r["vec_id"], r["component_id"])) for r in rows if r["vec_id"] != r["component_id"]}
    print("recall", len(found) / pairs)
    assert found <= planted and len(found) >= 0.95 * pairs
    assert len(rows) == 2 * len(found)


def test_embeddings_rows_dealt():
    """A vector lies in fewer than twelve leaves of the forest for 50,000 vectors."""
    x = planted_vectors(20_000, 0, 64, 4)[1]
    forest = embedding_dedup.Forest(x, 50_000, embedding_dedup.LEAF, 0.9, embedding_dedup.MISS)
    assert len(forest.place(x)[0]) < 12 * len(x)


def test_embeddings_lengths_and_names(spark):
    """Vectors of every length are compared with those of their length; other columns may have any name."""
    rng = np.random.default_rng(8)
    items = []
    for k, dims in enumerate([8] * 30 + [5] * 20 + [1] * 3 + [3]):
        items.append((k, [float(x) for x in np.eye(dims)[k % dims] + rng.standard_normal(dims) * 0.1]))
    items += [(100, []), (101, None)]
    frame = spark.createDataFrame([(i, v, 1, 2, "x") for i, v in items], "vec_id long, embedding array<double>, leaf int, n int, component_id string")
    got = {r["vec_id"]: (r["n_links"], r["component_id"]) for r in embedding_dedup.near_vectors(frame).collect()}
    want = {}
    for dims in (8, 5, 1, 3):
        want |= brute_vectors([(i, v) for i, v in items if v and len(v) == dims])
    assert got == want | {100: (0, 100), 101: (0, 101)}

# --- 4 decontamination ---

WORD = re.compile(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+")


def words(text):
    return WORD.findall("".join(c.lower() if "A" <= c <= "Z" else c for c in text or ""))


def brute_hits(docs, items):
    out = {}
    windows = {}
    for i, t in items:
        w = words(t)
        for s in range(max(len(w) - 9, 1) if w else 0):
            windows.setdefault(tuple(w[s : s + 10]), set()).add(str(i))
    for i, t in docs:
        w, hit, found = words(t), set(), set()
        for s in range(len(w)):
            for n in range(1, 11):
                if s + n <= len(w) and (got := windows.get(tuple(w[s : s + n]))):
                    hit |= set(range(s, s + n))
                    found |= got
        out[i] = (len(w), len(hit), sorted(found))
    return out


def test_decontamination_cases(spark):
    ten = "Alpha beta gamma delta epsilon zeta eta theta iota KAPPA"
    items = [(10, ten), (9, f"{ten} lambda"), (3, "short item Ünit"), (4, "lone"), (5, ""), (6, None), (7, "...")]
    docs = [(1, f"start, {ten.lower()}! end"), (2, "short  ITEM--Ünit here"), (3, "short item ünit"), (4, None), (5, ""), (6, f"x {ten} lambda y short item Ünit lone lone"), (7, " ".join(["lone"] * 3000)), (8, "alpha beta gamma delta epsilon zeta eta theta iota"), (None, ten)]
    frame, bench = docs_of(spark, docs), spark.createDataFrame(items, "item_id long, text string")
    got = {r["doc_id"]: (r["n_words"], r["n_hit"], list(r["items"])) for r in decontaminate.report(frame, bench).collect()}
    assert got == brute_hits(docs, items)
    assert {r["doc_id"] for r in decontaminate.remove_documents(frame, bench).collect()} == {3, 4, 5, 8}
    cut = {r["doc_id"]: r["text"] for r in decontaminate.remove_spans(frame, bench).collect()}
    assert words(cut[1]) == ["start", "end"] and cut[3] == "short item ünit" and cut[4] is None
    assert decontaminate.report(frame, bench.limit(0)).where("n_hit > 0").count() == 0
    assert decontaminate.report(frame.limit(0), bench).count() == 0
    again = decontaminate.report(frame.union(frame), bench)
    assert again.count() == 2 * len(docs)


# --- 5 and 7 tokens ---


def test_tokens_match_the_library(spark, rows, bpe, library):
    texts = [(i, t) for i, t in rows[:80]] + [(1000 + k, t) for k, t in enumerate(ODD)]
    frame = docs_of(spark, texts)
    ids = {i: library.encode(t or "", add_special_tokens=False).ids for i, t in texts}
    for r in token_count.count_tokens(frame, queries.tokenizer_path()).collect():
        assert r["n_tokens"] == len(ids[r["doc_id"]])
    for r in bpe_codec.digests(frame, queries.tokenizer_path()).collect():
        own = ids[r["doc_id"]]
        assert r["ids_sha256"] == hashlib.sha256(",".join(map(str, own)).encode()).hexdigest()
        assert r["decoded_sha256"] == hashlib.sha256(library.decode(own, skip_special_tokens=False).encode()).hexdigest()
    coded = bpe_codec.encode(frame, queries.tokenizer_path())
    assert {r["doc_id"]: r["ids"] for r in coded.collect()} == ids and coded.where("not exact").count() == 0
    assert {r["doc_id"]: r["decoded"] for r in bpe_codec.decode(coded, queries.tokenizer_path()).collect()} == {i: t or "" for i, t in texts}
    assert bpe_codec.encode(frame.limit(0), queries.tokenizer_path()).count() == 0


def test_whole_tokens_are_proved(bpe, library):
    whole = bpe.whole_tokens()
    some = list(whole)[::97]
    assert all(library.encode(w, add_special_tokens=False).ids == [whole[w]] for w in some) and len(whole) > 40_000


def test_table_of_words_may_be_emptied(bpe, library, monkeypatch):
    monkeypatch.setattr(bpe_codec, "KEPT_WORDS", 2)
    monkeypatch.setattr(token_count, "KEPT_WORDS", 2)
    codec, count = bpe_codec.Digests(bpe), token_count.Counter(bpe, {})
    for text in ("strange wordings", "other neologisms altogether", "strange wordings"):
        ids = library.encode(text, add_special_tokens=False).ids
        assert codec([text])[0][0] == len(ids) == count([text])[0]


# --- 6 suffix dedup ---


def brute_repeats(docs, length=100):
    seen, out = set(), {}
    for i, t in sorted(docs, key=lambda r: r[0]):
        raw = (t or "").encode()
        gone = np.zeros(len(raw), bool)
        for k in range(len(raw) - length + 1):
            x = raw[k : k + length]
            if x in seen:
                gone[k : k + length] = True
            seen.add(x)
        kept = bytes(np.frombuffer(raw, np.uint8)[~gone])
        out[i] = (len(raw), int(gone.sum()), int((gone[1:] & ~gone[:-1]).sum()) + int(len(raw) > 0 and gone[0]), hashlib.sha256(kept).hexdigest())
    return out


@pytest.mark.parametrize("portion", [750_000, 1_500])
def test_suffix_dedup(spark, rows, portion, monkeypatch):
    import random

    monkeypatch.setattr(suffix_dedup, "PORTION", portion)
    rnd = random.Random(2)
    base = "".join(rnd.choice("ab c") for _ in range(2500))
    docs = [(10_000 + k, base[rnd.randrange(1200) :][: rnd.randrange(50, 1200)] + "x" * rnd.choice([0, 99, 100, 101, 250])) for k in range(40)]
    docs += [(20_000, None), (20_001, ""), (20_002, "é" * 300), (20_003, "ab" * 2000), (20_004, base * 2), (20_005, base[:99]), (20_006, base[:100])] + (rows if portion > 10_000 else [])
    got = {r[0]: tuple(r)[1:] for r in suffix_dedup.digest(docs_of(spark, docs)).collect()}
    assert got == brute_repeats(docs)


@pytest.mark.parametrize("hot", [500_000, 1])
def test_suffix_dedup_repeated_ids_and_hot_buckets(spark, hot, monkeypatch):
    """Documents are (id, text), ordered by id, then by the hash of the text; buckets beyond HOT take the aggregates' way."""
    monkeypatch.setattr(suffix_dedup, "HOT", hot)
    word = lambda k, n: "".join(hashlib.sha256(f"{k}-{j}".encode()).hexdigest() for j in range(n))
    rows = [(1, word(1, 4)), (2, "<" + word(1, 3)), (3, word(2, 4)), (3, word(1, 4) + "!"), (3, "short"), (4, word(2, 2) + word(1, 2)), (3, "short"), (5, word(9, 3))]
    rows += [(10 + k, f"{k:05d}" + word(5, 2) + f"{k * 7:05d}") for k in range(30)]
    docs = docs_of(spark, rows)
    order = {(r[0], r[1]): n for n, r in enumerate(sorted({tuple(r) for r in docs.select("doc_id", "text", F.xxhash64("text")).collect()}, key=lambda r: (r[0], r[2])))}
    want = brute_repeats([(n, t) for (_, t), n in order.items()])
    got = suffix_dedup.digest(docs).collect()
    assert sorted(tuple(r) for r in got) == sorted((i, *want[order[i, t]]) for i, t in rows)
    assert all(r["n_removed"] <= r["n_bytes"] for r in got)


def test_suffix_dedup_crowded_pointers_store_no_rows(spark, monkeypatch):
    """Pointers that very many runs share keep to the windows: the same bytes go, and candidates aren't stored to be ranked."""
    passage = "".join(chr(97 + (k * k * 7 + k // 3) % 26) for k in range(180))
    docs = [(k, f"{k} own start {k * 7919} " + passage + f" own end {k * 104729} " + (passage[:140] if k % 3 else "")) for k in range(30)]
    want = sorted(map(tuple, suffix_dedup.digest(docs_of(spark, docs)).collect()))
    names, save = [], Scratch.save
    monkeypatch.setattr(Scratch, "save", lambda self, frame, name="t", *a: names.append(name) or save(self, frame, name, *a))
    monkeypatch.setattr(suffix_dedup, "HOT", 1)
    assert sorted(map(tuple, suffix_dedup.digest(docs_of(spark, docs)).collect())) == want and sum(r[2] for r in want) > 0
    assert "found" not in names and "one" not in names
    monkeypatch.setattr(suffix_dedup, "HOT_PORTIONS", 0)
    assert sorted(map(tuple, suffix_dedup.digest(docs_of(spark, docs)).collect())) == want and {"found", "one"} <= set(names)


def test_suffix_spans_and_edges(spark):
    text = hashlib.sha256(b"x").hexdigest() * 2 + "ab"
    text = text[:64] + hashlib.sha256(b"y").hexdigest() + "ab"
    got = {r["doc_id"]: r for r in suffix_dedup.remove_repeats(docs_of(spark, [(1, text), (2, "--" + text + "--")])).collect()}
    assert [tuple(s) for s in got[2]["spans"]] == [(2, 132)] and bytes(got[2]["kept"]) == b"----" and not got[1]["spans"]
    null_id = docs_of(spark, [(None, text), (1, text)])
    assert {r["n_removed"] for r in suffix_dedup.digest(null_id).collect()} == {0}
    assert suffix_dedup.digest(null_id.limit(0)).count() == 0


# --- 8 html ---


def page(body, extra=""):
    return f"<!DOCTYPE html><html><head><title>t</title><script>var a='<p>no</p>';</script></head><body><nav><ul><li><a href='/x'>menu</a></li></ul></nav>{extra}<article>{body}</article><footer>foot</footer></body></html>"


def test_html(spark):
    ad = "<div class='ad'>buy</div>"
    pages = [
        (1, "http://a.com/1", page("<h1>Title &amp; more</h1><p>One  two\nthree</p><p>Four</p>", ad), "Title & more\nOne two three\nFour"),
        (2, "http://a.com/2", page("<h1>T</h1><p>x</p><p>y</p><p>z</p><div class='comments'><p>nice</p></div>", ad), "T\nx\ny\nz"),
        (3, "http://a.com/3", page("<h1>T</h1><p>a <b>bold</b> word<br><p>unclosed<aside>side</aside>", ""), "T\na bold word\nunclosed"),
        (4, "http://a.com/4", None, ""), (5, None, page("<p>q&eacute;</p>"), "qé"), (6, "http://a.com/6", "", ""), (7, "http://b.org/", "just text", "just text"),
        (8, "http://a.com/8", page("<p>cut &copy") [:-60], None),
    ]
    frame = spark.createDataFrame([p[:3] for p in pages], "page_id long, url string, html string")
    got = {r["page_id"]: r["text"] for r in html_extract.main_text(frame).collect()}
    for i, _, _, want in pages:
        if want is not None:
            assert got[i] == want, i
    assert html_extract.main_text(frame.limit(0)).count() == 0


def test_html_mixed_layouts():
    pages = [f"<body><article><p>in {k}</p></article></body>" if k % 2 else f"<body><div><p>plain {k}</p></div></body>" for k in range(6)]
    wrapper = html_extract.Wrapper(html_extract.infer(pages))
    assert wrapper.fits([s for s, _ in html_extract.tokens(pages[0])])
    assert [html_extract.extract(p, wrapper) for p in pages] == [f"in {k}" if k % 2 else f"plain {k}" for k in range(6)]


def test_html_class_words():
    alone = lambda p: html_extract.extract(p, html_extract.Wrapper(html_extract.infer([p])))
    assert alone("<body class='home has-sidebar'><main class='search-page'><article class='post comment'><p>text</p></article></main></body>") == "text"
    assert alone("<body><div id='content-header-wrap'><p>text</p></div><div class='site-footer'>foot</div></body>") == "text"
    assert alone("<body><div class='widget'><p>all there is</p></div></body>") == "all there is"


def test_html_constant_texts_are_template():
    """Without article or main, what all pages share is template and what differs is main text; the wrapper decides."""
    page = lambda k: f"<body><div><p>Welcome to our site</p></div><div><h2>Title {k}</h2><p>Words of text number {k}</p></div><div><p>Copyright all rights</p></div></body>"
    pages = [page(k) for k in range(8)]
    wrapper = html_extract.Wrapper(html_extract.infer(pages))
    assert [html_extract.extract(p, wrapper) for p in pages] == [f"Title {k}\nWords of text number {k}" for k in range(8)]
    assert html_extract.extract(page(99), wrapper) == "Title 99\nWords of text number 99"
    alone = html_extract.Wrapper(html_extract.infer(pages[:1] * 8))  # equal pages prove nothing
    assert html_extract.extract(pages[0], alone) == "Welcome to our site\nTitle 0\nWords of text number 0\nCopyright all rights"


def test_html_copies_of_one_article_stay_whole():
    text = " ".join(f"word{k}" for k in range(150))
    pages = [f"<body><article><p>{text}</p><p>copy {k}</p></article></body>" for k in range(5)]
    wrapper = html_extract.Wrapper(html_extract.infer(pages))
    assert [html_extract.extract(p, wrapper) for p in pages] == [f"{text}\ncopy {k}" for k in range(5)]


def test_html_deep_pages():
    import time

    deep = "<body>" + "<div>" * 20_000 + "x" + "</div>" * 20_000 + "</i>" * 20_000 + "</body>"
    began = time.time()
    assert html_extract.extract(deep, html_extract.Wrapper(html_extract.infer([page("<p>a</p>")]))) == "x"
    assert time.time() - began < 10  # it was beyond 40 s when paths were written out


def test_html_repeated_rows_and_other_columns(spark):
    rows = [(1, "http://a.com/1", page("<p>one</p>"), "x")] * 3 + [(2, "http://a.com/2", page("<p>two</p>"), "y")]
    got = html_extract.main_text(spark.createDataFrame(rows, "page_id long, url string, html string, Text string"))
    assert sorted(tuple(r) for r in got.select("page_id", "text").collect()) == [(1, "one")] * 3 + [(2, "two")]


def test_html_space_between_inline():
    page = "<body><article><h1><span>A</span> <span>B</span></h1><ul><li><a>one</a> <a>two</a></li></ul><blockquote><b>x</b>\n<i>y</i>z</blockquote></article></body>"
    assert html_extract.extract(page, html_extract.Wrapper(html_extract.infer([page]))) == "A B\none two\nx yz"


def test_html_given_pages(spark, sf):
    import html

    got = {r["page_id"]: r["text"] for r in html_extract.main_text(table(spark, sf, "pages")).collect()}
    for r in table(spark, sf, "pages").collect():
        inner = re.search(r"<article>(.*?)</article>", r["html"], re.S)[1]
        blocks = (" ".join(html.unescape(re.sub("<[^>]*>", "", b)).split()) for b in re.split(r"</?p>|</?h1>", inner))
        assert got[r["page_id"]] == "\n".join(b for b in blocks if b)


def test_wrapper_generalises():
    pages = ["<ul><li>a</li></ul><p>x</p>", "<ul><li>a</li><li>b</li><li>c</li></ul><p>x</p>", "<ul><li>a</li></ul><h2>n</h2><p>x</p><p>y</p>"]
    wrapper = html_extract.Wrapper(html_extract.infer(pages))
    shapes = lambda p: [s for s, _ in html_extract.tokens(p)]
    assert all(wrapper.fits(shapes(p)) for p in pages)
    assert wrapper.fits(shapes("<ul><li>a</li><li>b</li></ul><p>x</p><p>y</p><p>z</p>"))
    assert not wrapper.fits(shapes("<table><tr><td>x</td></tr></table>"))


def test_html_wrapper_takes_all_pages(spark):
    """One page of a host with another text makes a slot of its place for all, whichever page it is and however the pages are dealt."""
    one = lambda k, label: f"<body><div><p>Welcome to our site</p></div><div><h2>{label}</h2><p>Words of text number {k}</p></div></body>"
    frame = lambda rows: spark.createDataFrame(rows, "page_id long, url string, html string")
    rows = [(k, f"http://a.com/{k}", one(k, "Second part" if k == 77 else "First part")) for k in range(120)]
    for parts in (1, 5):
        got = {r["page_id"]: r["text"] for r in html_extract.main_text(frame(rows).repartition(parts)).collect()}
        assert got == {k: f"{'Second' if k == 77 else 'First'} part\nWords of text number {k}" for k in range(120)}
    # a place that few pages have is none of which the host's pages prove anything
    rows = [(k, f"http://a.com/{k}", one(k, f"Part {k}").replace("<h2>", "<table><tr><td>Offer</td></tr></table><h2>" if k % 40 == 0 else "<h2>")) for k in range(120)]
    got = {r["page_id"]: r["text"] for r in html_extract.main_text(frame(rows)).collect()}
    assert got == {k: ("Offer\n" if k % 40 == 0 else "") + f"Part {k}\nWords of text number {k}" for k in range(120)}


def test_html_many_orders_of_parts():
    """Wrappers of pages that order their parts freely stay small and fit all of them; what frames them stays template."""
    import random

    dice = random.Random(5)
    kinds = ["<p>{}</p>", "<h2>{}</h2>", "<ul><li>{}</li></ul>", "<p>a <b>{}</b> c</p>", "<table><tr><td>{}</td></tr></table>", "<p>x <a href='/'>{}</a> y <i>z</i></p>"]
    pages = [f"<body><div><p>Welcome to our site</p></div><div>{''.join(dice.choice(kinds).format(f'w{dice.random()}') for _ in range(dice.randint(3, 15)))}</div><div><p>Copyright</p></div></body>" for _ in range(400)]
    wrapper = html_extract.Wrapper(html_extract.infer(pages))
    shapes = [[s for s, _ in html_extract.tokens(p)] for p in pages]
    assert all(wrapper.fits(s) for s in shapes)
    most = max(html_extract.tally(html_extract.fold(s)).total() for s in shapes)
    assert len(html_extract.shapes_in(wrapper.parts)) <= 2 * most
    assert not any("Welcome" in t or "Copyright" in t for t in (html_extract.extract(p, wrapper) for p in pages))


def test_html_classes_merge_in_any_order():
    pages = [f"<body><p>Same</p><ul>{'<li>x</li>' * (k % 3)}</ul><div>{k % 7}</div></body>" for k in range(30)]
    whole, halves = html_extract.Classes(), [html_extract.Classes(), html_extract.Classes()]
    for k, page in enumerate(pages):
        whole.add("h", page)
        halves[k % 2].add("h", page)
    merged = html_extract.Classes()
    for half in reversed(halves):
        for key, (n, parts) in half.found.items():
            merged.merge(key, n, html_extract.parts_of(html_extract.json.dumps(parts)))
    assert merged.found == whole.found and merged.aligned() == whole.aligned() and whole.aligned()[0] == 30


# --- 9 language ---


def test_language(spark, sf):
    docs = table(spark, sf, "documents")
    model = language_id.fit(docs.where(~language_id.held_out()))
    got = language_id.predict(docs, model).join(docs.select("doc_id", "lang"), "doc_id").where(language_id.held_out()).collect()
    assert sum(r["lang_pred"] == r["lang"] for r in got) >= 0.95 * len(got) and all(0 <= r["score"] <= 1 for r in got)
    odd = docs_of(spark, [(1, None), (2, ""), (3, "12345 !!"), (4, "x"), (5, "the " * 20000)])
    labels = {r["doc_id"]: (r["lang_pred"], r["score"]) for r in language_id.predict(odd, model).collect()}
    assert labels[1] == labels[2] == labels[3] == ("und", 0.0) and labels[4][0] != "und"
    assert {r["doc_id"] for r in language_id.select_known(odd, model).collect()} == {4, 5}
    nothing = language_id.fit(docs.limit(0))
    assert {r["lang_pred"] for r in language_id.predict(odd, nothing).collect()} == {"und"}


def test_code_lengths_are_those_of_the_definition(spark):
    """Costs of the tables against a direct walk through the contexts."""
    from math import log2

    from pyspark.sql import Row

    train = spark.createDataFrame([Row(lang="a", text="abracadabra abra"), Row(lang="b", text="zzz abz")])
    model = language_id.prepared(language_id.Model(language_id.gram_counts(train).toPandas()))
    text = b"abra zab"

    def direct(lang):
        counts = {n: dict(model.grams[lang, n].tolist()) for n in range(1, 5)}
        bits, raw = 0.0, bytes(3) + text
        for p in range(3, len(raw)):
            for n in (4, 3, 2, 1):
                context = int.from_bytes(raw[p - n + 1 : p], "big")
                here = {g & 255: c for g, c in counts[n].items() if g >> 8 == context}
                if not here:
                    continue
                total, distinct = sum(here.values()), len(here)
                if raw[p] in here:
                    bits += log2((total + distinct) / here[raw[p]])
                    break
                bits += log2((total + distinct) / distinct)
            else:
                bits += 8.0
        return bits

    got = model.lengths(np.frombuffer(text, np.uint8), np.array([0, len(text)]))[0]
    assert np.allclose(got, [direct("a"), direct("b")], rtol=1e-4)


# --- 10 simhash ---


def brute_fingerprint(text, width=3):
    import xxhash

    w = re.findall(r"[^\x20\x09-\x0D]+", "".join(c.lower() if "A" <= c <= "Z" else c for c in text or ""))
    if not w:
        return 0
    hashes = [xxhash.xxh64_intdigest(" ".join(w[k : k + width]).encode(), 42) for k in range(max(len(w) - width + 1, 1))]
    return sum(1 << b for b in range(64) if 2 * sum(h >> b & 1 for h in hashes) > len(hashes))


def test_simhash(spark, rows):
    docs = rows + [(5000, None), (5001, "  \n"), (5002, "Two x words"), (5003, "A b C\td"), (5004, rows[0][1]), (5005, rows[0][1].replace("the", "tha", 1))]
    got = {r["doc_id"]: r for r in simhash.near_duplicates(docs_of(spark, docs)).collect()}
    fps = {i: brute_fingerprint(t) for i, t in docs}
    assert {i: r["fp"] % (1 << 64) for i, r in got.items()} == fps
    ids = sorted(fps)
    root = {i: i for i in ids}
    for _ in range(3):
        for a in ids:
            root[a] = min(root[b] for b in ids if (fps[a] ^ fps[b]).bit_count() <= 3)
    assert {i: r["component_id"] for i, r in got.items()} == root
    kept = {r["doc_id"] for r in simhash.keep_one(docs_of(spark, docs)).collect()}
    assert kept == {i for i in ids if root[i] == i}
    assert simhash.near_duplicates(docs_of(spark, docs).limit(0)).count() == 0


@pytest.mark.parametrize("distance", [3, 6])
def test_links_lose_nothing(spark, distance):
    rng = np.random.default_rng(3)
    base = rng.integers(0, 1 << 63, 40, dtype=np.uint64)
    flips = [np.uint64(sum(1 << int(b) for b in rng.choice(64, rng.integers(0, 8), replace=False))) for _ in range(600)]
    fps = np.unique([base[k % 40] ^ f for k, f in enumerate(flips)])
    frame = spark.createDataFrame([(int(x),) for x in fps.view(np.int64)], "fp long")
    signed = fps.view(np.int64)
    near = np.bitwise_count(fps[:, None] ^ fps[None, :]) <= distance
    want = {(int(min(signed[a], signed[b])), int(max(signed[a], signed[b]))) for a, b in zip(*np.nonzero(near), strict=True) if a != b}
    plans = [None, [(list(range(0, 20)), distance - 2), (list(range(20, 64)), 1)]]
    for parts in plans:
        got = [tuple(r) for r in simhash.links(frame, distance, parts).collect()]
        assert len(got) == len(set(got)) and set(got) == want


def test_allocation_is_optimal():
    from itertools import product

    costs = [[1, 4, 20, 50], [2, 3, 9, 80], [5, 6, 7, 8]]
    cost, chosen = simhash.allocate(costs, 4)
    best = min(sum(row[e - 1] if e else 0 for row, e in zip(costs, es, strict=True)) for es in product(range(5), repeat=3) if sum(es) == 4)
    assert cost == best and sum(t + 1 for t in chosen) == 4


def test_verified_links(spark):
    text = " ".join(f"w{k}" for k in range(300))
    near, far = text.replace("w150 ", "v150 "), " ".join(f"w{k if k % 12 else -k}" for k in range(300))
    got = {r["doc_id"]: r["component_id"] for r in simhash.near_duplicates(docs_of(spark, [(1, text), (2, near), (3, far)]), distance=20, verify=(5, 0.8)).collect()}
    assert got == {1: 1, 2: 1, 3: 3}


def test_components(spark):
    chain = [(k, k + 1) for k in range(60)] + [(100, k) for k in range(101, 140)] + [(200, 201), (201, 200)]
    links = spark.createDataFrame(chain, "u long, v long")
    got = {}
    for r in components(Scratch(spark, "test"), links).collect():
        got.setdefault(r["root"], set()).add(r["node"])
    assert sorted(map(sorted, got.values())) == sorted([list(range(61)), list(range(100, 140)), [200, 201]])
    assert components(Scratch(spark, "test"), links.limit(0)).count() == 0


def varied(rng, words, changes):
    words = list(words)
    for k in rng.choice(len(words), changes, replace=False):
        words[k] = f"x{rng.integers(1 << 40)}"
    return " ".join(words)


def near_dedup_docs():
    """Near copies of one text and of others, a passage that many share, copies, short and empty texts."""
    rng = np.random.default_rng(11)
    bases = [[f"w{rng.integers(400)}" for _ in range(n)] for n in (120, 150, 300, 60)]
    texts = [varied(rng, bases[0], rng.integers(1, 7)) for _ in range(90)]
    texts += [varied(rng, b, rng.integers(0, 5)) for b in bases[1:] for _ in range(12)]
    texts += [" ".join(bases[3]) + f" own{k} " + varied(rng, bases[1][:20], 15) for k in range(20)]
    texts += [None, "", " \n", "Two words", "two  WORDS", "a b c d e", "a b c d e f", texts[3].upper()]
    return list(enumerate(texts, 1))


def components_by_brute_force(docs):
    from ordwork.llm.simhash import jaccard

    raw = [(t or "").encode() for _, t in docs]
    root = list(range(len(docs)))
    for a in range(len(docs)):
        for b in range(a):
            if jaccard(raw[a], raw[b], 5) >= 0.8:
                root = [root[b] if r == root[a] else r for r in root]
    least = {r: min(docs[k][0] for k in range(len(docs)) if root[k] == r) for r in root}
    return {i: least[root[k]] for k, (i, _) in enumerate(docs)}


def test_near_dedup_stage_finds_all_similar(spark):
    import corpus_pipeline

    docs = near_dedup_docs()
    want = components_by_brute_force(docs)
    kept = {r["doc_id"] for r in corpus_pipeline.dedup_near(spark, docs_of(spark, docs), "").collect()}
    assert kept == {i for i, c in want.items() if c == i} and 40 < len(kept) < len(docs) - 40
    assert corpus_pipeline.dedup_near(spark, docs_of(spark, docs).limit(0), "").count() == 0


def test_near_dedup_leaves_little_to_the_exact_search(spark, monkeypatch):
    """SimHash takes part, and texts that share only a passage with others give no rows to the index."""
    import corpus_pipeline
    from ordwork.llm import near_dedup

    seen = {}
    links, prefixes = simhash.links, near_dedup.prefixes
    monkeypatch.setattr(simhash, "links", lambda *a: seen.setdefault("links", links(*a)))
    monkeypatch.setattr(near_dedup, "prefixes", lambda *a: seen.setdefault("prefixes", prefixes(*a)))
    shared = " ".join(f"s{k}" for k in range(20))
    docs = [(k, shared + " " + " ".join(f"d{k}w{j}" for j in range(60))) for k in range(40)]
    docs += [(40, docs[3][1] + " end"), (41, docs[5][1].upper())]
    kept = {r["doc_id"] for r in corpus_pipeline.dedup_near(spark, docs_of(spark, docs), "").collect()}
    assert kept == set(range(40)) and "links" in seen and seen["prefixes"].select("t").distinct().count() <= 2


def test_near_dedup_stage_compares_texts(spark):
    import corpus_pipeline

    again = "the same long sentence comes again and again here " * 40
    docs = [(k, again + " ".join(f"d{k}w{j}" for j in range(120))) for k in (1, 2, 3)]
    fps = [simhash.fingerprint(t.encode(), 3) for _, t in docs]
    assert all((a ^ b).bit_count() <= 3 for a in fps for b in fps)
    assert {r["doc_id"] for r in corpus_pipeline.dedup_near(spark, docs_of(spark, docs), "").collect()} == {1, 2, 3}


def test_language_models_grow_with_what_was_seen(spark, monkeypatch):
    """A hundred languages stay small, each is told by its own words, and a text cut into portions keeps its length."""
    words = {f"l{k:03d}": " ".join(f"{chr(97 + k % 26)}{chr(97 + (k * 7 + j) % 26)}{k:x}q{j % 5}" for j in range(40)) for k in range(100)}
    train = spark.createDataFrame([(lang, text) for lang, text in words.items()], "lang string, text string")
    model = language_id.prepared(language_id.Model(language_id.gram_counts(train).toPandas()))
    assert sum(x.nbytes for levels in model.long for level in levels for x in level) <= 12 * sum(map(len, model.grams.values()))
    assert sum(x.nbytes for x in model.short) == 100 * 256 * 256 * 4
    column = pa.array([*words.values(), "".join(words.values()) * 3, "", None])
    whole = language_id.judged(column, model)
    assert [x[0] for x in whole[:100]] == list(words) and whole[-1] == ("und", 0.0, 0.0)
    monkeypatch.setattr(language_id, "PORTION", 700)
    cut = language_id.judged(column, model)
    assert [x[0] for x in cut] == [x[0] for x in whole]
    assert np.allclose([x[2] for x in cut], [x[2] for x in whole], rtol=1e-9)


def test_language_sample_of_few_long_texts(spark):
    rows = [(k, f"text {lang} " * 20_000, lang) for k, lang in enumerate(["aa", "bb", "cc", "dd"])] + [(9, "short", "ee")]
    frame = spark.createDataFrame(rows, "doc_id long, text string, lang string")
    got = {r["lang"]: r["n"] for r in language_id.sample(frame, "text", "lang", "doc_id", 20_000).groupBy("lang").agg(F.sum(F.octet_length("text")).alias("n")).collect()}
    assert got.pop("ee") == 5 and set(got) == {"aa", "bb", "cc", "dd"} and all(14_000 < n < 26_000 for n in got.values())


def test_language_sample_moves_no_text_and_is_the_same_with_many_languages(spark, monkeypatch):
    rows = [(k, f"words of text {k} " * 300, f"l{k % 3 if k % 2 else 0}") for k in range(40)] + [(50, None, "l0"), (51, "kept out", None), (52, "", "l1"), (1, "words of text 1 " * 300, "l1")]
    frame = spark.createDataFrame(rows, "doc_id long, text string, lang string")
    drawn = lambda: language_id.sample(frame, "text", "lang", "doc_id", 20_000)
    few = drawn()
    plan = few._jdf.queryExecution().executedPlan().toString()
    assert "BroadcastHashJoin" in plan and "hashpartitioning" not in plan
    monkeypatch.setattr(language_id, "SENT_LANGUAGES", 2)
    many = drawn()
    assert few.count() > 0 and few.exceptAll(many).count() == many.exceptAll(few).count() == 0
    assert language_id.sample(frame.limit(0), "text", "lang", "doc_id", 20_000).count() == 0


# --- pipeline ---


def test_pipeline(spark, sf):
    import corpus_pipeline

    docs = table(spark, sf, "documents")
    at = docs
    for name, stage in corpus_pipeline.STAGES[:-1]:
        out = stage(spark, at, sf)
        assert out.columns == docs.columns, name
        at = spark.createDataFrame(out.collect(), docs.schema)
    bench = [tuple(r) for r in table(spark, sf, "benchmark").collect()]
    left = [tuple(r) for r in at.select("doc_id", "text").collect()]
    assert all(h[1] == 0 for h in brute_hits(left, bench).values())
    sets = [(i, {" ".join(w[k : k + 5]) for k in range(max(len(w) - 4, 1))}) for i, t in left if (w := t.lower().split())]
    assert not [1 for k, (_, a) in enumerate(sets) for _, b in sets[:k] if a == b]
    last = corpus_pipeline.run(spark, sf)
    assert last.count() == len(left) and last.where("not exact").count() == 0
    assert len(corpus_pipeline.STAGES) == 5 and corpus_pipeline.ORACLE_SQL is None


# --- cases every operator and stage must bear ---


def test_tokens_in_portions(spark, bpe, library, monkeypatch):
    """Words merged in portions and texts cut into batches by bytes give what the library gives, long texts and repeated rows included."""
    from ordwork.llm import bpe as bpe_module

    texts = [*ODD, "word " * 20_000 + "".join(chr(97 + i % 26) for i in range(5000)), "same text", "same text"]
    whole = bpe.merge([w for t in texts if t for w in bpe.pieces(t)])
    for portion in (1, 50):
        monkeypatch.setattr(bpe_module, "PORTION", portion)
        ids, ends = bpe.merge([w for t in texts if t for w in bpe.pieces(t)])
        assert (ids == whole[0]).all() and (ends == whole[1]).all()
    docs = spark.createDataFrame([(i % 14, t, 5, "x") for i, t in enumerate(texts)], "doc_id long, text string, n_tokens int, `key` string").coalesce(1)
    want = sorted((i % 14, len(library.encode(t or "", add_special_tokens=False).ids)) for i, t in enumerate(texts))
    path = queries.tokenizer_path()
    assert sorted((r["doc_id"], r["n_tokens"]) for r in token_count.count_tokens(docs, path).collect()) == want
    assert sorted((r["doc_id"], r["n_tokens"]) for r in bpe_codec.digests(docs, path).collect()) == want
    coded = bpe_codec.encode(docs, path)
    assert sorted((r["doc_id"], r["n_tokens"]) for r in coded.collect()) == want and coded.columns == ["doc_id", "text", "key", "ids", "n_tokens", "exact"]
    for empty in (token_count.count_tokens(docs.limit(0), path), bpe_codec.digests(docs.limit(0), path), bpe_codec.encode(docs.limit(0), path)):
        assert empty.count() == 0


def test_language_cases(spark):
    """Nothing to learn from, nothing to predict, repeated rows, columns with the names of results."""
    docs = spark.createDataFrame([(1, "the cat and the dog", "en", 1.0), (1, "the cat and the dog", "en", 2.0), (2, "der Hund und die Katze", "de", 3.0), (3, None, "en", 4.0), (4, "12 34", None, 5.0)], "doc_id long, text string, lang string, score double")
    model = language_id.fit(docs)
    got = sorted((r["doc_id"], r["lang_pred"]) for r in language_id.predict(docs, model).collect())
    assert got == [(1, "en"), (1, "en"), (2, "de"), (3, "und"), (4, "und")]
    assert language_id.predict(docs.limit(0), model).count() == 0
    nothing = language_id.fit(docs.limit(0))
    assert {(r["lang_pred"], r["score"]) for r in language_id.predict(docs, nothing).collect()} == {("und", 0.0)}


def test_url_clashing_columns(spark):
    rules = [url_filter.Rule(text, verdict) for text, verdict in queries.RULES]
    pages = spark.createDataFrame([(1, "http://a.com/en/1", "h", "p", "r"), (1, "http://a.com/en/1", "h", "p", "r"), (2, None, "h", "p", "r"), (3, "http://b.org/x", "h", "p", "r")], "page_id long, url string, host string, token string, rule string")
    mined = url_filter.mine(pages.select("page_id", "url").withColumn("bad", F.lit(False)), "url", "bad")
    rows = url_filter.judge(pages.select("page_id", "url"), rules, mined).collect()
    assert sorted((r["page_id"], r["host"], r["rule"], r["verdict"]) for r in rows) == sorted([(1, "a.com", "com/en/", "block")] * 2 + [(2, "", None, "allow"), (3, "b.org", None, "allow")], key=str)


def test_pipeline_stages_bear_odd_rows(spark, sf, tmp_path):
    """Each stage over nulls, empty and repeated rows, a long text, and an empty table; all but the last keep the columns."""
    import corpus_pipeline

    given = table(spark, sf, "documents")
    some = given.orderBy("doc_id").limit(20)
    odd = some.withColumn("text", F.when(F.col("doc_id") % 5 == 0, F.lit(None)).when(F.col("doc_id") % 5 == 1, F.lit("")).when(F.col("doc_id") % 5 == 2, F.repeat(F.concat("text", F.lit("\n")), 300)).otherwise(F.col("text")))
    odd = odd.union(odd).union(some.where("doc_id % 5 > 2").withColumn("text", F.lit(None).cast("string")))
    odd.write.parquet(str(tmp_path / "odd"))
    odd = spark.read.parquet(str(tmp_path / "odd"))
    for name, stage in corpus_pipeline.STAGES:
        out = stage(spark, odd, sf)
        assert out.count() <= odd.count(), name
        assert stage(spark, odd.limit(0), sf).count() == 0, name
        assert name == corpus_pipeline.STAGES[-1][0] or out.columns == given.columns, name
