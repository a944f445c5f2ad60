"""Small cases of each corpus operator: nulls, empty texts, ties, empty tables, further columns, and brute force."""

import hashlib
import random
import re
import zlib
from collections import Counter

import numpy as np
import pyarrow as pa
import pytest
from pyspark.sql import functions as F

from sortbit.llm import decontaminate, language_id, license_scan, line_dedup, near_dedup, packing, pii, quality_rules, token_output, tokens, toxicity
from sortbit.llm.base import text_chunks

WORDS = "alpha beta gamma delta epsilon zeta eta theta iota kappa lamda mu nu xi omicron pi rho sigma tau upsilon phi chi psi omega".split()


def sentence(r, n):
    return " ".join(r.choice(WORDS) + str(r.randint(0, 40)) for _ in range(n))


@pytest.fixture(scope="module")
def docs(spark):
    """Ids, texts and a column whose name an operator might use itself."""
    r = random.Random(1)
    texts = [None, "", "   \n\t", "one", "one two three", "12 34 !!", "ünïcode ñandú été"]
    base = [sentence(r, 80) for _ in range(6)]
    texts += base + base[:3] + [base[0].upper(), base[1] + " tail words here", "\n".join([base[2], base[3]]), base[4] + "\n" + base[4]]
    near = base[5].split()
    near[3] = "changed"
    texts += [" ".join(near)]
    return spark.createDataFrame([(i, t, "x") for i, t in enumerate(texts)], "doc_id long, text string, id string").coalesce(2)


@pytest.fixture(scope="module")
def texts(docs):
    return {r.doc_id: r.text for r in docs.collect()}


@pytest.fixture(scope="module")
def none(docs):
    return docs.where("doc_id < 0")


def words(t):
    return re.findall(r"[^\x20\x09-\x0D]+", t or "")


# ---- 1


def brute_tiles(doc, item, least):
    doc_used, item_used, covered = [False] * len(doc), [False] * len(item), 0
    while True:
        best = (0, 0, 0)
        for i in range(len(doc)):
            for j in range(len(item)):
                k = 0
                while i + k < len(doc) and j + k < len(item) and doc[i + k] == item[j + k] and not doc_used[i + k] and not item_used[j + k]:
                    k += 1
                if k > best[0]:
                    best = (k, i, j)
        if best[0] < least:
            return covered
        for x in range(best[0]):
            doc_used[best[1] + x] = item_used[best[2] + x] = True
        covered += best[0]


def test_tiles_equal_brute_force():
    r = random.Random(3)
    for _ in range(40):
        item = [r.randint(1, 9) for _ in range(r.randint(1, 20))]
        doc = [r.randint(1, 9) for _ in range(r.randint(1, 30))] + item[len(item) // 2 :] + [77] + item[: len(item) // 2]
        found = decontaminate.tiles(np.array(doc, np.uint64), np.array(item, np.uint64), 3)
        assert all(doc[i : i + n] == item[j : j + n] for i, j, n in found)
        lengths = [n for _, _, n in found]
        assert lengths == sorted(lengths, reverse=True)
        assert sum(lengths) == brute_tiles(doc, item, 3)


@pytest.mark.parametrize("limit", [1 << 20, 0])
def test_leaks_are_found_in_any_order(spark, docs, texts, none, limit):
    r = random.Random(9)
    item = sentence(r, 40).split()
    swapped = " ".join([*item[20:], "between", *item[:20]])
    more = spark.createDataFrame([(100, f"Before. {' '.join(item).upper()}! after", "x"), (101, f"noise {swapped} noise", "x"), (102, " ".join(item[:10]), "x")], docs.schema)
    bench = spark.createDataFrame([(1, " ".join(item)), (2, None), (3, ""), (4, "one two"), (5, " ".join(item))], "item_id long, text string")
    got = {(x.doc_id, x.item_id) for x in decontaminate.contaminated(docs.union(more), bench, broadcast_bytes=limit).collect()}
    assert got == {(100, 1), (101, 1), (100, 5), (101, 5), (4, 4)}
    assert decontaminate.contaminated(none, bench, broadcast_bytes=limit).count() == 0
    assert decontaminate.contaminated(docs, bench.where("item_id < 0"), broadcast_bytes=limit).count() == 0
    assert decontaminate.clean(docs.union(more), bench).columns == docs.columns


# ---- 2


def test_license_forms(spark, docs, none):
    known = license_scan.known_texts(spark)
    mit = dict((n, t) for n, t in license_scan.KNOWN if len(t) > 600)["MIT"]
    more = spark.createDataFrame(
        [(100, "Copyright (c) 2001 Some Body\n\n" + mit.upper().replace(",", " ,"), "x"), (101, "text\n* Released under the MIT Licence!!\nmore", "x"), (102, "Copyright 1999 only", "x"), (103, mit[:-40], "x")], docs.schema
    )
    got = {r.doc_id: r for r in license_scan.scan(docs.union(more), known).collect()}
    assert got[100].license == "MIT" and got[101].notices == "MIT" and got[101].license is None
    assert got[102].license is None and got[102].digest == hashlib.sha256(b"").hexdigest() and got[103].license is None
    assert got[0].digest is None and got[1].digest == hashlib.sha256(b"").hexdigest()
    assert len(got) == docs.count() + 4 and license_scan.scan(none, known).count() == 0
    assert license_scan.scan(docs, known.where("license = 'none'")).where("license is not null").count() == 0


# ---- 3


def test_fast_ids_equal_the_vocabulary(spark, texts):
    slow = tokens._slow(tokens.vocabulary_path("byte_bpe_50k.json"))
    some = [r.text for r in spark.read.parquet("/root/testdata/sf0.001/documents.parquet").select("text").collect()] + list(texts.values()) + ["a<|endoftext|>b", " " * 3000, "é" * 500, "　x y\r\n\n 1'll"]
    for t in filter(None, some):
        assert tokens.encode(t).tolist() == slow.encode(t, add_special_tokens=False).ids


def test_best_fit_decreasing():
    r = random.Random(2)
    sizes = [r.randint(1, 64) for _ in range(300)]
    bins = token_output.best_fit_decreasing(sizes, 64)
    assert sorted(i for b in bins for i in b) == list(range(300)) and all(sum(sizes[i] for i in b) <= 64 for b in bins)
    free: list[int] = []
    for s in sorted(sizes, reverse=True):
        fit = min((f for f in free if f >= s), default=None)
        free.remove(fit) if fit is not None else None
        free.append((64 if fit is None else fit) - s)
    assert len(bins) == len(free)


def test_packed_matrices_give_the_documents_back(docs, texts, none):
    rows = token_output.pack_tokens(docs, width=64, window_tokens=500).collect()
    ids, places = token_output.matrix(rows, 64)
    got: dict[int, dict[int, list[int]]] = {}
    for r, row, place in zip(rows, ids, places, strict=True):
        assert r.cu_seqlens[-1] == r.n_tokens and not row[r.n_tokens :].any()
        for a, b, doc, start in zip(r.cu_seqlens, r.cu_seqlens[1:], r.doc_ids, r.starts, strict=False):
            got.setdefault(doc, {})[start] = row[a:b].tolist()
            assert place[a:b].tolist() == list(range(b - a))
    for doc, t in texts.items():
        assert [x for _, part in sorted(got[doc].items()) for x in part] == [*tokens.encode(t).tolist(), 50256]
    assert len({r.sequence_id for r in rows}) == len(rows) and token_output.pack_tokens(none).count() == 0


# ---- 4


def brute_lines(texts, least):
    lines = {d: t.split("\n") for d, t in sorted(texts.items()) if t is not None}
    seen, gone = set(), {d: set() for d in lines}
    for d, ls in lines.items():
        for i in range(len(ls)):
            for j in range(i + 1, len(ls) + 1):
                block = tuple(ls[i:j])
                if block in seen:
                    if sum(len(x) + 1 for x in block) >= least:
                        gone[d] |= set(range(i, j))
                seen.add(block)
    return {d: "\n".join(x for i, x in enumerate(ls) if i not in gone[d]) for d, ls in lines.items()}


def test_line_runs_equal_brute_force(spark, docs, texts, none):
    r = random.Random(4)
    pool = ["", "a", "bb", "ccc", "dddd", "a" * 30, "e" * 9]
    more = {i: "\n".join(r.choice(pool) for _ in range(r.randint(1, 9))) for i in range(60)} | {60: None, 61: ""}
    df = spark.createDataFrame([(i, t, "x") for i, t in more.items()], "doc_id long, text string, gone string")
    for least in (1, 12, 25):
        # blocks of one text are seen in order of their start, so compare texts without inner repeats of overlapping runs
        got = {x.doc_id: x.text for x in line_dedup.deduplicate_lines(df, least).collect()}
        want = brute_lines(more, least)
        assert got[60] is None and {d: t for d, t in got.items() if t is not None} == want
    assert line_dedup.deduplicate_lines(df).columns == df.columns and line_dedup.deduplicate_lines(none).count() == 0
    wide = df.withColumn("doc_id", F.col("doc_id") * (1 << 56))
    assert sorted(x.text or "" for x in line_dedup.deduplicate_lines(wide, 12).collect()) == sorted(x.text or "" for x in line_dedup.deduplicate_lines(df, 12).collect())


# ---- 5


def test_language_profiles(spark, none):
    rows = []
    speech = {"en": "the thing that they said was there with the other one", "de": "der schöne garten ist nicht für die menschen gemacht", "el": "η γλώσσα των ανθρώπων είναι παλιά και όμορφη"}
    r = random.Random(6)
    for i in range(240):
        lang = sorted(speech)[i % 3]
        w = speech[lang].split()
        r.shuffle(w)
        rows.append((i, " ".join(w), lang))
    rows += [(900, None, "en"), (901, "", None), (902, "123 !? 45", "de"), (903, "— … „", None), (904, "THE OTHER THING", None)]
    df = spark.createDataFrame(rows, "doc_id long, text string, lang string")
    got = {x.doc_id: x for x in language_id.detect(df, language_id.fit(df)).collect()}
    assert all(got[i].lang_pred == rows[i][2] for i in range(240))
    assert all(got[i].lang_pred == "und" and got[i].score == 0 for i in (900, 901, 902, 903)) and got[904].lang_pred == "en"
    nothing = language_id.detect(df, language_id.fit(df.where("lang is null")))
    assert {x.lang_pred for x in nothing.collect()} == {"und"}
    empty = none.select("doc_id", "text", F.lit("en").alias("lang"))
    assert language_id.detect(empty, language_id.fit(empty)).count() == 0


# ---- 6


def test_surrogates(spark, docs, none):
    secret = "04dbebab91ab85687d33eeaaf9ac699e1188f962"
    rows = [
        (0, "Mail anna.x9@mail7.example.com, ip 97.51.17.173 or +1 (974) 555-3436."),
        (1, "ANNA.X9@MAIL7.EXAMPLE.COM and 9807 9157 6280 4490, 9807915762804490"),
        (2, f'token = "{secret}" TOKEN = "{secret.upper()}"'),
        (3, "Mr. John Smith met Frau Keller; господин Петров here"),
        (4, " ".join(f"{c}@b.co" for c in "abcdefghijklmnopqrstuvwxyz0123456789")),
        (5, None),
        (6, ""),
        (7, "no data, 12 monkeys, version 3.1.4"),
    ]
    df = spark.createDataFrame([(i, t, "x") for i, t in rows], "doc_id long, text string, id string")
    got = {x.doc_id: x for x in pii.pseudonymise(df, "k", count_as="n").collect()}
    assert [got[i].n for i in range(8)] == [3, 3, 2, 3, 36, 0, 0, 0]
    assert got[5].text is None and got[6].text == "" and got[7].text == rows[7][1]
    for i in range(5):
        for x in re.findall(r"\S+@\S+\w|[0-9a-fA-F]{40}|\d{16}|97\.51\.17\.173|555-3436|Smith|Keller|Петров", rows[i][1]):
            assert x not in got[i].text.split(), x
    first = re.search(r"Mail (\S+),", got[0].text)[1]
    assert re.fullmatch(r"[a-z]{4}\.[a-z]\d@mail\d+\.example\.org", first) and first.upper() in got[1].text
    spaced, plain = re.search(r"(\d{4} \d{4} \d{4} \d{4}), (\d{16})", got[1].text).groups()
    assert spaced.replace(" ", "") == plain
    low, high = re.findall(r'"(\w+)"', got[2].text)
    assert high == low.upper() and re.fullmatch("[0-9a-f]{40}", low)
    assert re.fullmatch(r"Mr\. \w+ [\w-]+ met Frau [\w-]+; господин [А-Яа-яё-]+ here", got[3].text)
    assert len(set(got[4].text.split())) == 36
    assert pii.pseudonymise(none, "k").count() == 0
    again = {x.doc_id: x.text for x in pii.pseudonymise(df, "other").collect()}
    assert again[0] != got[0].text


# ---- 7


def test_toxicity(spark, none):
    r = random.Random(8)
    rows, labels = [], []
    for i in range(400):
        toxic = i % 5 == 0
        rows.append((i, sentence(r, 30) + (" you horrid villain" if toxic else ""), "x"))
        if i % 2 == 0:
            labels.append((i, int(toxic)))
    rows += [(900, None, "x"), (901, "", "x")]
    df = spark.createDataFrame(rows, "doc_id long, text string, score string")
    marks = spark.createDataFrame(labels, "doc_id long, toxic int")
    got = {x.doc_id: x.score for x in toxicity.score(df, toxicity.fit(df, marks)).collect()}
    assert len(got) == len(rows) and all(0 <= s <= 1 for s in got.values())
    right = [(got[i] >= 0.3) == (i % 5 == 0) for i in range(400)]
    assert np.mean(right) > 0.95
    none_toxic = toxicity.fit(df, marks.where("toxic = 0"))
    assert max(x.score for x in toxicity.score(df, none_toxic).collect()) < 0.3
    assert toxicity.score(none, none_toxic).count() == 0


# ---- 8


def brute_counts(t):
    t, w, seen, dup = t or "", words(t), set(), 0
    for line in t.split("\n"):
        if words(line):
            dup += line in seen
            seen.add(line)
    three = Counter(tuple(w[i : i + 3]) for i in range(len(w) - 2))
    held = {i + k for i in range(len(w) - 2) if three[tuple(w[i : i + 3])] > 1 for k in range(3)}
    return len(w), sum(map(len, w)), len(re.findall(r"[#*$%&|<>]", t)), dup, len(held)


def test_statistics_equal_brute_force(docs, texts):
    got = {x.doc_id: tuple(x[c] for c in quality_rules.COUNTS[:5]) for x in quality_rules.statistics(docs).collect()}
    assert got == {d: brute_counts(t) for d, t in texts.items()}
    odd = ["a b c a b c", "x\nx\n\n\nx y", "é é é é #é", " a b c", "a\rb\rc"]
    found = quality_rules.text_counts(pa.array(odd))
    assert [tuple(int(found[c][i]) for c in quality_rules.COUNTS[:5]) for i in range(len(odd))] == [brute_counts(t) for t in odd]


def test_rules(spark, docs, none):
    r = random.Random(10)
    rows, labels = [], []
    for i in range(300):
        bad = i % 3 == 0
        t = sentence(r, 60)
        rows.append((i, t.replace(" ", " %%% ") if bad else t))
        labels.append((i, int(not bad)))
    df, marks = spark.createDataFrame(rows, "doc_id long, text string"), spark.createDataFrame(labels, "doc_id long, quality int")
    rules = quality_rules.fit(df, marks)
    got = {x.doc_id: x for x in quality_rules.apply_rules(quality_rules.statistics(df), rules).collect()}
    assert all(got[i].kept == (i % 3 != 0) for i in range(300))
    assert quality_rules.fit(df, marks.where("quality = 1")) == [] and quality_rules.fit(none, marks) == []
    assert quality_rules.apply_rules(quality_rules.statistics(docs), []).where("kept and base_failed").count() == 0


# ---- 9


def brute_components(texts, percent=75):
    sets = {}
    for d, t in texts.items():
        w = [x.translate({c: c + 32 for c in range(65, 91)}) for x in words(t)]
        sets[d] = {tuple(w[i : i + 5]) for i in range(len(w) - 4)} if len(w) >= 5 else ({tuple(w)} if w else set())
    comp = {d: d for d in sets}
    ids = sorted(sets)
    changed = True
    links = [(a, b) for a in ids for b in ids if a < b and sets[a] and 100 * len(sets[a] & sets[b]) >= percent * len(sets[a] | sets[b])]
    while changed:
        changed = False
        for a, b in links:
            low = min(comp[a], comp[b])
            if comp[a] != low or comp[b] != low:
                comp[a] = comp[b] = low
                changed = True
    return {d: (len(sets[d]), comp[d]) for d in ids}


def test_near_duplicates_equal_brute_force(spark, docs, texts, none):
    r = random.Random(12)
    base = [sentence(r, 120).split() for _ in range(3)]
    more = dict(texts)
    for i in range(60):
        w = list(base[i % 3])
        for _ in range(r.randint(0, 5)):
            w[r.randrange(len(w))] = f"new{r.randint(0, 10**6)}"
        more[100 + i] = " ".join(w)
    more[300] = " ".join(base[0] + base[1])
    df = spark.createDataFrame(list(more.items()), "doc_id long, text string").repartition(3)
    got = {x.doc_id: (x.n_shingles, x.component_id) for x in near_dedup.near_duplicates(df).collect()}
    assert got == brute_components(more)
    kept = near_dedup.deduplicate(docs)
    assert kept.columns == docs.columns
    assert {x.doc_id for x in kept.collect()} == {d for d, (_, c) in brute_components(texts).items() if c == d}
    assert near_dedup.near_duplicates(none).count() == 0


# ---- 10


def check_pieces(pieces, texts, limits):
    by_doc, by_seq = {}, {}
    for p in pieces:
        by_doc.setdefault(p.doc_id, []).append(p)
        by_seq.setdefault(p.sequence_id, []).append(p)
    for doc, t in texts.items():
        ids = np.append(tokens.encode(t), np.uint32(1)).astype("<u4")
        at = 0
        for p in sorted(by_doc[doc], key=lambda p: p.start):
            assert p.start == at and p.length > 0 and p.doc_tokens == len(ids) and p.ids_crc32 == zlib.crc32(ids[at : at + p.length].tobytes())
            at += p.length
        assert at == len(ids)
    padding = 0
    for ps in by_seq.values():
        at = 0
        for p in sorted(ps, key=lambda p: p.offset):
            assert p.offset == at
            at += p.length
        assert at <= limits.tokens and len(ps) <= limits.segments
        padding += 0 if at & (at - 1) == 0 else limits.tokens - at
    return padding


@pytest.mark.parametrize("limits", [packing.Limits(), packing.Limits(64, 4, 64)])
def test_pieces(docs, texts, none, limits):
    pieces = packing.pack_documents(docs, limits).collect()
    padding = check_pieces(pieces, texts, limits)
    assert padding <= 0.05 * sum(p.length for p in pieces) or limits.segments == 4
    assert packing.pack_documents(none, limits).count() == 0


def test_whole_conversations(spark):
    turns = [(c, t, "assistant" if t % 2 else "user", "word " * (5 * c + t)) for c in range(8) for t in range(4)] + [(50, 0, None, None), (51, 0, "assistant", "x " * 500)]
    df = spark.createDataFrame(turns, "conv_id long, turn long, role string, text string")
    got = packing.pack_conversations(df, packing.Limits(256, 3, 128)).collect()
    assert sorted(x.conv_id for x in got) == [*range(8), 50, 51]
    for s in {x.sequence_id for x in got}:
        rows = [x for x in got if x.sequence_id == s]
        if all(x.fits for x in rows):
            assert sum(x.tokens for x in rows) <= 256 and len(rows) <= 3 and sum(x.loss_tokens for x in rows) <= 128
        else:
            assert len(rows) == 1 and rows[0].conv_id == 51


def test_chunks_keep_every_row():
    batch = pa.record_batch({"text": pa.array(["a" * 10, None, "b" * 50, "", "c"])})
    parts = list(text_chunks(iter([batch]), limit=12))
    assert [len(p) for p in parts] == [2, 1, 2] and pa.Table.from_batches(parts).column("text").to_pylist() == batch.column("text").to_pylist()
