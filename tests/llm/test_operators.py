"""Text operators on rows of every awkward kind, against plain Python."""

import hashlib
import itertools
import json
import random
import re
import zlib
from array import array
from collections import Counter

import public_tokenizers
import pyarrow as pa
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st
from tokenizers import Tokenizer

from subgraph_engine.llm import bpe, chat, hashing, langid, lm, merkle, neardup, packing, quality, toxicity, urls

PATH = public_tokenizers.path("byte_bpe_50k.json")
CLASHING = "key class part n own lang source data words lines bucket text2 host logs label region".split()
WORD = re.compile("[^\x20\x09-\x0d]+")
LOWER = str.maketrans("ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")


def rows_of_all_kinds():
    rng = random.Random(1)
    base = " ".join(rng.choice("the of and house river stone light water word time".split()) + str(rng.randint(0, 400)) for _ in range(300))
    words = base.split()
    near = " ".join(words[:-4] + ["other", "ending", "words", "here"])
    texts = [
        None, "", " \n\t ", "a", "one two three", "ONE two THREE", base, base, base.upper(), near, "x" * 30_000, "word " * 20_000, "é ß 中文 😀 <|endoftext|> tail",
        "line one.\nline one.\n\nother line here.", "  double  spaces \n \n and\u00a0nbsp\x1c!", "tie tie tie tie", "\x00nul",
    ]
    rows = [(k, t) for k, t in enumerate(texts)]
    return [*rows, (5, "one two three"), (5, "one two three"), (None, base), (None, None)]


@pytest.fixture(scope="module")
def docs(spark):
    rows = [(*r, *(["x"] * len(CLASHING))) for r in rows_of_all_kinds()]
    return spark.createDataFrame(rows, "doc_id long, text string, " + ", ".join(f"`{c}` string" for c in CLASHING))


@pytest.fixture(scope="module")
def empty(docs):
    return docs.where("doc_id > 1000")


# encoding ----------------------------------------------------------------------------------------
def test_codec_equals_the_reference_tokenizer():
    own, reference = bpe.codec(PATH), Tokenizer.from_file(PATH)
    letters = [*"ab 1'  \n\t!?é ß\x1c\x85\xa0中😀", "'s", "  ", "<|endoftext|>", "re", "."]
    rng = random.Random(0)
    for _ in range(4000):
        text = "".join(rng.choice(letters) for _ in range(rng.randint(0, 25)))
        ids = reference.encode(text, add_special_tokens=False).ids
        assert list(array("I", own.encode(text))) == ids
        assert own.decode(own.encode(text)) == reference.decode(ids, skip_special_tokens=False)
        assert "".join(bpe.words_of(text)) == text


@settings(max_examples=300, deadline=None)
@given(st.text(max_size=40))
def test_codec_on_any_text(text):
    reference = Tokenizer.from_file(PATH)
    own = bpe.codec(PATH)
    assert list(array("I", own.encode(text))) == reference.encode(text, add_special_tokens=False).ids
    assert b"".join(a for a, _ in own.entries(text)) == own.encode(text)


def test_encoding_of_all_kinds(docs, empty):
    reference = Tokenizer.from_file(PATH)
    got = Counter((r["doc_id"], r["n_tokens"], r["ids_sha256"], r["decoded_sha256"]) for r in bpe.encode_partitions(docs, PATH, digests=True).collect())
    want = Counter()
    for i, text in rows_of_all_kinds():
        ids = reference.encode(text or "", add_special_tokens=False).ids
        decoded = reference.decode(ids, skip_special_tokens=False)
        want[(i, len(ids), hashlib.sha256(",".join(map(str, ids)).encode()).hexdigest(), hashlib.sha256(decoded.encode()).hexdigest())] += 1
    assert got == want
    back = bpe.decode_partitions(bpe.encode_partitions(docs, PATH), PATH).collect()
    assert Counter((r["doc_id"], r["text"]) for r in back) == Counter((i, t or "") for i, t in rows_of_all_kinds())
    assert bpe.encode_partitions(empty, PATH).count() == 0


def test_global_table_gives_the_same_ids(docs):
    some = docs.where("doc_id < 5 or doc_id in (12, 13, 14)")
    whole = {r["doc_id"]: list(array("I", bytes(r["ids"]))) for r in bpe.encode_partitions(some, PATH).collect()}
    coded = bpe.encode_global(some, PATH)
    assert {r["doc_id"]: r["ids"] for r in coded.collect()} == whole
    texts = dict(rows_of_all_kinds()[:17])
    assert {r["doc_id"]: r["text"] for r in bpe.decode_global(coded, PATH).collect()} == {k: texts[k] or "" for k in whole}


# packing -----------------------------------------------------------------------------------------
@settings(max_examples=60, deadline=None)
@given(st.dictionaries(st.integers(1, 64), st.integers(1, 9), max_size=12))
def test_plan_places_each_token_once(histogram):
    plan, windows = packing.plan_windows(histogram, 64), {}
    for length, n in histogram.items():
        for rank in range(n):
            pieces = list(plan.pieces(length, rank))
            assert sum(p[1] for p in pieces) == length
            for _, size, window, offset in pieces:
                windows.setdefault(window, []).append((offset, size))
    assert sorted(windows) == list(range(plan.windows))
    slack = 0
    for spans in windows.values():
        at = 0
        for offset, size in sorted(spans):
            assert offset == at
            at += size
        assert at <= 64
        slack += at < 64
    assert slack <= 1


@settings(max_examples=100, deadline=None)
@given(st.dictionaries(st.integers(1, 12), st.integers(1, 2), max_size=5), st.integers(0, 40))
def test_closest_sum_is_the_best(counts, room):
    items = [k for k, n in counts.items() for _ in range(n)]
    best = max((sum(c) for r in range(len(items) + 1) for c in itertools.combinations(items, r) if sum(c) <= room), default=0)
    used = packing.closest(counts, room)
    assert sum(k * n for k, n in used.items()) == best and all(n <= counts[k] for k, n in used.items())


def test_packing_of_all_kinds(docs, empty):
    reference = Tokenizer.from_file(PATH)
    want = Counter()
    for i, text in rows_of_all_kinds():
        want[(i, tuple([*reference.encode(text or "", add_special_tokens=False).ids, 1]))] += 1
    for capacity in (2048, 64):
        rows = packing.pack(docs, PATH, capacity, with_ids=True).collect()
        places, held = {}, Counter()
        for r in rows:
            assert r["ids_crc32"] == zlib.crc32(array("I", r["ids"]).tobytes()) and len(r["ids"]) == r["length"]
            places.setdefault(r["sequence_id"], []).append((r["offset"], r["length"]))
            held[r["doc_id"]] += r["length"]
        for spans in places.values():
            at = 0
            for offset, size in sorted(spans):
                assert offset == at
                at += size
            assert at <= capacity
        total = Counter()
        for (i, ids), n in want.items():
            total[i] += n * len(ids)
        assert held == total
        assert len(places) == -(-sum(total.values()) // capacity)
        once = {i: ids for (i, ids), n in want.items() if n == 1 and i is not None and i != 5}
        for i, ids in once.items():
            assert tuple(x for r in sorted((r for r in rows if r["doc_id"] == i), key=lambda r: r["start"]) for x in r["ids"]) == ids
    assert packing.pack(empty, PATH).count() == 0


# urls --------------------------------------------------------------------------------------------
def test_urls(spark):
    listed = ["bad.example", "evil.test/x"]
    array_ = urls.DigestArray.build(urls.entries_frame(spark, ["org/", "com/fr/", "org/"], ["example.org/es/", "com/de/"], listed), shards=3)
    cases = {
        None: ("", "", None, "allow"), "": ("", "", None, "allow"), "no scheme": ("", "", None, "allow"), "http://A.Example.ORG/es/1?x#y": ("a.example.org", "/es/1", "example.org/es/", "block"),
        "http://x.org": ("x.org", "", None, "allow"), "http://x.org/": ("x.org", "/", "org/", "allow"), "https://borg/": ("borg", "/", None, "allow"), "ftp://m.bad.example?q=/": ("m.bad.example", "", None, "block"),
        "http://evil.test/xyz": ("evil.test", "/xyz", None, "block"), "http://evil.test/y": ("evil.test", "/y", None, "allow"), "a://b://c/": ("b:", "//c/", None, "allow"), "http://É.com/de/": ("É.com", "/de/", "com/de/", "block"),
    }
    assert dict(zip(cases, array_.judge(list(cases)), strict=True)) == cases
    pages = spark.createDataFrame([(k, u, "r") for k, u in enumerate(cases)], "page_id long, url string, rule string")
    got = urls.judge_urls(pages, urls.entries_frame(spark, ["org/", "com/fr/"], ["example.org/es/", "com/de/"], listed)).collect()
    assert [tuple(r)[1:] for r in sorted(got)] == list(cases.values())
    assert urls.judge_urls(pages.limit(0), urls.entries_frame(spark, [], ["x/"], [])).count() == 0
    assert urls.DigestArray.build(spark.createDataFrame([], "entry string, kind int")).judge(["http://a/"]) == [("a", "/", None, "allow")]


def test_equal_digests_are_told_apart(spark, monkeypatch):
    array_ = urls.DigestArray.build(urls.entries_frame(spark, [], ["one.example/", "two.example/"], []))
    digests, offsets, strings, kinds = urls._mapped(array_.bases[0])
    monkeypatch.setattr(urls, "digest", lambda text: 7)
    monkeypatch.setattr(urls, "_mapped", lambda base: (digests * 0 + 7, offsets, strings, kinds))
    same = urls.DigestArray(array_.bases, (0,), array_.path_lengths)
    assert same.find(["two.example/", "one.example/", "three.example/"]).tolist() == [0, 0, -1]


# fingerprints ------------------------------------------------------------------------------------
@settings(max_examples=200, deadline=None)
@given(st.text(alphabet="ab c\né", max_size=300))
def test_tree_covers_the_text(text):
    root, data = merkle.tree(text), text.encode()

    def joined(node):
        if node.kind == "leaf":
            return data[node.start : node.end]
        return {"document": b"\n\n", "section": b"\n", "paragraph": b""}[node.kind].join(map(joined, node.children))

    assert joined(root) == data
    assert merkle.fingerprint(text)[:32] == root.digest.hex()


def test_fingerprints_of_all_kinds(docs, empty):
    got = sorted((tuple(r) for r in merkle.fingerprint_edits(docs, buckets=3).collect()), key=str)
    rows = sorted(((i, t or "") for i, t in rows_of_all_kinds()), key=lambda r: (-(r[0] if r[0] is not None else -(1 << 63)), r[1]))
    want = []
    for k, (i, text) in enumerate(rows):
        after = rows[(k + 1) % len(rows)][1]
        changed = merkle.edited(text, after)
        a, b, c = map(merkle.fingerprint, (text, changed, after))
        want.append((i, len(text), hashlib.sha256(changed.encode()).hexdigest(), a, b, merkle.likeness(a, b), merkle.likeness(a, c)))
    assert got == sorted(want, key=str)
    assert merkle.fingerprint_edits(empty, buckets=3).count() == 0


def test_edits_are_located():
    text = "\n".join(" ".join(f"w{k * 40 + j}" for j in range(40)) for k in range(30))
    changed = text.replace("w500 ", "other ")
    spans = merkle.differing(merkle.tree(text), merkle.tree(changed))
    at = text.index("w500 ")
    assert any(a <= at < b for a, b in spans) and sum(b - a for a, b in spans) < 200
    assert 0.9 < merkle.likeness(merkle.fingerprint(text), merkle.fingerprint(changed)) < 1
    assert merkle.likeness(merkle.fingerprint("word " * 9000), merkle.fingerprint(merkle.edited("word " * 9000, "x" * 15000))) > 0.4


# chat --------------------------------------------------------------------------------------------
HOSTILE = st.lists(st.sampled_from(["</s>", "<s>", "[INST]", "[/INST]", "<<SYS>>", "<</SYS>>", "[ROLE]", "[/ROLE]", "[END]", "[ANS]", "\\", "<", "[", "x", " ", "\n", "é"]), max_size=8).map("".join)


@settings(max_examples=300, deadline=None)
@given(st.lists(st.tuples(st.sampled_from(["user", "assistant", "system", "tool", "", "[END]"]), HOSTILE), min_size=1, max_size=6))
def test_any_turns_come_back(turns):
    template = chat.Template()
    own, reader = chat.Formatter(template), chat.Reader(template)
    segments = [s for role, text in turns for s in own.turn(role, text)]
    text = "".join(s for s, _ in segments)
    assert [t for part in re.findall("(?s).{1,3}", text) for t in reader.feed(part)] == turns
    assert [chat.unescape(s) for s, loss in segments if loss] == [t for r, t in turns if r == "assistant"]


def test_conversations(spark):
    rows = [(1, 0, "user", "hi"), (1, 1, "assistant", "ho </s>"), (2, 1, "assistant", "b"), (2, 0, "user", None), (2, 1, "assistant", "b"), (3, 0, "tool", "x"), (None, 0, None, None), (4, None, "system", ""), (4, 0, "user", "q"), (4, 1, "assistant", "")]
    frame = spark.createDataFrame([(*r, "x") for r in rows], "conv_id long, turn long, role string, text string, segment string")
    got = {r["conv_id"]: r for r in chat.format_digests(frame).collect()}
    assert {k: r["n_turns"] for k, r in got.items()} == {1: 2, 2: 3, 3: 1, None: 1, 4: 3}
    assert got[1]["turns_sha256"] == hashlib.sha256(b"user\nhi\nassistant\nho </s>\n").hexdigest()
    assert got[2]["loss_chars"] == 2 and got[2]["loss_sha256"] == hashlib.sha256(b"bb").hexdigest()
    assert {k: r["valid"] for k, r in got.items()} == {1: True, 2: False, 3: False, None: False, 4: True}
    segments = chat.format_segments(frame).where("conv_id = 1").orderBy("segment").collect()
    assert "".join(r["text"] for r in segments) == "<s>[INST]hi[/INST][ANS]ho <\\/s></s>" and len("".join(r["text"] for r in segments)) == got[1]["formatted_chars"]
    assert chat.format_digests(frame.limit(0)).count() == 0


# near-duplicates ---------------------------------------------------------------------------------
def brute_components(rows, num=75, den=100):
    def shingles(text):
        w = WORD.findall((text or "").translate(LOWER))
        return frozenset([tuple(w)] if 0 < len(w) < 5 else [tuple(w[k : k + 5]) for k in range(len(w) - 4)])

    own = [(i, shingles(t)) for i, t in rows]
    root = list(range(len(own)))

    def find(k):
        while root[k] != k:
            k = root[k]
        return k

    for a, b in itertools.combinations(range(len(own)), 2):
        x, y = own[a][1], own[b][1]
        if x and y and den * len(x & y) >= num * len(x | y):
            root[find(a)] = find(b)
    out = []
    for k, (i, s) in enumerate(own):
        ids = [j for m, (j, _) in enumerate(own) if find(m) == find(k) and j is not None]
        out.append((i, len(s), min(ids) if i is not None else None))
    return sorted(out, key=str)


def test_near_duplicates_of_all_kinds(docs, empty):
    got = neardup.near_duplicates(docs).collect()
    assert sorted(((r["doc_id"], r["n_shingles"], r["component_id"]) for r in got), key=str) == brute_components(rows_of_all_kinds())
    assert all(r["kept"] == (r["doc_id"] is None or r["doc_id"] == r["component_id"]) for r in got)
    assert neardup.near_duplicates(empty).count() == 0


@pytest.mark.parametrize("blocks", [(2_000_000, 2048), (700, 3)])
def test_groups_of_near_copies(spark, monkeypatch, blocks):
    monkeypatch.setattr(neardup, "SET_BLOCK", blocks[0])
    monkeypatch.setattr(neardup, "RUN_BLOCK", blocks[1])
    rng = random.Random(4)
    rows = []
    for base in range(3):
        words = [f"w{rng.randint(0, 9999)}" for _ in range(120)]
        for copy in range(40):
            own = list(words)
            for _ in range(rng.randint(0, 6)):
                own[rng.randrange(120)] = f"e{rng.randint(0, 9)}"
            rows.append((len(rows), " ".join(own)))
    got = neardup.near_duplicates(spark.createDataFrame(rows, "doc_id long, text string")).collect()
    assert sorted(((r["doc_id"], r["n_shingles"], r["component_id"]) for r in got), key=str) == brute_components(rows)


# words -------------------------------------------------------------------------------------------
@settings(max_examples=200, deadline=None)
@given(st.lists(st.one_of(st.none(), st.text(alphabet="aAbB \t\n\x0b\x1cé", max_size=12)), max_size=6))
def test_word_hashes_follow_the_words(texts):
    hashes, at = hashing.word_hashes(pa.array(texts, pa.string()))
    words = [WORD.findall((t or "").translate(LOWER)) for t in texts]
    assert [b - a for a, b in itertools.pairwise(at.tolist())] == list(map(len, words))
    flat = [w for own in words for w in own]
    assert len(set(zip(flat, hashes.tolist(), strict=True))) == len(set(flat)) == len(set(hashes.tolist()))


# language ----------------------------------------------------------------------------------------
def test_language(spark, docs, empty):
    texts = {"en": "the house and the river of the town is old with the people", "de": "das haus und der fluss von der stadt ist alt mit den leuten", "fr": "la maison et la rivière de la ville est vieille avec les gens"}
    rng = random.Random(2)
    rows = [(k, " ".join(rng.choices(texts[lang].split(), k=40)), lang, f"www.{lang}-site.{'de' if lang == 'de' else 'com'}") for k, lang in enumerate(rng.choices(list(texts), k=200))]
    frame = spark.createDataFrame(rows, "doc_id long, text string, lang string, source string")
    model = langid.train_text(frame)
    got = {r["doc_id"]: r for r in langid.identify(frame, model).collect()}
    assert all(got[k]["language"] == lang and got[k]["kept"] for k, _, lang, _ in rows)
    assert not any(r["kept"] for r in langid.identify(frame, model, wanted=["es"]).collect())
    mixed = spark.createDataFrame([(1, "", "x.de"), (2, "", "www.fr-site.com"), (3, '<html lang="fr"> ok', "none.com"), (4, "щука и рыба " * 20, None)], "doc_id long, text string, source string")
    known = langid.identify(frame.select("doc_id", "text", "source").union(mixed.select((mixed.doc_id + 1000).alias("doc_id"), "text", "source")), model)
    judged = {r["doc_id"]: (r["language"], r["kept"]) for r in known.where("doc_id > 1000").collect()}
    assert judged[1001][0] == "de" and judged[1002][0] == "fr" and judged[1003][0] == "fr" and judged[1004] == ("und", False)
    assert langid.identify(docs, model).count() == docs.count()
    assert langid.identify(empty, langid.train_text(empty)).count() == 0


# toxicity ----------------------------------------------------------------------------------------
@settings(max_examples=200, deadline=None)
@given(st.lists(st.sampled_from([-1.0, 2.0, 0.5, 3.0]), min_size=1, max_size=14))
def test_segments_are_maximal(scores):
    """Recursively: the best span (the shortest, then leftmost), then the same on either side."""

    def best(a, b):
        spans = [(sum(scores[i:j]), i, j) for i in range(a, b) for j in range(i + 1, b + 1)]
        spans = [s for s in spans if s[0] > 0]
        if not spans:
            return []
        top = max(s[0] for s in spans)
        _, i, j = min((s for s in spans if s[0] == top), key=lambda s: (s[2] - s[1], s[1]))
        return [*best(a, i), (round(top, 6), i, j - 1), *best(j, b)]

    at = [k for k, s in enumerate(scores) if s > 0]
    import numpy as np

    got = toxicity.maximal_segments(np.array(at, int), np.array([scores[k] for k in at]), 1.0)
    assert sum(s for s, _, _ in got) == pytest.approx(sum(s for s, _, _ in best(0, len(scores))))
    assert max((s for s, _, _ in got), default=0) == pytest.approx(max((s for s, _, _ in best(0, len(scores))), default=0))


def toxic_rows(n=900):
    rng, plain, bad = random.Random(3), [f"word{k}" for k in range(300)], ["vile", "nasty", "foul", "rotten"]
    plain = ["".join(chr(97 + int(c)) for c in str(k * 7919)) for k in range(300)]
    rows, labels = [], []
    for k in range(n):
        words, toxic = rng.choices(plain, k=80), k % 6 == 0
        if toxic:
            for at in rng.sample(range(80), 5):
                words[at] = rng.choice(bad)
        rows.append((k, " ".join(words)))
        labels.append((k, int(toxic)))
    return rows, labels


def test_toxicity(spark, docs, empty):
    from pyspark.sql import functions as F

    rows, labels = toxic_rows()
    frame, marked = spark.createDataFrame(rows, "doc_id long, text string"), spark.createDataFrame([*labels, (None, 1), (1, None)], "doc_id long, toxic int")
    model = toxicity.train(frame, marked, F.col("id") % 4 != 2)
    got = {r["doc_id"]: r for r in toxicity.score_documents(frame, model).collect()}
    held = [(k, t) for k, t in labels if k % 4 == 2]
    assert sum(got[k]["predicted"] == t for k, t in held) >= 0.98 * len(held)
    every = toxicity.score_documents(docs, model).collect()
    assert len(every) == docs.count() and all(0 <= r["score"] <= 1 for r in every)
    assert toxicity.score_documents(empty, model).count() == 0
    nothing = toxicity.train(empty, marked.limit(0), F.lit(True))
    assert all(r["score"] == 0.5 and r["spans"] == [] for r in toxicity.score_documents(docs, nothing).collect())


# quality -----------------------------------------------------------------------------------------
def test_quality_of_all_kinds(docs, empty):
    got = {(r["doc_id"], r["n_words"]): r for r in quality.clean_lines(docs).collect()}
    for i, text in rows_of_all_kinds():
        words = WORD.findall(text or "")
        windows = Counter(zip(words, words[1:], words[2:], strict=False))
        covered = {k + j for k, w in enumerate(zip(words, words[1:], words[2:], strict=False)) if windows[w] > 1 for j in range(3)}
        lines = [x for x in (text or "").split("\n") if WORD.search(x)]
        r = got[(i, len(words))]
        want = (sum(map(len, words)), len(re.findall(r"[#*$%&|<>]", text or "")), len(lines) - len(set(lines)), len(covered), len(words) < 50 or 100 * len(covered) > 50 * len(words))
        assert (r["word_chars"], r["n_symbols"], r["n_dup_lines"], r["n_repeat_words"], r["base_failed"]) == want
    assert quality.clean_lines(empty).count() == 0


def test_quality_verdicts(spark):
    rng = random.Random(6)
    prose = "\n".join(" ".join(f"word{rng.randint(0, 9999)}" for _ in range(12)) + "." for _ in range(8))
    menu = "\n".join(" | ".join(f"item{rng.randint(0, 9999)}" for _ in range(8)) for _ in range(9))
    rows = [(1, prose), (2, menu), (3, prose + "\nHome | News | Mail | More\nAll rights reserved."), (4, "\n".join(f"cookies policy {k} for page {k * 7}." for k in range(20)))]
    got = {r["doc_id"]: r for r in quality.clean_lines(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    assert {k: r["kept"] for k, r in got.items()} == {1: True, 2: False, 3: True, 4: False}
    assert got[3]["cleaned"] == prose


def test_quality_runs_no_python(docs):
    plan = quality.clean_lines(docs.select("doc_id", "text"))._jdf.queryExecution().executedPlan().toString()
    assert "Python" not in plan and "Arrow" not in plan and "Exchange" not in plan


# language model ----------------------------------------------------------------------------------
def brute_model(texts):
    import math

    def padded(text):
        return ["<s>", "<s>", *text.encode().lower().split(), "</s>"]

    def grams(own):
        return zip(own, own[1:], own[2:], strict=False)

    one, three = Counter(w for t in texts for w in padded(t)[2:]), Counter(g for t in texts for g in grams(padded(t)))
    two = Counter((v, w) for _, v, w in three)  # different words before a pair
    before = Counter(w for _, w in two)
    n, v, total = sum(one.values()), len(one), len(two)
    d1, d2, d3 = (lm._discounts([sum(c == k for c in x.values()) for k in range(1, 5)]) for x in (before, two, three))
    g1 = sum(d * sum(min(c, 3) == k for c in before.values()) for k, d in enumerate(d1, 1)) / total if total else 1
    follow = {}
    for *context, w, c in [(*g, c) for table in (two, three) for g, c in table.items()]:
        own = follow.setdefault(tuple(context), [0, 0, 0, 0])
        own[0] += c
        own[min(c, 3)] += 1

    def mixed(c, d, own, below):
        return max(c - [0, *d][min(c, 3)], 0) / own[0] + sum(x * k for x, k in zip(d, own[1:], strict=True)) / own[0] * below

    def p(u, v_, w):
        a = before.get(w, 0)
        lone = (max(a - [0, *d1][min(a, 3)], 0) / total if total else 0) + g1 / (v + 1)
        if (v_,) in follow:
            lone = mixed(two.get((v_, w), 0), d2, follow[v_,], lone)
        if (u, v_) in follow:
            lone = mixed(three.get((u, v_, w), 0), d3, follow[u, v_], lone)
        return lone

    def score(text):
        own = padded(text)
        return len(own) - 2, sum(w in one for w in own[2:]), n, sum(math.log10((one.get(w, 0) + 1) / (n + v + 1)) for w in own[2:]), sum(math.log10(p(*g)) for g in grams(own))

    return score, p, one, v


def test_language_model_of_all_kinds(spark, docs, empty):
    rng = random.Random(8)
    rows = [*rows_of_all_kinds(), *((k, " ".join(rng.choices("a b c d e f g h".split(), k=30))) for k in range(100, 160))]
    frame = spark.createDataFrame(rows, "doc_id long, text string")
    held = {i: zlib.crc32(str(i).encode() if i is not None else b"") % 7 == 2 for i, _ in rows}
    score, p, one, v = brute_model([t or "" for i, t in rows if not held[i]])
    got = sorted((tuple(r) for r in lm.train_and_score(frame).collect()), key=str)
    want = sorted(((i, *score(t or ""), held[i]) for i, t in rows), key=str)
    assert [(g[0], *g[1:4], g[6]) for g in got] == [(w[0], *w[1:4], w[6]) for w in want]
    for g, w in zip(got, want, strict=True):
        assert g[4:6] == pytest.approx(w[4:6], rel=1e-9)
    for context in ((b"a", b"b"), ("<s>", "<s>"), ("<s>", b"a"), (b"never", b"a"), (b"never", b"seen")):
        assert sum(p(*context, w) for w in one) + p(*context, "nothing") == pytest.approx(1)
    assert lm.train_and_score(empty).count() == 0
    uniform = lm.score_documents(docs, lm.train(empty.select("text"))).where("doc_id = 0").first()
    assert uniform["score"] == uniform["base_score"] == 0


def test_vocabulary_files_are_not_in_the_repository():
    import subprocess
    from pathlib import Path

    names = subprocess.run(["git", "ls-files"], cwd=Path(__file__).parents[2], capture_output=True, text=True).stdout.split()
    assert not any(n.endswith((".tiktoken", ".model")) or "bpe" in n and n.endswith(".json") for n in names)
    assert json.dumps(names)
