"""The training-data operators against brute force, on fixtures with the edge cases."""

import base64
import collections
import hashlib
import random
import re
import zlib

import numpy as np
import pyarrow as pa
import pytest
import public_tokenizers as P
import tiktoken
from tokenizers import Tokenizer

from weftline.llm import bpe, components, decontaminate, jaccard, licences, quality, records, substrings, urls, warc, wordpiece

RANKS = P.path("byte_bpe_multi_50k.tiktoken")
WORDS = P.path("word_bpe_49k.json")
DOCS = "doc_id bigint, text string, lang string, items string, n_words string"


def documents():
    """Null and empty texts, null ids, copies, near copies, shared passages, hot words, long texts."""
    rng = random.Random(5)
    vocabulary = ["".join(rng.choice("abcdefgéß") for _ in range(rng.randint(1, 7))) for _ in range(400)]

    def words(n):
        return [rng.choice(vocabulary) for _ in range(n)]

    texts = [None, "", " \n\t", "one", "Two words", "a b c", "A B C", "a b c d"]
    passage, base = words(80), words(120)
    for i in range(12):
        own = words(rng.randint(20, 150))
        at = rng.randint(0, len(own))
        texts.append(" ".join(own[:at] + passage[rng.randint(0, 20) :] + own[at:]))
    for i in range(15):
        near = list(base)
        for _ in range(rng.randint(0, 4)):
            near[rng.randrange(len(near))] = rng.choice(vocabulary)
        texts.append(" ".join(near))
    texts += [" ".join(base)] * 5 + ["spam " * 300, "spam " * 200 + " ".join(words(60)), " ".join(words(6000))]
    texts += ["Line one is here.\nLine one is here.\nlast\tline  with   gaps\x0b.", "Not-ASCII É é 日本 \xa0 x\x1cy ²"]
    rows = [(i, t, "en", "clash", "clash") for i, t in enumerate(texts)]
    return rows + [(None, " ".join(base), None, None, None), rows[9], rows[9]]


@pytest.fixture(scope="module")
def docs(spark):
    return spark.createDataFrame(documents(), DOCS).repartition(3)


@pytest.fixture(scope="module")
def nothing(spark):
    return spark.createDataFrame([], DOCS)


def plain(text):
    return re.findall(r"[^\x20\x09-\x0D]+", text or "")


def lower(text):
    return re.sub("[A-Z]", lambda m: m[0].lower(), text or "")


def alnum(text):
    return re.findall(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+", lower(text))


def by_id(df):
    return {r["doc_id"]: r.asDict() for r in df.collect()}


# 1 licence scans


def test_licence_places(spark):
    texts = [
        "Under the MIT License, under the mit-license! CC BY-NC 4.0", "Apache License, Version 2.0", None, "",
        "cc by nc cc by nc", "plain words", "SPDX-License-Identifier: (MIT OR GPL-2.0-only) AND Apache-2.0\nrest",
        "the GNU General Public License, version 3.", "SPDX-License-Identifier: MIT OR (", "é under the mit license é",
    ]
    got = by_id(licences.scan_licences(spark.createDataFrame(list(enumerate(texts)), "doc_id int, text string")))
    for i, t in enumerate(texts):
        w, starts, labels = alnum(t), [], set()
        for phrase, label in licences.BASE.items():
            p = phrase.split()
            at = [k for k in range(len(w)) if w[k : k + len(p)] == p]
            starts += at
            labels |= {label} if at else set()
        r = got[i]
        assert (r["n_words"], r["n_base"], r["base_labels"]) == (len(w), len(starts), ",".join(sorted(labels)))
        assert (r["first_word"], r["last_word"]) == ((min(starts), max(starts)) if starts else (None, None))
        assert labels <= set(r["labels"].split(",")) and 0 <= r["score"] <= 1
    assert got[6]["allowed"] is True and got[8]["allowed"] is False and "gpl-3" in got[7]["labels"]


@pytest.mark.parametrize(
    ("told", "accepted", "good"),
    [
        ("MIT", {"mit"}, True), ("MIT AND GPL-3.0-only", {"mit"}, False), ("GPL-3.0-only OR MIT AND ISC", {"mit", "isc"}, True),
        ("(GPL-3.0-only OR MIT) AND ISC", {"mit"}, False), ("GPL-2.0-only WITH Classpath-exception-2.0", {"gpl-2.0-only with classpath-exception-2.0"}, True),
        ("GPL-2.0-only WITH Classpath-exception-2.0 OR X", {"y"}, False), ("MIT WITH X OR Y", {"mit"}, True),
    ],
)
def test_expressions(told, accepted, good):
    assert licences.satisfied(licences.postfix(told), frozenset(accepted)) is good


def test_malformed_expressions():
    for told in ("", "MIT OR", "AND MIT", "(MIT", "MIT)", "MIT ISC", "()", "(A OR B) WITH C", "A WITH (B OR C)", "A WITH B WITH C", "A WITH", "WITH B"):
        assert licences.postfix(told) is None
    assert licences.identifiers(licences.postfix("A with B or (C and D)")) == {"a with b", "c", "d"}


def test_long_expressions(spark):
    many = " with ".join(f"(a{i} or b{i})" for i in range(40))
    rows = [(1, f"SPDX-License-Identifier: {many}"), (2, "SPDX-License-Identifier: " + " OR ".join(["MIT"] * 50_000)), (3, "x" * 3_000_000)]
    got = by_id(licences.scan_licences(spark.createDataFrame(rows, "doc_id int, text string")))
    assert (got[1]["allowed"], got[2]["allowed"], got[3]["n_words"]) == (False, True, 1) and got[2]["labels"] == "mit"


# 2 substring dedup


def brute_repeats(rows, size=50):
    first = {}
    for i, t, *_ in rows:
        if i is not None:
            w = plain(t)
            for k in range(len(w) - size + 1):
                g = tuple(w[k : k + size])
                first[g] = min(first.get(g, i), i)
    out = {}
    for i, t, *_ in rows:
        w = plain(t)
        gone = set()
        if i is not None:
            for k in range(len(w) - size + 1):
                if first[tuple(w[k : k + size])] < i:
                    gone |= set(range(k, k + size))
        left = " ".join(x for k, x in enumerate(w) if k not in gone)
        out[i] = (len(w), len(gone), hashlib.sha256(left.encode()).hexdigest())
    return out


def test_repeats(docs):
    found = substrings.repeat_digests(docs).collect()
    assert len(found) == len(documents())
    got = {r["doc_id"]: (r["n_words"], r["n_removed"], r["kept_sha256"]) for r in found}
    assert got == brute_repeats(documents())
    assert sum(r[1] for r in got.values()) > 500


def test_repeats_removed(docs, nothing):
    kept = substrings.remove_repeats(docs)
    assert kept.columns == docs.columns
    want = brute_repeats(documents())
    for r in kept.collect():
        assert hashlib.sha256(" ".join(plain(r["text"])).encode()).hexdigest() == want[r["doc_id"]][2]
    assert {r["doc_id"] for r in kept.collect()} == {i for i, (n, gone, _) in want.items() if not gone or gone < n}
    assert substrings.remove_repeats(nothing).count() == 0 and substrings.repeat_digests(nothing).count() == 0


# 3 records


def test_records(spark, docs, nothing, tmp_path):
    folder = str(tmp_path / "records")
    manifest = records.write_records(docs, WORDS, folder).collect()
    got = records.read_records(spark, manifest, ids=True).collect()
    tokenizer = Tokenizer.from_file(WORDS)
    key = lambda r: (r[0] is not None, r[0] or 0)
    start = 0
    for (i, text, *_), r in zip(sorted(documents(), key=key), sorted(got, key=lambda r: r["start"])):
        ids = [*tokenizer.encode(text or "", add_special_tokens=False).ids, 2]
        assert (r["doc_id"], r["start"], r["n_tokens"], r["token_ids"]) == (i, start, len(ids), ids)
        assert r["ids_crc32"] == zlib.crc32(np.array(ids, "<u4").tobytes())
        start += len(ids)
    m = max(manifest, key=lambda m: m["n_docs"])
    read = list(records.read_at(m["path"], [2, 0]))
    mine = sorted((r for r in got if r["path"] == m["path"]), key=lambda r: r["offset"])
    assert [x.tolist() for _, x in read] == [mine[2]["token_ids"], mine[0]["token_ids"]]
    assert records.read_records(spark, records.write_records(nothing, WORDS, str(tmp_path / "none")).collect()).count() == 0


def test_damaged_record(tmp_path):
    import io

    whole = bytearray(records.frame(b"payload"))
    assert list(records.unframe(io.BytesIO(bytes(whole)))) == [b"payload"]
    whole[14] ^= 1
    with pytest.raises(ValueError):
        list(records.unframe(io.BytesIO(bytes(whole))))


def test_word_encoder_is_exact():
    coder, tokenizer, rng = records.WordEncoder(WORDS), Tokenizer.from_file(WORDS), random.Random(2)
    letters, texts = [*"abIİΣσς é,́'1.\n \t\xa0　\x1c<|>", "<|endoftext|>", "<|ENDOFTEXT|>", "\x01", "ﬁ", "'s"], []
    for _ in range(1500):
        text = "".join(rng.choice(letters) for _ in range(rng.randint(0, 30)))
        texts.append(text)
    flat, ends = coder.encode(pa.array([t.encode() for t in ["left out", *texts]], pa.binary()).slice(1))
    for text, begin, end in zip(texts, ends, ends[1:]):
        assert flat[begin:end].tolist() == tokenizer.encode(text, add_special_tokens=False).ids
    flat, ends = coder.encode(pa.array([], pa.binary()))
    assert (flat.tolist(), ends.tolist()) == ([], [0])


# 4 byte-level BPE


@pytest.fixture(scope="module")
def reference():
    with open(RANKS, "rb") as f:
        ranks = {base64.b64decode(a): int(b) for a, b in map(bytes.split, f)}
    return tiktoken.Encoding("own", pat_str=P.PATTERN, mergeable_ranks=ranks, special_tokens={})


def test_bpe(docs, nothing, reference):
    coded = bpe.encode(docs, RANKS, P.PATTERN)
    got = coded.collect()
    texts = {i: t or "" for i, t, *_ in documents()}
    assert len(got) == len(documents())
    for r in got:
        ids = reference.encode_ordinary(texts[r["doc_id"]])
        assert (r["token_ids"], r["n_tokens"]) == (ids, len(ids))
        assert r["ids_sha256"] == hashlib.sha256(np.array(ids, "<u4").tobytes()).hexdigest()
        assert r["decoded_sha256"] == hashlib.sha256(texts[r["doc_id"]].encode()).hexdigest()
    for r in bpe.decode(coded, RANKS, P.PATTERN).collect():
        assert bytes(r["text_bytes"]).decode() == texts[r["doc_id"]]
    assert bpe.encode(nothing, RANKS, P.PATTERN).count() == 0


def test_bpe_on_odd_texts(reference):
    coder, rng = bpe.Encoder(RANKS, P.PATTERN), random.Random(3)
    letters = [*"ab .,'s\n\t\xa0　\x1c\x1f\x85éßñ日本🙂1٣²re!?#", "  ", "\r\n", "don't ", " ́", "the "]
    for _ in range(2000):
        text = "".join(rng.choice(letters) for _ in range(rng.randint(0, 40)))
        assert np.frombuffer(coder.encode([text])[0], "<u4").tolist() == reference.encode_ordinary(text)
    for n in (255, 256, 257, 3000):
        text = "".join(rng.choice("abcdeé") for _ in range(n))
        assert np.frombuffer(coder.encode([text])[0], "<u4").tolist() == reference.encode_ordinary(text)


def test_bpe_takes_positions_of_any_length(reference, monkeypatch):
    monkeypatch.setattr(bpe, "POSITION_BITS", 8)
    ranks, text = bpe.Ranks(RANKS), "abcdetheing" * 90
    assert np.frombuffer(bpe.encode_lone(text.encode(), ranks), "<u4").tolist() == reference.encode_ordinary(text)


# 5 token counts


def brute_pieces(word, start, inner):
    n, at = 0, 0
    while at < len(word):
        known = inner if at else start
        size = next((k for k in range(len(word) - at, 0, -1) if word[at : at + k] in known), 0)
        if not size:
            return 0
        at, n = at + size, n + 1
    return n


def test_piece_counts_small_vocabularies():
    rng = random.Random(4)
    for _ in range(150):
        some = lambda: list({bytes(rng.choice(b"abc") for _ in range(rng.randint(1, 5))) for _ in range(rng.randint(1, 14))})
        start, inner = some(), some()
        automaton = wordpiece.Pieces(start, inner)
        for _ in range(60):
            word = bytes(rng.choice(b"abcd") for _ in range(rng.randint(1, 12)))
            assert automaton.count(word) == brute_pieces(word, set(start), set(inner))


def test_piece_counts(docs, nothing):
    with open(RANKS, "rb") as f:
        tokens = [base64.b64decode(x.split()[0]) for x in f]
    start, inner = {t[1:] for t in tokens if t[:1] == b" "}, {t for t in tokens if t[:1] != b" "}
    texts = {i: t for i, t, *_ in documents()}
    for r in wordpiece.count_pieces(docs, RANKS).collect():
        each = [brute_pieces(w.encode(), start, inner) for w in plain(texts[r["doc_id"]])]
        assert (r["n_words"], r["n_pieces"], r["n_unknown"]) == (len(each), sum(each) + each.count(0), each.count(0))
    assert wordpiece.count_pieces(nothing, RANKS).count() == 0


def test_every_word_is_spelt():
    usual, whole = wordpiece.from_ranks(RANKS), wordpiece.from_ranks(RANKS, spell_all=True)
    for word in ("漢字かな交じり文", "ภาษาไทย", "𐍈"):
        assert usual.count(word.encode()) == 0 < whole.count(word.encode()) <= len(word.encode())
    assert all(whole.count(w) == usual.count(w) for w in (b"the", b"tokenization", "é".encode()))


# 6 Jaccard join


def brute_components(rows, k, percent):
    sets = {}
    for i, t, *_ in rows:
        w = plain(lower(t))
        sets[i] = {tuple(w[j : j + k]) for j in range(len(w) - k + 1)} if len(w) >= k else ({tuple(w)} if w else set())
    up = {i: i for i in sets}

    def root(x):
        while up[x] != x:
            x = up[x]
        return x

    ids = [i for i in sets if i is not None]
    for a in ids:
        for b in ids:
            if a < b and sets[a] and sets[b]:
                o = len(sets[a] & sets[b])
                if 100 * o >= percent * (len(sets[a]) + len(sets[b]) - o):
                    x, y = root(a), root(b)
                    up[max(x, y)] = min(x, y)
    return {i: (len(s), root(i)) for i, s in sets.items()}


@pytest.mark.parametrize(("k", "percent"), [(3, 90), (5, 80), (2, 70)])
def test_jaccard(docs, k, percent):
    found = jaccard.jaccard_components(docs, k, percent).collect()
    assert len(found) == len(documents())
    got = {r["doc_id"]: (r["n_shingles"], r["component_id"]) for r in found}
    assert got == brute_components(documents(), k, percent)
    assert len({c for _, c in got.values()}) < len(got)


@pytest.mark.parametrize("bounds", [
    {"CUT_SETS": 4}, {"CUT_SETS": 5, "FLAT_ROWS": 2, "FIRST_WINDOW": 1, "GROWTH": 2, "ASKING_ROWS": 3}, {"FLAT_ROWS": 1, "BROADCAST_PAIRS": 0},
])
def test_jaccard_cuts(docs, monkeypatch, bounds):
    for name, value in bounds.items():
        monkeypatch.setattr(jaccard, name, value)
    got = {r["doc_id"]: (r["n_shingles"], r["component_id"]) for r in jaccard.jaccard_components(docs, 3, 80).collect()}
    assert got == brute_components(documents(), 3, 80)


def test_jaccard_one_stays(docs, nothing):
    want = brute_components(documents(), 5, 80)
    kept = jaccard.one_of_each(docs)
    assert kept.columns == docs.columns
    assert {r["doc_id"] for r in kept.collect()} == {i for i, (_, c) in want.items() if i is None or c == i}
    assert jaccard.jaccard_components(nothing).count() == 0


def test_count_tree_misses_nothing():
    rng = np.random.default_rng(1)
    base = rng.integers(0, 2**63, 300).astype(np.uint64)
    sets = [np.unique(np.concatenate([base[rng.random(300) > 0.1], rng.integers(0, 2**63, int(rng.integers(0, 40))).astype(np.uint64)])) for _ in range(120)]
    tree = jaccard.CountTree(np.stack([jaccard.count_vector(s) for s in sets]), np.array(list(map(len, sets))))
    for s in sets:
        got = set(tree.candidates(jaccard.count_vector(s), len(s), 80).tolist())
        assert {j for j, o in enumerate(sets) if jaccard.linked(s, o, 80)} <= got


def test_components(spark):
    links = [(i, i + 1) for i in range(40)] + [(100, 102), (102, 101), (7, 7), (200, 201)]
    got = {r["id"]: r["component"] for r in components.components(spark.createDataFrame(links, "a bigint, b bigint")).collect()}
    assert got == {**{i: 0 for i in range(41)}, 100: 100, 101: 100, 102: 100, 200: 200, 201: 200}


def test_components_of_long_paths(spark):
    shuffled = random.Random(3).sample(range(3000), 3000)
    falling = [10_000, *range(12_000, 10_000, -1)]
    links = [(10 + a, 10 + b) for a, b in zip(shuffled, shuffled[1:])] + list(zip(falling, falling[1:]))
    rows = components.components(spark.createDataFrame(links, "a bigint, b bigint").repartition(4)).collect()
    assert len(rows) == 5001
    assert {r["id"]: r["component"] for r in rows} == {**{10 + i: 10 for i in range(3000)}, **{i: 10_000 for i in falling}}


# 7 quality rules


def test_quality_measures(docs, nothing):
    found = quality.quality(docs).collect()
    assert len(found) == len(documents())
    texts = {i: t for i, t, *_ in documents()}
    for r in found:
        t = texts[r["doc_id"]] or ""
        w, lines, seen = plain(t), [x for x in t.split("\n") if plain(x)], set()
        dup = sum(x in seen or seen.add(x) is not None for x in lines)
        grams = collections.Counter(tuple(w[k : k + 5]) for k in range(len(w) - 4))
        again = {j for k in range(len(w) - 4) if grams[tuple(w[k : k + 5])] > 1 for j in range(k, k + 5)}
        base = len(w) < 10 or 100 * len(again) > 20 * len(w)
        assert (r["n_words"], r["word_chars"], r["n_dup_lines"], r["n_repeat_words"]) == (len(w), sum(map(len, w)), dup, len(again))
        assert r["n_symbols"] == len(re.findall(r"[#*$%&|<>]", t)) and r["base_failed"] == base and not (base and r["kept"])
    assert quality.quality(nothing).count() == 0


def test_quality_verdicts(spark):
    good = "The rules keep a text like this one, which has whole sentences.\nIt goes on for some lines that all end well.\n" * 1 + "Nothing here is out of order."
    bad = ["a | b | c | d | e | f | g\n" * 4, "WORDS!! SHOUTED!! LOUDLY!! HERE!! AND!! THERE!! ALL!! DAY!! LONG!! TOO!!", "x*** y### z$$$ q%%% r&&& s*** t### u$$$ v%%% w&&&", "no end of the sentence in this line of words here\n" + "nor is there one in the next line of the text"]
    got = {r["i"]: r for r in quality.quality(spark.createDataFrame(list(enumerate([good, *bad])), "i int, text string")).collect()}
    assert [got[i]["kept"] for i in range(5)] == [True, False, False, False, False]
    assert got[0]["clean_text"] == good


def test_navigation():
    for line, told in (
        ("делал", False), ("Он сделал это вчера.", False), ("главная | новости | о нас", False), ("главная » новости » блог", True), ("首页 · 新闻 ·", True),
        ("这是 一 句 话。", False), ("a | b", False), ("a > b > c", True), ("a >> b > c", False), ("л" * 1_000_000 + " x y", False), ("a|" * 500_000, True),
    ):
        assert quality.navigation(line) is told, line[:40]
    long = ("л" * 24 + " ") * 2 + "слово " * 50_000
    assert quality.failed_rule(long.encode(), long.encode().split(), quality.Rules()) == "open"


def test_quality_against_labels(spark, tiny):
    tiny = tiny.replace("sf0.001", "sf0.01")
    judged = quality.quality(spark.read.parquet(f"{tiny}/documents.parquet"), results=("kept", "base_failed"))
    rows = judged.join(spark.read.parquet(f"{tiny}/labels.parquet"), "doc_id").filter("not base_failed").collect()
    good = [r["kept"] for r in rows if r["quality"]]
    bad = [r["kept"] for r in rows if not r["quality"]]
    assert np.mean(good) > 0.97 and np.mean(bad) < 0.2


# 8 URL filters


def test_urls(spark):
    told = ["https://A.Example.NET/en/1?x=1", "http://example.net/fr/", "http://x.net", "http://x.net?q", "no host", None, "", "http://b.org/fr/x", "http://example.com/de/1#f", "http://badexample.com/de/", "s://h/p?a://b/c"]
    pages = spark.createDataFrame(list(enumerate(told)), "page_id int, url string")
    got = {r["page_id"]: r for r in urls.filter_urls(pages).collect()}
    for i, u in enumerate(told):
        host = re.sub(r"[A-Z]", lambda m: m[0].lower(), (re.match(r".*?://([^/?#]*)", u or "") or [0, ""])[1])
        path = (re.match(r".*?://[^/?#]*([^?#]*)", u or "") or [0, ""])[1]
        fits = [r for r in urls.RULES for h, _, p in [r.partition("/")] if (host == h or host.endswith("." + h)) and path.startswith("/" + p)]
        rule = max(fits, key=len, default=None)
        assert (got[i]["host"], got[i]["path"], got[i]["rule"]) == (host, path, rule)
        assert got[i]["verdict"] == (urls.RULES[rule] if rule else got[i]["verdict"]) and got[i]["verdict"] in ("allow", "block")


def test_url_trees_on_held_out_urls():
    rng = random.Random(6)
    make = lambda bad: f"http://{'x' * rng.randint(2, 9)}.{rng.choice(['info', 'biz'] if bad else ['com', 'org'])}/" + "/".join(str(rng.randint(1, 10**6)) if bad else "page" for _ in range(rng.randint(1, 4)))
    y = np.array([rng.random() < 0.4 for _ in range(1500)], float)
    some = [make(v > 0) for v in y]
    known = urls.Suffixes.of([urls.parts_of(u)[0] for u in some[:1000]], y[:1000])
    model = urls.UrlModel(known, urls.Trees.fit(urls.features(some[:1000], known), y[:1000]))
    assert ((model.block_probability(some[1000:]) > 0.5) == (y[1000:] > 0)).mean() > 0.95


def test_urls_without_labels(spark):
    got = urls.filter_urls(spark.createDataFrame([(1, "http://a.info/x")], "page_id int, url string")).collect()
    assert got[0]["verdict"] in ("allow", "block")
    assert urls.filter_urls(spark.createDataFrame([], "page_id int, url string")).count() == 0


def test_url_sample_is_bounded_and_exact(spark):
    rows = [(f"http://a.net/{i % 700}", i % 2 == 0) for i in range(3000)] + [("http://hot.org/fr/", True)] * 3000
    told = spark.createDataFrame(rows, "url string, blocked boolean").repartition(5)
    for n in (10, 1000, 5900, 20_000):
        assert urls.fit_urls(told, rows=n).suffixes.prior >= 0


# 9 decontamination


def brute_hits(rows, items, n=10):
    grams = collections.defaultdict(set)
    for item, text in items:
        w = alnum(text)
        for k in range(len(w) - min(n, len(w)) + 1):
            if w:
                grams[tuple(w[k : k + n])].add(item)
    out = {}
    for i, t, *_ in rows:
        w, hit, found = alnum(t), set(), set()
        for size in {len(g) for g in grams}:
            for k in range(len(w) - size + 1):
                if got := grams.get(tuple(w[k : k + size])):
                    hit |= set(range(k, k + size))
                    found |= got
        out[i] = (len(w), len(hit), sorted(map(str, found)))
    return out


@pytest.mark.parametrize("broadcast", [True, False])
def test_decontamination(spark, docs, nothing, monkeypatch, broadcast):
    if not broadcast:
        monkeypatch.setattr(decontaminate, "BROADCAST_BYTES", 0)
    rows = documents()
    items = [(1, " ".join(rows[10][1].split()[5:25]).upper()), (2, "one"), (3, None), (4, "!!"), (10, " ".join(rows[10][1].split()[8:20])), (11, "Spam " * 12), (12, "never in any of the documents at all is this one"), (2, "one")]
    benchmark = spark.createDataFrame(items, "item_id bigint, text string")
    flagged = decontaminate.flag(docs, benchmark)
    found = flagged.collect()
    assert len(found) == len(rows)
    got = {r["doc_id"]: (r["n_words"], r["n_hit"], r["items"]) for r in found}
    assert got == brute_hits(rows, items)
    clean = decontaminate.decontaminate(docs, benchmark)
    assert clean.columns == docs.columns and {r["doc_id"] for r in clean.collect()} == {i for i, r in got.items() if not r[1]}
    cut = decontaminate.decontaminate(docs, benchmark, how="spans")
    assert all(len(alnum(r["text"])) == got[r["doc_id"]][0] - got[r["doc_id"]][1] for r in cut.collect())
    assert decontaminate.flag(nothing, benchmark).count() == 0
    assert decontaminate.flag(docs, benchmark.limit(0)).filter("contaminated").count() == 0


def test_decontamination_is_native(docs, spark):
    plan = decontaminate.flag(docs, spark.createDataFrame([(1, "a b c")], "item_id int, text string"))._jdf.queryExecution().executedPlan().toString()
    assert not re.search("Python|Arrow|Pandas", plan)


# 10 WARC


def test_warc(spark, monkeypatch):
    inside = "x\r\n\r\n" + warc.record(7, "http://fake", b"fake block", None).decode() + "tail"
    rows = [(1, "http://a", "<p>é</p>"), (2, "http://b", "<p>é</p>"), (3, None, None), (4, "u r\r\nl", ""), (5, "http://c", inside), (6, "http://d", "WARC/1.1\r\n" * 50), (None, "n", "<p>é</p>"), (8, "l", "y" * 70_000), (9, "m", inside * 30), (2, "http://b", "<p>é</p>")]
    pages = spark.createDataFrame(rows, "page_id bigint, url string, html string").repartition(2)
    for split in (1 << 20, 1000, 97):
        made = warc.write_warc(pages, warc.scratch(spark, "warc")).collect()
        got = warc.read_warc(spark, [(m["path"], m["bytes"]) for m in made], split_bytes=split, payload=True).collect()
        assert len(got) == len(rows)
        first = {}
        for i, _, html in rows:
            if i is not None:
                first[html or ""] = min(first.get(html or "", i), i)
        texts = {i: (h or "").encode() for i, _, h in rows}
        for r in got:
            html = texts[r["page_id"]]
            own = first.get(html.decode(), r["page_id"])
            assert (r["payload_bytes"], r["payload_digest"]) == (len(html), base64.b32encode(hashlib.sha1(html).digest()).decode())
            assert (r["record_type"], r["refers_to"]) == (("response", None) if own == r["page_id"] else ("revisit", own))
            assert bytes(r["html"]) == (html if r["record_type"] == "response" else b"")
    assert warc.archive(pages.limit(0)).count() == 0


def test_warc_long_urls(spark):
    long = {1: 66_000, 3: 69_000, 5: 1_000_000}
    rows = [(i, "http://" + "u" * long.get(i, 10), f"<p>{i}</p>" + "WARC/1.1\r\nA: b\r\n" * 9) for i in range(40)]
    pages = spark.createDataFrame(rows, "page_id bigint, url string, html string").coalesce(1)
    made = warc.write_warc(pages, warc.scratch(spark, "warc")).collect()
    for split in (1 << 23, 200_000, 20_000):
        got = warc.read_warc(spark, [(m["path"], m["bytes"]) for m in made], split_bytes=split, payload=True).collect()
        assert sorted((r["page_id"], r["url"], bytes(r["html"]).decode()) for r in got) == rows


# names of columns


CLASHING = {
    "n_words": "a", "kept": "b", "items": "c", "spans": "d", "n_hit": "e", "_id": "f", "_decided": "g", "judged": "h", "made": "i", "gone": "j", "verdict": "k",
    "a.b": "l", "a`b": "m", "left": "n", "id": "o", "raw": "p", "_made": "q", "labels": "r", "token_ids": "s", "hit": "t", "clean_text": "u", "url_host": "v",
}


def test_clashing_names(spark):
    text = "The rules keep a text like this one, which has whole sentences. It goes on and on and says little more than that."
    frame = spark.createDataFrame([(1, text, *CLASHING.values()), (2, None, *CLASHING.values())], ["doc_id", "text", *CLASHING])
    frame = frame.withColumn("doc_id", frame["doc_id"].cast("long"))
    bench = spark.createDataFrame([(1, "nothing of this is in there")], "item_id int, text string")

    def kept(out, results=(), lost=()):
        rows = [r.asDict() for r in out.collect()]
        assert rows and all(r[n] == v for r in rows for n, v in CLASHING.items() if n not in results)
        assert set(out.columns) == (set(frame.columns) - set(lost)) | set(results)

    kept(quality.quality(frame, results=("kept",)), ("kept",))
    kept(quality.quality(frame), tuple(quality.FIELDS))
    kept(quality.good_documents(frame))
    kept(jaccard.one_of_each(frame))
    kept(substrings.remove_repeats(frame))
    kept(decontaminate.decontaminate(frame, bench))
    kept(decontaminate.decontaminate(frame, bench, how="spans"))
    kept(decontaminate.flag(frame, bench), ("n_words", "n_hit", "items", "spans", "contaminated"))
    kept(licences.scan_licences(frame), tuple(licences.FIELDS), ("text",))
    kept(wordpiece.count_pieces(frame, RANKS), tuple(wordpiece.FIELDS), ("text",))
    kept(bpe.encode(frame, RANKS, P.PATTERN), ("n_tokens", "token_ids", "ids_sha256", "decoded_sha256"), ("text",))
    kept(urls.filter_urls(frame, url="text"), urls.RESULTS)


# very long texts


def test_very_long_texts(spark):
    rng = random.Random(3)
    long = " ".join(rng.choice("abcdefgh") * rng.randint(1, 9) for _ in range(60_000))
    texts = [long, "spam " * 60_000, "x" * 20_000_000, "y" * 1_000_000 + "\n" + "z " * 1000, long + " tail", "spam " * 60_001 + "tail"]
    rows = list(enumerate(texts))
    frame = spark.createDataFrame(rows, "doc_id bigint, text string").repartition(2)
    repeats = {r["doc_id"]: (r["n_words"], r["n_removed"]) for r in substrings.repeat_digests(frame).collect()}
    assert repeats == {0: (60_000, 0), 1: (60_000, 0), 2: (1, 0), 3: (1001, 0), 4: (60_001, 60_000), 5: (60_002, 60_001)}
    judged = by_id(quality.quality(frame, results=("n_words", "n_repeat_words", "kept")).drop("text"))
    assert judged[1]["n_repeat_words"] == 60_000 and not judged[1]["kept"] and judged[2]["n_words"] == 1
    assert by_id(licences.scan_licences(frame))[0]["n_words"] == 60_000
    flagged = by_id(decontaminate.flag(frame, spark.createDataFrame([(7, "spam " * 12)], "item_id int, text string")).drop("text"))
    assert {i for i, r in flagged.items() if r["contaminated"]} == {1, 5} and flagged[1]["n_hit"] == 60_000
    counted = by_id(wordpiece.count_pieces(frame, RANKS, spell_all=True))
    assert counted[2]["n_words"] == 1 and counted[2]["n_pieces"] > 1000
    found = {r["doc_id"]: r["component_id"] for r in jaccard.jaccard_components(frame, 3, 90).collect()}
    assert found == {0: 0, 1: 1, 2: 2, 3: 3, 4: 0, 5: 5}


# the pipeline


def test_pipeline(spark, tiny, reference):
    import corpus_pipeline

    got = {r["doc_id"]: r for r in corpus_pipeline.run(spark, tiny).collect()}
    docs = [(r["doc_id"], r["text"]) for r in spark.read.parquet(f"{tiny}/documents.parquet").collect()]
    bench = [(r["item_id"], r["text"]) for r in spark.read.parquet(f"{tiny}/benchmark.parquet").collect()]
    rows = [(i, t) for i, t in docs if quality.judge((t or "").encode(), quality.Rules())[6]]
    groups = brute_components(rows, 5, 80)
    rows = [(i, t) for i, t in rows if groups[i][1] == i]
    repeats = brute_repeats(rows)
    first = {}
    left = []
    for i, t in rows:
        w = plain(t)
        for k in range(len(w) - 49):
            g = tuple(w[k : k + 50])
            first[g] = min(first.get(g, i), i)
    for i, t in rows:
        if repeats[i][1]:
            w = plain(t)
            gone = {j for k in range(len(w) - 49) if first[tuple(w[k : k + 50])] < i for j in range(k, k + 50)}
            t = " ".join(x for k, x in enumerate(w) if k not in gone)
        if t or not repeats[i][1]:
            left.append((i, t))
    hits = brute_hits(left, bench)
    left = {i: t for i, t in left if not hits[i][1]}
    assert set(got) == set(left) and 0 < len(left) < len(docs)
    for i, t in left.items():
        assert got[i]["token_ids"] == reference.encode_ordinary(t)
        assert got[i]["decoded_sha256"] == hashlib.sha256(t.encode()).hexdigest()
