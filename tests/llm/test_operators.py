"""The text operators against brute force and round trips, with nulls, empty and repeated rows."""

import base64
import hashlib
import itertools
import math
import zlib
from collections import Counter

import duckdb
import numpy as np
import pytest
from pyspark.sql import functions as F

from radarlake.llm import decontaminate, flac, language, near_dup, ngram, oracles, packing, pii, queries, suffixes, token_orc, warc
from radarlake.llm.tokens import Encoder

LONG = "the quick brown fox jumps over the lazy dog near the river bank and " * 40
TEXTS = [LONG, LONG, LONG[:-20] + "something else", None, "", "a", "a\tb", "mail me at x.y@z.org or +1 (555) 123-4567, ip 10.0.0.256 and 10.0.0.25", "card 4111 1111 1111 1111 and DE89370400440532013000", "Grüße aus Köln, ça va? ñandú", "!!! 123 ???", "unique words only here " + LONG[100:220]]
SCHEMA = "doc_id long, text string, lang string, source string, n_chars long, extra int"


@pytest.fixture(scope="module")
def docs(spark):
    rows = [(i, t, "en", "s", len(t or ""), 1) for i, t in enumerate(TEXTS)] + [(1, LONG, "en", "s", 1, 2)]
    return spark.createDataFrame(rows, SCHEMA)


@pytest.fixture(scope="module")
def none(spark):
    return spark.createDataFrame([], SCHEMA)


def rows(df):
    return [r.asDict() for r in df.collect()]


def test_flac_round_trip(docs, none):
    for r in rows(flac.round_trip(docs)):
        raw = (TEXTS[r["doc_id"]] or "").encode()
        payload = raw + bytes(max(64, -(-len(raw) // 64) * 64) - len(raw))
        assert (r["n_bytes"], r["payload_bytes"]) == (len(raw), len(payload))
        assert r["payload_sha256"] == hashlib.sha256(payload).hexdigest() and r["tail_crc32"] == zlib.crc32(payload[-64:])
    for r in rows(flac.encode(docs)):
        raw = (TEXTS[r["doc_id"]] or "").encode()
        samples = flac.decode_stream(bytes(r["media"]))[0]
        assert bytes((samples + 128).astype(np.uint8))[: len(raw)] == raw
    assert flac.round_trip(none).count() == 0


def test_flac_refuses_damage():
    data = np.frombuffer(LONG[:1024].encode(), np.uint8)
    media, at = flac.encode_many(data, np.array([0, 1024]))
    broken = media.copy()
    broken[-30] ^= 4
    with pytest.raises(ValueError):
        flac.decode_many(broken, at)
    with pytest.raises(ValueError):
        flac.decode_stream(broken.tobytes())


def test_pii_spans(docs, none):
    got = {r["doc_id"]: r for r in rows(pii.digest(docs))}
    at = TEXTS[7].rindex("10.0.0.25")
    assert got[7]["spans"] == f"email:11:20,ip:{at}:{at + 9},phone:24:41"
    assert (got[8]["n_card"], got[8]["n_iban"]) == (1, 1)
    assert got[3]["base_sha256"] == hashlib.sha256(b"").hexdigest()
    masked = {r["doc_id"]: r["text"] for r in rows(pii.redact(docs))}
    assert masked[7] == "mail me at [email] or [phone], ip 10.0.0.256 and [ip]" and masked[3] is None
    assert pii.digest(none).count() == 0


def test_language(spark):
    text = {"en": "the house and the garden of the king", "de": "das haus und der garten von dem könig", "fr": "la maison et le jardin de le roi"}
    rows_ = [(i, text[k], k) for i, k in enumerate(list(text) * 60)] + [(900, None, "en"), (901, "123 !", "en"), (902, "", None)]
    df = spark.createDataFrame(rows_, "doc_id long, text string, lang string")
    out = {r["doc_id"]: r for r in rows(language.classify(df, queries.vocabulary("piece_bpe_32k.model")))}
    assert all(out[i]["lang_pred"] == k for i, _, k in rows_[:180])
    assert {out[i]["lang_pred"] for i in (900, 901, 902)} == {"und"}


def segmentations(word, p):
    """Probability and expected uses of pieces (a dict) by listing every segmentation."""
    total, uses = 0.0, Counter()
    def cut(rest, pieces, q):
        nonlocal total
        if not rest:
            total += q
            for x in pieces:
                uses[x] += q
        for m in range(1, len(rest) + 1):
            if rest[:m] in p:
                cut(rest[m:], [*pieces, rest[:m]], q * p[rest[:m]])
    cut(word, [], 1.0)
    return total, {k: v / total for k, v in uses.items()}


def test_forward_sums_all_segmentations():
    vocabulary = language.pieces(queries.vocabulary("piece_bpe_32k.model"))
    assert vocabulary.longest > 8
    rng = np.random.default_rng(3)
    p = rng.random(vocabulary.size) + 1e-3
    p /= p.sum()
    number = lambda x: int(vocabulary.edges(np.frombuffer(x, np.uint8)[None, :])[-1][3][0])
    words_ = [b" internationalization"[:16], b" responsibilities"[:16], " größe süd mann".encode()[:16]]
    known = {}
    for w in words_:
        for i in range(16):
            for j in range(i + 1, 17):
                found = [x for x in vocabulary.edges(np.frombuffer(w[i:j], np.uint8)[None, :]) if x[0] == x[1] == j - i]
                if found:
                    known[w[i:j]] = p[found[0][3][0]]
    text = np.frombuffer(b"".join(words_), np.uint8).reshape(3, 16)
    edges = vocabulary.edges(text)
    alpha = language.forward(p, 3, 16, edges)[16]
    uses = language.expected(p, 3, 16, edges, np.array([1.0, 2.0, 3.0]))
    want = np.zeros(len(p))
    for k, w in enumerate(words_):
        total, each = segmentations(w, known)
        assert np.isclose(alpha[k], total)
        assert np.allclose(np.exp(language.forward_long(np.log(p)[:, None], vocabulary, text[k])), total)
        one = language.expected_long(np.log(p), vocabulary, text[k], k + 1.0)
        for x, n in each.items():
            want[number(x)] += n * (k + 1)
            assert np.isclose(one[number(x)], n * (k + 1))
    assert np.allclose(uses, want)


def test_long_words_are_summed_whole():
    """A word of any length: what ends at block borders and beyond the widest piece is as in the plain recursion."""
    vocabulary = language.pieces(queries.vocabulary("piece_bpe_32k.model"))
    text = np.frombuffer((" " + "donaudampfschifffahrt" * 12).encode(), np.uint8)
    want = [(e, m.tolist(), x.tolist()) for e, m, x in vocabulary.ends(text)]
    assert [(e, m.tolist(), x.tolist()) for e, m, x in vocabulary.ends(text, block=7)] == want and len(want) == len(text)
    logs = np.log(np.full((vocabulary.size, 2), 1e-5))
    plain = np.zeros((len(text) + 1, 2))
    for e, m, x in want:
        plain[e] = np.logaddexp.reduce(plain[e - np.array(m)] + logs[x], axis=0)
    assert np.allclose(language.forward_long(logs, vocabulary, text), plain[-1])


def test_language_of_odd_rows(spark, none):
    path = queries.vocabulary("piece_bpe_32k.model")
    assert language.classify(none, path).count() == 0 and language.keep(none, path).count() == 0
    text = {"en": "the house and the garden of the king", "de": "das haus und der garten von dem könig"}
    rows_ = [(i if i < 118 else None, text[k], k, "s", 0.25) for i, k in enumerate(list(text) * 60)] + [(5, text["de"] + " " + "wort" * 3000, None, "t", 0.5), (5, None, "de", None, None)]
    df = spark.createDataFrame(rows_, "doc_id long, text string, lang string, lang_pred string, score double")
    kept = language.keep(df, path)
    assert kept.columns == df.columns
    assert sorted(map(str, kept.collect())) == sorted(str(r) for r in df.collect() if r["text"])


def test_language_held_out_accuracy(spark):
    """On the given table, of languages it learned from other documents."""
    docs = spark.read.parquet("/root/testdata/sf0.01/documents.parquet")
    told = language.classify(docs, queries.vocabulary("piece_bpe_32k.model")).join(docs.select("doc_id", "lang"), "doc_id")
    n, right = told.filter("held_out and lang is not null and lang_pred <> 'und'").selectExpr("count(*)", "count_if(lang = lang_pred)").first()
    assert n > 150 and right / n >= 0.97


def test_warc_round_trip(spark):
    html = ["<p>x</p>", "<p>x</p>", None, "", "y" * 3000, "y" * 3000]
    pages = spark.createDataFrame([(i, f"http://h/{i}", h) for i, h in enumerate(html)], "page_id long, url string, html string")
    got = {r["page_id"]: r for r in rows(warc.round_trip(pages, chunk=700))}
    for i, h in enumerate(html):
        raw = (h or "").encode()
        first = next(k for k, x in enumerate(html) if (x or "") == (h or ""))
        assert got[i]["payload_digest"] == base64.b32encode(hashlib.sha1(raw).digest()).decode() and got[i]["payload_bytes"] == len(raw)
        assert (got[i]["record_type"], got[i]["refers_to"]) == (("response", None) if first == i else ("revisit", first))
    assert got[4]["chunks"] > 4


def naive_repeats(texts):
    first = {}
    for d, t in texts:
        for i in range(len(t) - 49):
            first.setdefault(t[i : i + 50], d)
    for d, t in texts:
        gone = bytearray(len(t))
        for i in range(len(t) - 49):
            if first[t[i : i + 50]] < d:
                gone[i : i + 50] = b"\1" * 50
        yield d, len(t), sum(gone), hashlib.sha256(bytes(x for x, g in zip(t, gone) if not g)).hexdigest()


@pytest.mark.parametrize("common", [16, 1])
def test_repeats_against_brute_force(spark, monkeypatch, common):
    monkeypatch.setattr(suffixes, "SAMPLE", 2 if common == 1 else 64)
    monkeypatch.setattr(suffixes, "COMMON_LEAST", common)
    rng = np.random.default_rng(0)
    passage = "a passage that many documents share, of more than fifty bytes in all, with an é. "
    word = lambda: "".join(rng.choice(list("abcdef"), 4))
    texts = [" ".join(word() for _ in range(40)) + passage[: 40 + i % 45] + " ".join(word() for _ in range(20)) for i in range(40)]
    texts += [texts[3], texts[5][:90] + "x" + texts[5][90:], "", "aa" * 200, "aa" * 120]
    df = spark.createDataFrame([(i, t) for i, t in enumerate(texts)] + [(99, None)], "doc_id long, text string")
    got = {r["doc_id"]: r for r in rows(suffixes.remove_repeats(df))}
    for d, n, gone, kept in naive_repeats([(i, t.encode()) for i, t in enumerate(texts)]):
        assert (got[d]["n_bytes"], got[d]["n_removed"], got[d]["kept_sha256"]) == (n, gone, kept)
    assert got[99]["n_bytes"] == 0


def test_suffix_sort():
    text = np.frombuffer(b"banana bandana banana!", np.uint8)
    starts = np.arange(len(text) - 6)
    order, share = suffixes.sort_suffixes(text, starts, np.full(len(starts), 6), np.zeros(len(starts), np.int64))
    strings = [bytes(text[s : s + 6]) for s in starts[order]]
    assert strings == sorted(strings) and (share >= 6).tolist() == [False, *(a == b for a, b in zip(strings, strings[1:]))]


@pytest.mark.parametrize("lying", [False, True])
def test_suffix_sort_of_unequal_sizes(monkeypatch, lying):
    """Sizes, groups and shared bytes against sorted(); with a hash that calls all strings equal the bytes decide."""
    if lying:
        monkeypatch.setattr(suffixes, "common_extension", lambda prefix, a, b, limit: limit.copy())
    rng = np.random.default_rng(1)
    text = rng.choice(np.frombuffer(b"ab", np.uint8), 400)
    starts, size = rng.integers(0, 380, 200), rng.integers(1, 20, 200)
    group = np.sort(rng.integers(0, 9, 200))
    order, share = suffixes.sort_suffixes(text, starts, size, group)
    raw = [bytes(text[s : s + n]) for s, n in zip(starts, size)]
    assert [(group[i], raw[i]) for i in order] == sorted(zip(group, raw))
    for k in range(1, 200):
        i, j = order[k], order[k - 1]
        want = next((n for n, (p, q) in enumerate(zip(raw[i], raw[j])) if p != q), min(size[i], size[j])) if group[i] == group[j] else 0
        assert share[k] == want


def test_equal_keys_of_unequal_bytes():
    text = np.frombuffer(b"abcabdabcxyabd", np.uint8)
    at, size = np.array([0, 3, 6, 9, 11]), np.array([3, 3, 3, 2, 3])
    order, first = suffixes.equal_groups(text, at, size, np.full(5, 7, np.uint64), np.array([4, 3, 2, 1, 0]))
    groups = [sorted(x.tolist()) for x in np.split(order, np.flatnonzero(first)[1:])]
    assert sorted(groups) == [[0, 2], [1, 4], [3]]


def test_segments_do_not_depend_on_steps(monkeypatch):
    rng = np.random.default_rng(2)
    data = rng.choice(np.frombuffer(b"abc ", np.uint8), 3000)
    offsets = np.array([0, 700, 700, 730, 2990, 3000])
    def strings():
        s = suffixes.Segments(data, offsets)
        return {(r, x): bytes(data[lo + p : lo + p + 18]) for r, lo, hi, p in zip(s.row, s.lo, s.hi, s.place) for x in range(lo, hi + 1)}
    whole = strings()
    monkeypatch.setattr(suffixes, "STEP", 64)
    assert strings() == whole and len(whole) == 651 + 2211


def test_repeats_with_odd_ids(spark):
    text = "a sentence that is longer than fifty bytes, so that it can be removed"
    df = spark.createDataFrame([(-5, text), (3, "before " + text), (3, text), (7, text), (7, "nothing else"), (None, text), (None, None)], "doc_id long, text string")
    got = sorted((r["doc_id"] is None, r["doc_id"] or 0, r["n_bytes"], r["n_removed"]) for r in rows(suffixes.remove_repeats(df)))
    n = len(text)
    assert got == [(False, -5, n, 0), (False, 3, n, n), (False, 3, n + 7, n), (False, 7, 12, 0), (False, 7, n, n), (True, 0, 0, 0), (True, 0, n, 0)]
    assert suffixes.remove_repeats(df.limit(0)).count() == 0


@pytest.mark.parametrize("name", ["byte_bpe_50k.json", "word_bpe_49k.json"])
def test_token_ids_are_the_librarys(name):
    encode = Encoder(queries.vocabulary(name))
    texts = [*(t or "" for t in TEXTS), "a  b\n\n c'S we'LL ½ ²x £9   ª", "x'sy!'s ''t 12 345 \n\n\n", "Œuvre — é <|endoftext|>", "\x1f \x85"]
    raw = [t.encode() for t in texts]
    ids, at = encode.chunk(np.frombuffer(b"".join(raw), np.uint8), np.concatenate([[0], np.cumsum([len(x) for x in raw])]))
    for t, a, b in zip(texts, at[:-1], at[1:]):
        assert ids[a:b].tolist() == encode.whole(t).tolist()


def test_orc_round_trip(docs):
    path = queries.vocabulary("word_bpe_49k.json")
    encode = Encoder(path)
    got = sorted((r["doc_id"], r["start"], r["n_tokens"], r["ids_crc32"]) for r in rows(token_orc.round_trip(docs, path, 2)))
    start = 0
    for d, s, n, crc in got:
        ids = np.array([*encode.whole(TEXTS[d] or "").tolist(), 2], "<u4")
        assert (s, n, crc) == (start, len(ids), zlib.crc32(ids.tobytes()))
        start += n


def test_near_duplicates_against_sql(spark, docs, none):
    pairs = [(r["doc_id"], r["text"]) for r in docs.dropDuplicates(["doc_id"]).collect()]
    for k in range(12):
        w = LONG.split()
        w[7 * k + 3] = f"edit{k}"
        pairs.append((100 + k, " ".join(w)))
    df = spark.createDataFrame(pairs, "doc_id long, text string")
    pdf = df.toPandas()  # noqa: F841
    for n, percent in ((3, 85), (5, 80)):
        want = sorted(duckdb.sql(oracles.near_duplicates(n, percent, "pdf")).fetchall())
        got = sorted((r["doc_id"], r["n_shingles"], r["component_id"], r["kept"]) for r in rows(near_dup.groups(df, n, percent)))
        assert got == want
    assert near_dup.groups(none, 5, 80).count() == 0


def test_packing_is_exact(docs):
    path = queries.vocabulary("byte_bpe_50k.json")
    encode = Encoder(path)
    pieces = rows(packing.pack(docs.dropDuplicates(["doc_id"]), path, 0))
    for d, text in enumerate(TEXTS):
        ids = np.array([*encode.whole(text or "").tolist(), 0], "<u4")
        mine = sorted((p["start"], p["length"], p["ids_crc32"]) for p in pieces if p["doc_id"] == d)
        at = 0
        for s, n, crc in mine:
            assert s == at and crc == zlib.crc32(ids[s : s + n].tobytes())
            at += n
        assert at == len(ids)
    by = {}
    for p in pieces:
        by.setdefault(p["sequence_id"], []).append((p["offset"], p["length"]))
    for parts in by.values():
        at = 0
        for o, n in sorted(parts):
            assert o == at
            at += n
        assert at <= 1024 and at & (at - 1) == 0


def test_passages(spark, none):
    item = "one two three four five six seven eight nine ten eleven twelve"
    changed = item.replace("four", "4").replace("nine", "9")
    df = spark.createDataFrame([(1, "before " + item + " after"), (2, changed), (3, "one two three only"), (4, None), (5, item[:20])], "doc_id long, text string")
    tests = spark.createDataFrame([(7, item), (8, ""), (9, None)], "item_id long, text string")
    got = {(r["doc_id"], r["item_id"]): r["n_matched"] for r in rows(decontaminate.find(df, tests))}
    assert got == {(1, 7): 12, (2, 7): 10}
    assert {r["doc_id"] for r in rows(decontaminate.remove(df, tests))} == {3, 4, 5}
    assert decontaminate.find(none, tests).count() == 0


def test_kneser_ney_against_brute_force(spark):
    rng = np.random.default_rng(3)
    texts = [" ".join(rng.choice(list("abcdefghij"), size=rng.integers(0, 30), p=np.arange(10, 0, -1) / 55)) for _ in range(80)] + [None, "zz unknown"]
    df = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    got = {r["doc_id"]: r for r in rows(ngram.fit_and_score(df))}
    tok = [[*(t or "").lower().split(), None] for t in texts]
    train = [t for i, t in enumerate(tok) if zlib.crc32(str(i).encode()) % 10]
    uni = Counter(w for t in train for w in t)
    n, v = sum(uni.values()), len(uni)
    pairs = Counter(x for t in train for x in zip(["<s>", *t], t))
    triples = Counter(x for t in train for x in zip(["<s>", *t], t, t[1:]))
    left = {x: k if x[0] == "<s>" else len({u for u, v_, w in triples if (v_, w) == x}) for x, k in pairs.items()}
    of = lambda c: [sum(1 for x in c.values() if x == k) for k in range(1, 5)]
    follows = Counter(w for _, w in pairs)
    f, d, e = ngram.discounts(of(triples)), ngram.discounts(of(left)), ngram.discounts(of(follows))
    total = sum(follows.values())
    share = sum(e[min(c, 3)] for c in follows.values()) / total
    one = lambda w: max(follows[w] - e[min(follows[w], 3)], 0) / total + share / (v + 1)

    def level(counts, k, d_, low):
        m = sum(counts)
        return max(k - d_[min(k, 3)], 0) / m + sum(d_[min(x, 3)] for x in counts) / m * low if m else low

    def two(c, w):
        return level([k for x, k in left.items() if x[0] == c], left.get((c, w), 0), d, one(w))

    for i, t in enumerate(tok):
        base = sum(math.log10((uni[w] + 0.1) / (n + 0.1 * (v + 1))) for w in t)
        s = math.log10(two("<s>", t[0]))
        for u, c, w in zip(["<s>", *t], t, t[1:]):
            s += math.log10(level([k for x, k in triples.items() if x[:2] == (u, c)], triples[u, c, w], f, two(c, w)))
        r = got[i]
        assert (r["n_tokens"], r["train_tokens"], r["n_known"]) == (len(t), n, sum(w in uni for w in t))
        assert np.isclose(r["base_score"], base) and np.isclose(r["score"], s)


def test_kneser_ney_sums_to_one(spark):
    """After any two words, also unseen ones, the known words and one unknown word share all probability."""
    texts = ["a b c a b d", "a b c", "b c a", "c c c c a b", "", "a b c a b d"] * 3
    df = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    model = ngram.fit(df)
    words_ = ngram.Words(model.path, model.first)
    size = model.size
    for context in ("a b", "b c", "c c", "d a", "d d"):
        second, last, number, _ = ngram._triples(words_, np.frombuffer(context.encode(), np.uint8), np.array([0, 3]))
        total = 0.0
        for w in [*range(size), -1]:
            number[2] = w
            total += 10.0 ** ngram.log10_words(model, second, last, number)[2]
        assert np.isclose(total, 1.0), context


def test_kneser_ney_of_odd_rows(spark, none):
    assert ngram.fit_and_score(none).count() == 0
    df = spark.createDataFrame([(None, "a b"), (None, None), (-1, ""), (-1, "a b c " * 9000), (4, "x" * 70000 + " a b")], "doc_id long, text string")
    got = rows(ngram.fit_and_score(df))
    assert len(got) == 5 and sorted(r["n_tokens"] for r in got) == [1, 1, 3, 4, 27001]


def test_pipeline_stages_keep_clean_documents(spark, sf):
    import corpus_pipeline as p

    docs = spark.read.parquet(f"{sf}/documents.parquet")
    told = p.identified(spark, docs, sf)
    assert told.columns == docs.columns and told.count() >= 0.99 * docs.count()
    clean = p.redacted(spark, docs.limit(20), sf)
    assert clean.columns == docs.columns and clean.count() == 20


@pytest.mark.parametrize("n", range(1, 41))
def test_seeds_leave_a_hit_for_every_length(n):
    """All ways, or many drawn ones, to replace as many words as the overlap allows: the item is found."""
    allowed = n - math.ceil(0.8 * n - 1e-9)
    words_ = [f"w{i}" for i in range(n)]
    items = decontaminate.Items([7], [" ".join(words_)])
    rng = np.random.default_rng(n)
    if math.comb(n, allowed) <= 400:
        ways = list(itertools.combinations(range(n), allowed))
    else:
        ways = [tuple(rng.choice(n, allowed, replace=False).tolist()) for _ in range(400)]
    texts = [" ".join(["before"] + [f"x{i}" if i in way else w for i, w in enumerate(words_)] + ["after", "it"]).encode() for way in ways]
    offsets = np.concatenate([[0], np.cumsum([len(t) for t in texts])])
    found = items.search(*decontaminate.word_hashes(np.frombuffer(b"".join(texts), np.uint8), offsets), 0.8)
    hits = {r: (size - n, place) for r, _, n, size, place in found}
    exact = n <= decontaminate.SHORT
    assert len(hits) == len(ways) if exact else len(hits) >= 0.995 * len(ways)
    assert set(hits.values()) == {(allowed, 1)}


def test_remove_is_row_by_row(spark, none):
    item = "alpha beta gamma delta epsilon zeta eta theta iota kappa"
    tests_ = spark.createDataFrame([(1, item), (2, None), (3, ""), (None, "clean words here"), (1, "mu nu xi")], "item_id long, text string")
    rows_ = [(1, f"x {item} y", "a"), (1, "clean words here", "b"), (None, item, "c"), (None, None, "d"), (4, "", "e"), (5, "mu nu xi", "f"), (6, "mu nu", "g")]
    df = spark.createDataFrame(rows_, "doc_id long, text string, overlap string")
    assert sorted(r["overlap"] for r in decontaminate.remove(df, tests_).collect()) == ["b", "d", "e", "g"]
    assert sorted(r["overlap"] for r in decontaminate.remove(df, tests_, block_bytes=80).collect()) == ["b", "d", "e", "g"]
    assert decontaminate.remove(df, tests_).columns == df.columns and decontaminate.remove(none, tests_).count() == 0
    assert decontaminate.find(df, tests_.limit(0)).count() == 0 and decontaminate.remove(df, tests_.limit(0)).count() == 7


def test_warc_of_odd_pages(spark):
    big = "z" * 5000 + "é"
    rows_ = [(None, "u", "same"), (5, "u", "same"), (3, None, "same"), (3, "v", big), (9, "v", big), (9, "v", big), (None, "u", "only null"), (None, "u", "only null"), (2, "u", None)]
    pages = spark.createDataFrame(rows_, "page_id long, url string, html string")
    got = sorted((str(r["page_id"]), r["payload_bytes"], r["record_type"], r["refers_to"]) for r in rows(warc.round_trip(pages, chunk=700)))
    assert got == sorted([("None", 4, "revisit", 3), ("5", 4, "revisit", 3), ("3", 4, "response", None), ("3", 5002, "response", None), ("9", 5002, "revisit", 3), ("9", 5002, "revisit", 3), ("None", 9, "response", None), ("None", 9, "response", None), ("2", 0, "response", None)])
    assert warc.round_trip(pages.limit(0)).count() == 0


def test_step_groups_are_balanced(spark):
    """Every group of a tier but its last one has the same tokens, over all tasks."""
    texts = ["word " * (1 + 37 * i % 400) for i in range(400)]
    df = spark.createDataFrame([(i, t) for i, t in enumerate(texts)], "doc_id long, text string").repartition(5)
    made = packing.pack(df, queries.vocabulary("byte_bpe_50k.json"), 0, step_tokens=2048)
    sums = {}
    for r in rows(made):
        sums.setdefault(r["tier"], Counter())[r["step_group"]] += r["length"]
    assert len(sums) > 1
    for tier, groups in sums.items():
        assert sorted(groups) == list(range(len(groups)))
        assert all(groups[g] == 2048 for g in range(len(groups) - 1)) and 0 < groups[len(groups) - 1] <= 2048
    assert packing.pack(df.limit(0), queries.vocabulary("byte_bpe_50k.json"), 0).count() == 0


def equal_hash_pair():
    """Two texts of 1,024 letters whose polynomial hashes modulo 2**64 are equal for any odd base: a Thue-Morse word and its mirror."""
    bits = [bin(i).count("1") & 1 for i in range(1024)]
    return "".join("ab"[b] for b in bits), "".join("ba"[b] for b in bits)


@pytest.mark.parametrize("name", ["byte_bpe_50k.json", "word_bpe_49k.json"])
def test_token_ids_where_hashes_lie(name):
    from radarlake.llm import common

    one, two = (x.encode() for x in equal_hash_pair())
    data, at = np.frombuffer(one + two, np.uint8), np.array([0, 1024, 2048])
    lying = common.span_hashes(common.prefix_hashes(data), at[:-1], at[1:])
    assert lying[0] == lying[1]
    told = common.string_hashes(data, at[:-1], at[1:])
    assert told[0] != told[1]
    encode = Encoder(queries.vocabulary(name))
    for _ in range(2):
        ids, rows_ = encode.chunk(data, at)
        for k, text in enumerate((one, two)):
            assert ids[rows_[k] : rows_[k + 1]].tolist() == encode.whole(text.decode()).tolist()


def test_string_hashes_do_not_depend_on_place(monkeypatch):
    from radarlake.llm import common

    rng = np.random.default_rng(4)
    data = rng.choice(np.frombuffer(b"ab ", np.uint8), 5000)
    start, end, _, low = common.words(data, np.array([0, len(data)]))
    whole = common.string_hashes(low, start, end)
    raw = [bytes(low[a:b]) for a, b in zip(start, end)]
    known = {}
    for w, h in zip(raw, whole.tolist()):
        assert known.setdefault(w, h) == h
    assert len(set(known.values())) == len(known)
    monkeypatch.setattr(common, "HASH_BLOCK", 97)
    assert np.array_equal(common.string_hashes(low, start, end), whole)
    assert len(common.string_hashes(low, start[:0], end[:0])) == 0
    long_ = np.frombuffer(b"q" * 40000 + b" " + b"q" * 40000 + b" " + b"q" * 40001, np.uint8)
    h = common.word_hashes(long_, np.array([0, len(long_)]))[0]
    assert h[0] == h[1] != h[2]


def test_flac_reads_other_legal_streams():
    """A frame with an escaped residual partition, which the lanes don't read, among streams as they are written."""
    rng = np.random.default_rng(6)
    payload = rng.integers(0, 256, 64).astype(np.uint8)
    media, at = flac.encode_many(np.concatenate([payload, payload]), np.array([0, 64, 128]))
    raw = media.tobytes()
    one = raw[: at[1]]
    bits = [0, *map(int, "001000"), 0]  # a fixed predictor of order 0
    bits += [0, 0, *[0] * 4, *[1] * 4, *map(int, f"{8:05b}")]  # Rice codes of 4 bits, one partition, escaped, 8 bits a value
    for v in payload.tolist():
        bits += map(int, f"{(v - 128) & 255:08b}")
    bits += [0] * (-len(bits) % 8)
    head = bytes([0xFF, 0xF8, 0x70, 0x02, 0, 0, 63])
    body = head + bytes([flac._crc(head, flac._CRC8, 8)]) + bytes(int("".join(map(str, bits[i : i + 8])), 2) for i in range(0, len(bits), 8))
    frame = body + flac._crc(body, flac._CRC16, 16).to_bytes(2, "big")
    other = one[: flac.Stream(one).frames] + frame
    both = np.frombuffer(other + raw[at[1] :], np.uint8)
    out, rows_ = flac.decode_many(both, np.array([0, len(other), len(both)]))
    assert rows_.tolist() == [0, 64, 128] and np.array_equal(out, np.concatenate([payload, payload]))
    broken = bytearray(other)
    broken[-5] ^= 1
    with pytest.raises(ValueError):
        flac.decode_many(np.frombuffer(bytes(broken), np.uint8), np.array([0, len(broken)]))


def test_flac_blocks_are_seekable(spark, tmp_path):
    big = "".join(chr(32 + (i * i) % 90) for i in range(1 << 18)) * 5  # over a chunk of text
    df = spark.createDataFrame([(1, "abc"), (2, big), (None, "no id"), (3, None)], "doc_id long, text string")
    path = flac.write_pcm(flac.encode(df), f"file://{tmp_path}/pcm", block=1000)
    blocks = spark.read.parquet(path)
    for first, count in ((0, 1), (999, 2), (123456, 70000), (len(big) - 1, 5)):
        got = b"".join(bytes(r["pcm"]) for r in sorted(flac.seek(blocks, 2, first, count).collect(), key=lambda r: r["sample_offset"]))
        want = big.encode() + bytes(-len(big) % 64)
        assert bytes(b ^ 0x80 for b in got) == want[first : first + count]
    got = {r["doc_id"]: r for r in rows(flac.round_trip(df))}
    assert got[2]["payload_sha256"] == hashlib.sha256(big.encode() + bytes(-len(big) % 64)).hexdigest() and got[None]["n_bytes"] == 5 and got[3]["payload_bytes"] == 64


def test_orc_lookup_prunes(spark, docs, tmp_path):
    """Ids read back by id, over the whole folder and where statistics and Bloom filters leave nothing."""
    path = queries.vocabulary("word_bpe_49k.json")
    df = spark.createDataFrame([(i, f"text number {i} " * (i % 7)) for i in range(0, 4000, 2)], "doc_id long, text string")
    folder = token_orc.write(df, f"file://{tmp_path}/orc", path, 2, shards=4)
    encode = Encoder(path)
    for i in (0, 998, 3998):
        (r,) = token_orc.lookup(spark, folder, F.col("doc_id") == i).collect()
        assert r["ids"] == [*encode.whole(f"text number {i} " * (i % 7)).tolist(), 2]
    assert token_orc.lookup(spark, folder, F.col("doc_id") == 999).count() == 0
    plan = token_orc.lookup(spark, folder, F.col("doc_id") == 998)._jdf.queryExecution().executedPlan().toString()
    assert "EqualTo(doc_id,998)" in plan
    assert sum(1 for _ in token_orc.lookup(spark, folder, F.col("doc_id").between(100, 198)).collect()) == 50
    assert token_orc.round_trip(df.limit(0), path, 2).count() == 0


def test_long_texts_cross_every_chunk(spark):
    """A text beyond all chunk limits: token ids, packing, n-grams, near copies, passages and repeats are those of the whole text."""
    words_ = [f"w{i * 7919 % 600011}" for i in range(420_000)]
    big = " ".join(words_)
    near = " ".join([*words_[:-50], *("changed" for _ in range(50))])
    df = spark.createDataFrame([(1, big), (2, near), (3, big), (4, "short text"), (5, None)], "doc_id long, text string")
    path = queries.vocabulary("byte_bpe_50k.json")
    whole = [*Encoder(path).whole(big).tolist(), 0]
    pieces = sorted((r["start"], r["length"], r["ids_crc32"], r["doc_tokens"]) for r in rows(packing.pack(df.filter("doc_id = 1"), path, 0)))
    assert [p[0] for p in pieces] == [sum(p[1] for p in pieces[:k]) for k in range(len(pieces))] and sum(p[1] for p in pieces) == len(whole) == pieces[0][3]
    assert all(c == zlib.crc32(np.array(whole[s : s + n], "<u4").tobytes()) for s, n, c, _ in pieces)
    groups = {r["doc_id"]: r["component_id"] for r in rows(near_dup.groups(df))}
    assert groups == {1: 1, 2: 1, 3: 1, 4: 4, 5: 5}
    gone = {r["doc_id"]: r["n_removed"] for r in rows(suffixes.remove_repeats(df))}
    assert gone[1] == gone[4] == gone[5] == 0 and gone[3] == len(big.encode()) and 0 < gone[2] < len(near)
    item = " ".join(words_[300_000:300_030])
    tests_ = spark.createDataFrame([(9, item)], "item_id long, text string")
    found = {(r["doc_id"], r["place"]) for r in rows(decontaminate.find(df, tests_))}
    assert found == {(1, 300_000), (2, 300_000), (3, 300_000)}
    scored = {r["doc_id"]: r for r in rows(ngram.fit_and_score(df))}
    assert scored[1]["n_tokens"] == 420_001 and scored[1]["score"] == pytest.approx(scored[3]["score"])


def test_near_duplicates_of_odd_rows(spark, none):
    assert near_dup.groups(none).count() == 0 and near_dup.keep_one(none).count() == 0
    base = [f"t{i}" for i in range(60)]
    a, b, c = " ".join(base), " ".join([*base[:-1], "end"]), " ".join(f"z{i}" for i in range(60))
    rows_ = [(1, a, 1), (1, a, 2), (2, b, 3), (2, c, 4), (7, c, 5), (None, b, 6), (None, "alone only here", 7), (None, None, 8), (9, "", 9), (-3, "alone only here", 10)]
    df = spark.createDataFrame(rows_, "doc_id long, text string, row_a int")
    got = sorted((str(r["doc_id"]), str(r["component_id"]), r["kept"]) for r in rows(near_dup.groups(df)))
    assert got == sorted([("1", "1", True), ("1", "1", True), ("2", "1", False), ("2", "2", True), ("7", "2", False), ("None", "1", False), ("None", "-3", False), ("None", "None", True), ("9", "9", True), ("-3", "-3", True)])
    kept = near_dup.keep_one(df)
    assert kept.columns == df.columns and {r["row_a"] for r in kept.collect()} in ({1, 4, 8, 9, 10}, {2, 4, 8, 9, 10})


@pytest.mark.parametrize(("members", "shingles_"), [(7, 1 << 21), (2048, 900)])
def test_large_groups_of_near_copies_stay_whole(spark, monkeypatch, members, shingles_):
    """A chain and a clump of near copies in blocks and stars of a few members: one component each."""
    monkeypatch.setattr(near_dup, "BLOCK", members)
    monkeypatch.setattr(near_dup, "BLOCK_SHINGLES", shingles_)
    monkeypatch.setattr(near_dup, "STAR", 5)
    base = [f"c{i}" for i in range(200)]
    chain = [" ".join([*base[k * 8 :], *(f"n{i}" for i in range(k * 8))]) for k in range(20)]
    rng = np.random.default_rng(8)
    clump = []
    for k in range(60):
        w = [f"d{i}" for i in range(150)]
        w[int(rng.integers(150))] = f"only{k}"
        clump.append(" ".join(w))
    df = spark.createDataFrame(list(enumerate([*chain, *clump])), "doc_id long, text string")
    got = {r["doc_id"]: r["component_id"] for r in rows(near_dup.groups(df, n=3, percent=85))}
    sets = [{tuple(t.split()[i : i + 3]) for i in range(len(t.split()) - 2)} for t in [*chain, *clump]]
    want = {}
    for i in range(80):
        want[i] = i
    for _ in range(80):
        for i, j in itertools.combinations(range(80), 2):
            both = len(sets[i] & sets[j])
            if 100 * both >= 85 * (len(sets[i]) + len(sets[j]) - both):
                want[i] = want[j] = min(want[i], want[j])
    assert got == want


def test_banding_recall():
    """Pairs just above the threshold of both queries: the share that no band joins."""
    rng = np.random.default_rng(9)
    for percent in (80, 85):
        missed = 0
        for _ in range(300):
            common = rng.integers(0, 1 << 63, 4 * percent, dtype=np.uint64)
            other = rng.integers(0, 1 << 63, 2 * (400 - 4 * percent), dtype=np.uint64)
            half = len(other) // 2
            sets = np.concatenate([np.sort(np.concatenate([common, other[:half]])), np.sort(np.concatenate([common, other[half:][:0]]))])
            at = np.array([0, len(common) + half, len(sets)])
            x = near_dup.signatures(sets, at, near_dup.BANDS * near_dup.ROWS).reshape(2, near_dup.BANDS, near_dup.ROWS)
            missed += not (x[0] == x[1]).all(1).any()
        assert missed <= 1


def test_spanning_links_are_exact():
    rng = np.random.default_rng(10)
    sets = [np.unique(rng.choice(np.arange(1, 60, dtype=np.uint64), rng.integers(20, 40))) for _ in range(40)]
    node = np.arange(40)
    own = np.concatenate([np.ones(40, bool), np.zeros(40, bool)])
    a, b = near_dup.spanning([*sets, *sets], np.concatenate([node, node]), np.concatenate([node, node]), own, 60)
    alike = lambda x, y: 100 * len(np.intersect1d(sets[x], sets[y])) >= 60 * len(np.union1d(sets[x], sets[y]))
    assert all(alike(x, y) for x, y in zip(a, b)) and len(a) < 40
    def parts(links):
        root = list(range(40))
        for _ in range(40):
            for x, y in links:
                root[x] = root[y] = min(root[x], root[y])
        return root
    assert parts(list(zip(a, b))) == parts([(x, y) for x in range(40) for y in range(x) if alike(x, y)])


def shingles(text, n):
    w = [x for x in "".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in text or "").replace("\x0b", " ").replace("\x0c", " ").split(" ")]
    w = [y for x in w for y in x.replace("\t", " ").replace("\n", " ").replace("\r", " ").split(" ") if y]
    return {tuple(w[i : i + n]) for i in range(len(w) - n + 1)} if len(w) >= n else ({tuple(w)} if w else set())


@pytest.fixture(scope="module")
def small_corpus(spark, tmp_path_factory):
    """The given small tables with rows that each stage must drop or change."""
    import shutil

    folder = tmp_path_factory.mktemp("corpus")
    source = "/root/testdata/sf0.001"
    bench = spark.read.parquet(f"{source}/benchmark.parquet").orderBy("item_id").first()["text"]
    docs = spark.read.parquet(f"{source}/documents.parquet")
    kept = docs.collect()
    clean = next(r for r in kept if r["lang"] == "en" and len(r["text"].split()) > 120)
    words_ = clean["text"].split()
    planted = [
        (9001, None, "en", "s", 0), (9002, "", "en", "s", 0), (9003, "1234 !!", None, "s", 7), (9004, clean["text"], "en", "s", 1), (9005, " ".join([*words_[:-2], "two", "changed"]), "en", "s", 1),
        (9006, "the words before it are in english " + bench + " and the words after it too", "en", "s", 1),
        (9007, " ".join(reversed(words_)) + " write to jane.doe@example.org or call +1 (555) 123-4567 about it", "en", "s", 1), (9004, clean["text"], "en", "s", 1),
    ]
    spark.createDataFrame(planted, docs.schema).unionByName(docs).write.parquet(f"{folder}/documents.parquet")
    shutil.copy(f"{source}/benchmark.parquet", folder)
    return str(folder), clean["doc_id"]


def test_pipeline_against_brute_force(spark, small_corpus):
    import corpus_pipeline as p

    folder, clean = small_corpus
    docs = spark.read.parquet(f"{folder}/documents.parquet")
    key = lambda r: (r["doc_id"], r["text"], r["lang"], r["source"], r["n_chars"])
    given = [key(r) for r in docs.collect()]

    told = p.identified(spark, docs, folder)
    kept = [key(r) for r in told.collect()]
    assert sorted(map(str, kept)) == sorted(str(r) for r in given if r[1] and any(c.isalpha() for c in r[1])) and told.columns == docs.columns

    told = p.stored(told, "a")
    sets = [shingles(r[1], 5) for r in kept]
    root = list(range(len(kept)))
    for _ in range(4):
        for i, j in itertools.combinations(range(len(kept)), 2):
            both = len(sets[i] & sets[j])
            if both and 100 * both >= 80 * (len(sets[i]) + len(sets[j]) - both):
                root[i] = root[j] = min(root[i], root[j])
    group = lambda i: i if root[i] == i else group(root[i])
    first = {}
    for i, r in enumerate(kept):
        first[group(i)] = min(first.get(group(i), (1 << 62,)), r[:1])
    one = {v[0] for v in first.values()}
    told = p.distinct_texts(spark, told, folder)
    kept2 = [key(r) for r in told.collect()]
    assert sorted(r[0] for r in kept2) == sorted(one) and {9004, 9005}.isdisjoint(one) and clean in one

    told = p.stored(told, "b")
    items = [t.split() for (t,) in spark.read.parquet(f"{folder}/benchmark.parquet").select(F.lower("text")).collect()]
    def holds(text):
        w = text.lower().split()
        return any(sum(w[a + k] == x for k, x in enumerate(item) if 0 <= a + k < len(w)) >= 0.8 * len(item) for item in items for a in range(-len(item) // 5, len(w)))
    told = p.decontaminated(spark, told, folder)
    kept3 = [key(r) for r in told.collect()]
    assert sorted(r[0] for r in kept3) == sorted(r[0] for r in kept2 if not holds(r[1])) and 9006 not in {r[0] for r in kept3}

    told = p.stored(told, "c")
    spans = {r["doc_id"]: r["spans"] for r in pii.digest(told).collect()}
    told = p.redacted(spark, told, folder)
    for r in told.collect():
        before = next(x for x in kept3 if x[0] == r["doc_id"])[1]
        cut = sorted(((int(b), -int(e), k) for k, b, e in (s.split(":") for s in spans[r["doc_id"]].split(",") if s)))
        out, at = "", 0
        for b, e, k in cut:
            if b >= at:
                out += before[at:b] + f"[{k}]"
            at = max(at, -e)
        assert r["text"] == out + before[at:] and r["n_chars"] == len(r["text"])
        if r["doc_id"] == 9007:
            assert "[email]" in r["text"] and "[phone]" in r["text"] and "jane" not in r["text"]

    final = {r["doc_id"]: r["text"] for r in told.collect()}
    encode = Encoder(queries.vocabulary("byte_bpe_50k.json"))
    whole = {d: [*encode.whole(t).tolist(), 0] for d, t in final.items()}
    for made in (p.packed(spark, told, folder), p.run(spark, folder)):
        seen = {}
        for r in sorted(made.collect(), key=lambda r: (r["doc_id"], r["start"])):
            ids = whole[r["doc_id"]]
            assert r["start"] == seen.get(r["doc_id"], 0) and r["doc_tokens"] == len(ids)
            assert r["ids_crc32"] == zlib.crc32(np.array(ids[r["start"] : r["start"] + r["length"]], "<u4").tobytes())
            seen[r["doc_id"]] = r["start"] + r["length"]
        assert seen == {d: len(x) for d, x in whole.items()}


def test_pipeline_stages_of_odd_rows(spark, sf):
    import corpus_pipeline as p

    schema = "doc_id long, text string, lang string, source string, n_chars long, lang_pred string, row_a long, held boolean"
    rows_ = [(None, "the cat sat on the mat and looked at the house", "en", None, None, "x", 1, True), (1, None, None, None, None, None, None, None), (1, "", "de", "s", 0, "y", 2, False), (1, "das haus und der garten von dem alten könig im wald", "de", "s", 3, "z", 3, None)]
    df = spark.createDataFrame(rows_ * 40, schema)
    for name, stage in p.STAGES:
        empty = stage(spark, df.limit(0), sf)
        assert empty.count() == 0
        made = stage(spark, df, sf)
        if name != "packing":
            assert made.columns == df.columns and empty.columns == df.columns
        made.count()
    assert p.distinct_texts(spark, df, sf).count() == 4 and p.redacted(spark, df, sf).count() == 160


def test_token_files_and_packing_of_odd_rows(spark):
    """Null and repeated ids, null and empty texts, a column that has a name of the output."""
    rows_ = [(None, "first text", 1), (3, None, 2), (3, "again", 3), (3, "again", 4), (-7, "", 5), (9, "é ü £ ½", 6)]
    df = spark.createDataFrame(rows_, "doc_id long, text string, start int")
    path = queries.vocabulary("word_bpe_49k.json")
    encode = Encoder(path)
    want = Counter((d, zlib.crc32(np.array([*encode.whole(t or "").tolist(), 2], "<u4").tobytes())) for d, t, _ in rows_)
    got = rows(token_orc.round_trip(df, path, 2))
    assert Counter((r["doc_id"], r["ids_crc32"]) for r in got) == want
    starts = sorted((r["start"], r["n_tokens"]) for r in got)
    assert [s for s, _ in starts] == [sum(n for _, n in starts[:k]) for k in range(len(starts))]
    order = [r["doc_id"] for r in sorted(got, key=lambda r: r["start"])]
    assert order == sorted(order, key=lambda d: (d is not None, d or 0))
    path = queries.vocabulary("byte_bpe_50k.json")
    pieces = rows(packing.pack(df, path, 0))
    whole = Counter()
    for d, t, _ in rows_:
        whole[d] += len(Encoder(path).whole(t or "")) + 1
    made = Counter()
    for r in pieces:
        made[r["doc_id"]] += r["length"]
    assert made == whole


def test_personal_data_of_odd_rows(spark, none):
    long_ = "x " * 100_000 + "jane@example.org" + " y" * 100_000
    df = spark.createDataFrame([(None, "a@b.co", 1), (1, None, 2), (1, "", 3), (1, long_, 4)], "doc_id long, text string, spans int")
    got = sorted((str(r["doc_id"]), r["n_email"], r["spans"]) for r in rows(pii.digest(df)))
    assert got == [("1", 0, ""), ("1", 0, ""), ("1", 1, "email:200000:200016"), ("None", 1, "email:0:6")]
    kept = pii.redact(df)
    assert kept.columns == df.columns and {r["text"] for r in kept.collect()} == {"[email]", None, "", long_.replace("jane@example.org", "[email]")}
    assert pii.digest(none).count() == 0
