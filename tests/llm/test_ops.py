"""The corpus operators against brute force, on small tables with nulls, ties, repeats and odd columns."""

import hashlib
import re
import zlib

import numpy as np
import public_tokenizers
import pytest
from pyspark.sql import functions as F
from sitereach.llm import bytebpe, decontaminate, linear, neardup, permindex, personal, piececount, store, suffixdedup, tokenfiles

DOCS = "doc_id long, text string, spans string, kind string"


def table(spark, texts, ids=None):
    """Documents with columns whose names clash with those used inside."""
    ids = list(range(len(texts))) if ids is None else ids
    return spark.createDataFrame([(i, t, "x", None) for i, t in zip(ids, texts, strict=True)], DOCS)


PASSAGE = "the quick brown fox jumps over the lazy dog while seven wizards brew some jolly good potion tonight again and again"


def words(n, seed):
    rng = np.random.default_rng(seed)
    return " ".join("".join(chr(97 + c) for c in rng.integers(0, 26, rng.integers(2, 9))) for _ in range(n))


TEXTS = [
    words(60, 1) + " " + PASSAGE,
    PASSAGE + " " + words(40, 2),
    None,
    "",
    "short",
    words(60, 1) + " " + PASSAGE,
    "äöü ß 漢字 \U0001d11e " + words(30, 3) + PASSAGE[:60],
    "ab" * 200,
    "ab" * 90,
    words(3000, 4) + PASSAGE + words(10, 5),
    " \t\n ",
]


# ---------------------------------------------------------------- 1
def brute_repeats(rows):
    first = {}
    for d, t in rows:
        b = (t or "").encode()
        for i in range(len(b) - 49):
            first[b[i : i + 50]] = min(d, first.get(b[i : i + 50], d))
    out = []
    for d, t in rows:
        b = (t or "").encode()
        gone = bytearray(len(b))
        for i in range(len(b) - 49):
            if first[b[i : i + 50]] < d:
                gone[i : i + 50] = b"\1" * 50
        kept = bytes(c for c, g in zip(b, gone, strict=True) if not g)
        out.append((d, len(b), sum(gone), sum(1 for i in range(len(b)) if gone[i] and (not i or not gone[i - 1])), hashlib.sha256(kept).hexdigest()))
    return sorted(out)


def test_repeats(spark):
    rows = list(enumerate(TEXTS))
    got = suffixdedup.remove_repeats(table(spark, TEXTS)).select("doc_id", "n_bytes", "n_removed", "n_spans", "kept_sha256").collect()
    assert sorted(map(tuple, got)) == brute_repeats(rows)


def test_repeats_many_partial_overlaps(spark):
    rng = np.random.default_rng(3)
    base = words(200, 9)
    texts = []
    for i in range(40):
        a, b = sorted(rng.integers(0, len(base), 2))
        c, d = sorted(rng.integers(0, len(base), 2))
        texts.append(words(5, 100 + i) + base[a:b] + words(3, 200 + i) + base[c:d])
    got = suffixdedup.remove_repeats(table(spark, texts)).select("doc_id", "n_bytes", "n_removed", "n_spans", "kept_sha256").collect()
    assert sorted(map(tuple, got)) == brute_repeats(list(enumerate(texts)))


def test_repeats_rows(spark):
    text = words(50, 7)
    got = suffixdedup.remove_repeats(table(spark, [text, text, text, None], [5, 5, None, None])).select("doc_id", "n_removed").collect()
    n = len(text)
    assert sorted(((r[0] or -1), r[1]) for r in got) == [(-1, 0), (-1, n), (5, 0), (5, 0)]
    assert suffixdedup.remove_repeats(table(spark, [])).count() == 0


@pytest.mark.parametrize(("n", "kinds"), [(0, 3), (1, 3), (500, 3), (30_000, 3), (30_000, 1 << 40), (9000, 1)])
def test_multikey_order(n, kinds):
    rng = np.random.default_rng(0)
    keys = [rng.integers(0, kinds, n).astype(np.uint64) for _ in range(4)]
    order, group = suffixdedup.multikey_order(keys)
    rows = list(zip(*(k[order].tolist() for k in keys), strict=True))
    assert rows == sorted(rows) and sorted(order.tolist()) == list(range(n))
    assert len(set(group.tolist())) == len(set(rows)) == len(set(zip(group.tolist(), rows, strict=True)))


def test_splitters_of_two_symbols():
    rng = np.random.default_rng(1)
    w = rng.integers(0, 4, (5000, 2)).astype(np.uint64)
    edges = np.unique(w[rng.integers(0, 5000, 9)], axis=0)
    want = [sum((e[0], e[1]) <= (a, b) for e in edges.tolist()) for a, b in w.tolist()]
    assert suffixdedup.bucket_of(edges, w[:, 0], w[:, 1]).tolist() == want


def test_repeats_of_a_hot_phrase(spark):
    # one phrase of 30 bytes in every text, in many surroundings, and a line of 60 bytes in a third of them
    phrase, line = "the same phrase in every text ", "this line of sixty bytes stands in a third of all the texts.."
    texts = [words(8, i) + " " + phrase + words(8, 1000 + i % 40) + (line if i % 3 == 0 else "") + words(4, 2000 + i) for i in range(300)]
    got = suffixdedup.remove_repeats(table(spark, texts)).select("doc_id", "n_bytes", "n_removed", "n_spans", "kept_sha256").collect()
    assert sorted(map(tuple, got)) == brute_repeats(list(enumerate(texts)))


# ---------------------------------------------------------------- 2
def test_token_files(spark):
    from tokenizers import Tokenizer

    t = Tokenizer.from_file(public_tokenizers.path("byte_bpe_50k.json"))
    texts = [*TEXTS, "it's 3 o'clock ñandú ²½ _x_ <|endoftext|>", "<|endoftext|> a <|endoftext|><|endoftext|>b <|endoftext", "tab\t\tnew\n\nline  end  ", "\x1c\x1f x\x85  　y 日本語 42٣ \U0001e6c0a ʼn we'll"]
    folder = store.new_path(spark, "files")
    index = tokenfiles.write(table(spark, texts), folder, length=64, file_ids=500)
    got = {r["doc_id"]: tuple(r)[1:] for r in tokenfiles.read_documents(index, folder).collect()}
    start = 0
    for d, text in enumerate(texts):
        ids = [*t.encode(text or "", add_special_tokens=False).ids, 2]
        assert got[d] == (start, len(ids), zlib.crc32(np.array(ids, "<u4").tobytes()))
        start += len(ids)
    assert index.select("shard", "file").distinct().count() > index.select("shard").distinct().count()  # files are bounded
    row = index.where("shard = 0").orderBy("file", "place").first()
    shard = tokenfiles.Shard(tokenfiles.file_name(folder, row["shard"], row["file"]))
    assert len(shard.sequence(0)) == 64 and shard.mask(0).to_pylist() == [True] * 64
    # memory-mapped, not copied: the second mask begins 8 bytes behind the first in the same buffer
    assert not shard.values[0].flags.owndata and shard.mask(1).buffers()[1].address == shard.masks[0].buffers()[1].address and shard.mask(1).offset == 64
    ids = index.where(f"shard = {row['shard']} and file = {row['file']}").agg(F.sum("n_tokens")).first()[0]
    assert sum(m.true_count for m in shard.masks) == ids
    empty = store.new_path(spark, "files")
    assert tokenfiles.read_documents(tokenfiles.write(table(spark, []), empty), empty).count() == 0


def test_pieces_are_cut_as_by_the_library():
    from tokenizers import pre_tokenizers

    known = tokenfiles.pieces(public_tokenizers.path("byte_bpe_50k.json"))
    edges = [c for a, b in tokenfiles._NEWER for c in (a - 1, a, b, b + 1)]
    for c in [*range(0x3100), *range(0x3100, 0x110000, 61), *edges]:
        text = f"a{chr(c)} 1{chr(c)} !{chr(c)}{chr(c)} {chr(c)}"
        if not 0xD800 <= c < 0xE000 and not tokenfiles._UNKNOWN.search(text):
            cut = pre_tokenizers.ByteLevel(add_prefix_space=False).pre_tokenize_str(text)
            want = [text[a:b] for _, (a, b) in cut]
            assert want == tokenfiles._PIECE.findall(text), hex(c)
            assert tokenfiles._LATIN.search(text) or want == tokenfiles._LATIN_PIECE.findall(text), hex(c)
    assert known.byte_level


# ---------------------------------------------------------------- 3
def brute_groups(rows, size, percent):
    sets = {}
    for d, t in rows:
        w = re.findall(r"[^\x20\x09-\x0D]+", re.sub("[A-Z]", lambda m: m[0].lower(), t or ""))
        sets[d] = {tuple(w[i : i + size]) for i in range(len(w) - size + 1)} if len(w) >= size else ({tuple(w)} if w else set())
    parent = {d: d for d in sets}

    def root(x):
        while parent[x] != x:
            x = parent[x]
        return x

    for a in sets:
        for b in sets:
            both = len(sets[a] & sets[b])
            if a < b and sets[a] and sets[b] and 100 * both >= percent * (len(sets[a]) + len(sets[b]) - both):
                x, y = root(a), root(b)
                parent[max(x, y)] = min(x, y)
    return sorted((d, len(s), root(d), root(d) == d) for d, s in sets.items())


@pytest.mark.parametrize(("size", "percent"), [(3, 85), (5, 80)])
def test_near_duplicates(spark, size, percent):
    rng = np.random.default_rng(5)
    base = words(120, 50).split()
    texts = list(TEXTS)
    for i in range(60):
        w = list(base)
        for j in rng.integers(0, len(w), int(rng.integers(0, 7))):
            w[j] = f"edit{i}"
        texts.append(" ".join(w))
    texts += ["One Two", "one two", "one"]
    got = neardup.groups(table(spark, texts), size, percent).collect()
    assert sorted(map(tuple, got)) == brute_groups(list(enumerate(texts)), size, percent)


def test_sketch_fills_and_estimates():
    a = np.unique(np.random.default_rng(1).integers(0, 1 << 62, 300).astype(np.uint64))
    b = np.concatenate([a[:270], a[:30] + np.uint64(7)])
    s = neardup.sketches([np.sort(a), np.unique(b), a[:1], a[:3]], 400)
    assert (s != np.uint64(0xFFFFFFFFFFFFFFFF)).all()
    assert abs((s[0] == s[1]).mean() - 270 / 330) < 0.1


def test_block_links_join_components():
    sets = [np.arange(i, i + 100, dtype=np.uint64) for i in range(0, 40, 4)] + [np.arange(1000, 1050, dtype=np.uint64)]
    links = neardup.block_links(np.arange(11), np.zeros(11, int), sets, 85)
    assert len(links) == 9 and all(10 not in x for x in links)


def test_near_duplicates_odd_rows(spark):
    t = words(30, 1)
    got = neardup.groups(table(spark, [t, t, t, None], [3, 3, None, 9]), 3, 85).collect()
    assert sorted(((r[0] or -1), r[2] or -1, r[3]) for r in got) == [(-1, -1, True), (3, 3, True), (3, 3, True), (9, 9, True)]
    assert neardup.groups(table(spark, []), 3, 85).count() == 0


# ---------------------------------------------------------------- 4, 5
def test_classifiers(spark):
    rng = np.random.default_rng(2)
    rows, labels = [], []
    for i in range(600):
        bad = i % 3 == 0
        rows.append(" ".join((f"w{x}!!" if bad else f"w{x}") for x in rng.integers(0, 300, 40)) + (" awful" if i % 5 == 0 else ""))
        labels.append((i, int(not bad), int(i % 5 == 0), "x"))
    docs, lab = table(spark, [*rows, None, ""]), spark.createDataFrame(labels, "doc_id long, quality int, toxic int, text string")
    for fit, mod, held, least, column in ((linear.fit_quality, 3, 1, 0.5, 1), (linear.fit_toxic, 4, 2, 0.3, 2)):
        out = linear._contract(linear.score(docs, fit(docs, lab)), mod, held, least).collect()
        assert len(out) == 602 and all(0 <= r["score"] <= 1 and r["predicted"] == int(r["score"] >= least) for r in out)
        test = [r for r in out if r["held_out"] and r["doc_id"] < 600]
        assert test and all(r["held_out"] == (zlib.crc32(str(r["doc_id"]).encode()) % mod == held) for r in out)
        assert np.mean([r["predicted"] == labels[r["doc_id"]][column] for r in test]) > 0.95
    none = linear.score(docs, linear.fit_quality(docs, lab.limit(0))).collect()
    assert {round(r["score"], 9) for r in none} == {0.5}


def test_kept_rows_are_whole(spark):
    docs = table(spark, ["a b c"] * 5)
    model = linear.train(["a b c", "x y z"], np.array([1.0, 0.0]), linear.quality_features, **linear.QUALITY)
    assert linear.kept(docs, model, 0.01).columns == docs.columns


# ---------------------------------------------------------------- 6
def test_token_counts(spark):
    from tokenizers import Tokenizer, models, pre_tokenizers

    t = Tokenizer(models.Unigram(piececount.vocabulary(public_tokenizers.path("piece_bpe_32k.model")), unk_id=0, byte_fallback=True))
    t.pre_tokenizer = pre_tokenizers.Metaspace(replacement=piececount.MARK, prepend_scheme="always", split=True)
    texts = [*TEXTS, "  a  b ", "a▁b", "日本 𝄞𝄞 x", "<s> <0x41>", "aaaaaaaa"]
    got = {r[0]: r[1] for r in piececount.token_counts(table(spark, texts)).collect()}
    assert [got[i] for i in range(len(texts))] == [len(t.encode(x or "", add_special_tokens=False).ids) for x in texts]


# ---------------------------------------------------------------- 7
PII = [
    "mail a.b@c.d.e, and x@y@z.com or %q@w.org. a@b then 1.2.3.4.5.6.7.8 and 300.1.1.1 or 01.002.3.255",
    "card 4242 4242 4242 4242 or 4242-4242-4242-4241, call +1 (415) 555-2671 or +49 30 1234.",
    "\U0001d11e ä +1 (415) 555-2671 \U0001d11e b@c.de",
    None,
    "",
    "a@b.c.d%e@f.g " + "1" * 5000 + " " + "x" * 5000,
]


def brute_spans(text):
    found = []
    for kind, pattern in (("email", r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+"), ("ip", r"[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)"), ("card", r"[0-9]([\x20-]?[0-9])+"), ("phone", r"\+[0-9][\x20().0-9-]+[0-9]")):
        for m in re.finditer(pattern, text or ""):
            digits = re.sub("[^0-9]", "", m[0])
            total = sum((int(c) * (1 + i % 2)) - 9 * (int(c) * (1 + i % 2) > 9) for i, c in enumerate(reversed(digits)))
            if kind == "email" or (kind == "ip" and all(int(x) <= 255 for x in m[0].split("."))) or (kind == "card" and 13 <= len(digits) <= 19 and total % 10 == 0) or (kind == "phone" and 9 <= len(digits) <= 15):
                found.append(f"{kind}:{m.start()}:{m.end()}")
    return found


def test_base_spans(spark):
    got = {r["doc_id"]: r for r in personal.digest(table(spark, PII)).collect()}
    for i, text in enumerate(PII):
        want = brute_spans(text)
        assert got[i]["spans"] == ",".join(want)
        assert got[i]["base_sha256"] == hashlib.sha256(",".join(want).encode()).hexdigest()
        assert got[i]["n_email"] == sum(x.startswith("email") for x in want)


def test_context_finds_new_spans(spark):
    texts = [f"Please Telefon: +1 (415) 555-2{i:03d} thanks {words(10, i)}" for i in range(6)] + ["Telefon: 030/1234567 and room 12345678 here"]
    got = {r["doc_id"]: r["spans"] for r in personal.digest(table(spark, texts)).collect()}
    assert got[6] == f"near_phone:9:{len('Telefon: 030/1234567')}"


def test_context_finds_runs_of_words_and_mail_without_digits(spark):
    seeds = [f"Please Telefon: +1 (415) 555-2{i:03d} thanks {words(10, i)}" for i in range(6)] + [f"Tel1 +1 (415) 555-3{i:03d} Mail: ann{chr(97 + i)}@site.org {words(9, i)}" for i in range(6)]
    texts = ["Telefon: 0301 234567 and", "Telefon: 030 1234567", "Tel1 0301299999 x", "Mail: joe(at)site.org now", "so Mail: joe at site dot org", "see Telefon: 0301888888 +1 (415) 555-2671 end", "room 12345678 and eve(at)site.org"]
    got = [r["spans"] for r in personal.digest(table(spark, seeds + texts)).orderBy("doc_id").collect()][len(seeds) :]
    want = [("near_phone", "0301 234567"), ("near_phone", "030 1234567"), ("near_phone", "0301299999"), ("near_email", "joe(at)site.org"), ("near_email", "joe at site dot org"), ("near_phone", "0301888888")]
    for text, spans, (kind, value) in zip(texts, got, want, strict=False):
        assert f"{kind}:{text.index(value)}:{text.index(value) + len(value)}" in spans.split(",")
    assert [len(x.split(",")) for x in got[:5]] == [1] * 5 and got[6] == ""
    docs = spark.createDataFrame(list(enumerate(seeds + texts)), "doc_id long, text string")
    out = [r["text"] for r in personal.redacted(docs).orderBy("doc_id").collect()][len(seeds) :]
    assert out[:2] == ["Telefon: <near_phone> and", "Telefon: <near_phone>"] and out[5] == "see Telefon: <near_phone> <phone> end"


def test_context_goes_on_until_nothing_is_new(spark):
    # three values of each generation come first behind one word, and again and again behind the next
    texts, new = [f"w-0 +1 (415) 555-2{i:03d} end" for i in range(30)], []
    for g in range(4):
        values = [f"77{g}{i}000" for i in range(3)]
        new += range(len(texts), len(texts) + 3)
        texts += [f"w-{g} {v} end" for v in values] + [f"w-{g + 1} {v} end" for v in values * 10]
    got = {r["doc_id"]: r["spans"] for r in personal.digest(table(spark, texts)).collect()}
    assert [got[i] for i in new] == ["near_phone:4:11"] * 12


def test_context_finds_the_labelled_keys(spark):
    # the list is made from the documents by their fixed wording; the operator knows the shape of lower-case keys only
    docs = spark.read.parquet("/root/testdata/sf0.01/documents.parquet")
    want = {(r["doc_id"], m.start(1), m.end(1)) for r in docs.collect() for m in re.finditer(r'(?i)token = "([0-9a-f]{40})"', r["text"] or "")}
    got = {(r["doc_id"], int(a), int(b)) for r in personal.digest(docs).collect() for k, a, b in (x.split(":") for x in r["spans"].split(",") if x) if k == "near_key"}
    assert len(want) >= 10 and got == want


def test_contexts_of_two_words_and_of_both_sides(spark):
    keys = [hashlib.sha1(str(i).encode()).hexdigest() for i in range(8)]
    assert all(re.search("[a-f]", k) for k in keys)
    texts = [f"{words(5, i)} is my key `{k}` friend {words(5, 50 + i)}" for i, k in enumerate(keys[:4])] + [f"the way is the key of it and the friend is my house {i}" for i in range(40)]
    texts += ["so is my key `ZZ-99-0001` friend", "code 0000777 is here", "the key 12345678 was lost"]
    texts += [f"{words(4, 80 + i)} open {k} sesame {words(4, 90 + i)}" for i, k in enumerate(keys[4:])] + ["I open the door"] * 3 + ["sesame seeds"] * 20 + ["now open 555-000-1 sesame"]
    got = [r["spans"] for r in personal.digest(table(spark, texts)).orderBy("doc_id").collect()]
    at = lambda i, v: f"near_key:{texts[i].index(v)}:{texts[i].index(v) + len(v)}"
    assert got[44] == at(44, "ZZ-99-0001") and got[45] == got[46] == "" and got[-1] == at(-1, "555-000-1")


def test_running_sums_of_every_length(spark):
    n = [0, 1, 2, personal.BLOCK - 1, personal.BLOCK, personal.BLOCK + 1, 3 * personal.BLOCK + 7]
    rows = [(x, list(range(1, x + 1))) for x in n]
    got = spark.createDataFrame(rows, "n int, v array<bigint>").select("n", personal.running(F.col("v"), lambda a, b: a + b).alias("r")).collect()
    assert {r["n"]: r["r"] for r in got} == {x: [i * (i + 1) // 2 for i in range(x)] for x in n}


def test_long_rows_take_time_in_proportion(spark):
    import time

    took = {}
    for size in (1, 150_000, 600_000):
        text = " ".join(f"w{i} a{i}@b.org 1.2.3.{i % 256} the {i}" for i in range(size // 30))[:size]
        docs = spark.createDataFrame([(1, text, "en", "s", len(text))], "doc_id long, text string, lang string, source string, n_chars long")
        began = time.perf_counter()
        row = personal.digest(docs).first()
        assert size < 9 or row["n_email"] > size // 60
        out = personal.redacted(docs).first()
        took[size] = time.perf_counter() - began
        assert out["text"].count("<email>") == row["n_email"]
    assert took[600_000] - took[1] < 8 * (took[150_000] - took[1]) + 10, took


def test_redaction(spark):
    docs = spark.createDataFrame([(i, t, "en", "s", len(t or "")) for i, t in enumerate([*PII, "﻿x b@c.de y"])], "doc_id long, text string, lang string, source string, n_chars long")
    out = {r["doc_id"]: r for r in personal.redacted(docs).collect()}
    assert out[2]["text"] == "\U0001d11e ä <phone> \U0001d11e <email>" and out[2]["n_chars"] == len(out[2]["text"])
    assert out[6]["text"] == "﻿x <email> y" and out[3]["text"] is None and out[4]["text"] == ""
    assert personal.redacted(docs).columns == docs.columns


# ---------------------------------------------------------------- 8
def test_byte_bpe(spark):
    enc = bytebpe.encoder(public_tokenizers.path("byte_bpe_50k.tiktoken"), public_tokenizers.PATTERN)
    texts = [*TEXTS, words(30_000, 8)]
    got = {r["doc_id"]: r for r in bytebpe.digests(bytebpe.encode_decode(table(spark, texts))).collect()}
    for i, text in enumerate(texts):
        ids = enc.encode_ordinary(text or "")
        assert got[i]["n_tokens"] == len(ids)
        assert got[i]["ids_sha256"] == hashlib.sha256(" ".join(map(str, ids)).encode()).hexdigest()
        assert got[i]["decoded_sha256"] == hashlib.sha256((text or "").encode()).hexdigest()
    back = {r[0]: bytes(r[1]).decode() for r in bytebpe.decode(bytebpe.encode(table(spark, texts))).collect()}
    assert back[0] == texts[0]


# ---------------------------------------------------------------- 9
def test_decontamination(spark):
    items = [words(30, 70), words(12, 71), "one two three", "", None]
    w = items[0].split()
    texts = [words(500, 80) + " " + items[0].upper() + " " + words(50, 81), " ".join([*w[:2], "x", *w[3:]]), " ".join(w[:14]), "zero one two three four", "one two", None, ""]
    it = spark.createDataFrame(list(enumerate(items)), "item_id long, text string")
    got = sorted((r["doc_id"], r["item_id"]) for r in decontaminate.matches(table(spark, texts), it).collect())
    assert got == [(0, 0), (1, 0), (3, 2)]
    assert sorted(r["doc_id"] for r in decontaminate.clean(table(spark, texts), it).collect()) == [2, 4, 5, 6]
    assert decontaminate.matches(table(spark, texts), it.limit(0)).count() == 0


def test_items_without_an_id_are_searched_for(spark):
    items = spark.createDataFrame([(None, words(30, 70)), (1, words(12, 71))], "item_id long, text string")
    docs = table(spark, [words(9, 1) + " " + words(30, 70), words(12, 71), words(40, 2)])
    assert sorted(((r["doc_id"], r["item_id"]) for r in decontaminate.matches(docs, items).collect())) == [(0, None), (1, 1)]
    assert [r["doc_id"] for r in decontaminate.clean(docs, items).collect()] == [2]


# ---------------------------------------------------------------- 10
def test_nearest(spark):
    rng = np.random.default_rng(4)
    x = rng.normal(size=(3000, 16)).astype(np.float32)
    rows = [(i, v.tolist(), 0) for i, v in enumerate(x)] + [(3000 + i, x[20].tolist(), 0) for i in range(40)]
    rows += [(4000, None, 0), (4020, [0.0] * 16, 0), (4040, [float("nan")] * 16, 0), (None, x[0].tolist(), 0), (20, x[20].tolist(), 1), (4060, [1.0], 0)]
    got = permindex.nearest(spark.createDataFrame(rows, "vec_id long, embedding array<float>, rank int"), 20, 20).toPandas()
    ids = np.array([*range(3000), *range(3000, 3040)])
    all_ = np.concatenate([x, np.repeat(x[20][None], 40, 0)]).astype(float)
    hits = total = 0
    for q, group in got.groupby("query_id"):
        s = (all_ * all_[q if q < 3000 else 20]).sum(axis=1)
        order = [i for i in np.lexsort((ids, -s)) if ids[i] != q][:20]
        hits += len({int(ids[i]) for i in order} & set(group["vec_id"]))
        total += 20
        assert list(group.sort_values("rank")["rank"]) == list(range(1, 21))
    assert total == 20 * 152 and hits / total >= 0.9
    twenty = got[got["query_id"] == 20].sort_values("rank")["vec_id"].tolist()
    copies = [v for v in twenty if v >= 3000]  # equal scores: the smaller ids come first
    assert len(copies) > 5 and copies == list(range(3000, 3000 + len(copies)))


@pytest.mark.parametrize("spread", [0.5, 1.0])
def test_nearest_of_unequal_lengths(spark, spread):
    rng = np.random.default_rng(6)
    x = rng.normal(size=(6000, 64))
    x *= np.exp(spread * rng.normal(size=(6000, 1))) / np.linalg.norm(x, axis=1, keepdims=True)
    got = permindex.nearest(spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(x)], "vec_id long, embedding array<double>"), 100, 20).toPandas()
    s = x @ x[::100].T
    want = {(100 * j, int(i)) for j in range(60) for i in [i for i in np.argsort(-s[:, j]) if i != 100 * j][:20]}
    recall = len(want & set(zip(got["query_id"], got["vec_id"], strict=True))) / len(want)
    print("recall", spread, recall)
    assert recall >= 0.98


def test_nearest_of_odd_tables(spark):
    schema = "vec_id long, embedding array<float>, score string"
    assert permindex.nearest(spark.createDataFrame([], schema), 20, 20).count() == 0
    # one id with two vectors, repeated rows, fewer candidates than k
    rows = [(0, [1.0, 0.0], "x"), (0, [0.0, 2.0], "x"), (0, [1.0, 0.0], "y"), (1, [3.0, 0.0], "x"), (2, [0.0, 1.0], None)]
    got = [tuple(r) for r in permindex.nearest(spark.createDataFrame(rows, schema), 20, 20).orderBy("rank").collect()]
    assert got == [(0, 1, 1, 3.0), (0, 2, 2, 2.0)]


@pytest.mark.parametrize("sf", ["0.01", "0.1"])
def test_recall_as_shipped(spark, sf):
    table_ = spark.read.parquet(f"/root/testdata/sf{sf}/embeddings.parquet")
    rows = table_.select("vec_id", "embedding").collect()
    ids, x = np.array([r[0] for r in rows]), np.array([r[1] for r in rows], float)
    got = set(map(tuple, permindex.nearest(table_, 20, 20).select("query_id", "vec_id").collect()))
    want = set()
    for i in np.flatnonzero(ids % 20 == 0):
        want |= {(int(ids[i]), int(ids[j])) for j in [j for j in np.lexsort((ids, -(x @ x[i]))) if ids[j] != ids[i]][:20]}
    assert len(got & want) >= 0.95 * len(want) and len(got) == len(want)


# ---------------------------------------------------------------- pipeline
def test_pipeline_stages(spark):
    import corpus_pipeline

    sf = "/root/testdata/sf0.001"
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    before = {r["doc_id"]: r["text"] for r in docs.collect()}
    for name, stage in corpus_pipeline.STAGES:
        held = {r["doc_id"]: r["text"] for r in docs.collect()}
        docs = store.cut(stage(spark, docs, sf), name)
        if name != "token_ids":
            assert docs.columns == ["doc_id", "text", "lang", "source", "n_chars"]
        if name == "near_duplicates":
            assert sorted(r[0] for r in docs.select("doc_id").collect()) == [d for d, _, _, kept in brute_groups(sorted(held.items()), 5, 80) if kept]
        if name == "quality":
            bad = spark.read.parquet(f"{sf}/labels.parquet").where("quality = 0").join(docs, "doc_id").count()
            assert 0.8 * len(before) < docs.count() <= len(before) and bad <= 2
    assert docs.where(F.size("ids") != F.col("n_tokens")).count() == 0
    assert set(r["doc_id"] for r in docs.collect()) <= set(before)


def test_redaction_of_added_spans(spark):
    texts = [f"Please Telefon: +1 (415) 555-2{i:03d} thanks {words(10, i)}" for i in range(6)] + ["Telefon: 030/1234567 and room 12345678 b@c.de here"]
    docs = spark.createDataFrame([(i, t, "en", "s", len(t)) for i, t in enumerate(texts)], "doc_id long, text string, lang string, source string, n_chars long")
    out = {r["doc_id"]: r["text"] for r in personal.redacted(docs).collect()}
    assert out[6] == "Telefon: <near_phone> and room 12345678 <email> here" and out[0].startswith("Please Telefon: <phone> thanks")
