"""Each operator against a brute-force version on small tables with nulls, empties, repeated rows and clashing names."""

import collections
import hashlib
import random
import re
import zlib

import numpy as np
import public_tokenizers
import pytest
from pyspark.sql import functions as F

from neardup.llm import decontaminate, lines, pieces, private, quality, shards, shingle_join, substrings, token_files, toxicity
from neardup.session import scratch_path

BPE, PIECES = public_tokenizers.path("byte_bpe_50k.json"), public_tokenizers.path("piece_bpe_32k.model")
WORD = re.compile("[^\x20\x09-\x0d]+")
ODD = ["", " ", "\n\n", "a", "  two  spaces ", "tab\tand nbsp　wide", "it's '' 's", "▁ mark▁", "日本語 text🙂", "x" * 3000, "end. \n next,\nline.", "<|endoftext|> y", "\x00\x1c\x85 z"]


def words_of(n, seed):
    r = random.Random(seed)
    return [f"w{r.randrange(10**6)}" for _ in range(n)]


def texts():
    long = " ".join(words_of(400, 1))
    cut = " ".join(words_of(400, 1)[150:300]) + " " + " ".join(words_of(60, 2))
    return [*ODD, long, long, cut, " ".join(words_of(300, 3)) + "\n" + cut, None, None]


@pytest.fixture(scope="module")
def docs(spark):
    rows = [(i, t, "en", i) for i, t in enumerate(texts())] + [(3, "a", "en", 0), (None, "no id", None, None)]
    return spark.createDataFrame(rows, "doc_id bigint, text string, lang string, n_tokens bigint")


@pytest.fixture(scope="module")
def none(docs):
    return docs.limit(0)


def shingles(text, k=5):
    low = "".join(c.lower() if "A" <= c <= "Z" else c for c in text or "")
    w = WORD.findall(low)
    return [tuple(w[i : i + k]) for i in range(len(w) - k + 1)] if len(w) >= k else ([tuple(w)] if w else [])


# --- 1


def test_token_files_round_trip(spark, docs):
    from tokenizers import Tokenizer

    plain, path = Tokenizer.from_file(BPE), scratch_path(spark, "t")
    token_files.write_token_files(docs, path, BPE, 2, range_rows=5)
    got = token_files.read_token_files(spark, path).orderBy("start").collect()
    want = sorted(docs.collect(), key=lambda r: (r.doc_id is not None, r.doc_id or 0))
    assert [r.doc_id for r in got] == [r.doc_id for r in want]
    start = 0
    for g in got:
        assert g.start == start
        start += len(g.ids)
    by = collections.defaultdict(list)
    for g in got:
        by[g.doc_id].append(list(g.ids))
    for r in want:
        assert [*plain.encode(r.text or "", add_special_tokens=False).ids, 2] in by[r.doc_id]
    one = token_files.read_one(spark, path, 4)
    assert one.tolist() == [*plain.encode(ODD[4], add_special_tokens=False).ids, 2]
    digests = {r.doc_id: r for r in token_files.read_digests(spark, path).collect()}
    assert digests[5].ids_crc32 == zlib.crc32(np.array([*plain.encode(ODD[5], add_special_tokens=False).ids, 2], "<u4").tobytes())


def test_reading_one_document_skips_files(spark):
    from neardup.plans.rules import plan_text

    path = scratch_path(spark, "t")
    docs = spark.range(4000).select((F.col("id") * 3).alias("doc_id"), F.concat(F.lit("text "), "id").alias("text"))
    token_files.write_token_files(docs, path, BPE, 2, range_rows=100)
    files = [r.n for r in spark.read.parquet(f"{path}/blocks").groupBy("range_id").agg(F.sum(F.size("doc_ids")).alias("n")).collect()]
    assert len(files) >= 30 and max(files) < 300
    some = token_files._blocks_with(spark, path, 3 * 1234)
    assert "GreaterThanOrEqual(last_id" in plan_text(some) and some.count() == 1
    assert token_files.read_one(spark, path, 3 * 1234).tolist() == token_files.read_token_files(spark, path).where(F.col("doc_id") == 3 * 1234).first().ids
    assert token_files.read_one(spark, path, 4) is None


def test_token_files_of_nothing(none):
    assert token_files.token_files_of(none, BPE).count() == 0


def test_part_table_equals_the_library():
    from tokenizers import Tokenizer

    plain, table, r = Tokenizer.from_file(BPE), token_files.PartTable(BPE, entries=50), random.Random(4)
    bits = [" ", "  ", "\n", "a", "The", "'s", ".", ",", "...", "é", " ", "　", "42", "<|endoftext|>", "²", "日", "\t"]
    for _ in range(3000):
        t = "".join(r.choice(bits) for _ in range(r.randint(0, 12)))
        assert table.encode(t) == np.array(plain.encode(t, add_special_tokens=False).ids, np.uint32).tobytes(), repr(t)


# --- 9


def test_piece_table_equals_the_library():
    import sentencepiece

    plain, table, r = sentencepiece.SentencePieceProcessor(model_file=PIECES), pieces.PieceTable(PIECES, entries=40), random.Random(4)
    bits = [" ", "  ", "\n", "a", "The", "é", "▁", "　", "<s>", "日", "🙂", "\x00", "<0x41>", "ing"]
    for t in [*ODD, *("".join(r.choice(bits) for _ in range(r.randint(0, 12))) for _ in range(3000))]:
        ids = [1, *plain.encode(t), 2]
        assert table.encode(t) == (np.array(ids, np.uint32).tobytes(), plain.decode(ids)), repr(t)


def test_piece_encoding_of_a_table(docs, none):
    got = pieces.encode_documents(docs, PIECES).collect()
    assert len(got) == docs.count() and {tuple(r.ids) for r in got if r.id == 0} == {(1, 2)}
    assert pieces.encode_digests(none, PIECES).count() == 0


def test_table_of_distinct_words(spark, docs, monkeypatch):
    """Counts of all words, a bounded table of frequent ones, and the library's ids whatever its size; repeated and null ids stay."""
    import sentencepiece

    plain, table = sentencepiece.SentencePieceProcessor(model_file=PIECES), pieces.PieceTable(PIECES)
    want = collections.Counter(w for r in docs.collect() if r.text for w in table.words(r.text)[0] if len(w) <= pieces.KEEP)
    counts = pieces.word_counts(docs.select("text"), PIECES)
    assert {r.word: r.n for r in counts.collect()} == want
    for most in (0, 5, 30, 10**6):
        found = [r.word for r in pieces.frequent_words(counts, most).collect()]
        assert len(found) <= most and all(want[f] > want[w] for f in found for w in want if w not in set(found))
    assert len(found) == len(want)
    again = docs.unionByName(docs.where("doc_id = 3"))
    truth = sorted((str(r.doc_id), hashlib.sha256(np.array([1, *plain.encode(r.text or ""), 2], "<u4").tobytes()).hexdigest()) for r in again.collect())
    for most in (pieces.HEAD, 3):
        monkeypatch.setattr(pieces.shared_table, "__defaults__", (most,))
        assert sorted((str(r.doc_id), r.ids_sha256) for r in pieces.encode_digests(again, PIECES).collect()) == truth


# --- 8


def test_quality_features(docs, none):
    got = {(r.doc_id, r.n_words, r.word_chars): r for r in quality.quality_report(docs).collect()}
    for d in docs.collect():
        t = d.text or ""
        w = WORD.findall(t)
        runs = collections.Counter(tuple(w[i : i + 5]) for i in range(len(w) - 4))
        cover = {j for i in range(len(w) - 4) if runs[tuple(w[i : i + 5])] > 1 for j in range(i, i + 5)}
        seen, dup = set(), 0
        for line in t.split("\n"):
            if WORD.search(line):
                dup += line in seen
                seen.add(line)
        r = got[d.doc_id, len(w), sum(map(len, w))]
        assert (r.n_symbols, r.n_dup_lines, r.n_repeat_words) == (sum(c in "#*$%&|<>" for c in t), dup, len(cover))
        assert r.base_failed == (len(w) < 10 or 100 * len(cover) > 20 * len(w)) and not (r.kept and r.base_failed)
    assert quality.quality_report(none).count() == 0


def test_quality_order_does_not_change_the_verdict(spark):
    rows = [(i, " ".join(words_of(12 + i, i))) for i in range(20)] + [(90, "a b c d e " * 9), (91, "short"), (92, " ".join(f"x{i}### " for i in range(40)))]
    df = spark.createDataFrame(rows, "doc_id bigint, text string")
    feats = lambda order: quality.cascade(quality.Features(*quality.texts_of(__import__("pyarrow").array([t for _, t in rows]))), order) < 0
    assert (feats(quality.RULES) == feats(quality.RULES[::-1])).all()
    assert {r.doc_id for r in quality.quality_filter(df).collect()} == set(range(20))


def test_quality_of_a_very_long_text_and_clashing_columns(spark):
    words = words_of(60_000, 1)
    text = " ".join(words) + "\n" + " ".join(words[:5]) + "\nx###\nx###"
    df = spark.createDataFrame([(1, text, 7), (1, text, 7), (2, "", 8)], "doc_id bigint, text string, kept int")
    got = quality.quality_report(df).collect()
    long = [r for r in got if r.doc_id == 1]
    assert len(got) == 3 and len(long) == 2 and long[0] == long[1]
    assert (long[0].n_words, long[0].n_symbols, long[0].n_dup_lines, long[0].n_repeat_words, long[0].kept) == (60_007, 6, 1, 10, True)
    kept = quality.quality_filter(df)
    assert kept.columns == df.columns and [(r.doc_id, r["kept"]) for r in kept.collect()] == [(1, 7), (1, 7)]


# --- 4


def test_folding_and_exceptions():
    assert toxicity.fold("1D10T іdіоt ｉｄ​iot") == "idiot idiot idiot"
    lex = toxicity.Lexicon({"trash": 3.0, "idiot": 4.0}, ("trash can",))
    assert [x[2] for x in lex.hits("an 1d10t, the trash can and tra$h notidiot")] == [4.0, 3.0]
    assert toxicity.Lexicon({}, ()).features("text") == (0.0, 0.0) == toxicity.Lexicon({"abcd": 1.0}).features(None)


def test_toxicity_learns_and_scores(spark, none):
    r = random.Random(3)
    rows = [(i, " ".join(words_of(30, i) + (["blargh" + "xyz"[i % 3]] if i % 4 == 0 else []))) for i in range(200)]
    df = spark.createDataFrame([*rows, (1000, None)], "doc_id bigint, text string")
    labels = spark.createDataFrame([(i, int(i % 4 == 0)) for i, _ in rows] + [(7777, 1), (None, None)], "doc_id bigint, toxic int")
    got = {x.doc_id: x for x in toxicity.score_documents(df, labels).collect()}
    assert all(got[i].predicted == int(i % 4 == 0) for i, _ in rows) and got[1000].predicted == 0
    assert all(x.held_out == (zlib.crc32(str(i).encode()) % 5 == 0) for i, x in got.items())
    report = toxicity.held_out_report(toxicity.score_documents(df, labels), labels).first()
    assert report.n == sum(x.held_out for i, x in got.items() if i < 200) and report.accuracy == report.precision == report.recall == 1
    assert r and toxicity.score_documents(df, labels.limit(0)).count() == 201 and toxicity.score_documents(none, labels).count() == 0


def plain_hits(folded, terms, exceptions):
    """Every term at every place where a word begins, in plain loops."""
    spans = [(i, i + len(e)) for e in exceptions for i in range(len(folded)) if folded.startswith(e, i) and (i == 0 or not folded[i - 1].isalnum())]
    return sorted((i, i + len(t), w) for t, w in terms.items() for i in range(len(folded)) if folded.startswith(t, i) and (i == 0 or not folded[i - 1].isalnum()) and not any(s <= i and i + len(t) <= e for s, e in spans))


def test_matching_against_plain_loops():
    r = random.Random(7)
    terms, exceptions = {"idio": 1.0, "idiot": 2.0, "tras": 3.0, "dolt": 1.5}, ("idiot proof", "trash can", "trash can idiot")
    lexicon = toxicity.Lexicon(terms, exceptions)
    bits = ["idiot", "1d10t", "trash", "tra$h", "can", "proof", " ", " ", "-", "dolts", "adolt", "é", "\u200b", "і", "x", "\n", "İ"]
    for text in [*("".join(r.choice(bits) for _ in range(r.randint(0, 12))) for _ in range(3000)), "trash can idiot proof " * 5000]:
        folded = toxicity.fold(text)
        if len(text) < 1000:
            assert sorted(lexicon.hits(text)) == plain_hits(folded, terms, exceptions), repr(text)
    assert lexicon.hits("trash can idiot proof " * 5000) == []


def test_exceptions_are_learnt_from_harmless_rows(spark):
    rows = [(f"you blargh {k}", 1) for k in range(40)] + [(f"the blargh museum {k}", 0) for k in range(3)] + [(f"nice text {k}", 0) for k in range(40)]
    df = spark.createDataFrame(rows, "text string, toxic int")
    found = toxicity.learn_exceptions(df, {"blar": 2.0})
    assert set(found) == {"the blargh", "blargh museum"}
    assert toxicity.Lexicon({"blar": 2.0}, found).hits("see the blargh museum") == [] and toxicity.Lexicon({"blar": 2.0}, found).hits("you blargh")
    assert toxicity.learn_exceptions(df.limit(0), {"blar": 2.0}) == () == toxicity.learn_exceptions(df, {})


def test_equal_texts_score_alike_and_held_out_rows_are_told(spark):
    docs, labels = (spark.read.parquet(f"/root/testdata/sf0.1/{t}.parquet") for t in ("documents", "labels"))
    docs = docs.withColumn("score", F.lit(0.5)).withColumn("toxic", F.lit(1))
    scored = toxicity.score_documents(docs, labels)
    report = toxicity.held_out_report(scored, labels).first()
    assert report.n > 500 and report.precision >= 0.9 and report.recall >= 0.9, report
    by_text = collections.defaultdict(set)
    for x in scored.join(docs.select("doc_id", "text"), "doc_id").collect():
        by_text[x.text].add(x.score)
    assert all(len(s) == 1 for s in by_text.values())


# --- 6


def plain_spans(text):
    """The contract's patterns as they stand, one after the other."""
    out = []
    for m in re.finditer(r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+", text):
        out.append((m.start(), 0, m.end()))
    for m in re.finditer(r"[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)", text):
        if max(map(int, m.group().split("."))) <= 255:
            out.append((m.start(), 1, m.end()))
    for m in re.finditer(r"[0-9]([\x20-]?[0-9])+", text):
        d = [int(c) for c in m.group() if c.isdigit()][::-1]
        if 14 <= len(d) <= 19 and (sum(d[::2]) + sum(sum(divmod(2 * x, 10)) for x in d[1::2])) % 10 == 0:
            out.append((m.start(), 2, m.end()))
    for m in re.finditer(r"\+[0-9][\x20().0-9-]+[0-9]", text):
        if 10 <= sum(c.isdigit() for c in m.group()) <= 15:
            out.append((m.start(), 3, m.end()))
    return ",".join(f"{private.KINDS[k]}:{s}:{e}" for s, k, e in sorted(out))


@pytest.fixture(scope="module")
def tagger(spark):
    return private.train_tagger(spark.read.parquet("/root/testdata/sf0.001/documents.parquet").select("doc_id", "text"))


def test_base_spans():
    t = "mail a.b@x.example.com or 10.0.0.300 10.1.2.3 card 4111 1111 1111 1111, +1 (499) 555-6503 +12"
    assert private.digest(private.base_spans(t)) == "email:5:22,ip:37:45,card:51:70,phone:72:89"
    assert private.digest(private.base_spans("10.1.2.3@x.com")) == "email:0:14,ip:0:8"
    assert private.digest(private.base_spans("4111111111111111@x.com")) == "email:0:22,card:0:16"
    assert private.base_spans("") == [] == private.base_spans("@ @@ + . 1")
    assert not private.luhn("4111111111111112")
    r = random.Random(2)
    bits = ["1", "4111 1111 1111 1111", "10.0.0.1", ".", "@", "a", "+", " ", "-", "+1 (499) 555-6503", "x.y", "é", "255", "(", ")", "\n"]
    for _ in range(4000):
        t = "".join(r.choice(bits) for _ in range(r.randint(0, 9)))
        assert private.digest(private.base_spans(t)) == plain_spans(t), repr(t)


def test_private_data_of_a_whole_table(spark, tagger):
    docs = spark.read.parquet("/root/testdata/sf0.01/documents.parquet").withColumn("spans", F.lit("x")).withColumn("n_email", F.lit(9))
    texts = {r.doc_id: r.text for r in docs.collect()}
    got = private.find_private(docs, tagger).collect()
    assert len(got) == len(texts)
    for r in got:
        want = plain_spans(texts[r.doc_id])
        kinds = collections.Counter(x.split(":")[0] for x in want.split(",") if x)
        assert (r.n_email, r.n_ip, r.n_card, r.n_phone) == tuple(kinds[k] for k in private.KINDS)
        assert r.base_sha256 == hashlib.sha256(want.encode()).hexdigest()
        assert {x for x in want.split(",") if x} <= set(r.spans.split(",")) and r.n_added == len([x for x in r.spans.split(",") if x]) - sum(kinds.values())


def test_tagger_finds_numbers_that_no_pattern_finds(tagger):
    r, texts, want = random.Random(9), [], []
    digits = lambda n: "".join(r.choice("0123456789") for _ in range(n))
    for k in range(200):
        a, b, c = digits(3), digits(3), digits(4)
        body, kind = r.choice([f"({a}) {b}-{c}", f"{a}-{b}-{c}", f"{a}.{b}.{c}"]), 3
        if k % 2:
            x = digits(15)
            x = next(x + str(i) for i in range(10) if private.luhn(x + str(i)))
            body, kind = r.choice("./").join(x[i : i + 4] for i in range(0, 16, 4)), 2
        # Anywhere in a text that is much longer than a window, so that spans lie over edges of windows.
        head, tail = " ".join(words_of(r.randint(0, 40), k)).replace("w", "no "), " and so on" * 30
        head = re.sub("[0-9]+", "th", head) + " "
        texts.append(head + body + tail)
        want.append((len(head), len(head) + len(body), kind))
    found = private.tagged_spans(texts, tagger)
    assert sum(w in f for w, f in zip(want, found, strict=True)) >= 0.9 * len(want)
    assert sum(len(f) for f in private.tagged_spans([t.replace("0", "x").replace("1", "y")[:20] for t in texts], tagger)) <= 10
    assert found == [private.tagged_spans([t], tagger)[0] for t in texts]


def test_best_path_of_a_batch_equals_all_paths():
    """Viterbi over scores of different lengths against every path."""
    import itertools

    tagger, r = private.Tagger(1), np.random.default_rng(0)
    tagger.p["T"] = r.standard_normal(tagger.p["T"].shape).astype(np.float32)
    e, sizes = r.standard_normal((3, 4, private.TAGS)).astype(np.float32), np.array([4, 1, 3])
    got = tagger.best_path(e, sizes)
    for i, n in enumerate(sizes.tolist()):
        worth = lambda p: sum(e[i, t, p[t]] for t in range(n)) + sum(tagger.p["T"][p[t - 1], p[t]] for t in range(1, n))  # noqa: B023, E731
        assert tuple(got[i, :n]) == max(itertools.product(range(private.TAGS), repeat=n), key=worth)


def test_tagger_gradients_and_private_data(spark, none, tagger):
    other, r = private.Tagger(1), np.random.default_rng(0)
    x, y = r.integers(0, private.N_CLASSES, (3, 7)), r.integers(0, private.TAGS, (3, 7))
    _, g = other.step(x, y)
    for name, at in (("E", (int(x[0, 0]), 1)), ("fW", (2, 3)), ("bW", (9, 5)), ("O", (1, 2)), ("T", (0, 1))):
        keep, eps = other.p[name][at], 1e-2
        other.p[name][at] = keep + eps
        up = other.step(x, y)[0]
        other.p[name][at] = keep - eps
        down = other.step(x, y)[0]
        other.p[name][at] = keep
        assert abs((up - down) / (2 * eps) - g[name][at]) < 2e-2
    df = spark.createDataFrame([(1, "call +1 (499) 555-6503 now"), (2, None), (3, ""), (3, "x" * 5000 + " a@b.cd"), (3, "")], "doc_id bigint, text string")
    got = sorted((r.doc_id, r.n_email, r.n_phone, r.spans) for r in private.find_private(df, tagger).collect())
    assert got == [(1, 0, 1, "phone:5:22"), (2, 0, 0, ""), (3, 0, 0, ""), (3, 0, 0, ""), (3, 1, 0, "email:5001:5007")]
    assert private.find_private(none, tagger).count() == 0


# --- 3


@pytest.mark.parametrize("hot", [4096, 1])
def test_repeated_strings(docs, none, hot):
    rows = docs.collect()
    raw = [(r.text or "").encode() for r in rows]
    for size, anchor in ((400, 80), (40, 10)):
        count = collections.Counter(t[i : i + size] for t in raw for i in range(len(t) - size + 1))
        want = []
        for r, t in zip(rows, raw, strict=True):
            gone = np.zeros(len(t) + 1, bool)
            for i in range(len(t) - size + 1):
                if count[t[i : i + size]] > 1:
                    gone[i : i + size] = True
            kept = bytes(c for c, g in zip(t, gone, strict=False) if not g)
            want.append((r.doc_id or -1, len(t), int(gone.sum()), int((np.diff(gone.astype(int)) == 1).sum() + gone[0]), hashlib.sha256(kept).hexdigest()))
        got = substrings.removal_digests(docs, size, anchor, hot).collect()
        assert sorted((r.doc_id or -1, *tuple(r)[1:]) for r in got) == sorted(want)
    assert substrings.removal_digests(none).count() == 0


def test_radix_passes_order_windows_and_keep_the_repeated_ones():
    r = random.Random(3)
    raw = bytes(r.choice(b"ab") for _ in range(600)) * 2 + bytes(r.choice(b"abc") for _ in range(300))
    sums = substrings.prefix_hash(np.frombuffer(raw, np.uint8))
    for size, digit in ((40, 8), (9, 4), (12, 5), (7, 80)):
        starts = np.arange(len(raw) - size + 1)
        group = starts % 3
        found, rank = substrings.radix_sorted(sums, starts, group, size, digit)
        count = collections.Counter((int(g), raw[s : s + size]) for s, g in zip(starts, group, strict=True))
        assert sorted(found.tolist()) == [s for s in starts.tolist() if count[s % 3, raw[s : s + size]] > 1] and len(found)
        # One rank for each content, in order of groups and then of digits.
        contents = [(int(group[s]), raw[s : s + size]) for s in found.tolist()]
        assert (np.diff(rank) >= 0).all() and len({*zip(rank.tolist(), contents, strict=True)}) == len(set(contents)) == len(set(rank.tolist()))
        assert (np.diff(group[found]) >= 0).all()


# --- 5


def run_oracle(rows, least):
    """Longest match of every place with every earlier one, in plain loops."""
    seqs = {d: [(k, x) for k, x in enumerate((t or "").split("\n")) if WORD.search(x)] for d, t in rows}
    places, out = [(d, i) for d in sorted(seqs) for i in range(len(seqs[d]))], {d: set() for d, _ in rows}
    for k, (d, i) in enumerate(places):
        for e, j in places[:k]:
            n = 0
            while i + n < len(seqs[d]) and j + n < len(seqs[e]) and seqs[d][i + n][1] == seqs[e][j + n][1]:
                n += 1
            if sum(len(WORD.findall(x)) for _, x in seqs[d][i : i + n]) >= least:
                out[d].update(x for x, _ in seqs[d][i : i + n])
    return {d: "\n".join(x for k, x in enumerate((t or "").split("\n")) if k not in out[d]) for d, t in rows}


@pytest.fixture(scope="module")
def line_docs(spark):
    r = random.Random(5)
    pool = [f"line {k} " + " ".join(words_of(k % 6, k)) for k in range(14)] + [" ".join(words_of(9, 50)), "", "x", "y", "  "]
    long_run = "\n".join(f"u{k} v{k}" for k in range(40))
    rows = [(i, "\n".join(r.choice(pool) for _ in range(r.randint(0, 25)))) for i in range(40)] + [(50, None), (51, "x\n" * 30), (52, long_run), (53, "a\n" + long_run + "\nb"), (54, "")]
    return rows, spark.createDataFrame(rows, "doc_id bigint, text string")


def test_line_dedup_against_longest_matches(line_docs, none):
    rows, plain = line_docs
    # Columns with the names that are used inside.
    df = plain
    for name in ("at", "d", "t", "name", "check", "row", "cut", "_cut", "_d", "_t", "_n_removed", "sources", "a.b"):
        df = df.withColumn(name, F.lit(name))
    for least in (8, 1):
        done = lines.run_dedup(df, least)
        assert done.columns == df.columns
        got = done.collect()
        assert {x.doc_id: x.text or "" for x in got} == run_oracle(rows, least) and {tuple(x)[2:] for x in got} == {tuple(df.columns[2:])}
    assert next(x.text for x in got if x.doc_id == 50) is None
    assert lines.line_dedup_report(none).count() == 0
    twice = plain.where("doc_id = 3").unionByName(plain.where("doc_id = 3"))
    assert len({x.text for x in lines.run_dedup(twice).collect()}) == 1 and lines.run_dedup(twice).count() == 2


def test_doubling_levels_and_maximal_runs(line_docs):
    """Every level has the places whose runs occur more than once, and the intervals give runs as long as they go."""
    rows, df = line_docs
    sequences = lines.line_sequences(df, 10)
    seqs = {d: [x for x in (t or "").split("\n") if WORD.search(x)] for d, t in rows}
    for k, level in enumerate(lines.doubled(sequences, 10)):
        n = 1 << k
        count = collections.Counter(tuple(s[i : i + n]) for s in seqs.values() for i in range(len(s) - n + 1))
        want = sorted((d, i) for d, s in seqs.items() for i in range(len(s) - n + 1) if count[tuple(s[i : i + n])] > 1)
        assert sorted((x.d, x["at"]) for x in level.collect()) == want and len(want) > 10
    _, copies = lines.later_copies(sequences, lines.doubled(sequences, 10))
    found = {x.d: [[(r["at"], r.end) for r in s.runs] for s in x.sources] for x in lines.maximal_runs(copies).collect()}
    assert found[53] == [[(1, 41)]] and 52 not in found and 50 not in found


def test_line_dedup_with_a_hot_line_and_hot_keys(spark, monkeypatch):
    """The same rows whether names are heavy, and broadcast, or not."""
    hot, rows = " ".join(words_of(20, 1)), []
    for i in range(60):
        rows.append((i, "\n".join([" ".join(words_of(6, 100 + i)), hot if i % 3 else "x", " ".join(words_of(6, 300 + i % 7)), " ".join(words_of(6, 400 + i % 7))])))
    df = spark.createDataFrame(rows, "doc_id bigint, text string")
    want = run_oracle(rows, 10)
    from neardup.operators import skew

    for keys in (1_000, 5):
        monkeypatch.setattr(skew, "HEAVY_KEYS", keys)
        monkeypatch.setattr(skew.join_counted, "__defaults__", ("inner", "n", keys))
        assert {x.doc_id: x.text for x in lines.run_dedup(df).collect()} == want


def test_pipeline_adds_up_no_overlapping_runs(spark):
    import corpus_pipeline

    a, b, c = (" ".join(words_of(4, k)) for k in (1, 2, 3))
    rows = [(1, f"{a}\n{b}"), (2, f"{b}\n{c}"), (3, f"{a}\n{b}\n{c}"), (4, f"{a}\n{b}\n{c}")]
    got = {x.doc_id: x.text for x in corpus_pipeline.repeated_lines(spark, spark.createDataFrame(rows, "doc_id bigint, text string"), "").collect()}
    # The fourth is a copy as a whole: it is for the next stage to drop.
    assert got == dict(rows)
    assert {x.doc_id: x.text for x in lines.run_dedup(spark.createDataFrame(rows, "doc_id bigint, text string")).collect()} == {**dict(rows), 4: ""}


def test_pipeline_cuts_a_repeated_line_on_its_own(spark):
    import corpus_pipeline

    line, other = " ".join(words_of(60, 1)), [" ".join(words_of(12, k)) for k in range(2, 6)]
    rows = [(1, f"{other[0]}\n{line}\n{other[1]}", 9), (2, f"{other[2]}\n{line}\n{other[3]}", 9), (3, line, 9)]
    docs = spark.createDataFrame(rows, "doc_id bigint, text string, n_chars bigint")
    got = {x.doc_id: (x.text, x.n_chars) for x in corpus_pipeline.repeated_lines(spark, docs.where("doc_id <> 2"), "").collect()}
    # The third is no version of the first, as it is too short for that, and nothing is left of it.
    assert got == {1: (rows[0][1], 9)}
    more = spark.createDataFrame([(2, f"{other[2]}\n{line}\n{other[3]} " + " ".join(words_of(300, 9)), 9)], docs.schema)
    got = {x.doc_id: (x.text, x.n_chars) for x in corpus_pipeline.repeated_lines(spark, docs.where("doc_id = 1").unionByName(more), "").collect()}
    kept = f"{other[2]}\n{other[3]} " + " ".join(words_of(300, 9))
    assert got == {1: (rows[0][1], 9), 2: (kept, len(kept))}


# --- 2


def test_shingle_components(spark, none, monkeypatch):
    r = random.Random(8)
    base, rows = words_of(60, 5), []
    for i in range(70):
        w = list(base)
        for _ in range(r.randrange(4)):
            w[r.randrange(60)] = f"x{r.randrange(10**6)}"
        rows.append((i * 3, " ".join(w)))
    rows += [(5000, None), (5001, ""), (5002, "a b"), (5003, "A  b"), (5000, "a b"), (None, "a b")]
    df = spark.createDataFrame(rows, "doc_id bigint, text string").withColumn("cid", F.lit(9)).withColumn("n", F.lit(9))
    sets = [(d, set(shingles(t))) for d, t in rows]
    root = list(range(len(sets)))

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    for i, (d, s) in enumerate(sets):
        for j, (e, q) in enumerate(sets[:i]):
            if d is not None and e is not None and s & q and 100 * len(s & q) >= 80 * len(s | q):
                root[find(i)] = find(j)
    low = {}
    for i, (d, _) in enumerate(sets):
        if d is not None:
            low[find(i)] = min(low.get(find(i), 1 << 60), d)
    want = sorted((d if d is not None else -1, len(s), low[find(i)] if d is not None else -1) for i, (d, s) in enumerate(sets))
    for small, chunk in ((12, 1024), (1, 3)):
        monkeypatch.setattr(shingle_join, "SMALL", small)
        monkeypatch.setattr(shingle_join, "CHUNK", chunk)
        got = shingle_join.shingle_components(df).collect()
        assert sorted((-1 if x.doc_id is None else x.doc_id, x.n_shingles, -1 if x.component_id is None else x.component_id) for x in got) == want
    assert shingle_join.shingle_components(none).count() == 0


def test_one_of_each_tells_rows_with_equal_ids_apart(spark):
    a, b, c = (" ".join(words_of(40, k)) for k in (1, 2, 3))
    rows = [(3, a, 1), (5, a, 2), (5, b, 3), (6, c, 4), (6, c, 5), (7, c + " x", 6), (8, "d e", 7), (8, "D  e", 8), (9, "", 9), (9, "", 10), (None, a, 11), (None, a, 12)]
    docs = spark.createDataFrame(rows, "doc_id bigint, text string, t bigint").withColumn("_h", F.lit(1)).withColumn("_d", F.lit("x")).withColumn("row", F.lit(2)).withColumn("d", F.lit(3))
    done = shingle_join.one_of_each(docs)
    assert done.columns == docs.columns
    got = done.collect()
    count = collections.Counter((x.doc_id, (x.text or "").lower().split()[:1] == ["d"] and "d" or x.text) for x in got)
    assert count == {(3, a): 1, (5, b): 1, (6, c): 1, (8, "d"): 1, (9, ""): 2, (None, a): 2}


def test_bitmaps_never_rule_out_a_link():
    r = np.random.default_rng(2)
    for _ in range(200):
        n = int(r.integers(5, 400))
        a = np.unique(r.integers(0, 2**63, n).astype(np.uint64))
        b = np.unique(np.concatenate((a[: int(len(a) * 0.95)], r.integers(0, 2**63, max(1, n // 25)).astype(np.uint64))))
        shared = len(np.intersect1d(a, b))
        block = shingle_join.Block([1, 2], [1, 2], [len(a), len(b)], [shingle_join.bitmap(a), shingle_join.bitmap(b)])
        if 100 * shared >= 80 * (len(a) + len(b) - shared):
            assert len(block.all_pairs()[0]) == 1 == len(block.spanning_pairs()[0])


def test_signature_trees_prune_and_lose_nothing():
    """Blocks with groups of near copies of different sizes: pairs of nodes are left out, and all links are found."""
    r, pruned, looked = np.random.default_rng(4), 0, 0
    for n_groups, each in ((2, 2), (3, 4), (8, 12), (20, 30)):
        sets = []
        for g in range(n_groups):
            base = np.unique(r.integers(0, 2**63, 40 + 9 * g).astype(np.uint64))
            sets += [np.unique(np.concatenate((base[int(r.integers(3)) :], r.integers(0, 2**63, int(r.integers(1, 4))).astype(np.uint64)))) for _ in range(each)]
        block = shingle_join.Block(list(range(len(sets))), list(range(len(sets))), [len(s) for s in sets], [shingle_join.bitmap(s) for s in sets])
        tree = shingle_join.SignatureTree(block)
        seen = {tuple(sorted((int(block.ids[x]), int(block.ids[y])))) for i, j in tree.leaf_pairs() for x, y in zip(i, j, strict=True)}
        links = set()
        for a in range(len(sets)):
            for b in range(a):
                shared = len(np.intersect1d(sets[a], sets[b]))
                if 100 * shared >= 80 * (len(sets[a]) + len(sets[b]) - shared):
                    links.add((b, a))
        found = {tuple(sorted(p)) for p in zip(*(x.tolist() for x in block.all_pairs()), strict=True)}
        assert links and links <= found <= seen and len(seen) < len(sets) * (len(sets) - 1) // 2
        pruned, looked = pruned + tree.pruned, looked + tree.looked
    assert pruned > 0.2 * looked


# --- 10


def test_decontamination(spark, none):
    items = [(i, " ".join(words_of(20 + i, 100 + i))) for i in range(6)] + [(6, "one two three"), (7, None), (8, "")]
    def changed(i, k):
        w = words_of(20 + i, 100 + i)
        w[k] = "Z"
        return " ".join(w)
    rows = [(1, "pre " + items[0][1] + " post"), (2, changed(5, 0)), (3, changed(5, 12)), (4, None), (5, "One  TWO three"), (6, items[1][1].upper() + " x " + items[2][1]), (6, "clean text here"), (None, items[3][1])]
    df, bench = spark.createDataFrame(rows, "doc_id bigint, text string").withColumn("item_id", F.lit(3)), spark.createDataFrame(items, "item_id bigint, text string")
    want = set()
    for d, t in rows:
        for i, x in items:
            s, q = shingles(t), shingles(x)
            n = min(len(s), len(q))
            for p in range(len(s) - n + 1) if n else ():
                a, b = collections.Counter(s[p : p + n]), collections.Counter(q)
                if 10 * (a & b).total() >= 8 * (a | b).total():
                    want.add((d, i))
    assert {(x.doc_id, x.item_id) for x in decontaminate.contaminated(df, bench).collect()} == want and len(want) == 6
    kept = {(x.doc_id, x.text) for x in decontaminate.without_benchmark(df, bench).collect()}
    assert kept == {(3, changed(5, 12)), (4, None), (6, "clean text here")}
    assert decontaminate.contaminated(none, bench).count() == 0 == decontaminate.contaminated(df, bench.limit(0)).count()


def test_hamming_index_finds_all_within_the_radius():
    r = random.Random(1)
    prints = [r.getrandbits(64) for _ in range(300)]
    index, brought = decontaminate.HammingIndex(prints, 20), 0
    for _ in range(200):
        p = prints[r.randrange(300)]
        for k in r.sample(range(64), r.randrange(30)):
            p ^= 1 << k
        assert index.near(p) == [i for i, q in enumerate(prints) if (p ^ q).bit_count() <= 20]
        brought += len(index.candidates(p))
    assert brought < 0.45 * 200 * 300


def test_fingerprints_of_like_windows_are_within_the_radius():
    """Recall at the least similarity that counts, 0.8 exactly."""
    r, missed = np.random.default_rng(5), 0
    for _ in range(1500):
        n = 9 * int(r.integers(2, 12))
        a = r.integers(0, 2**63, n).astype(np.uint64)
        b = np.concatenate((a[: 8 * n // 9], r.integers(0, 2**63, n // 9).astype(np.uint64)))
        assert decontaminate.weighted_jaccard(a, b) == (8 * n // 9, 10 * n // 9)
        missed += (decontaminate.simhash(a) ^ decontaminate.simhash(b)).bit_count() > decontaminate.RADIUS
    assert missed <= 6


def test_fingerprints_of_many_windows_are_those_of_each(monkeypatch):
    """Running sums and batches of lookups, in parts, against one window after the other."""
    monkeypatch.setattr(decontaminate, "REACH", 64)
    monkeypatch.setattr(decontaminate, "AT_ONCE", 500)
    monkeypatch.setattr(decontaminate, "MOST_HELD", 300)
    r = np.random.default_rng(4)
    bag = r.integers(0, 2**63, 400).astype(np.uint64)
    bags = [bag[k : k + 12].copy() for k in range(0, 380, 9)] + [bag[5:17]]
    index, prints, only = decontaminate.HammingIndex([decontaminate.simhash(b) for b in bags]), decontaminate.Prints(bag, 70, 390), np.arange(len(bags)) % 3 != 1
    for size in (1, 12, 70):
        starts = np.flatnonzero(r.random(390 - size + 1) < 0.4)
        got = prints.of(starts, size)
        assert got.tolist() == [decontaminate.simhash(bag[s : s + size]) for s in starts]
        k, i = index.near_all(np.append(got, got[:5]), only)
        want = [(n, j) for n, x in enumerate([*got.tolist(), *got[:5].tolist()]) for j in index.near(x) if only[j]]
        assert list(zip(k.tolist(), i.tolist(), strict=True)) == want and want


def test_items_that_share_shingles_are_told_apart_by_fingerprints(spark):
    """Items with a common half, copies of items, long texts and repeated rows, against every window of every document."""
    half = words_of(30, 1)
    items = [(k, " ".join(half + words_of(30, 10 + k))) for k in range(6)] + [(6, " ".join(half + words_of(30, 10))), (7, " ".join(half))]
    rows = [(k, " ".join(words_of(500, 50 + k) + items[k % 8][1].split() + words_of(900, 70 + k))) for k in range(10)] + [(3, " ".join(half)), (3, " ".join(half))]
    got = sorted((x.doc_id, x.item_id) for x in decontaminate.contaminated(spark.createDataFrame(rows, "doc_id bigint, text string"), spark.createDataFrame(items, "item_id bigint, text string")).collect())
    want = []
    for d, t in rows:
        s = shingles(t)
        for i, x in items:
            q = shingles(x)
            n = min(len(s), len(q))
            if any(10 * (collections.Counter(s[p : p + n]) & collections.Counter(q)).total() >= 8 * (collections.Counter(s[p : p + n]) | collections.Counter(q)).total() for p in range(len(s) - n + 1)):
                want.append((d, i))
    assert got == sorted(want)


# --- 7


def test_shards_commit_and_compact(spark, tmp_path):
    store = shards.ShardStore(spark, f"{tmp_path}/s")
    with pytest.raises(FileNotFoundError):
        store.read()
    for k in range(6):
        store.append(spark.range(k * 100, k * 100 + 100, numPartitions=1).select(F.col("id").alias("doc_id"), F.repeat(F.col("id").cast("string"), 50).alias("text")))
    assert store.versions() == [1, 2, 3, 4, 5, 6] and store.manifest().count() == 6
    old = sorted(r.doc_id for r in store.read(3).collect())
    store.compact(target=1 << 20)
    assert store.manifest().count() < 6 and store.read().count() == 600 == store.read().select("doc_id").distinct().count()
    assert sorted(r.doc_id for r in store.read(3).collect()) == old == list(range(300))
    with pytest.raises(shards.CommitConflict):
        store.commit(store.manifest(), store.versions()[-1] - 1)
    # Files of an append that hasn't committed are young, and stay.
    spark.range(5).write.parquet(f"{tmp_path}/s/data/append-running")
    assert store.vacuum(keep=99) == 0
    assert store.vacuum(older_than=0) >= 6 and store.read().count() == 600 and len(store.versions()) == 1
    store.append(spark.range(0).select(F.col("id").alias("doc_id"), F.lit("x").alias("text")))
    assert store.read().count() == 600


def test_compaction_makes_files_of_about_the_target_size(spark, tmp_path):
    """The largest file stays near the target while the store grows: a task of a merge reads no more than about a target."""
    largest, target = [], 200_000
    for n in (8, 32):
        store = shards.ShardStore(spark, f"{tmp_path}/{n}")
        for k in range(4):
            rows = spark.range(k * 1000, k * 1000 + 250 * n // 4, numPartitions=n // 4).select(F.col("id").alias("doc_id"), F.concat_ws("", *(F.sha2((F.col("id") * 31 + i).cast("string"), 512) for i in range(4))).alias("text"), F.lit(None).cast("string").alias("path"))
            store.append(rows.unionByName(spark.createDataFrame([(None, None, "x")], "doc_id bigint, text string, path string")))
        store.compact(target=target, fanout=2)
        sizes = [r.bytes for r in store.manifest().collect()]
        largest.append(max(sizes))
        assert store.read().count() == 250 * n // 4 * 4 + 4 and store.read().where("doc_id IS NULL AND text IS NULL AND path = 'x'").count() == 4
    assert max(largest) < 2 * target and sum(sizes) > 3 * target


def test_a_second_writer_has_to_try_again(spark, tmp_path):
    one, two = (shards.ShardStore(spark, f"{tmp_path}/s") for _ in range(2))
    rows = spark.range(10).select(F.col("id").alias("doc_id"), F.lit("x").alias("text"))
    one.append(rows)
    base = two.versions()[-1]
    one.append(rows)
    with pytest.raises(shards.CommitConflict):
        two.commit(two.manifest(), base)
    assert two.append(rows) == 3 and one.read().count() == 30


def test_sharding_keeps_all_columns(spark, tmp_path, monkeypatch):
    from neardup.llm import catalog

    rows = [(i, f"text {i}", "en" if i % 2 else None, "s", i) for i in range(9)] + [(None, None, None, None, None)]
    docs = spark.createDataFrame(rows, "doc_id bigint, text string, lang string, source string, n_chars bigint")
    docs.write.parquet(f"{tmp_path}/documents.parquet")
    monkeypatch.setattr("neardup.session.scratch_path", lambda spark, name: f"{tmp_path}/{name}")
    assert catalog.op7_sharding(spark, str(tmp_path)).columns == ["doc_id", "n_bytes", "text_md5"]
    kept = shards.ShardStore(spark, f"{tmp_path}/shards").read()
    assert kept.columns == docs.columns and sorted(map(str, kept.collect())) == sorted(map(str, docs.collect()))


# --- pipeline


def test_pipeline_keeps_one_of_copies_and_no_blank_text(spark, tmp_path):
    """Copies of texts of many lines, near copies, equal ids with different texts, and columns with names that are used inside."""
    import corpus_pipeline

    lined = lambda seed, n: "\n".join(" ".join(words_of(30, seed + k)) for k in range(n))
    base, other = lined(1, 6), lined(100, 5)
    near = "\n".join([*base.split("\n")[:3], *(x.replace(" w", " v", 1) for x in base.split("\n")[3:])])
    pieced = "\n".join([base.split("\n")[0], other.split("\n")[1]] + ["short line"])
    rows = [(1, base), (2, base), (3, base), (4, near), (5, other), (5, lined(300, 4)), (5, other), (6, pieced), (7, lined(500, 1)), (8, lined(500, 1)), (9, lined(700, 3) + "\n" + base.split("\n")[0])]
    docs = spark.createDataFrame(rows, "doc_id bigint, text string")
    for name in ("row", "d", "t", "h", "sources", "cut", "_t", "rows"):
        docs = docs.withColumn(name, F.lit(name))
    docs.write.parquet(f"{tmp_path}/documents.parquet")
    spark.createDataFrame([], "item_id bigint, text string").write.parquet(f"{tmp_path}/benchmark.parquet")
    got = spark.read.parquet(f"{tmp_path}/documents.parquet")
    for _, stage in corpus_pipeline.STAGES[:-1]:
        got = stage(spark, got, str(tmp_path))
        assert got.columns == docs.columns
    kept = sorted((r.doc_id, r.text) for r in got.collect())
    # The sixth is put together from lines of others and goes, the ninth loses the line that it shares.
    assert kept == sorted([(1, base), (5, other), (5, lined(300, 4)), (7, lined(500, 1)), (9, lined(700, 3))])


def test_pipeline_against_its_parts(spark, tmp_path):
    import corpus_pipeline

    r = random.Random(6)
    item = " ".join(words_of(25, 77))
    rows = [(i, "\n".join(" ".join(words_of(r.randint(8, 14), 1000 * i + k)) for k in range(5)), "en", "s", 0) for i in range(12)]
    shared = "\n".join(" ".join(words_of(10, 99000 + k)) for k in range(2))
    rows += [(20, rows[0][1].replace("\n", " "), "en", "s", 0), (21, "short", "en", "s", 0), (22, None, "en", "s", None), (23, item + "\n" + rows[1][1].replace("\n", " x "), "en", "s", 0), (24, shared + "\n" + " ".join(words_of(40, 5)), "en", "s", 0), (25, shared + "\n" + " ".join(words_of(90, 6)), "en", "s", 0)]
    spark.createDataFrame(rows, "doc_id bigint, text string, lang string, source string, n_chars bigint").write.parquet(f"{tmp_path}/documents.parquet")
    spark.createDataFrame([(1, item)], "item_id bigint, text string").write.parquet(f"{tmp_path}/benchmark.parquet")
    docs = spark.read.parquet(f"{tmp_path}/documents.parquet")
    for name, stage in corpus_pipeline.STAGES[:-1]:
        docs = stage(spark, docs, str(tmp_path))
        assert docs.columns == ["doc_id", "text", "lang", "source", "n_chars"], name
    kept = {x.doc_id: x.text for x in docs.collect()}
    assert set(kept) == {*range(12), 24, 25} and kept[24].startswith(shared) and kept[25] == " ".join(words_of(90, 6))
    done = {x.doc_id: x for x in corpus_pipeline.run(spark, str(tmp_path)).collect()}
    assert set(done) == set(kept)
    table = pieces.PieceTable(PIECES)
    for d, t in kept.items():
        ids, text = table.encode(t)
        assert (done[d].ids_sha256, done[d].decoded_sha256) == (hashlib.sha256(ids).hexdigest(), hashlib.sha256(text.encode()).hexdigest())
