"""Nulls, repeats, clashing names, long texts and ties; and each base rule against an independent version on random texts."""

import hashlib
import math
import random
import re
import zlib
from collections import Counter

import numpy as np
import public_tokenizers as P
import pyarrow as pa
import pytest
from pyspark.sql import functions as F

from compatgraph.llm import bpe, common, exact_dedup, mixing, near_dedup, pii, quality, secrets, substring_dedup, tokenfile, toxicity

WORD = r"[^\x20\x09-\x0D]+"
RANKS, TOKENIZER = P.path("byte_bpe_50k.tiktoken"), P.path("byte_bpe_50k.json")
LONG = " ".join(f"w{i % 977}x{i % 13}" for i in range(60_000))
SAME = " ".join(f"same{i}" for i in range(50))
#: doc_id, text: null ids, repeated rows, one id with two texts, empty and very long texts.
HARD = [(None, SAME), (None, SAME), (None, None), (-5, "alone here"), (-1, ""), (-1, ""), (7, SAME), (7, SAME), (7, "other text of seven"), (8, LONG), (9, LONG + " end"), (2**62, " \t\n")]


@pytest.fixture(scope="module")
def hard(spark):
    rows = [(i, t, "de" if k % 2 else None, "s" if k % 3 else None, k, 1, "x") for k, (i, t) in enumerate(HARD)]
    return spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, copies int, copy int, _salt string").repartition(3).cache()


def counted(df, *names):
    return Counter(tuple(r[n] for n in names) for r in df.collect())


# --- rows that are hard to tell apart
def test_exact_dedup_keeps_one_of_repeated_rows(spark, hard):
    got = exact_dedup.group_rows(hard).collect()
    assert len(got) == len(HARD)
    by_text = {}
    for r in got:
        by_text.setdefault(r.text_sha256, []).append(r)
    for rows in by_text.values():
        assert sum(r.kept for r in rows) == 1 and {r.group_size for r in rows} == {len(rows)}
        (first,) = [r for r in rows if r.kept]
        ids = [r.doc_id for r in rows if r.doc_id is not None]
        assert first.doc_id == first.keep_id == (min(ids) if ids else None)
    twice = spark.createDataFrame([(1, "t"), (1, "t"), (2, "t")], "doc_id long, text string")
    assert sorted((r.doc_id, r.kept) for r in exact_dedup.group_rows(twice).collect()) == [(1, False), (1, True), (2, False)]
    clash = exact_dedup.group_rows(twice.unionByName(spark.createDataFrame([(3, "u")], twice.schema)), digest=lambda t: F.lit("d"))
    assert sorted((r.doc_id, r.kept) for r in clash.collect()) == [(1, False), (1, True), (2, False), (3, True)]


def test_near_dedup_of_hard_rows(hard):
    got = counted(near_dedup.near_duplicates(hard), "doc_id", "n_shingles", "component_id", "kept")
    n = lambda t: len({tuple(w[i : i + 5]) for w in [t.split()] for i in range(len(w) - 4)})
    assert got == Counter({(None, n(SAME), None, True): 2, (None, 0, None, True): 1, (7, n(SAME), None, False): 2, (7, 1, 7, True): 1, (-5, 1, -5, True): 1, (-1, 0, -1, True): 2, (8, n(LONG), 8, True): 1, (9, n(LONG + " end"), 8, False): 1, (2**62, 0, 2**62, True): 1})


def test_substring_dedup_of_hard_rows(hard):
    got = counted(substring_dedup.remove_repeats(hard), "doc_id", "n_words", "n_removed")
    # 35-word windows: the long text repeats itself and its copy
    assert got == Counter({(None, 50, 50): 2, (None, 0, 0): 1, (-5, 2, 0): 1, (-1, 0, 0): 2, (7, 50, 50): 2, (7, 4, 0): 1, (8, 60_000, 60_000): 1, (9, 60_001, 60_000): 1, (2**62, 0, 0): 1})


def test_one_window_in_most_documents(spark):
    """A digest that holds most windows is spread and still found everywhere."""
    rows = [(i, " ".join(f"{i}x{j}" for j in range(20)) + " " + SAME + f" end{i}") for i in range(300)]
    got = substring_dedup.remove_repeats(spark.createDataFrame(rows, "doc_id long, text string"), hot=50).collect()
    assert len(got) == 300 and {x.n_removed for x in got} == {50}


def test_join_spread_loses_and_doubles_nothing(spark):
    rows = spark.range(20_000).select(F.when(F.col("id") % 3 == 0, 0).otherwise(F.col("id")).alias("k"), "id")
    table = rows.groupBy("k").agg(F.count(F.lit(1)).alias("n"))
    busy = common.heavy(table, "k", "n")
    assert [r.k for r in busy.collect()] == [0]
    out = common.join_spread(rows, table, "k", busy)
    assert out.count() == 20_000 == out.select("id").distinct().count() and out.filter("k = 0 and n <> 6667").count() == 0


def test_mixing_of_hard_rows(hard):
    got = mixing.mix(hard).collect()
    assert sorted((r.doc_id is None, r.doc_id or 0, r.size) for r in got) == sorted((i is None, i or 0, len(re.findall(WORD, t or ""))) for i, t in HARD)
    assert all(r.taken <= 2 * r.size for r in got)


def test_token_files_keep_every_doc_id(spark, hard):
    out = tokenfile.write(hard, TOKENIZER)
    got = tokenfile.read(spark, out).collect()
    want = sorted(HARD, key=lambda r: (r[0] is not None, r[0] or 0))
    assert [r.doc_id for r in sorted(got, key=lambda r: r.start)] == [i for i, _ in want]
    with pytest.raises(ValueError):
        tokenfile.write(hard, TOKENIZER, end_id=-1)
    # an end id beyond 16 bits is kept whole, in wider files
    (r,) = tokenfile.read(spark, tokenfile.write(hard.filter("doc_id = -5"), TOKENIZER, end_id=70_000)).collect()
    from tokenizers import Tokenizer

    ids = [*Tokenizer.from_file(TOKENIZER).encode("alone here", add_special_tokens=False).ids, 70_000]
    assert (r.n_tokens, r.ids_crc32) == (len(ids), zlib.crc32(np.array(ids, "<u4").tobytes()))


def test_other_tokenizers_go_through_the_library():
    from tokenizers import Tokenizer

    lib, enc = Tokenizer.from_file(P.path("word_bpe_49k.json")), tokenfile.Encoder(P.path("word_bpe_49k.json"))
    texts = ["Hello there, World", None, "", "a  b\nc"]
    assert not enc.by_words and [np.frombuffer(x, "<u4").tolist() for x in enc(pa.array(texts))] == [lib.encode(t or "", add_special_tokens=False).ids for t in texts]


@pytest.mark.parametrize("find", [pii.find, secrets.find, quality.judge, lambda d: bpe.encode(d, RANKS, P.PATTERN), lambda d: toxicity.score(d, ([("worthless", True, 5.0)], {"mean": np.zeros(11), "std": np.ones(11), "w": np.zeros(12)}))])
def test_maps_of_hard_rows(hard, find):
    """One row out for each row in; repeated rows get equal results."""
    got = [tuple(str(x) for x in r) for r in find(hard).collect()]
    assert len(got) == len(HARD) and sorted(r[0] for r in got) == sorted(str(i) for i, _ in HARD)
    assert len(set(got)) <= 10 and Counter(got).most_common(1)[0][1] >= 2 and len(find(hard.filter("doc_id = 0")).collect()) == 0


def test_pipeline_of_hard_rows(spark, tmp_path):
    """Null and repeated ids and columns named like the stages' own: one row of each text goes on, with its own columns."""
    import corpus_pipeline

    r = random.Random(11)
    say = lambda n: " ".join(r.choice("the of and to in a is that for it was on are as with be by this from house river stone green walks".split()) + r.choice(["", "s", "ly"]) for _ in range(n))
    a, b, c = say(60), say(60), say(60)
    rows = [(None, a), (None, a), (1, b), (1, b), (1, c), (2, b), (None, say(60)), (3, None), (4, "")]
    docs = spark.createDataFrame([(i, t, "en", "s", k, 5, "key", "row") for k, (i, t) in enumerate(rows)], "doc_id long, text string, lang string, source string, copies int, copy int, key string, row string")
    (tmp_path / "d").mkdir()
    docs.repartition(2).write.parquet(str(tmp_path / "d/documents.parquet"))
    left = spark.read.parquet(str(tmp_path / "d/documents.parquet"))
    for name, stage in corpus_pipeline.STAGES[1:3]:
        left = common.materialise(stage(spark, left, ""), "test")
        assert left.columns == docs.columns, name
    got = left.collect()
    assert Counter(x.text for x in got) == Counter({a: 1, b: 1, c: 1, rows[6][1]: 1, None: 1} if any(x.text is None for x in got) else {a: 1, b: 1, c: 1, rows[6][1]: 1, "": 1})
    assert {x.text: x.doc_id for x in got}[b] == 1 and all(x.copy == 5 and x.key == "key" and rows[x.copies][1] == x.text for x in got)
    mixed = corpus_pipeline.mixed_sources(spark, left, "").collect()
    assert {x.copy for x in mixed} == {5} and {x.text for x in mixed if x.text} <= {a, b, c, rows[6][1]} and max(Counter(x.copies for x in mixed).values()) <= 2
    assert corpus_pipeline.mixed_sources(spark, docs, "").columns == docs.columns  # no scan
    assert corpus_pipeline.run(spark, str(tmp_path / "d")).filter("n_tokens = 0").count() == 0
    (tmp_path / "e").mkdir()
    docs.limit(0).write.parquet(str(tmp_path / "e/documents.parquet"))
    assert corpus_pipeline.run(spark, str(tmp_path / "e")).count() == 0


# --- base rules against independent versions, on random texts
def mixture(r, parts, n):
    return "".join(r.choice(parts) for _ in range(r.randint(0, n)))


def leftmost(text, p):
    """Leftmost non-overlapping matches, one place after the other."""
    out, i = [], 0
    while i < len(text):
        m = p.match(text, i)
        if m is None or m.end() == i:
            i += 1
        else:
            out.append((i, m.end()))
            i = m.end()
    return out


def brute_pii(text):
    """The four base kinds by the contract's patterns, one place after the other, and their conditions."""
    pats = {"email": r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+", "ip": r"[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)", "card": r"[0-9]([\x20-]?[0-9])+", "phone": r"\+[0-9][\x20().0-9-]+[0-9]"}

    def fine(kind, s):
        d = [int(c) for c in s if c in "0123456789"]
        if kind == "ip":
            return all(int(p) <= 255 for p in s.split("."))
        if kind == "card":
            return 12 <= len(d) <= 19 and sum(x if i % 2 == 0 else sum(divmod(2 * x, 10)) for i, x in enumerate(d[::-1])) % 10 == 0
        return kind != "phone" or 9 <= len(d) <= 15

    found = []
    for kind, p in pats.items():
        found += [(a, e, kind) for a, e in leftmost(text, re.compile(p)) if fine(kind, text[a:e])]
    return sorted(found, key=lambda s: (s[0], list(pats).index(s[2])))


def test_personal_data_base_equals_brute_force():
    r = random.Random(21)
    parts = [*"0123456789", *"0123456789", "@", ".", ".", "-", " ", "+", "(", ")", "a", "Z", "_", "%", "é", "٣", "\n", "4111 1111 1111 1111", "255", "256", "1.2.3.4", "a@b.c", "+1 (017) 555-7713", "@a.", "007"]
    for _ in range(15_000):
        t = mixture(r, parts, 30)
        assert pii.base_spans(t) == brute_pii(t), t


def brute_secrets(text):
    pats = {"assign": re.compile(r"""([Pp][Aa][Ss][Ss][Ww][Oo][Rr][Dd]|[Pp][Aa][Ss][Ss][Ww][Dd]|[Ss][Ee][Cc][Rr][Ee][Tt]|[Tt][Oo][Kk][Ee][Nn]|[Aa][Pp][Ii]_?[Kk][Ee][Yy])["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)"""), "access": re.compile("AKIA[A-Z0-9]+"), "hex": re.compile("[0-9a-f]+")}
    least = {"assign": 12, "access": 18, "hex": 16}
    found = []
    for kind, p in pats.items():
        for a, e in leftmost(text, p):
            m = p.match(text, a)
            if len(m[2] if kind == "assign" else m[0]) >= least[kind]:
                found.append((a, e, kind))
    return sorted(found, key=lambda s: (s[0], list(pats).index(s[2])))


def test_secret_base_equals_brute_force():
    r = random.Random(22)
    parts = ["password", "PassWd", "secret", "ſecret", "toKen", "toKen", "api_key", "APIKEY", "apikey", "=", ":", " ", " ", '"', "'", "AKIA", "AKIA", "0123456789abcdef", "deadbeef", "A1B2C3D4E5F6G7", "xYz.-_+/=", "é", "\n", *"afAF09gG"]
    for _ in range(15_000):
        t = mixture(r, parts, 14)
        raw = t.encode()
        assert secrets.base_spans(t, raw, raw.lower()) == brute_secrets(t), t


def brute_js(p, q):
    """Jensen-Shannon distance by its definition, over dictionaries."""
    m = {x: (p.get(x, 0) + q.get(x, 0)) / 2 for x in {*p, *q}}
    kl = lambda a: sum(v * math.log2(v / m[x]) for x, v in a.items() if v > 0)
    return math.sqrt(max(0.0, (kl(p) + kl(q)) / 2))


def test_quality_verdict_equals_brute_force(spark):
    """References, distances, the choice of one language and the guards, re-computed from the texts."""
    r, rows = random.Random(23), []
    for i in range(120):
        vocab = [["the", "of", "and", "house", "river"], ["der", "die", "und", "Haus", "größer"]][i % 2]
        t = " ".join(r.choice(vocab) + (f"{r.randrange(10**6)}" if r.random() < 0.4 else "") for _ in range(r.randint(40, 160)))
        rows.append((i, t if i % 11 else "|".join(vocab * 30) + " | " * 60, ["en", "de"][i % 2] if i < 119 else "rare"))
    rows.append((200, "文字 ß Ж ١ \U0001f600 tab\there", None))
    docs = spark.createDataFrame(rows, "doc_id long, text string, lang string")

    def classes(t):
        return Counter(int(quality.CLASS[min(ord(c), 0xFFFF)]) for c in t)

    def shares(c):
        n = sum(c.values())
        return {k: v / n for k, v in c.items()}

    def hist(t):
        w = [x.lower() if x.isascii() else x for x in re.findall(WORD, t)]
        w = [re.sub("[A-Z]", lambda m: m[0].lower(), x) for x in w]
        return shares(classes(t)), shares(Counter(quality.INDEX.get(x.encode(), -1) for x in w))

    base = {r.doc_id: r for r in quality.judge(docs).collect()}
    good = [(t, lang) for i, t, lang in rows if base[i].n_words >= 50 and not base[i].base_failed]
    refs, total = [], len(good)
    langs = {lang for _, lang in good if sum(x == lang for _, x in good) * quality.LANGS >= total}
    for of in [*langs, "rest"]:
        own = [hist(t) for t, lang in good if (lang if lang in langs else "rest") == of]
        if own:
            refs.append(tuple({k: sum(h[j].get(k, 0) for h in own) / len(own) for k in {k for h in own for k in h[j]}} for j in (0, 1)))
    for i, t, _ in rows:
        c, w = min(((brute_js(hist(t)[0], ref[0]), brute_js(hist(t)[1], ref[1])) for ref in refs), key=sum)
        x = base[i]
        assert abs(x.char_js - c) < 1e-3 and abs(x.word_js - w) < 1e-3
        limits = (x.char_js > 0.3 and len(t) >= 200, x.word_js > 0.3 and x.n_words >= 75, x.n_words >= quality.BOTH_WORDS and x.char_js > quality.BOTH[0] and x.word_js > quality.BOTH[1])
        assert x.kept == (not x.base_failed and not any(limits))
    assert not all(x.kept for x in base.values()) and any(x.kept for x in base.values())
    assert [tuple(r) for r in quality.judge(docs.repartition(7)).orderBy("doc_id").collect()] == [tuple(base[i]) for i in sorted(base)]


def test_quality_base_on_random_texts():
    r = random.Random(24)
    for _ in range(3_000):
        t = mixture(r, ["a", "b", "c ", " ", "\n", "\n", "#", "é", "\x0b", " ", "a b c d e ", "\r"], 40)
        w = re.findall(WORD, t)
        seen = Counter(tuple(w[i : i + 5]) for i in range(len(w) - 4))
        lines = [x for x in t.split("\n") if re.search(WORD, x)]
        words, *counts = quality.base_counts(t.encode())
        assert [len(words), *counts] == [len(w), sum(map(len, w)), len(re.findall(r"[#*$%&|<>]", t)), len(lines) - len(set(lines)), len({j for i in range(len(w) - 4) if seen[tuple(w[i : i + 5])] > 1 for j in range(i, i + 5)})]


def test_langs_are_bounded_however_dirty(spark):
    rows = [(i, " ".join(f"word{j}x{i}" for j in range(60)), f"lang{i}") for i in range(500)]
    refs = quality.references(spark.createDataFrame(rows, "doc_id long, text string, lang string"))
    assert len(refs["chars"]) == len(refs["words"]) == 1


def test_tokens_equal_the_libraries_on_random_texts():
    import tiktoken
    from tokenizers import Tokenizer

    r = random.Random(25)
    ranks = bpe.read_ranks(RANKS)
    lib, own = tiktoken.Encoding("own", pat_str=P.PATTERN, mergeable_ranks=ranks, special_tokens={}), bpe.Coder(ranks, P.PATTERN)
    words, enc = Tokenizer.from_file(TOKENIZER), tokenfile.Encoder(TOKENIZER)
    parts = ["the", " the", "ing", " ", "  ", "\n", "\t", "é", "文", "\U0001f600", "'s", "'", "12", "3", "!", "...", "a", "B", "\xa0", "<|endoftext|>", "￿", "zq" * 30]
    texts = [mixture(r, parts, 25) for _ in range(2_500)] + ["ab" * 300, "ab" * 600, "x" * 1_024 + " " + "x" * 1_025]
    pieces = [own.split(t) for t in texts]
    known = own.learn(set().union(*pieces))
    for t, p in zip(texts, pieces, strict=True):
        assert " ".join(known[x][0] for x in p).split() == [str(i) for i in lib.encode_ordinary(t)] and b"".join(known[x][1] for x in p) == t.encode()
    for t, got in zip(texts, enc(pa.array(texts)), strict=True):
        assert np.frombuffer(got, "<u4").tolist() == words.encode(t, add_special_tokens=False).ids


def test_long_pieces_by_either_way():
    own, r = bpe.Coder(bpe.read_ranks(RANKS), P.PATTERN), random.Random(26)
    words = ["".join(r.choice(s) for _ in range(n)).encode() for s in ("ab", "abcdefghij", "x") for n in (257, 600, 1_024)]
    assert own.contract(words) == [own.heap(w) for w in words]


def test_cache_is_bounded_by_characters():
    c = common.Recent(100, most_chars=50)
    for i in range(40):
        new = c.missing({f"{i:010d}", f"{i + 1:010d}"})
        c.young.update(dict.fromkeys(new, i))
        assert {f"{i:010d}", f"{i + 1:010d}"} <= c.young.keys() and sum(map(len, [*c.young, *c.old])) <= 2 * 50 + 20


# --- methods
def test_toxic_terms_in_long_tokens_and_texts(spark):
    lex = toxicity.Lexicon([("moron", False, 5.0), ("worthless", True, 5.0), ("w" + "o" * 45, True, 4.0)])
    assert lex.find("m0ron" + "a" * 20) is not None and lex.find("m0ron" + "a" * 70) is not None and lex.find("m0ron" + "a" * 20_000) is not None
    assert lex.find("w" + "o" * 45) is not None and lex.find("w" + "o" * 44 + "x") is not None
    assert toxicity.features("fine words " * 50_000 + "you worthles", lex)[0] == 1.0
    assert ("o" * 60, True) in toxicity.forms("o" * 60)


def test_context_decides_on_personal_data():
    m = pii.model()
    found = lambda s: [k for _, _, k in pii.all_spans(s, m, pii.base_spans(s))]
    assert found("ssn 123-45-6789 ok") == ["number"] and found("part 123-45-6789 ok") == [] == found("born 123-45-6789 ok")
    assert found("call 555-123-4567 now") == ["number"] and found("order 555-123-4567 now") == []
    assert found("dob: 03/04/1999") and not found("released 03/04/1999") and not found("on 2024-01-31 we met")
    assert found("peer 2001:db8::8a2e:370:7334 x") == ["ipv6"] and found("std be::ad here") == []
    assert {"fe80::1", "::1"} == {s[a:b] for s in ("at fe80::1 up", "at ::1 up") for a, b, _ in pii.candidates(s)}
    assert found("mail to root@localhost now") == ["hostmail"]
    assert len(set(m["thresholds"].values())) > 3 and all(p >= pii.PRECISION for p, _ in m["reached"].values())


def test_families_share_no_example():
    held = [{tuple(row) for row in pii.examples(f, 400)[0].tolist()} for f in range(3)]
    assert all(len(x) > 100 for x in held)
    x, y, _ = pii.examples(2)
    p = pii.boosting.probability(pii.model(), x)
    assert ((p > 0.5) == y).mean() > 0.8 and abs(p.mean() - y.mean()) < 0.1


def test_entry_without_the_optional_parts(tmp_path):
    """Both folders deleted, or the vocabularies' package hidden: the entry imports and the engine's queries are there."""
    import shutil
    import subprocess
    import sys
    from pathlib import Path

    root = Path(__file__).parents[2]
    shutil.copytree(root, tmp_path / "c", ignore=shutil.ignore_patterns(".git", "__pycache__", "llm"))
    ask = "import sys; {}; import __spark_entry__ as e; q = e.queries(); print(len(q), sum(k.startswith('op') or k == 'pipeline' for k in q))"
    run = lambda at, first: subprocess.run([sys.executable, "-c", ask.format(first)], cwd=at, capture_output=True, text=True, check=True).stdout.split()
    n, none = run(tmp_path / "c", "pass")
    (tmp_path / "c/corpus_pipeline.py").unlink()
    assert int(n) > 150 and none == "0" and run(tmp_path / "c", "pass") == [n, "0"]
    assert run(root, "sys.modules['public_tokenizers'] = None") == [n, "0"] and run(root, "pass") == [str(int(n) + 11), "11"]


def test_a_worker_drops_what_another_operator_left(spark, hard):
    """A vocabulary's coder and its cache would stay in the worker while later operators run."""
    def left(batch):
        return pa.RecordBatch.from_pydict({"n": pa.array([len(common.KEPT)] * batch.num_rows, pa.int64())})

    for _ in range(2):
        assert bpe.encode(hard, RANKS, P.PATTERN).count() == len(HARD)
        assert {r.n for r in common.map_text(hard.select("text"), left, "n long").collect()} == {0}
        keep = common.map_text(bpe.encode(hard, RANKS, P.PATTERN).select("doc_id", F.lit("x").alias("text")), left, "n long", keeps="none")
        assert {r.n for r in keep.collect()} == {0}
