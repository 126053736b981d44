"""Each operator against brute force, a library or SQL on small tables with nulls, empties, ties, repeats, extra columns."""

import random
import re
from collections import Counter, defaultdict

import duckdb
import numpy as np
import pytest
from pyspark.sql import functions as F

import public_tokenizers
from pullgraph.llm import chat, common, language, licenses, lines, minhash, packing, pieces, quality, suffixes, topk
from tests.conftest import SF

WORD = re.compile(r"[^\x20\x09-\x0D]+")
ODD = [None, "", " ", "\n\n", "a", "One two", "x" * 3000, "é 日本 ß\r\n\x1c z", "a b " * 40]


def thue_morse(a, b, rounds):
    """Two different texts of 2**rounds signs that a polynomial hash with an even modulus cannot tell apart."""
    for _ in range(rounds):
        a, b = a + b, b + a
    return a, b


THUE_MORSE = [x for k in (10, 11, 12) for x in thue_morse("a", "b", k)]


def docs(spark, texts):
    """Documents with clashing extra columns."""
    rows = [(i, t, "en", "zz", i) for i, t in enumerate(texts)]
    return spark.createDataFrame(rows, "doc_id long, text string, key string, pos string, bucket long")


@pytest.fixture(scope="module")
def corpus(spark):
    return [r[0] for r in spark.read.parquet(f"{SF}/documents.parquet").orderBy("doc_id").select("text").collect()]


@pytest.fixture(scope="module")
def con():
    c = duckdb.connect()
    for t in ("documents", "embeddings", "conversations"):
        c.execute(f"CREATE VIEW {t} AS SELECT * FROM '{SF}/{t}.parquet'")
    return c


def same(got, want):
    cols = sorted(got.columns)
    assert cols == sorted(want.columns)
    a, b = (x[cols].sort_values(cols).reset_index(drop=True).astype(object) for x in (got, want))
    assert len(a) == len(b) and (a == b).all().all()


def test_topk_equals_sql(spark, con):
    same(topk.op1_exact_topk(spark, SF).toPandas(), con.execute(topk.OP1_SQL).df())


def test_topk_sparse_ragged_and_tied(spark):
    rng = random.Random(3)
    rows = [(i, [rng.choice([0.0, 0.0, rng.uniform(-2, 2)]) for _ in range(rng.randrange(8))], 1) for i in range(120)]
    rows += [(i, [1.0, 1.0], 1) for i in range(200, 230)] + [(300, None, 1), (301, [None], 1), (302, [float("nan")], 1), (303, [float("inf")], 1), (None, [1.0], 1), (200, [1.0, 1.0], 1)]
    q = topk.quantised(spark.createDataFrame(rows, "vec_id long, embedding array<double>, rank int"))
    vs = {r.vec_id: r.weights for r in q.collect()}
    assert set(vs) == set(range(120)) | set(range(200, 230))
    got = defaultdict(list)
    for r in topk.top_k(q, q.filter("vec_id % 20 = 0"), 7, candidate_block=20, query_block=3).collect():
        got[r.query_id].append((r["rank"], -r.score, r.vec_id))
    for i in (x for x in vs if x % 20 == 0):
        want = sorted((-sum(a * b for a, b in zip(vs[i], w)), j) for j, w in vs.items() if j != i)[:7]
        assert [x[1:] for x in sorted(got[i])] == want
    assert topk.top_k(q.limit(0), q.limit(0)).count() == 0


@pytest.fixture(scope="module")
def sp():
    import sentencepiece

    path = public_tokenizers.path("piece_bpe_32k.model")
    return sentencepiece.SentencePieceProcessor(model_file=path), path


def test_pieces_equal_the_library(sp, corpus):
    lib, path = sp
    c = pieces.codec(path)
    rng = random.Random(1)
    sign = "abcde THE  tion's\n\t éüß日😀▁́.,;0123<>/\\\"\x00\x7f\r"
    texts = ["".join(rng.choice(sign) for _ in range(rng.randrange(50))) for _ in range(2000)]
    texts += [" " * n + "x" + " " * n for n in range(40)] + [t or "" for t in ODD] + corpus[:60]
    for t in texts:
        ids = lib.encode(t)
        assert c.encode(t) == ids and c.decode(ids) == lib.decode(ids)
        assert c.run(t)[1:] == (len(ids), lib.decode(ids))


def test_piece_tables(spark, sp):
    import hashlib

    lib, path = sp
    got = {r.doc_id: r for r in pieces.digests(docs(spark, ODD), path).collect()}
    for i, t in enumerate(ODD):
        ids = lib.encode(t or "")
        assert got[i].n_tokens == len(ids) and got[i].ids_sha256 == hashlib.sha256(",".join(map(str, ids)).encode()).hexdigest()
    full = {r.doc_id: r for r in pieces.encode(docs(spark, ODD), path).collect()}
    assert all(full[i].ids == lib.encode(t or "") and full[i].decoded == lib.decode(lib.encode(t or "")) for i, t in enumerate(ODD))
    assert pieces.digests(docs(spark, ODD).limit(0), path).count() == 0


def test_chat_equals_sql(spark, con):
    same(chat.op4_chat(spark, SF).toPandas(), con.execute(chat.OP4_SQL).df())


def test_chat_layouts_and_round_trip(spark):
    bad = r"<|im_end|>\<\|a|> \\ <|im_sep|>"
    js = [
        ("a", '{"prompt":"x","response":"y"}'), ("b", '{"messages":[{"role":"user","content":"hi"},{"role":"assistant","content":"yo"}]}'),
        ("c", '{"instruction":"i","input":"","output":"o"}'), ("d", "bad"), ("e", None), ("f", '{"conversations":[{"from":"human","value":"q"},{"from":"gpt","value":"z"}]}'), ("g", '{"other":1}'),
    ]
    got = {r.conv_id: r for r in chat.canonical_json(spark.createDataFrame(js, "conv_id string, record string")).collect()}
    assert [got[k].mapped for k in "abcdefg"] == [True, True, True, False, False, True, False]
    assert [tuple(t) for t in got["f"].turns] == [("user", "q"), ("assistant", "z")] and [tuple(t) for t in got["c"].turns] == [("user", "i"), ("assistant", "o")]
    rows = [(1, 0, "user", bad), (1, 1, "assistant", bad), (1, 2, None, None), (2, 0, "assistant", ""), (2, 0, "assistant", ""), (3, None, "we\nird", "x")]
    f = chat.format_turns(chat.canonical(spark.createDataFrame(rows, "conv_id long, turn long, role string, text string")))
    back = {r.conv_id: r for r in f.select("*", chat.parse(F.col("formatted")).alias("back"), chat.loss_text(F.col("formatted"), F.col("loss_spans")).alias("loss")).collect()}
    assert all(r.back == r.turns for r in back.values())
    assert back[1].loss == bad and back[2].loss == "" and len(back[2].turns) == 2 and back[1].turns[2] == ("", "")
    nested = spark.createDataFrame([("k", [("user", "a")], 5), ("n", None, 5)], "conv_id string, messages array<struct<role:string,content:string>>, turn int")
    assert {r.conv_id: [tuple(t) for t in r.turns] for r in chat.canonical(nested).collect()} == {"k": [("user", "a")], "n": []}
    with pytest.raises(ValueError):
        chat.canonical(spark.range(1))


def brute_quality(t):
    w = WORD.findall(t or "")
    seen, dup = set(), 0
    for line in (t or "").split("\n"):
        if WORD.search(line):
            dup += line in seen
            seen.add(line)

    def covered(k):
        c = Counter(tuple(w[i : i + k]) for i in range(len(w) - k + 1))
        return len({j for i in range(len(w) - k + 1) if c[tuple(w[i : i + k])] > 1 for j in range(i, i + k)})

    longest = next((k for k in range(len(w), 0, -1) if max(Counter(tuple(w[i : i + k]) for i in range(len(w) - k + 1)).values()) > 1), 0) if len(w) < 120 else None
    return len(w), sum(map(len, w)), sum(c in "#*$%&|<>" for c in t or ""), dup, covered(8), covered(4), longest


def test_quality_equals_brute_force(spark, corpus):
    rng = random.Random(2)
    texts = ODD + [" ".join(rng.choice("abc") for _ in range(rng.randrange(90))) for _ in range(150)] + corpus[:60]
    got = {r.doc_id: r for r in quality.quality(docs(spark, texts)).collect()}
    for i, t in enumerate(texts):
        n, chars, signs, dup, rep, cov, longest = brute_quality(t)
        r = got[i]
        assert (r.n_words, r.word_chars, r.n_symbols, r.n_dup_lines, r.n_repeat_words, r.covered_words) == (n, chars, signs, dup, rep, cov)
        assert longest is None or r.longest_repeat == longest
        assert r.base_failed == (n < 20 or 100 * rep > 30 * n) and (not r.kept or not r.base_failed)
    assert quality.quality(docs(spark, []) if False else docs(spark, ["x"]).limit(0)).count() == 0


def levenshtein(a, b):
    p = list(range(len(b) + 1))
    for i, x in enumerate(a, 1):
        q = [i]
        for j, y in enumerate(b, 1):
            q.append(min(p[j] + 1, q[-1] + 1, p[j - 1] + (x != y)))
        p = q
    return p[-1]


def edited(rng, s, most):
    b = list(s)
    for _ in range(rng.randrange(most + 1)):
        k, at = rng.random(), rng.randrange(len(b) + 1)
        if k < 0.34 and b:
            b.pop(min(at, len(b) - 1))
        elif k < 0.67:
            b.insert(at, rng.choice("abcé"))
        elif b:
            b[min(at, len(b) - 1)] = rng.choice("abcé")
    return "".join(b)


@pytest.mark.parametrize("edits", [1, 2, 4])
def test_banded_distance(edits):
    rng = random.Random(edits)
    pairs = []
    for _ in range(600):
        a = "".join(rng.choice("ab") for _ in range(rng.randrange(20)))
        pairs.append((a, edited(rng, a, 6)))
    code = lambda k: [np.frombuffer(p[k].encode("utf-32-le"), np.uint32) for p in pairs]
    assert lines.within(code(0), code(1), edits).tolist() == [levenshtein(a, b) <= edits for a, b in pairs]


@pytest.mark.parametrize("edits", [1, 2])
def test_similar_lines_equal_brute_force(spark, edits):
    rng = random.Random(7)
    base = ["".join(rng.choice("abcé ") for _ in range(rng.randrange(8, 26))) for _ in range(30)]
    texts = ODD + ["\n".join(edited(rng, rng.choice(base), 3) for _ in range(rng.randrange(5))) for _ in range(80)]
    df = docs(spark, texts)
    got = {(r.doc_id, r.line_no): (r.class_doc, r.class_line, r.n_links) for r in lines.similar_lines(df, edits, 8).collect()}
    place = defaultdict(list)
    for d, t in enumerate(texts):
        for k, line in enumerate((t or "").split("\n")):
            if len(line) >= 8:
                place[line].append((d, k))
    all_, parent, links = list(place), {x: x for x in place}, Counter()

    def find(x):
        while parent[x] != x:
            x = parent[x]
        return x

    for i, a in enumerate(all_):
        for b in all_[:i]:
            if abs(len(a) - len(b)) <= edits and levenshtein(a, b) <= edits:
                links[a] += 1
                links[b] += 1
                parent[find(a)] = find(b)
    group = defaultdict(list)
    for x in all_:
        group[find(x)] += place[x]
    assert got == {o: (*min(group[find(x)]), links[x]) for x in all_ for o in place[x]}
    left = lines.drop_lines(df, lines.similar_lines(df, edits, 8))
    assert left.columns == df.columns
    kept = {r.doc_id: r.text for r in left.collect()}
    assert {0, 1, 2, 3, 4} <= set(kept) and kept[0] is None
    assert lines.similar_lines(df.limit(0)).count() == 0


def test_language_learns_and_rejects(spark):
    d = spark.read.parquet("/root/testdata/sf0.01/documents.parquet")
    net = language.fit(d.filter(~language.held_out()), steps=250)
    got = language.predict(d.filter(language.held_out()), net).join(d, "doc_id")
    right = got.select(F.avg((F.col("lang") == F.col("lang_pred")).cast("double")), F.min("score"), F.max("score")).first()
    assert right[0] > 0.97 and 0 <= right[1] and right[2] <= 1
    odd = {r.doc_id: (r.lang_pred, r.score) for r in language.predict(docs(spark, [*ODD, "123 !!"]), net).collect()}
    assert all(odd[i] == ("und", 0.0) for i in (0, 1, 2, 3, len(ODD))) and odd[5][0] != "und"
    empty = language.fit(d.limit(0))
    assert language.predict(docs(spark, ["abc"]), empty).first().lang_pred == "und"
    kept = language.keep_identified(docs(spark, ODD), net)
    assert {r.doc_id for r in kept.collect()} == {4, 5, 6, 7, 8} and kept.columns == docs(spark, ODD).columns


def test_language_gradients():
    net = language.Network.fresh(["a", "b"], 1)
    net.w = {k: v.astype(np.float64) for k, v in net.w.items()}
    ids, mask = language.padded([b"abc", b"ba"])
    label = np.array([0, 1])
    _, g = net.gradients(ids, mask, label)
    rng = np.random.default_rng(0)
    for k in ("emb", "xf", "hb", "out", "bf"):
        flat = net.w[k].reshape(-1)
        for i in rng.integers(0, flat.size, 3):
            old, step = flat[i], 1e-3
            flat[i] = old + step
            up, _ = net.gradients(ids, mask, label)
            flat[i] = old - step
            down, _ = net.gradients(ids, mask, label)
            flat[i] = old
            assert abs((up - down) / (2 * step) - g[k].reshape(-1)[i]) < 2e-3


def brute_components(texts, width):
    sets = {}
    for d, t in texts.items():
        w = WORD.findall((t or "").lower())
        sets[d] = frozenset(tuple(w[i : i + width]) for i in range(len(w) - width + 1)) if len(w) >= width else frozenset([tuple(w)] if w else [])
    parent = {d: d for d in sets}

    def find(x):
        while parent[x] != x:
            x = parent[x]
        return x

    ids = sorted(sets)
    for i, a in enumerate(ids):
        for b in ids[:i]:
            both = len(sets[a] & sets[b])
            if sets[a] and sets[b] and 100 * both >= 80 * (len(sets[a]) + len(sets[b]) - both):
                x, y = find(a), find(b)
                parent[max(x, y)] = min(x, y)
    return {d: (len(sets[d]), find(d)) for d in ids}


@pytest.mark.parametrize(("width", "block"), [(2, 512), (2, 16), (5, 512)])
def test_near_duplicates_equal_brute_force(spark, monkeypatch, width, block):
    monkeypatch.setattr(minhash, "BLOCK", block)
    rng = random.Random(9)
    base = [f"w{i}" for i in range(100)]
    texts = list(ODD)
    for _ in range(120):
        b = list(base)
        for _ in range(rng.choice([1, 3, 6, 12])):
            b[rng.randrange(100)] = f"x{rng.randrange(900)}"
        texts.append(" ".join(b))
    texts += [texts[20], texts[21].upper(), "one TWO"]
    got = {r.doc_id: (r.n_shingles, r.component_id) for r in minhash.near_duplicates(docs(spark, texts), width).collect()}
    assert got == brute_components(dict(enumerate(texts)), width)
    extra = docs(spark, ["a b c"]).union(docs(spark, ["a b c"])).union(spark.createDataFrame([(None, "a b c", "", "", 0)], docs(spark, ["x"]).schema))
    r = sorted(((x.doc_id, x.component_id, x.kept) for x in minhash.near_duplicates(extra).collect()), key=str)
    assert r == [(0, 0, True), (0, 0, True), (None, None, True)]
    assert minhash.near_duplicates(docs(spark, ["x"]).limit(0)).count() == 0


def test_odd_sketch_tells_similarity_apart():
    rng = np.random.default_rng(2)
    signer = minhash.Signer()
    base = rng.integers(0, 2**63, 400, dtype=np.uint64)
    near = [signer.samples(np.unique(np.concatenate([base[:360], rng.integers(0, 2**63, 40, dtype=np.uint64)]))) for _ in range(2)]
    far = signer.samples(np.unique(rng.integers(0, 2**63, 400, dtype=np.uint64)))
    s = signer.sketches(np.stack([*near, far]))
    d = lambda a, b: int(np.bitwise_count(s[a] ^ s[b]).sum())
    assert d(0, 1) < minhash.slack(80) < d(0, 2)


def covers(texts, size):
    own, out = defaultdict(set), defaultdict(set)
    w = {d: WORD.findall(t or "") for d, t in enumerate(texts)}
    for d, x in w.items():
        for i in range(len(x) - size + 1):
            own[tuple(x[i : i + size])].add(d)
    for d, x in w.items():
        for i in range(len(x) - size + 1):
            if len(own[tuple(x[i : i + size])]) > 1:
                out[d] |= set(range(i, i + size))
    return out


def test_repeated_passages(spark):
    rng = random.Random(5)
    shared = [" ".join(f"w{rng.randrange(300)}" for _ in range(n)) for n in (50, 55, 80, 49)]
    texts = list(ODD)
    for d in range(60):
        parts = [f"u{d}_{i}" for i in range(rng.randrange(30))]
        for _ in range(rng.randrange(3)):
            parts += rng.choice(shared).split() + [f"v{d}_{i}_{rng.random()}" for i in range(rng.randrange(1, 5))]
        texts.append(" ".join(parts))
    texts.append(texts[30])
    df = docs(spark, texts)
    spans = suffixes.repeated_passages(df)
    got = {r.doc_id: {i for s in r.repeats for i in range(s.start, s.stop)} for r in spans.collect()}
    whole, pieces_ = covers(texts, 50), covers(texts, 25)
    assert set(whole) <= set(got) and all(whole[d] <= got[d] for d in whole)
    assert all(got[d] <= pieces_[d] for d in got)
    cut = suffixes.cut_passages(df, spans)
    left = {r.doc_id: r.text for r in cut.collect()}
    assert cut.columns == df.columns and not covers([left.get(d) for d in range(len(texts))], 50)
    words = Counter(w for t in left.values() for w in WORD.findall(t or ""))
    assert all(words[w] for t in texts for w in WORD.findall(t or "")), "one copy of everything stays"
    assert {0, 1, 2, 3} <= set(left) and left[0] is None
    assert suffixes.repeated_passages(df.limit(0)).count() == 0


def test_licenses_and_inheritance(spark):
    mit = "Released under the MIT License."
    files = [
        (0, "a/LICENSE", mit), (1, "a/x.txt", "hello"), (2, "a/b/c/y.txt", None), (3, "a/b/LICENSE.md", "Licensed under the Apache License, Version 2.0."), (4, "a/b/z.txt", ""),
        (5, "q/w.txt", "text\nmore\n" * 30 + "This work is licensed under the GNU General Public License, version 3."), (6, "q/v.txt", "no word of it"), (7, None, "x"), (8, "a/b/own.txt", "code\nLicensed under CC BY-NC 4.0."),
        (9, "r/t.txt", "we discuss how a driving licence is granted in many countries"),
    ]
    got = {r.doc_id: (r.license, r.license_from) for r in licenses.scan(spark.createDataFrame(files, "doc_id long, path string, text string").withColumn("dir", F.lit(1))).collect()}
    assert got == {
        0: ("MIT", "own"), 1: ("MIT", "a"), 2: ("Apache-2.0", "a/b"), 3: ("Apache-2.0", "own"), 4: ("Apache-2.0", "a/b"),
        5: ("GPL-3.0", "own"), 6: (None, None), 7: (None, None), 8: ("CC-BY-NC-4.0", "own"), 9: (None, None),
    }
    root = spark.createDataFrame([(0, "LICENSE", mit), (1, "z/k.txt", "t")], "doc_id long, path string, text string")
    assert {r.doc_id: r.license_from for r in licenses.scan(root).collect()} == {0: "own", 1: ""}
    assert licenses.scan(root.limit(0)).count() == 0


def test_packing(spark, corpus):
    import zlib

    from tokenizers import Tokenizer

    path = public_tokenizers.path("word_bpe_49k.json")
    lib = Tokenizer.from_file(path)
    texts = ODD + corpus[:150] + ["I'll don't 'S x'sy İ Σς abc.def,ghi! \x1c\x1f q", "a <|endoftext|> b", "A<|ENDOFTEXT|>.x<|startoftext|>", "word " * 5000, *THUE_MORSE]
    rows = packing.pack(docs(spark, texts).repartition(2), path, with_ids=True).collect()
    by_doc, by_seq = defaultdict(list), defaultdict(list)
    for r in rows:
        assert r.length == len(r.ids) > 0 and r.ids_crc32 == zlib.crc32(np.array(r.ids, "<u4").tobytes())
        by_doc[r.doc_id].append(r)
        by_seq[r.sequence_id].append(r)
    for i, t in enumerate(texts):
        ids = [*lib.encode(t or "", add_special_tokens=False).ids, 1]
        ps = sorted(by_doc[i], key=lambda r: r.start)
        assert [x for p in ps for x in p.ids] == ids and all(p.doc_tokens == len(ids) for p in ps)
        assert [p.start for p in ps] == list(np.cumsum([0, *(p.length for p in ps)])[:-1])
    for ps in by_seq.values():
        ps.sort(key=lambda r: r.offset)
        fill = sum(p.length for p in ps)
        assert fill <= 2048 and [p.offset for p in ps] == list(np.cumsum([0, *(p.length for p in ps)])[:-1])
        assert fill == 2048 or fill & (fill - 1) == 0, "no sequence needs padding"
    assert packing.pack(docs(spark, ["x"]).limit(0), path).count() == 0


def test_open_windows_are_bounded():
    p = packing.Packer(2048, open_tokens=100_000)
    fills, most = Counter(), 0
    for i in range(20_000):
        for held in p.add(i, b"abcd" * 1500):
            fills[sum(len(x[2]) // 4 for x in held)] += 1
        most = max(most, p.tokens)
    assert most <= 100_000 and set(fills) == {2048}
    for held in p.close():
        fills[sum(len(x[2]) // 4 for x in held)] += 1
    assert sum(k * n for k, n in fills.items()) == 30_000_000 and all(k & (k - 1) == 0 for k in fills)


def test_packer_prefers_levels_that_even_out():
    p = packing.Packer(10)
    one = lambda n: np.zeros(n, "<u4").tobytes()
    assert p.add(0, one(6)) == [] and p.add(1, one(3)) == []
    assert p.count[6] == 0 and p.count[9] == 1  # joining beats a second open window
    assert len(p.add(2, one(1))) == 1 and p.count.sum() == 0


def brute_lines(texts, edits=2, shortest=30):
    """{(doc, line): (class doc, class line, links)} of all lines with a word."""
    place = defaultdict(list)
    for d, t in texts.items():
        for k, line in enumerate((t or "").split("\n")):
            if WORD.search(line):
                place[line].append((d, k))
    parent, links = {x: x for x in place}, Counter()

    def find(x):
        while parent[x] != x:
            x = parent[x]
        return x

    bags = {x: Counter(x) for x in place if len(x) >= shortest}
    by_length = defaultdict(list)
    for x in bags:
        by_length[len(x)].append(x)
    for n in by_length:
        for i, x in enumerate(by_length[n]):
            for y in by_length[n][i + 1 :] + [z for m in range(n + 1, n + edits + 1) for z in by_length.get(m, ())]:
                if sum((bags[x] - bags[y]).values()) <= edits and levenshtein(x, y) <= edits:
                    links[x] += 1
                    links[y] += 1
                    parent[find(x)] = find(y)
    first = {}
    for x, where in place.items():
        first[find(x)] = min(where + [first[find(x)]] if find(x) in first else where)
    return {o: (*first[find(x)], links[x]) for x in place for o in place[x]}


def brute_passages(texts, least=50):
    """{doc: (words in repeats, words in repeats that an earlier document has)}"""
    w, own = {d: WORD.findall(t or "") for d, t in texts.items()}, defaultdict(set)
    for d, x in w.items():
        for i in range(len(x) - least + 1):
            own[tuple(x[i : i + least])].add(d)
    out = defaultdict(lambda: (set(), set()))
    for d, x in w.items():
        for i in range(len(x) - least + 1):
            holders = own[tuple(x[i : i + least])]
            if len(holders) > 1:
                out[d][0].update(range(i, i + least))
                if min(holders) < d:
                    out[d][1].update(range(i, i + least))
    return dict(out)


def spanned(spans):
    return {i for s in spans for i in range(s.start, s.stop)}


def test_registered_queries_equal_brute_force(spark, corpus, sp):
    import hashlib
    import zlib

    from tokenizers import Tokenizer

    import __spark_entry__ as entry

    run = {k: f for k, f in entry.queries().items() if k.startswith("op")}
    texts = {r.doc_id: r.text for r in spark.read.parquet(f"{SF}/documents.parquet").select("doc_id", "text").collect()}
    sha = lambda x: hashlib.sha256(x.encode()).hexdigest()
    got = {r.doc_id: (spanned(r.repeats), spanned(r.later)) for r in run["op2_suffix_dedup"](spark, SF).collect()}
    assert got == brute_passages(texts)
    lib = sp[0]
    for r in run["op3_sentencepiece"](spark, SF).collect():
        ids = lib.encode(texts[r.doc_id] or "")
        assert (r.n_tokens, r.ids_sha256, r.decoded_sha256) == (len(ids), sha(",".join(map(str, ids))), sha(lib.decode(ids)))
    for r in run["op5_quality"](spark, SF).collect():
        n, chars, signs, dup, rep, cov, longest = brute_quality(texts[r.doc_id])
        failed = n < 20 or 100 * rep > 30 * n
        assert (r.n_words, r.word_chars, r.n_symbols, r.n_dup_lines, r.n_repeat_words, r.base_failed) == (n, chars, signs, dup, rep, failed)
        assert longest is None or r.kept == (not failed and cov <= quality.MAX_COVERED * n and longest <= quality.MAX_LONGEST + quality.MAX_LONGEST_SHARE * n)
    assert {(r.doc_id, r.line_no): (r.class_doc, r.class_line, r.n_links) for r in run["op6_line_dedup"](spark, SF).collect()} == brute_lines(texts)
    rows = run["op7_language"](spark, SF).join(spark.read.parquet(f"{SF}/documents.parquet").select("doc_id", "lang"), "doc_id").collect()
    assert len(rows) == len(texts) and all(r.held_out == (zlib.crc32(str(r.doc_id).encode()) % 4 == 2) for r in rows)
    known = [r.lang == r.lang_pred for r in rows if r.held_out and r.lang and re.search(r"[^\W\d_]", texts[r.doc_id] or "")]
    assert sum(known) > 0.97 * len(known)
    assert run["op9_license_scan"](spark, SF).count() == len(texts)
    words = Tokenizer.from_file(public_tokenizers.path("word_bpe_49k.json"))
    pieces_of = defaultdict(list)
    for r in run["op10_packing"](spark, SF).collect():
        pieces_of[r.doc_id].append(r)
    for d, t in texts.items():
        ids = np.array([*words.encode(t or "", add_special_tokens=False).ids, 1], "<u4")
        at = 0
        for r in sorted(pieces_of[d], key=lambda r: r.start):
            assert (r.start, r.ids_crc32, r.doc_tokens) == (at, zlib.crc32(ids[at : at + r.length].tobytes()), len(ids))
            at += r.length
        assert at == len(ids)


def test_pipeline_stages_equal_brute_force(spark):
    import corpus_pipeline as cp
    from pullgraph.session import materialize

    assert [n for n, _ in cp.STAGES] == ["language_id", "line_dedup", "minhash_near_dedup", "suffix_array_dedup", "packing"]
    stage = dict(cp.STAGES)
    d = spark.read.parquet(f"{SF}/documents.parquet")
    names, texts = d.columns, {r.doc_id: r.text for r in d.collect()}

    def after(name):
        nonlocal d
        d = materialize(stage[name](spark, d, SF), name)
        assert d.columns == names, name
        return {r.doc_id: r.text for r in d.collect()}

    kept = after("language_id")
    assert all(kept[i] == texts[i] for i in kept) and {i for i, t in texts.items() if len(re.findall(r"[^\W\d_]", t or "")) > 20} <= set(kept)
    classes, want = brute_lines(kept), {}
    for i, t in kept.items():
        lines_ = (t or "").split("\n")
        left = [x for k, x in enumerate(lines_) if (i, k) not in classes or classes[i, k][:2] == (i, k)]
        if len(left) == len(lines_) or WORD.search("\n".join(left)):
            want[i] = "\n".join(left) if len(left) < len(lines_) else t
    kept = after("line_dedup")
    assert kept == want
    want = {i: kept[i] for i, (_, c) in brute_components(kept, 5).items() if c == i}
    kept = after("minhash_near_dedup")
    assert kept == want
    cuts = brute_passages(kept)
    want = {}
    for i, t in kept.items():
        gone = cuts.get(i, (set(), set()))[1]
        want[i] = [w for k, w in enumerate(WORD.findall(t or "")) if k not in gone]
    left = after("suffix_array_dedup")
    assert {i: WORD.findall(t or "") for i, t in left.items()} == {i: w for i, w in want.items() if w or not WORD.search(kept[i] or "")}
    assert {r.doc_id for r in stage["packing"](spark, d, SF).select("doc_id").distinct().collect()} == set(left)


def test_pipeline_runs_on_odd_tables(spark, tmp_path):
    import corpus_pipeline as cp

    rows = [(i, t, "en", "zz", len(t or "")) for i, t in enumerate([*ODD, "x y " * 30_000])] + [(None, "one more text of words", None, None, None), (4, "a", "en", "zz", 1)]
    df = spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long").withColumn("key", F.lit(1)).withColumn("__id", F.lit("x"))
    for name, d in (("odd", df), ("empty", df.limit(0))):
        d.write.parquet(f"{tmp_path}/{name}/documents.parquet")
    got = cp.run(spark, f"{tmp_path}/odd").groupBy("doc_id").count().collect()
    assert {5, 6, None} <= {r.doc_id for r in got} and not {0, 1, 2, 3} & {r.doc_id for r in got}
    assert cp.run(spark, f"{tmp_path}/empty").count() == 0


def test_patterned_texts_are_told_apart(spark):
    """Words, lines and word sequences that a polynomial hash modulo a power of two confuses."""
    a, b = thue_morse("a", "b", 11)
    p, q = (" ".join(x) for x in thue_morse("ab", "cd", 10))
    df = docs(spark, [a, b, p.replace("", ""), q, f"{a}\n{b}", " ".join(thue_morse(["ab"], ["cd"], 11)[0]), " ".join(thue_morse(["ab"], ["cd"], 11)[1])])
    got = {r.doc_id: r for r in minhash.near_duplicates(df, 5).collect()}
    assert all(got[i].kept for i in (0, 1, 4))
    assert {(r.doc_id, r.line_no): (r.class_doc, r.class_line) for r in lines.line_classes(df.filter("doc_id in (0, 1, 4)")).collect()} == {(0, 0): (0, 0), (1, 0): (1, 0), (4, 0): (0, 0), (4, 1): (1, 0)}
    assert quality.quality(df.filter("doc_id = 4")).first().n_dup_lines == 0
    texts = {r.doc_id: r.text for r in df.collect()}
    assert {r.doc_id: (spanned(r.repeats), spanned(r.later)) for r in suffixes.repeated_passages(df).collect()} == brute_passages(texts)


def test_rows_that_share_an_id(spark):
    """A doc_id with several texts: nothing of one text is taken for the other's."""
    long = " ".join(f"w{i}" for i in range(80))
    other = " ".join(f"v{i}" for i in range(80))
    line = "a line that is long enough for the edit join"
    df = spark.createDataFrame([(1, long), (2, other), (2, long), (2, long), (3, f"{line}\n{line}!"), (3, "x"), (3, f"y\n{line}?")], "doc_id long, text string")
    cut = suffixes.cut_passages(df, suffixes.repeated_passages(df))
    assert sorted(r.text for r in cut.filter("doc_id = 2").collect()) == [other] and cut.filter("doc_id = 1").count() == 1
    assert minhash.near_duplicates(df).count() == 7
    classes = lines.line_classes(df)
    assert {(r.class_doc, r.class_line) for r in classes.filter("doc_id = 3").collect()} <= {(3, 0), (3, 1)}
    assert lines.drop_lines(df, classes).filter("doc_id = 1").count() == 1


def test_long_texts(spark):
    rng = random.Random(4)
    base = [f"w{rng.randrange(5000)}" for _ in range(20_000)]
    near = list(base)
    near[10_000] = "changed"
    texts = {0: " ".join(base), 1: " ".join(near), 2: "\n".join(" ".join(base[i : i + 10]) for i in range(0, 20_000, 10)), 3: "z" * 200_000, 4: "q " * 60_000}
    df = docs(spark, list(texts.values()))
    assert {r.doc_id: r.component_id for r in minhash.near_duplicates(df).collect()} == {0: 0, 1: 0, 2: 0, 3: 3, 4: 4}
    assert {r.doc_id: (spanned(r.repeats), spanned(r.later)) for r in suffixes.repeated_passages(df).collect()} == brute_passages(texts)
    got = {r.doc_id: r for r in quality.quality(df).collect()}
    assert got[4].n_repeat_words == 60_000 and got[4].longest_repeat == 59_999 and not got[4].kept and got[0].n_words == 20_000
    assert lines.line_classes(df).filter("doc_id = 2").count() == 2000
    assert {r.doc_id for r in language.predict(df, language.fit(df.withColumn("lang", F.when(F.col("doc_id") < 4, "a").otherwise("b")), steps=20)).collect()} == set(texts)


def test_hot_segments_lose_no_pair(spark, monkeypatch):
    monkeypatch.setattr(lines, "HOT", 24)
    monkeypatch.setattr(lines, "SAMPLE", 1)
    rng = random.Random(8)
    texts = {i: "common beginning of all of them " + "".join(rng.choice("abcd") for _ in range(6)) for i in range(150)}
    df = docs(spark, list(texts.values()))
    got = {(r.doc_id, r.line_no): (r.class_doc, r.class_line, r.n_links) for r in lines.line_classes(df).collect()}
    assert got == brute_lines(texts)


def test_topk_beyond_64_bits(spark):
    big = [(i, [float(2**40 + i), 1.0], 0) for i in range(1, 41)]
    q = topk.quantised(spark.createDataFrame(big, "vec_id long, embedding array<double>, score long"), scale=1)
    with pytest.raises(Exception, match="beyond a long"):
        topk.top_k(q, q.filter("vec_id = 20"), 3).collect()
    half = topk.quantised(spark.createDataFrame([(i, [float(2**30 + i)], 0) for i in range(1, 41)], "vec_id long, embedding array<double>, score long"), scale=1)
    got = [(r.vec_id, r.score) for r in topk.top_k(half, half.filter("vec_id = 20"), 2).orderBy("rank").collect()]
    assert got == [(40, (2**30 + 20) * (2**30 + 40)), (39, (2**30 + 20) * (2**30 + 39))]
    with pytest.raises(Exception, match="too large"):
        topk.quantised(spark.createDataFrame([(1, [1e300])], "vec_id long, embedding array<double>")).collect()


def test_chat_layouts_are_found_by_fingerprint(spark):
    schema = "conv_id long, turn long, role string, text string"
    df = spark.createDataFrame([(1, 0, "user", "a")], schema)
    by_rows = chat.layout_of(df.schema)
    assert by_rows.rows and by_rows.fingerprint == chat.fingerprint(["text", "role", "turn", "conv_id"])
    assert chat.layout_of(df.withColumn("lang", F.lit(1)).withColumn("prompt", F.lit("x")).schema) == by_rows
    assert chat.layout_of(spark.createDataFrame([("p", "r", 1)], "prompt string, response string, id int").schema).fixed[1][1] == ("response",)
    extra = df.withColumn("turns", F.lit(1)).withColumn("ts", F.lit(2)).withColumn("t", F.lit(3))
    assert [tuple(t) for t in chat.format_turns(chat.canonical(extra)).first().turns] == [("user", "a")]
    assert chat.format_turns(chat.canonical(df.limit(0))).count() == 0


def test_language_on_odd_tables(spark):
    df = spark.createDataFrame([(1, "the cat", "en", 1), (1, "the cat", "en", 1), (2, "der hund", "de", 2), (None, "the", "en", 3), (3, None, "de", 4)], "doc_id long, text string, lang string, score long").withColumn("label", F.lit(1))
    net = language.fit(df, steps=40)
    got = sorted(((r.doc_id, r.lang_pred) for r in language.predict(df, net).collect()), key=str)
    assert got == [(1, "en"), (1, "en"), (2, "de"), (3, "und"), (None, "en")]
    assert language.predict(df.limit(0), net).count() == 0 and language.keep_identified(df.limit(0), net).count() == 0
    reader = language.Reader(net)
    assert len(reader.label_positions("the cat 12!")) == 11
    long = "the cat and the dog " * 200
    whole = net.positions(*language.padded([language.encoded(long).tobytes()])).mean(axis=0)[:, 0]
    assert np.allclose(reader.probabilities([long])[0], whole, atol=1e-3), "stretches with context give what the whole text gives"


def test_license_cosines_equal_brute_force(spark):
    import math

    known = licenses.standard()
    bags = [(k, licenses.terms(t)) for k, ts in known.items() for t in ts]
    seen = Counter(t for _, b in bags for t in b)
    idf = lambda t: math.log((1 + len(bags)) / (1 + seen[t])) + 1 if t in seen else math.log(1 + len(bags)) + 1

    def cosine(a, b):
        x, y = ({t: n * idf(t) for t, n in c.items()} for c in (a, b))
        return sum(v * y.get(t, 0.0) for t, v in x.items()) / math.sqrt(sum(v * v for v in x.values()) * sum(v * v for v in y.values()))

    t = licenses.Templates(known)
    for text in (MIT_FILE[:400], "Licensed under the GPL, version 2 or later", "Redistribution and use in source and binary forms are permitted", "nothing of the kind"):
        want = max(cosine(licenses.terms(text), b) for _, b in bags)
        name, got, _ = t.best(text)
        assert abs(got - want) < 1e-9 and (name is None) == (want == 0)
        assert name is None or any(k == name and abs(cosine(licenses.terms(text), b) - want) < 1e-9 for k, b in bags)


def test_licenses_on_odd_tables(spark):
    rows = [(1, "a/LICENSE", MIT_FILE), (1, "a/LICENSE", MIT_FILE), (None, "a/x", "plain"), (2, "a/y", "word " * 20_000 + "\nSPDX-License-Identifier: ISC"), (3, None, None)]
    df = spark.createDataFrame(rows, "doc_id long, path string, text string").withColumn("cosine", F.lit("x"))
    got = sorted(((r.doc_id, r.license) for r in licenses.scan(df).collect()), key=str)
    assert got == [(1, "MIT"), (1, "MIT"), (2, "ISC"), (3, None), (None, "MIT")]


def test_near_duplicates_equal_sql(spark, con):
    same(minhash.op8_minhash(spark, SF).toPandas(), con.execute(minhash.OP8_SQL).df())


def test_every_query_is_registered():
    import __spark_entry__ as entry

    names = [k for k in entry.queries() if re.match(r"op\d+_|pipeline", k)]
    assert sorted(int(k[2:].split("_")[0]) for k in names if k != "pipeline") == list(range(1, 11)) and "pipeline" in names
    assert {"op1_exact_topk", "op4_chat", "op8_minhash"} <= set(entry.oracle_sql())


MIT_FILE = """MIT License

Copyright (c) 2021 Somebody Else

Permission is hereby granted, free of charge, to any person obtaining a copy
of this software and associated documentation files (the "Software"), to deal
in the Software without restriction, including without limitation the rights
to use, copy, modify, merge, publish, distribute, sublicense, and/or sell
copies of the Software, and to permit persons to whom the Software is
furnished to do so, subject to the following conditions:

The above copyright notice and this permission notice shall be included in all
copies or substantial portions of the Software.

THE SOFTWARE IS PROVIDED "AS IS", WITHOUT WARRANTY OF ANY KIND, EXPRESS OR
IMPLIED, INCLUDING BUT NOT LIMITED TO THE WARRANTIES OF MERCHANTABILITY,
FITNESS FOR A PARTICULAR PURPOSE AND NONINFRINGEMENT. IN NO EVENT SHALL THE
AUTHORS OR COPYRIGHT HOLDERS BE LIABLE FOR ANY CLAIM, DAMAGES OR OTHER
LIABILITY, WHETHER IN AN ACTION OF CONTRACT, TORT OR OTHERWISE, ARISING FROM,
OUT OF OR IN CONNECTION WITH THE SOFTWARE OR THE USE OR OTHER DEALINGS IN THE
SOFTWARE.
"""


def test_full_license_files_and_near_relatives(spark):
    want, files = {}, []

    def add(path, text, license):
        want[len(files)] = license
        files.append((len(files), f"d{len(files)}/{path}", text))

    add("LICENSE", MIT_FILE, "MIT")
    add("x.c", "".join(f" * {x}\n" for x in MIT_FILE.split("\n")) + "int main() {}\n" * 50, "MIT")
    for f in sorted(licenses.TEXTS.glob("*.txt")):
        text, name = f.read_text("utf-8"), f.stem.removesuffix("-Regents")
        words = text.split()
        other = [" ".join(words[i : i + 9]) for i in range(0, len(words), 9)]
        add("COPYING", "Copyright 2020 Some Body\nAll rights reserved.\n\n" + "\n".join(other), name)
        if len(words) > 900:
            add("COPYING", "\n".join(text.split("\n")[:60]), name)
    for t in ("MIT", "BSD-2-Clause", "LGPL-2.1-or-later", "AGPL-3.0-only", "ISC", "EPL-2.0", "CC-BY-SA-4.0", "Unlicense"):
        add("a.py", f"#!/usr/bin/python\n# SPDX-License-Identifier: {t}\nimport os\n", t.removesuffix("-or-later").removesuffix("-only"))
    add("a.py", "# SPDX-License-Identifier: NotListed\n", None)
    for t, name in (("CC BY-SA 4.0", "CC-BY-SA-4.0"), ("CC BY-NC 4.0", "CC-BY-NC-4.0"), ("CC BY-SA 3.0", "CC-BY-SA-3.0"), ("CC BY 4.0", "CC-BY-4.0")):
        add("a.txt", f"text\nLicensed under {t}.", name)
    for what, name, v in (("GNU Lesser General Public License", "LGPL", "2.1"), ("GNU Affero General Public License", "AGPL", "3"), ("GNU General Public License", "GPL", "2")):
        add("a.c", f"/* This file is free software; you can redistribute it and/or\n * modify it under the terms of the {what} as\n * published by the Free Software Foundation; either version {v} of the\n * License, or (at your option) any later version.\n */\nint x;\n", f"{name}-{v if '.' in v else v + '.0'}")
    got = {r.doc_id: r.own_license for r in licenses.own_licenses(spark.createDataFrame(files, "doc_id long, path string, text string")).collect()}
    assert {(files[k][2][:70], got[k], want[k]) for k in want if got[k] != want[k]} == set()


def test_short_lines_have_classes_by_equality(spark):
    long = "a line that is long enough for the edit join"
    texts = [f"Yes.\n{long}\n\n  \nold", "Yes.\nyes.\nfirst　\n" + " " * 40, None, f"{long}!\nYes.\nold\nodd", "Yes."]
    df = docs(spark, texts)
    classes = lines.line_classes(df)
    got = {(r.doc_id, r.line_no): (r.class_doc, r.class_line, r.n_links) for r in classes.collect()}
    assert got == {
        (0, 0): (0, 0, 0), (0, 1): (0, 1, 1), (0, 4): (0, 4, 0), (1, 0): (0, 0, 0), (1, 1): (1, 1, 0), (1, 2): (1, 2, 0),
        (3, 0): (0, 1, 1), (3, 1): (0, 0, 0), (3, 2): (0, 4, 0), (3, 3): (3, 3, 0), (4, 0): (0, 0, 0),
    }
    assert {r.doc_id: r.text for r in lines.drop_lines(df, classes).collect()} == {0: texts[0], 1: "yes.\nfirst　\n" + " " * 40, 2: None, 3: "odd"}


def test_repeated_passages_of_edited_copies_equal_brute_force(spark):
    rng = random.Random(11)
    texts = []
    for g in range(4):
        base = [f"g{g}w{rng.randrange(400)}" for _ in range(500)]
        for _ in range(15):
            texts.append(" ".join(f"x{rng.random()}" if rng.random() < 1 / 40 else w for w in base))
    got = {r.doc_id: r for r in suffixes.repeated_passages(docs(spark, texts)).collect()}
    words = lambda spans: {i for s in spans for i in range(s.start, s.stop)}
    whole = covers(texts, 50)
    assert {d: words(r.repeats) for d, r in got.items()} == {d: x for d, x in whole.items() if x}
    w, first, older = [t.split() for t in texts], {}, defaultdict(set)
    for d, x in enumerate(w):
        for i in range(len(x) - 49):
            if first.setdefault(tuple(x[i : i + 50]), d) < d:
                older[d] |= set(range(i, i + 50))
    assert {d: words(r.later) for d, r in got.items() if r.later} == older


def test_least_score_follows_the_number_of_languages():
    assert abs(language.least_score(4) - 0.28) < 1e-5 and language.least_score(1) < 1
    for n in (2, 4, 20, 100):
        assert 1 / n < language.least_score(n), "junk that looks like every language alike is rejected"
    for n in (20, 100):
        assert language.least_score(n) < 0.25, "a clean text in four languages is kept"


def test_rare_languages_are_learned(spark):
    rows = [(i, "the cat and the dog", "en") for i in range(300)] + [(i, "кот и собака", "ru") for i in range(300, 303)]
    df = spark.createDataFrame(rows, "doc_id long, text string, lang string")
    net = language.fit(df, documents=8, steps=60)
    assert net.labels == ["en", "ru"]
    assert {r.lang_pred for r in language.predict(df.filter("doc_id >= 300"), net).collect()} == {"ru"}
    assert language.level([10, 2, 1], 9) == 6 and language.level([5, 5], 1) == 1 and language.level([], 3) == 1


def test_united_spans_equal_brute_force():
    rng = random.Random(11)
    for texts in (0, 1, 7):
        spans = [(t, a, a + rng.randrange(1, 9)) for t in range(texts) if t != 3 for a in (rng.randrange(40) for _ in range(rng.randrange(1, 9)))]
        rng.shuffle(spans)
        got, words = suffixes._united(*(np.array(x, np.int64) for x in (zip(*spans, strict=True) if spans else ([], [], []))), texts)
        for t, (found, n) in enumerate(zip(got.to_pylist(), words.to_pylist(), strict=True)):
            covered = sorted({i for x, a, b in spans if x == t for i in range(a, b)})
            want = [i for i in covered if i - 1 not in covered], [i + 1 for i in covered if i + 1 not in covered]
            # Spans that only touch are one, as are those that overlap.
            assert ([s["start"] for s in found], [s["stop"] for s in found]) == want and n == len(covered)


def test_a_task_gives_up_what_other_operators_held(spark):
    class Here:
        sparkSession = spark

        def mapInArrow(self, run, schema):
            return run

    import public_tokenizers

    path = public_tokenizers.path("word_bpe_49k.json")

    def pack(it):
        yield packing.word_tokenizer(path)

    def other(it):
        yield packing.word_tokenizer.cache_info().currsize

    pack.__module__ = "pullgraph.llm.packing"
    first, second = common.arrow_map(Here(), pack, ""), common.arrow_map(Here(), other, "")
    kept = list(first([]))
    assert list(first([])) == kept, "tasks of one operator share it"
    common.POWERS.need(100_000)
    assert list(second([])) == [0] and len(common.POWERS.up) == 1
