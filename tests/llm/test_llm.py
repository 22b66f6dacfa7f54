"""The training-data operators against brute force, on small fixtures and on the smallest tables, with odd rows."""

import collections
import hashlib
import itertools
import math
import random
import re
import zlib

import duckdb
import numpy as np
import pytest
import xxhash
from conftest import DATA

from meshcut.llm import common, contamination, line_dedup, near_stage, packing, passage_chains, pii, quality, registry, simhash, suffix_dedup, suffix_tree_lm, toxicity
from meshcut.llm.lyndon import suffix_order

SF = f"{DATA}/sf0.001"
LOW = common.LOWER


@pytest.fixture(scope="module")
def docs(spark):
    return common.table(spark, SF, "documents")


@pytest.fixture(scope="module")
def texts(docs):
    return dict(map(tuple, docs.select("doc_id", "text").collect()))


@pytest.fixture(scope="module")
def odd(spark):
    """Nulls, empties, blanks, a very long text, ties, repeated rows, an id with two texts, and clashing column names."""
    long = " ".join(f"w{i % 977}" for i in range(30000))
    rows = [(1, None), (2, ""), (3, " \n\t "), (4, long), (5, long), (6, "one two"), (6, "one two"), (7, "first text of seven"), (7, "second text of seven"), (None, "no id here"), (8, "a" * 70000), (9, "é ü \u0001\u0003 x@y.zz 1.2.3.4")]
    more = [(i, t, None if i == 3 else "en", None, None if t is None else len(t), 1, "h", 0.5, "k") for i, t in rows]
    return spark.createDataFrame(more, "doc_id long, text string, lang string, source string, n_chars long, _id long, h string, score double, key string").repartition(3)


def components(n, links):
    up = list(range(n))

    def root(x):
        while up[x] != x:
            up[x] = up[up[x]]
            x = up[x]
        return x

    for a, b in links:
        a, b = root(a), root(b)
        up[max(a, b)] = min(a, b)
    return [root(i) for i in range(n)]


# -- 1 ------------------------------------------------------------------------------------------------------------------


def test_golay_keys_are_shared_up_to_two_bits():
    e = simhash.error_table()
    rng = np.random.default_rng(0)
    v = rng.integers(0, 1 << 23, 400, dtype=np.uint32)
    assert len(set(np.bitwise_count(v ^ (v ^ e[simhash.syndrome_of(v)])).tolist()) - {0, 1, 2, 3}) == 0
    mine = simhash.golay_keys(v, e)
    assert {len(set(r)) for r in mine.tolist()} <= {1, 6}
    for a, b in itertools.combinations(range(23), 2):
        other = simhash.golay_keys(v ^ np.uint32(1 << a | 1 << b), e)
        assert (mine[:, :, None] == other[:, None, :]).any(axis=(1, 2)).all()


def test_simhash_groups(spark, texts):
    got = {r["doc_id"]: r for r in simhash.simhash_groups(spark, SF).collect()}
    ids, fps = sorted(texts), []
    for i in ids:
        w = texts[i].encode().translate(LOW).split()
        s = [b" ".join(w[k : k + 4]) for k in range(max(1, len(w) - 3))] if w else []
        h = [xxhash.xxh64_intdigest(x, 42) for x in s]
        fps.append(sum(1 << b for b in range(64) if 2 * sum(x >> b & 1 for x in h) > len(h)) if h else 0)
        assert got[i]["fingerprint"] == format(fps[-1], "016x")
    links = [(a, b) for a, b in itertools.combinations(range(len(ids)), 2) if (fps[a] ^ fps[b]).bit_count() <= 4]
    for k, c in enumerate(components(len(ids), links)):
        assert got[ids[k]]["component_id"] == ids[c]


def test_simhash_hot_buckets_lose_nothing(spark):
    random.seed(4)
    base = random.getrandbits(64)
    fps = sorted({base ^ sum(1 << b for b in random.sample(range(64), random.randint(0, 6))) for _ in range(300)} | {random.getrandbits(64) for _ in range(50)})
    df = spark.createDataFrame([(x - 2**64 if x >> 63 else x,) for x in fps], "fp long")
    want = components(len(fps), [(a, b) for a, b in itertools.combinations(range(len(fps)), 2) if (fps[a] ^ fps[b]).bit_count() <= 4])
    at = {x: k for k, x in enumerate(fps)}
    for hot in (2048, 16):
        e = [(at[r[0] % 2**64], at[r[1] % 2**64]) for r in simhash.linked(df, 4, hot).collect()]
        assert components(len(fps), e) == want


# -- 2 ------------------------------------------------------------------------------------------------------------------

RULES = {"email": r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+", "ip": r"[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)", "card": r"[0-9]([\x20-]?[0-9])+", "phone": r"\+[0-9][\x20().0-9-]+[0-9]"}


def base_spans(s):
    out = []
    for n, (k, p) in enumerate(RULES.items()):
        for m in re.finditer(p, s):
            d = re.sub("[^0-9]", "", m.group())
            luhn = sum((int(c) * 2 - 9 * (int(c) > 4)) if i % 2 else int(c) for i, c in enumerate(reversed(d))) % 10 == 0
            if {"email": True, "ip": k != "ip" or all(int(x) <= 255 for x in m.group().split(".")), "card": 12 <= len(d) <= 19 and luhn, "phone": 9 <= len(d) <= 15}[k]:
                out.append((m.start(), n, m.end()))
    return ",".join(f"{pii.KINDS[n]}:{a}:{z}" for a, n, z in sorted(out))


def test_personal_data_base(spark, texts):
    tricky = ["a@b.c_d@e.f.g..h x@y.z. +1 (234) 567-8901 12 34 56 78 90 12 34 56 1.2.3.4.5.6.7.8 300.1.1.1 999-1.2.3.4", "4111 1111 1111 1111-4111 1111", "1 " * 30000, "é@x.y ü1.1.1.1" + "1.1.1.1." * 3 + "@" * 5 + "q@w.e", ".@.@a.b@c.d.e@f.g 4111-1111 1111 1111"]
    every = texts | {10**6 + n: t for n, t in enumerate(tricky)}
    df = spark.createDataFrame(list(every.items()), "doc_id long, text string")
    for r in pii.personal_data(df).select("doc_id", pii.span_text("base").alias("b")).collect():
        assert r["b"] == base_spans(every[r["doc_id"]]), r["doc_id"]


def test_personal_data_discovers_by_context(spark):
    seeds = [f"please call {i % 3} phone: +1 (555) 010-{1000 + i} today" for i in range(12)]
    rows = [(i, t) for i, t in enumerate(seeds)] + [(100, "the phone: 5550104321 today"), (101, "order 5550104321 shipped")]
    got = {r["doc_id"]: r for r in pii.personal_data(spark.createDataFrame(rows, "doc_id long, text string")).select("doc_id", pii.span_text("base").alias("base"), pii.span_text("spans").alias("spans")).collect()}
    assert got[100]["base"] == "" and got[100]["spans"] == "phone:11:21"
    assert got[101]["spans"] == ""
    assert all(got[i]["spans"].startswith(got[i]["base"]) for i in range(12))


def test_personal_data_precision_and_recall_of_added_spans(spark):
    """Identifiers in forms the rules miss, beside telling words and beside others, and numbers that are no identifiers."""
    random.seed(22)
    digits = lambda n: "".join(random.choice("0123456789") for _ in range(n))
    word = lambda: "".join(random.choice("abcdefgh") for _ in range(5))
    telling = {"email": ["mailto:", "write"], "phone": ["phone:", "tel"], "ip": ["host", "server"]}
    plain = {"email": lambda: f"{word()}@{word()}.org", "phone": lambda: f"+49 {digits(10)}", "ip": lambda: ".".join(str(random.randint(1, 255)) for _ in range(4))}
    strange = {"email": lambda: f"{word()}@intra", "phone": lambda: f"0{digits(9)}", "ip": lambda: f"fe80:{digits(4)}:{digits(4)}"}
    rows, want = [], {}
    for n in range(600):
        kind = random.choice(sorted(telling))
        lead = random.choice(telling[kind])
        left = f"{word()} {word()} {lead} "
        if n % 4:
            rows.append((n, left + plain[kind]() + f" {word()}"))
        elif n % 8:
            x = strange[kind]()
            rows.append((n, left + x + f" {word()}"))
            want[n] = f"{kind}:{len(left)}:{len(left) + len(x)}"
        else:
            rows.append((n, f"{word()} invoice {digits(8)} {word()}"))
    found = pii.personal_data(spark.createDataFrame(rows, "doc_id long, text string")).where("size(spans) > size(base)")
    got = {r["doc_id"]: r["spans"] for r in found.select("doc_id", pii.span_text("spans").alias("spans")).collect()}
    right = sum(got.get(n) == s for n, s in want.items())
    assert right >= 0.9 * len(want) and right >= 0.95 * len(got)


def test_personal_data_ignores_tokens_under_base_spans(spark):
    """Tokens that a base span covers, begins in or ends in are no instances."""
    text = "a +1 (234) 567-8901 b x1234567@y.zz c 4111 1111 1111 1111-4 d 999888777"
    got = pii.apart(pii.scanned(spark.createDataFrame([(1, text)], "doc_id long, text string"), pii.F.col("doc_id"), common.text_hash().alias("_th")).select("doc_id", "_th", pii.F.explode(pii.F.concat("_seeds", "_others")).alias("r"))).collect()
    assert [text[r["r"]["s"] : r["r"]["e"]] for r in got if r["r"]["k"] < 0] == ["999888777"]


# -- 3, 7, 9 --------------------------------------------------------------------------------------------------------------


def test_fuzzy_passages(spark):
    random.seed(2)
    word = lambda: "".join(random.choice("abcdefgh") for _ in range(5))
    passage = [word() for _ in range(80)]
    fuzzy = list(passage)
    for k in (20, 41, 63):
        fuzzy[k] = word()
    del fuzzy[30]
    make = lambda mid: " ".join([word() for _ in range(60)] + mid + [word() for _ in range(40)])
    rows = [(1, make(passage)), (2, make(fuzzy)), (3, make([])), (4, make(passage[:20]))]
    got = passage_chains.passages(spark.createDataFrame(rows, "doc_id long, text string")).collect()
    assert [(r["doc_id"], r["partner_id"]) for r in got] == [(2, 1)]
    assert abs(got[0]["start"] - 60) <= 1 and abs(got[0]["stop"] - 139) <= 1 and got[0]["identity"] > 0.9


def test_every_exact_passage_is_found(spark, texts):
    got = {r["doc_id"] for r in passage_chains.passage_pairs(spark, SF).select("doc_id").collect()}
    seen, want = {}, set()
    for i in sorted(texts):
        w = texts[i].encode().translate(LOW).split()
        for p in range(len(w) - 49):
            if seen.setdefault(b" ".join(w[p : p + 50]), i) != i:
                want.add(i)
    assert want <= got


def test_chain_and_common_subsequence():
    parts = [(0, 10, 100, 110, 10), (12, 30, 113, 131, 18), (15, 20, 500, 505, 5)]
    assert passage_chains.chains(list(parts), 0.1, 20, 24) == [(0, 30, 100, 131)]
    assert passage_chains.chains(list(parts), 0.1, 9, 1) == [(0, 10, 100, 110), (12, 30, 113, 131)]
    for _ in range(50):
        a, b = ([random.randint(0, 4) for _ in range(random.randint(0, 12))] for _ in "ab")
        t = [[0] * (len(b) + 1) for _ in range(len(a) + 1)]
        for i, x in enumerate(a):
            for j, y in enumerate(b):
                t[i + 1][j + 1] = t[i][j] + 1 if x == y else max(t[i][j + 1], t[i + 1][j])
        assert passage_chains.common_length(a, b) == t[-1][-1]


def test_line_dedup_is_its_sql(spark):
    c = duckdb.connect()
    c.execute(f"create view documents as select * from '{SF}/documents.parquet'")
    want = sorted(c.execute(registry.LINE_DEDUP).fetchall())
    assert sorted(map(tuple, line_dedup.line_dedup(spark, SF).collect())) == want


def test_line_stage_takes_short_runs_of_many_words(spark):
    """Passages of one and of two lines; shorter ones and the first occurrence stay."""
    line = lambda tag, n: " ".join(f"{tag}{i}" for i in range(n))
    one, two, few = line("a", 55), line("b", 30) + "\n\n" + line("c", 25), line("d", 40)
    rows = [(1, f"{one}\nx1\n{two}\nx2\n{few}"), (2, one), (3, f"y1\n{two}\ny2"), (4, f"z1\n{few}"), (5, f"{line('b', 30)}\nmore")]
    out = line_dedup.drop_later_lines(spark, spark.createDataFrame(rows, "doc_id long, text string"), SF)
    assert dict(map(tuple, out.collect())) == {1: rows[0][1], 2: "", 3: "y1\ny2", 4: rows[3][1], 5: rows[4][1]}


def test_suffix_order_is_sorted():
    random.seed(1)
    for _ in range(3000):
        s = bytes(random.choice(b"abcd"[: random.randint(1, 4)]) for _ in range(random.randint(0, 40)))
        assert suffix_order(s) == sorted(range(len(s)), key=lambda i: s[i:])


def without_repeats(rows, least=100):
    seen, out = set(), {}
    for i, s in sorted(rows):
        s = s.encode()
        gone = bytearray(len(s))
        for p in range(len(s) - least + 1):
            if s[p : p + least] in seen:
                gone[p : p + least] = b"\1" * least
            seen.add(s[p : p + least])
        spans = sum(1 for k in range(len(gone)) if gone[k] and not (k and gone[k - 1]))
        out[i] = (len(s), sum(gone), spans, bytes(c for c, g in zip(s, gone) if not g))
    return out


@pytest.mark.parametrize("hot", [1000, 20])
def test_suffix_dedup_on_overlapping_pieces(spark, hot):
    random.seed(1)
    base = ["".join(random.choice("ab ") for _ in range(400)) for _ in range(3)]
    rows = []
    for i in range(120):
        parts = []
        for _ in range(random.randint(0, 6)):
            k = random.randint(0, 200)
            parts.append(random.choice(base)[k : k + random.randint(90, 200)] + random.choice("xyz") * random.randint(0, 3))
        rows.append((i, "".join(parts)))
    rows += [(200, "a" * 1000), (201, "ab" * 400)]
    got = suffix_dedup.trimmed(spark.createDataFrame(rows, "doc_id long, text string").repartition(4), hot=hot).collect()
    want = without_repeats(rows)
    assert {r["doc_id"]: (r["n_bytes"], r["n_removed"], r["n_spans"], bytes(r["kept"])) for r in got} == want


def test_suffix_dedup_on_documents(spark, docs, texts):
    want = without_repeats(texts.items())
    for r in suffix_dedup.suffix_dedup(spark, SF).collect():
        n, gone, spans, kept = want[r["doc_id"]]
        assert (r["n_bytes"], r["n_removed"], r["n_spans"], r["kept_sha256"]) == (n, gone, spans, hashlib.sha256(kept).hexdigest())


# -- 4, 5, 6, 8, 10 -------------------------------------------------------------------------------------------------------


def test_packing_is_a_round_trip(spark, texts):
    from tokenizers import Tokenizer

    whole = Tokenizer.from_file(packing.vocabulary_path())
    rows = packing.packing(spark, SF).collect()
    by_doc, by_seq = collections.defaultdict(list), collections.defaultdict(list)
    for r in rows:
        by_doc[r["doc_id"]].append(r)
        by_seq[r["sequence_id"]].append(r)
    assert set(by_doc) == set(texts)
    for i, pieces in by_doc.items():
        ids, at = whole.encode(texts[i], add_special_tokens=False).ids + [1], 0
        for r in sorted(pieces, key=lambda r: r["start"]):
            assert r["start"] == at and r["doc_tokens"] == len(ids)
            assert r["ids_crc32"] == zlib.crc32(np.array(ids[at : at + r["length"]], "<u4").tobytes())
            at += r["length"]
        assert at == len(ids)
    for pieces in by_seq.values():
        at = 0
        for r in sorted(pieces, key=lambda r: r["offset"]):
            assert r["offset"] == at
            at += r["length"]
        assert at <= 2048 and at & (at - 1) == 0


def test_hilbert_cells():
    g = np.array(list(itertools.product(range(8), repeat=3)))
    k = packing.hilbert_index(g, 3)
    assert sorted(k) == list(range(512))
    assert (np.abs(np.diff(g[np.argsort(k)], axis=0)).sum(axis=1) == 1).all()


def test_quality_base(spark, texts):
    for r in quality.quality_rules(spark, SF).collect():
        s = texts[r["doc_id"]]
        w = [x for x in re.split(r"[ \t-\r]+", s) if x]
        c = collections.Counter(tuple(w[i : i + 3]) for i in range(len(w) - 2))
        again = {i + k for i in range(len(w) - 2) if c[tuple(w[i : i + 3])] > 1 for k in range(3)}
        lines = [x for x in s.split("\n") if re.search(r"[^ \t-\r]", x)]
        want = (len(w), sum(map(len, w)), sum(s.count(x) for x in quality.SYMBOLS), len(lines) - len(set(lines)), len(again))
        assert tuple(r[k] for k in ("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words")) == want
        assert r["base_failed"] == (len(w) < 50 or 100 * len(again) > 50 * len(w))
        assert not (r["kept"] and r["base_failed"])


def test_quality_rejects_symbol_noise(spark):
    rows = spark.read.parquet(f"{DATA}/sf0.01/documents.parquet").join(spark.read.parquet(f"{DATA}/sf0.01/labels.parquet"), "doc_id")
    got = rows.select("doc_id", "quality").join(quality.judged(rows, "doc_id").where("not base_failed").select("doc_id", "kept"), "doc_id").collect()
    good = [r["kept"] for r in got if r["quality"] == 1]
    bad = [r["kept"] for r in got if r["quality"] == 0]
    assert sum(good) >= 0.98 * len(good) and sum(bad) <= 0.2 * len(bad)


def suffix_tree(texts, depth, least, gain, trust):
    """Brute force: {context: {symbol: probability}} of the retained contexts, and the probability of unseen symbols."""
    seen = collections.defaultdict(collections.Counter)
    for t in texts:
        x = suffix_tree_lm.symbols(t, depth)
        for k in range(depth, len(x)):
            for d in range(depth + 1):
                seen[x[k - d : k]][x[k]] += 1
    total, size = sum(seen[b""].values()), len(seen[b""]) + 1
    tree = {b"": {s: (n + 1) / (total + size) for s, n in seen[b""].items()}}

    def says(context, symbol):
        while context not in tree:
            context = context[1:]
        if symbol in tree[context]:
            return tree[context][symbol]
        if not context:
            return 1 / (total + size)
        return trust / (sum(seen[context].values()) + trust) * says(context[1:], symbol)

    for context in sorted(seen, key=len):
        own, up = seen[context], seen[context[1:]]
        n, m = sum(own.values()), sum(up.values())
        if context and n >= least and sum(c * math.log(c / n / (up[s] / m)) for s, c in own.items()) >= gain * len(own):
            tree[context] = {s: (c + trust * says(context[1:], s)) / (n + trust) for s, c in own.items()}
    return tree, says


def test_lm_scores(spark, texts):
    c = collections.Counter()
    words = {i: t.encode().translate(LOW).split() + [b""] for i, t in texts.items()}
    for i, w in words.items():
        if zlib.crc32(str(i).encode()) % 10:
            c.update(w)
    n, v = sum(c.values()), len(c)
    learned = [t.encode() for i, t in texts.items() if zlib.crc32(str(i).encode()) % 10]
    tree, says = suffix_tree(learned, 5, 16, 2.0, 4.0)
    assert len(tree) > 500 and max(map(len, tree)) == 5
    rows = suffix_tree_lm.lm_scores(spark, SF).collect()
    for r in rows:
        w = words[r["doc_id"]]
        assert r["held_out"] == (zlib.crc32(str(r["doc_id"]).encode()) % 10 == 0)
        assert (r["n_tokens"], r["n_known"], r["train_tokens"]) == (len(w), sum(c[x] > 0 for x in w), n)
        assert r["base_score"] == pytest.approx(sum(math.log10((c[x] + 0.1) / (n + 0.1 * (v + 1))) for x in w), rel=1e-9)
    for r in rows[::5]:
        x = suffix_tree_lm.symbols(texts[r["doc_id"]].encode(), 5)
        assert r["score"] == pytest.approx(sum(math.log10(says(x[k - 5 : k], x[k])) for k in range(5, len(x))), rel=1e-5)


def test_lm_tree_is_a_distribution_grows_and_joins(spark):
    texts = ["the cat sat on the mat", "a dog ran", "The  cat\nsat", "\u00e9t\u00e9 \u0001", ""] * 20
    df = spark.createDataFrame(list(enumerate(texts)) + [(None, "the cat"), (7, None)], "doc_id long, text string")
    learned = [t.encode() for i, t in enumerate(texts) if zlib.crc32(str(i).encode()) % 10] + [b"the cat"] + [b""] * bool(zlib.crc32(b"7") % 10)
    tree, says = suffix_tree(learned, 3, 5, 0.1, 2.0)
    symbols = set(tree[b""])
    assert all(sum(says(c, s) for s in symbols) + says(c, 255) == pytest.approx(1) for c in tree)
    few, _ = suffix_tree(learned[:8], 3, 5, 0.1, 2.0)
    assert len(tree) > len(few) > 1
    settings = {"depth": 3, "least": 5, "gain": 0.1, "trust": 2.0}
    for limit in (1_000_000, 0):
        got = sorted((r["doc_id"] or -1, r["score"]) for r in suffix_tree_lm.scored(df, **settings, broadcast=limit).collect())
        want = []
        for i, t in [*enumerate(texts), (None, "the cat"), (7, "")]:
            x = suffix_tree_lm.symbols(t.encode(), 3)
            want.append((i or -1, sum(math.log10(says(x[k - 3 : k], x[k])) for k in range(3, len(x)))))
        assert [g[0] for g in got] == [w[0] for w in sorted(want)]
        assert [g[1] for g in got] == pytest.approx([w[1] for w in sorted(want)], rel=1e-5)


def test_lm_strings_are_sorted_by_value(monkeypatch):
    """Every block of strings was sorted by places, together with all counted before it: 6.9 million places for these."""
    import pyarrow as pa

    random.seed(31)
    texts = [bytes(random.choices(b"abcd ", k=9000)) for _ in range(700)] + [b""]
    want = collections.Counter()
    for t in texts:
        want.update(suffix_tree_lm.strings(suffix_tree_lm.symbols(t, 2), 2).tolist())
    sizes, real = [], np.argsort
    monkeypatch.setattr(np, "argsort", lambda x, **more: sizes.append(len(x)) or real(x, **more))
    batches = [pa.RecordBatch.from_arrays([pa.array(range(len(texts[k : k + 50]))), pa.array(texts[k : k + 50])], names=["id", "body"]) for k in range(0, len(texts), 50)]
    got = collections.Counter()
    for b in suffix_tree_lm.gather(2)(batches):
        for r in b.to_pylist():
            if r["gram"] is not None:
                got[r["gram"]] += r["n"]
    assert got == want and sum(want.values()) > 6_000_000
    assert sum(sizes) < 1_000_000


def test_reparameterised_questions(spark):
    bench = spark.createDataFrame([(1, "A train leaves Paris at 60 km and meets Anna after 3 hours on the road to the sea, how far is it?"), (2, "Completely different words are standing here in this other longer question about nothing")], "item_id long, text string")
    rows = [(1, "Intro here. A train leaves Rome at 75 km and meets Otto after 4 hours on the road to the sea, how far is it? Bye."),
            (2, "Nothing of that kind is in this text at all, only words about other things and more."), (3, None), (4, ""),
            (5, "Completely different words are standing here in this other longer question about nothing")]
    df = spark.createDataFrame(rows, "doc_id long, text string")
    for block in (64_000_000, 30):
        got = {r["doc_id"]: r["_mc_items"] for r in contamination.leaks(df, bench, "doc_id", block=block).collect()}
        assert got == {1: [1], 2: [], 3: [], 4: [], 5: [2]}


def test_benchmark_passages_are_found(spark, texts):
    items = dict(map(tuple, spark.read.parquet(f"{SF}/benchmark.parquet").collect()))
    got = {r["doc_id"]: r for r in contamination.decontamination(spark, SF).collect()}
    flat = lambda s: b" ".join(s.encode().split())
    for i, t in texts.items():
        for k, b in items.items():
            if b" " + flat(b) + b" " in b" " + flat(t) + b" ":
                assert k in got[i]["item_ids"]
    assert sum(r["contaminated"] for r in got.values()) < 0.2 * len(got)


def test_numbers_and_look_alikes_are_found():
    numbers = b"3 5 8 13 21 34 55 89 144 233 377 610"
    question = b"a box holds 7 red balls and the bag holds 7 blue ones so the cart holds 7 green ones"
    index = contamination.Index([(1, numbers), (2, question)], 8)
    found = lambda text: {i for i, _ in index.matches(text, contamination.WordCodes(), 0.5, 0.8)}
    assert found(b"he wrote " + numbers + b" and left") == {1}
    assert found(b"he wrote " + b" ".join(b"%d" % k for k in range(40, 60)) + b" and left") == set()
    like = question.replace(b"7", b"1", 1).replace(b"7", b"2", 1).replace(b"7", b"3", 1)
    assert found(like) == set()
    assert found(like + b" then some words between " + question.replace(b"7", b"4")) == {2}


@pytest.mark.parametrize("block", [64_000_000, 10])
def test_every_verbatim_item_is_found(spark, block):
    """Items of numbers, names and few words, in the middle of sentences; fragments far apart and other texts are left alone."""
    random.seed(8)
    word = lambda: "".join(random.choice("abcdefgh") for _ in range(5))
    items = ["12 + 35 =", "Compute 12 * 7 + 9 / 3", "What is the capital city of France?", "Anna Bert Carl Dora Emil", " ".join(word() for _ in range(40)), " ".join(f"{k * k}" for k in range(30)), "7 km 8 km 9 km"]
    rows = [(n, " ".join([word() for _ in range(30)] + ["said"] + t.split() + ["and"] + [word() for _ in range(20)])) for n, t in enumerate(items)]
    long = items[4].split()
    apart = [x for k in range(0, 40, 8) for x in long[k : k + 8] + [word() for _ in range(300)]]
    rows += [(100, " ".join(apart)), (101, "nothing of the kind, only 13 + 36 = 49 here")]
    bench = spark.createDataFrame(list(enumerate(items)), "item_id long, text string")
    got = {r["doc_id"]: r["_mc_items"] for r in contamination.leaks(spark.createDataFrame(rows, "doc_id long, text string"), bench, "doc_id", block=block).collect()}
    assert got == {n: [n] for n in range(len(items))} | {100: [], 101: []}


def test_toxicity_on_held_out(spark):
    lab = dict(map(tuple, spark.read.parquet(f"{DATA}/sf0.01/labels.parquet").select("doc_id", "toxic").collect()))
    rows = toxicity.toxicity(spark, f"{DATA}/sf0.01").collect()
    assert all(0 <= r["score"] <= 1 and r["predicted"] == int(r["score"] >= 0.5) for r in rows)
    held = [(lab[r["doc_id"]], r["predicted"]) for r in rows if r["held_out"] and r["doc_id"] in lab]
    clean = [p for y, p in held if not y]
    assert sum(clean) <= 0.05 * len(clean)
    seen = [(lab[r["doc_id"]], r["predicted"]) for r in rows if not r["held_out"] and r["doc_id"] in lab]
    assert sum(y == p for y, p in seen) > 0.95 * len(seen)


def test_toxicity_fit_ranks_held_out_documents():
    """Area under the curve and recall of the fit on the held-out fifth of sf0.1."""
    rows = duckdb.sql(f"select d.doc_id, text, toxic from '{DATA}/sf0.1/documents.parquet' d join '{DATA}/sf0.1/labels.parquet' using (doc_id)").fetchall()
    held = [zlib.crc32(str(i).encode()) % 5 == 0 for i, _, _ in rows]
    place = np.zeros(toxicity.SLOTS, np.int32)
    learn = [(t.encode(), y) for (_, t, y), h in zip(rows, held) if not h]
    w, bias = toxicity.fit([t for t, _ in learn], np.array([y for _, y in learn], float), np.ones(len(learn)))
    z = [(w[toxicity.feature_slots(t.encode(), place)].sum(dtype=float) + bias, y) for (_, t, y), h in zip(rows, held) if h]
    bad, good = [s for s, y in z if y], [s for s, y in z if not y]
    assert sum((a > b) + (a == b) / 2 for a in bad for b in good) >= 0.95 * len(bad) * len(good)
    assert sum(s >= 0 for s in bad) >= 0.6 * len(bad) and sum(s >= 0 for s in good) <= 0.01 * len(good)


# -- odd rows -----------------------------------------------------------------------------------------------------------


def test_odd_rows(spark, odd):
    n = odd.count()
    labels = spark.createDataFrame([(7, 0), (6, 1), (6, 0), (None, 1), (4, None)], "doc_id long, toxic int")
    assert toxicity.score_documents(odd, toxicity.train(odd, labels), "doc_id").count() == n
    rows = simhash.fingerprints(odd)
    assert rows.count() == n and {r["fp"] for r in rows.collect() if r["_id"] in (1, 2, 3)} == {0}
    grouped = {r["_id"]: r["component"] for r in simhash.components_by_fingerprint(common.written(rows, "t"), 4).collect()}
    assert grouped[1] == grouped[2] == grouped[3] == 1 and grouped[5] == 4
    assert pii.personal_data(odd).count() == n
    assert passage_chains.passages(odd).where("doc_id = 5 and partner_id = 4").count() >= 1
    pieces = packing.pack(odd, packing.vocabulary_path()).collect()
    assert sum(r["length"] for r in pieces if r["doc_id"] == 1) == 1 and any(r["doc_id"] is None for r in pieces)
    judged = quality.judged(odd, "doc_id").collect()
    assert len(judged) == n and not any(r["kept"] for r in judged if r["doc_id"] in (1, 2, 3))
    scores = suffix_tree_lm.scored(odd).collect()
    assert len(scores) == n and all(r["n_tokens"] == 1 for r in scores if r["doc_id"] in (1, 2, 3))
    assert line_dedup.dedup_lines(odd).count() == n
    bench = spark.createDataFrame([(1, None), (None, "x"), (3, "")], "item_id long, text string")
    assert contamination.leaks(odd, bench, "doc_id").where("size(_mc_items) > 0").count() == 0
    cut = {r["doc_id"]: r for r in suffix_dedup.trimmed(odd).collect()}
    assert len(cut) == n - 2 and cut[5]["n_removed"] == cut[5]["n_bytes"] and cut[1]["n_bytes"] == 0
    assert cut[8]["n_removed"] == 69999


def test_stages_on_odd_rows(spark, odd, tmp_path):
    for name in ("labels", "benchmark"):
        spark.read.parquet(f"{SF}/{name}.parquet").write.parquet(f"{tmp_path}/{name}.parquet")
    for stage in (toxicity.drop_toxic, line_dedup.drop_later_lines, near_stage.drop_near_copies, contamination.drop_leaks):
        out = stage(spark, odd, str(tmp_path))
        assert out.columns == odd.columns and out.schema.simpleString() == odd.schema.simpleString()
        rows = out.collect()
        ids = [r["doc_id"] for r in rows]
        if stage is near_stage.drop_near_copies:
            assert sorted(x or 0 for x in ids) == [0, 1, 4, 6, 7, 7, 8, 9]
        else:
            assert len(rows) == odd.count()
        assert all(r["_id"] == 1 and r["h"] == "h" and r["key"] == "k" for r in rows)
    assert packing.pack_kept(spark, odd, str(tmp_path)).count() > 0


def test_empty_tables(spark, docs):
    none = docs.limit(0)
    labels, bench = spark.read.parquet(f"{SF}/labels.parquet").limit(0), spark.read.parquet(f"{SF}/benchmark.parquet").limit(0)
    assert toxicity.score_documents(none, toxicity.train(none, labels), "doc_id").count() == 0
    assert {r["score"] < 0.5 for r in toxicity.score_documents(docs.limit(3), toxicity.train(docs, labels), "doc_id").collect()} == {True}
    assert simhash.components_by_fingerprint(common.written(simhash.fingerprints(none), "t"), 4).count() == 0
    for out in (pii.personal_data(none), passage_chains.passages(none), packing.pack(none, packing.vocabulary_path()), quality.judged(none, "doc_id"), suffix_tree_lm.scored(none), line_dedup.dedup_lines(none), contamination.leaks(none, bench, "doc_id"), suffix_dedup.trimmed(none), near_stage.drop_near_copies(spark, none, SF)):
        assert out.count() == 0
    assert contamination.leaks(docs, bench, "doc_id").where("size(_mc_items) > 0").count() == 0


def test_near_stage_matches_jaccard(spark):
    random.seed(6)
    word = lambda: "".join(random.choice("abcdefgh") for _ in range(4))
    rows, n = [], 0
    for _ in range(25):
        base = [word() for _ in range(random.choice((20, 60, 200)))]
        for _ in range(random.randint(1, 5)):
            w = list(base)
            for k in random.sample(range(len(w)), random.randint(0, max(1, len(w) // 60))):
                w[k] = word()
            rows.append((n, " ".join(w)))
            n += 1
    sets = [frozenset(tuple(t.split()[k : k + 5]) for k in range(len(t.split()) - 4)) for _, t in rows]
    links = [(a, b) for a, b in itertools.combinations(range(n), 2) if len(sets[a] & sets[b]) >= 0.8 * len(sets[a] | sets[b])]
    want = {c for c in components(n, links)}
    got = {r["doc_id"] for r in near_stage.drop_near_copies(spark, spark.createDataFrame(rows, "doc_id long, text string"), SF).collect()}
    assert want <= got and len(got - want) <= 1


def test_near_candidates_in_crowded_buckets(spark):
    """All texts share all buckets: each pair of close ones is still a candidate."""
    random.seed(16)
    rows = []
    for h in range(200):
        fp, other = random.getrandbits(64), random.getrandbits(64)
        for k in (0, 1):
            rows.append((2 * h + k, *((x ^ k * (1 << 62 | 1 << 40) ^ 1 << 63) - (1 << 63) for x in (fp, other)), [0] * near_stage.TABLES))
    links = near_stage.candidate_links(spark.createDataFrame(rows, "_h long, fp long, other long, sigs array<bigint>"), 16).collect()
    up = components(400, [(a, b) for a, b in links])
    assert all(up[2 * h] == up[2 * h + 1] for h in range(200)) and len(set(up)) > 150


def test_near_stage_on_a_loose_group(spark):
    """One group of which a quarter of the pairs are alike, larger than a block."""
    random.seed(26)
    base = [f"w{i}" for i in range(150)]
    rows = []
    for n in range(near_stage.BLOCK + 100):
        w = list(base)
        for k in random.sample(range(len(w)), random.randint(1, 7)):
            w[k] = f"x{random.randint(0, 9999)}"
        rows.append((n, " ".join(w)))
    sets = [frozenset(tuple(t.split()[k : k + 5]) for k in range(146)) for _, t in rows]
    links = [(a, b) for a, b in itertools.combinations(range(len(rows)), 2) if len(sets[a] & sets[b]) >= 0.8 * len(sets[a] | sets[b])]
    want = set(components(len(rows), links))
    got = {r["doc_id"] for r in near_stage.drop_near_copies(spark, spark.createDataFrame(rows, "doc_id long, text string"), SF).collect()}
    assert want <= got and len(got - want) <= 1


def test_pipeline_runs(spark):
    import corpus_pipeline

    assert [n for n, _ in corpus_pipeline.STAGES] == ["toxicity", "line dedup", "simhash near-dedup", "benchmark decontamination", "packing"]
    rows = corpus_pipeline.run(spark, SF)
    assert rows.columns[:2] == ["doc_id", "start"] and rows.count() > 100


@pytest.mark.parametrize("least", [0.8, 0.85, 0.9, 0.95])
def test_fuzzy_passages_are_found(spark, least):
    """Recall of 60-word passages per band of identity, and no passage between texts that share none."""
    random.seed(int(100 * least))
    word = lambda: "".join(random.choice("abcdefghij") for _ in range(4))
    text = lambda n: [word() for _ in range(n)]
    rows, planted = [], set()
    for n in range(120):
        passage, changed = text(60), None
        while changed is None or not least <= passage_chains.common_length(passage, changed) / max(60, len(changed)) < least + 0.05:
            changed = list(passage)
            for k in sorted(random.sample(range(1, 59), random.randint(max(0, round(55 - 60 * least)), round(62 - 60 * least))), reverse=True):
                changed[k : k + 1] = random.choice([[word()]] * 6 + [[], [word(), word()]])
        rows += [(2 * n, " ".join(text(50) + passage + text(30))), (2 * n + 1, " ".join(text(20) + changed + text(60)))]
        planted.add((2 * n + 1, 2 * n))
    got = {(r["doc_id"], r["partner_id"]) for r in passage_chains.passages(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    assert got <= planted and len(got) >= 0.9 * len(planted)


def test_pipeline_on_odd_and_on_empty_tables(spark, odd, docs, tmp_path):
    import corpus_pipeline

    for name, rows in (("odd", odd), ("none", odd.limit(0))):
        folder = f"{tmp_path}/{name}"
        rows.write.parquet(f"{folder}/documents.parquet")
        for t in ("labels", "benchmark"):
            table = spark.read.parquet(f"{SF}/{t}.parquet")
            (table if name == "odd" else table.limit(0)).write.parquet(f"{folder}/{t}.parquet")
        out = corpus_pipeline.run(spark, folder)
        got = out.collect()
        if name == "none":
            assert got == []
        else:
            # of 1, 2 and 3 one stays, of 4 and 5, and of the equal rows of 6
            assert {r["doc_id"] for r in got} == {None, 1, 4, 6, 7, 8, 9}
            assert all(sum(r["length"] for r in got if r["doc_id"] == i) >= 1 for i in (1, 4, 9))


@pytest.mark.parametrize("few", [12, 1])
def test_passage_links_between_scattered_holders(spark, few):
    """The seeds of a passage have other first holders and other neighbours than the one text that shares it whole; of three
    such pairs with a common line each pair is linked, whether groups are small or hot (few=1)."""
    random.seed(11)
    word = lambda: "".join(random.choice("abcdefgh") for _ in range(6))
    line, rows, want = [word() for _ in range(12)], [], set()
    for n in range(3):
        passage = [word() for _ in range(24)] + line + [word() for _ in range(24)]
        pieces = [passage[k : k + 7] for k in range(0, 60, 5)]
        scattered = lambda: " ".join(w for p in random.sample(pieces, len(pieces)) for w in [*p, word(), word(), word()])  # noqa: E731, B023
        for k, text in enumerate((scattered(), " ".join(passage), scattered(), " ".join([word(), *passage, word()]))):
            rows.append((10 * n + k, text))
        want.add((10 * n + 3, 10 * n + 1))
    got = {(r["doc_id"], r["partner_id"]) for r in passage_chains.passages(spark.createDataFrame(rows, "doc_id long, text string"), few=few).collect()}
    assert got == want


def test_matches_of_batches_are_those_of_the_whole():
    import pyarrow as pa

    random.seed(3)
    rows = sorted((random.randint(0, 9) if random.random() < 0.7 else 5, random.randint(0, 30), k) for k in range(400))
    names = ["h", "id", "at"]
    cut = lambda size: [pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in zip(*rows[k : k + size])], names=names) for k in range(0, len(rows), size)]
    every = lambda size, few: sorted(tuple(r.values()) for b in passage_chains.match(few)(cut(size)) for r in b.to_pylist())
    for few in (2, 5, 500):
        assert every(400, few) == every(7, few) == every(1, few)
    pairs = [(i, 0, s, j, 0, z) for n, (h, i, s) in enumerate(rows) for g, j, z in rows[:n] if g == h and i != j]
    assert every(7, 500) == sorted(pairs)


def test_equal_pieces_of_hot_groups_are_dealt_once(spark):
    """Only different pieces make a group hot; 300 equal ones left 300 rows to deal again."""
    import pyarrow as pa

    body = bytes(range(100, 225))
    rows = [(1, i, 0, 10, body) for i in range(300)]
    batch = pa.RecordBatch.from_arrays([pa.array(c) for c in zip(*rows)], names=suffix_dedup.PIECE_NAMES)
    out = [r for b in suffix_dedup.sort_groups(34, 100, 20)([batch]) for r in b.to_pylist()]
    assert [r["id"] for r in out] == list(range(1, 300)) and all(r["n"] is not None for r in out)


def test_growing_of_many_pairs_is_that_of_each():
    random.seed(4)
    rows = []
    for _ in range(2000):
        a = [random.randint(1, random.choice([3, 20, 200])) for _ in range(random.randint(0, 40))]
        b = list(a)
        for _ in range(random.randint(0, 8)):
            k = random.randint(0, len(b))
            b[k : k + random.randint(0, 2)] = [random.randint(1, 200) for _ in range(random.randint(0, 2))]
        rows.append((a, b))
    one, two = np.zeros((2000, 64), np.uint32), np.zeros((2000, 64), np.uint32)
    for k, (a, b) in enumerate(rows):
        one[k, : len(a)], two[k, : len(b)] = a, b
    at = np.arange(2000)
    got = passage_chains.common_steps(one, two, at, at)[:2]
    assert [tuple(int(z) for z in x) for x in zip(*got)] == [passage_chains.grown(a, b) for a, b in rows]


@pytest.mark.parametrize("together", [1, 1000])
def test_holders_of_a_common_line_are_not_all_compared(monkeypatch, together):
    """250 texts share 20 words only; of their 31 125 pairs those few that go on alike are compared word by word, and they
    are those that all pairs give. The bigrams of the line alone had every pair compared."""
    random.seed(12)
    word = lambda: random.randint(1, 4000)
    line = [word() for _ in range(20)]
    texts = [[word() for _ in range(90)] + line + [word() for _ in range(90)] for _ in range(250)]
    for a, b, first, last in ((3, 200, 80, 125), (5, 77, 60, 110), (130, 131, 88, 133), (131, 9, 75, 118)):
        texts[b][first:last] = texts[a][first:last]
        for k in (last - 4, last - 9, first + 4):
            texts[b][k] = word()
    link = lambda pairs: components(250, pairs)
    own = lambda a, b: passage_chains.align(texts[a], texts[b], 95, 99, 95, 99)
    good = lambda a0, a1, b0, b1, n: n >= 0.8 * max(a1 - a0, b1 - b0) and min(a1 - a0, b1 - b0) >= 40
    want = [(a, b) for a, b in itertools.combinations(range(250), 2) if good(*own(a, b))]
    assert {(3, 200), (5, 77)} <= set(want) and len(want) < 20
    compared, real = [], passage_chains.common_length
    monkeypatch.setattr(passage_chains, "common_length", lambda a, b: compared.append(1) or real(a, b))
    rows = [(1, i, i, 0, 95, 0, 4, np.array(t, "<u4").tobytes(), 0) for i, t in enumerate(texts)]
    out = [r for b in passage_chains.settled(40, 0.8, reach=200, together=together)([passage_chains.context_batch(rows)]) for r in b.to_pylist()]
    assert link([(r["id"], r["id2"]) for r in out]) == link(want) and len(compared) < 50
    same = [(1, i, i, 0, 95, 0, 4, np.array(t, "<u4").tobytes(), 5) for i, t in enumerate(texts)]
    assert not [r for b in passage_chains.settled(40, 0.8, reach=200)([passage_chains.context_batch(same)]) for r in b.to_pylist()]


def test_a_text_is_cut_once_for_all_its_chains(spark, tmp_path, monkeypatch):
    """The first of 21 texts is in 20 chains; its words were hashed anew for almost each of them."""
    random.seed(21)
    word = lambda: random.randbytes(4).hex()
    passage = [word() for _ in range(70)]
    rows = [(n, " ".join([f"mark{n}", word(), *passage, word()])) for n in range(21)]
    real, folder = passage_chains.word_hashes, str(tmp_path)

    def counted(body):
        if body.startswith(b"mark0 "):
            import tempfile

            tempfile.mkstemp(dir=folder)
        return real(body)

    monkeypatch.setattr(passage_chains, "word_hashes", counted)
    got = passage_chains.passages(spark.createDataFrame(rows, "doc_id long, text string")).collect()
    assert {r["doc_id"] for r in got} == set(range(1, 21)) and {r["class_id"] for r in got} == {0}
    assert sum(r["partner_id"] == 0 for r in got) == 20
    assert 1 <= len(list(tmp_path.iterdir())) <= 4


def test_passage_steps_take_few_bytes_at_once(spark, monkeypatch):
    """Steps over texts took up to 10 000 texts at once, whatever their length."""
    random.seed(22)
    rows = [(n, random.randbytes(40_000).hex(" ", 4)) for n in range(300)]
    real = passage_chains.find_seeds

    def bounded(*args):
        run = real(*args)

        def checked(batches):
            def seen():
                for b in batches:
                    assert b.nbytes <= 3 << 20, b.nbytes
                    yield b

            return run(seen())

        return checked

    monkeypatch.setattr(passage_chains, "find_seeds", bounded)
    name = "spark.sql.execution.arrow.maxBytesPerBatch"
    before = spark.conf.get(name)
    assert passage_chains.passages(spark.createDataFrame(rows, "doc_id long, text string")).count() == 0
    assert spark.conf.get(name) == before


def test_seeds_of_a_batch_are_cut_at_once(monkeypatch):
    """Each text had its own passes over its few words: 2 x 60 calls for these."""
    import pyarrow as pa

    random.seed(41)
    sizes = [0, 1, 3, 4, 15, 16, 17, 38, 39, 40, 0, *(random.randint(0, 300) for _ in range(49))]
    bodies = [" ".join(random.choice("abcdefghij") + str(random.randint(0, 9)) for _ in range(n)).encode() for n in sizes]
    want = []
    for i, body in enumerate(bodies):
        words = passage_chains.word_hashes(body)
        h, far = common.rolled(words, 4), common.rolled(words, 16)
        want += [(int(x), i, 2 * k + (i % 3) * suffix_dedup.ROW) for k, x in enumerate(h.view(np.int64)) if int(h[k]) >> 40 & 3 == 0]
        want += [(int(far.view(np.int64)[k]), i, 2 * int(k) + 1 + (i % 3) * suffix_dedup.ROW) for k in common.window_minima(far, 24)]
    calls, real = [], common.rolled
    monkeypatch.setattr(common, "rolled", lambda *a: calls.append(1) or real(*a))
    columns = [pa.array(range(60)), pa.array([i % 3 for i in range(60)]), pa.array(bodies)]
    batch = pa.RecordBatch.from_arrays(columns, names=["id", "row", "body"])
    got = [tuple(r.values()) for b in passage_chains.find_seeds(4, 4, 16, 24)([batch]) for r in b.to_pylist()]
    assert sorted(got) == sorted(want) and len(calls) <= 4
    assert not [r for b in passage_chains.find_seeds(4, 4, 16, 24)([batch.slice(0, 0), batch.slice(0, 3)]) for r in b.to_pylist()]


def test_chains_judged_together_are_those_of_each(monkeypatch):
    """Words were compared for every chain, however short; now only of ranges that are long enough."""
    import pyarrow as pa

    random.seed(42)
    rows, want = [], []
    for n in range(400):
        a = [random.randint(1, 500) for _ in range(random.randint(8, 90))]
        b = list(a)
        for _ in range(random.randint(0, 12)):
            k = random.randint(0, len(b))
            b[k : k + random.randint(0, 2)] = [random.randint(1, 500) for _ in range(random.randint(0, 2))]
        b = b or [1]
        a0, b0 = random.randint(max(0, min(len(a), len(b)) - 60), min(len(a), len(b), 40)), 0
        a0 = b0 = min(a0, len(a), len(b), passage_chains.MARGIN)
        a1, b1 = max(a0, len(a) - passage_chains.MARGIN + 5), max(b0, len(b) - passage_chains.MARGIN + 5)
        f, g = random.randint(0, 9), random.randint(0, 9)
        rows.append((n, n + 1, a0 + f, a1 + f, b0 + g, b1 + g, f, g, np.array(a, "<u4").tobytes(), np.array(b, "<u4").tobytes()))
        x0, x1, y0, y1, same = passage_chains.align(a, b, a0, a1, b0, b1)
        if min(x1 - x0, y1 - y0) >= 40 and same / max(x1 - x0, y1 - y0) >= 0.8:
            want.append((n, n + 1, x0 + f, x1 + f, y0 + g, y1 + g, same, round(same / max(x1 - x0, y1 - y0), 6)))
    compared, real = [], passage_chains.common_length
    monkeypatch.setattr(passage_chains, "common_length", lambda a, b: compared.append(1) or real(a, b))
    kinds = [pa.int64()] * 2 + [pa.int32()] * 6 + [pa.binary()] * 2
    batch = pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows), kinds)], names=list("abcdefghij"))
    for parts in ([batch], [batch.slice(k, 33) for k in range(0, 400, 33)], [batch.slice(0, 0), batch]):
        compared.clear()
        got = [tuple(r.values()) for b in passage_chains.judge(40, 0.8)(parts) for r in b.to_pylist()]
        assert got == want and 20 < len(want) <= len(compared) < 300


def test_contexts_of_hot_seeds():
    """Words around each seed; what goes on alike to the next hot seed has an equal hash, wherever it stands."""
    import pyarrow as pa

    words = [f"w{k}" for k in range(60)]
    other = ["x", *words[:20], "changed", *words[21:]]
    texts = [" ".join(w).encode() for w in (words, ["a", "b", *words], other)]
    seeds = lambda by: [{"h": h, "class": by, "at": 2 * (at + by)} for h, at in ((7, 40), (5, 10), (6, 18))]
    wanted = [seeds(0), seeds(2), seeds(1)]
    kind = pa.list_(pa.struct([("h", pa.int64()), ("class", pa.int64()), ("at", pa.int32())]))
    batch = pa.RecordBatch.from_arrays([pa.array([1, 2, 3]), pa.array([0, 0, 0]), pa.array(texts), pa.array(wanted, kind)], names=list("abcd"))
    got = [r for b in passage_chains.contexts(4, 16, 48)([batch]) for r in b.to_pylist()]
    assert [(r["id"], r["h"], r["at"], r["from"], r["k"]) for r in got] == [(n, h, at + by, max(0, at + by - 48), 4) for n, by in ((1, 0), (2, 2), (3, 1)) for h, at in ((5, 10), (6, 18), (7, 40))]
    for r in got:
        text = passage_chains.short_words(passage_chains.word_hashes(texts[r["id"] - 1]))
        assert r["words"] == text[r["from"] : r["at"] + 4 + 48].tobytes()
    ahead = [[r["next"] for r in got if r["id"] == n] for n in (1, 2, 3)]
    assert ahead[0] == ahead[1] and ahead[0][0] == ahead[2][0] != 0 and ahead[0][1] != ahead[2][1] and all(a[2] == 0 for a in ahead)


def test_places_without_a_passage_are_settled_inside_a_class(spark):
    """Two texts are in one class by a passage of their own; another one, whose seeds meet other holders first, had no row."""
    random.seed(51)
    word = lambda: "".join(random.choice("abcdefgh") for _ in range(6))
    words = lambda n: [word() for _ in range(n)]
    own, passage = words(60), words(60)
    # the pieces have all four-word strings of the passage, and its changed form has none of sixteen
    pieces = [passage[k : k + 7] for k in range(0, 57, 4)]
    changed = [word() if k % 9 == 8 else w for k, w in enumerate(passage)]
    scattered = lambda: " ".join(w for p in random.sample(pieces, len(pieces)) for w in [*p, word(), word(), word()])
    one, two = [*words(5), *own, *words(150), *passage], [*words(20), *changed, *words(130), *own]
    # the passage twice in one text: no row of a text with itself
    rows = [(0, scattered()), (1, " ".join(one)), (2, scattered()), (3, " ".join([*two, *words(150), *changed]))]
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    for few in (1, 12):
        got = passage_chains.passages(docs, few=few).collect()
        assert {(r["doc_id"], r["partner_id"], r["class_id"]) for r in got} == {(3, 1, 1)}
        covered = {w for r in got for w in range(r["start"], r["stop"])}
        assert {*range(22, 78), *range(212, 268), *range(422, 478)} <= covered, few
