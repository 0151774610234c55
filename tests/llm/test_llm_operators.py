"""The dealt operators against brute force, on edge cases, and on held-out rows."""

import hashlib
import math
import itertools
import random
import re
import zlib
from collections import Counter

import numpy as np
import pyarrow as pa
import pytest
from pyspark.sql import functions as F

from driftlattice.llm import context_tree, decontaminate, jaccard, language, lattice_dedup, licences, mixing, private_terms, shared, substring, toxicity

WORD = re.compile(r"[^\x20\x09-\x0D]+")
SCHEMA = "doc_id long, text string, lang string, source string, n_chars long"
LONG = "lorem ipsum " * 20_000


def low(text):
    return re.sub("[A-Z]", lambda m: m[0].lower(), text or "")


@pytest.fixture(scope="module")
def docs(spark):
    """Copies, near copies, shared passages, nulls in each column, blank and very long texts, repeated rows."""
    rng = random.Random(11)
    words = ["".join(rng.choice("aeioubcdrst") for _ in range(rng.randint(2, 7))) for _ in range(400)]
    rows = []
    passage = rng.choices(words, k=70)
    for i in range(60):
        body = rng.choices(words, k=rng.choice([3, 20, 80, 150]))
        if i % 5 == 0:
            body[2:2] = passage
        rows.append((i, " ".join(body), rng.choice(["en", "de"]), f"s{i % 4}", None))
    for i in range(60, 75):
        body = rows[i % 7 + 1][1].split(" ")
        if i % 2:
            body[len(body) // 2] = "changed"
        rows.append((i, "\n".join(body) if i % 3 else " ".join(body).upper(), "en", "s0", 1))
    rows += [(100, None, "en", "s1", None), (101, "", None, "s1", None), (102, " \t\n", "en", None, None), (103, LONG, "en", "s0", None), (104, "é ß 中文 \u0001", "de", "s0", None), rows[3], rows[3], (None, rows[4][1], None, None, None)]
    return spark.createDataFrame(rows, SCHEMA), rows


@pytest.fixture(scope="module")
def empty(spark):
    return spark.createDataFrame([], SCHEMA)


def plain(df):
    return df.collect()


# ---------------------------------------------------------------- hashes


def test_words_of_a_buffer_are_the_texts_words():
    rng = random.Random(1)
    texts = ["".join(rng.choice("ab \t\né\x0b\x1c") for _ in range(rng.randint(0, 30))) for _ in range(300)] + [None, "", " "]
    raw, offsets = shared.text_buffer(pa.array(texts).slice(5))
    start, end, first = shared.spans(raw, offsets)
    got = [[bytes(raw[start[k] : end[k]]).decode() for k in range(a, b)] for a, b in zip(first, first[1:])]
    assert got == [WORD.findall(t or "") for t in texts[5:]]


def test_hashes_tell_words_and_windows_apart():
    rng = random.Random(2)
    words = ["".join(rng.choice("abc") for _ in range(rng.randint(1, 5))) for _ in range(3000)]
    raw, offsets = shared.text_buffer(pa.array([" ".join(words)]))
    start, end, first = shared.spans(raw, offsets)
    h = shared.Hasher(3)
    value = h.words(raw, start, end)
    assert len(set(zip(words, value.tolist()))) == len(set(words)) == len(set(value.tolist()))
    for width in (1, 2, 5):
        win = h.windows(value, width)
        seq = [tuple(words[i : i + width]) for i in range(len(words) - width + 1)]
        assert len(set(zip(seq, win.tolist()))) == len(set(seq)) == len(set(win.tolist()))


def test_components(spark):
    rng = random.Random(4)
    links = [(rng.randrange(200), rng.randrange(200)) for _ in range(150)] + [(300 + i, 301 + i) for i in range(40)]
    parent = {i: i for i in range(400)}

    def find(x):
        while parent[x] != x:
            x = parent[x]
        return x

    for a, b in links:
        a, b = sorted((find(a), find(b)))
        parent[b] = a
    nodes = spark.createDataFrame([(i,) for i in range(400)], "id long")
    got = {r.id: r.component for r in shared.components(nodes, spark.createDataFrame(links, "a long, b long")).collect()}
    assert got == {i: find(i) for i in range(400)}


# ---------------------------------------------------------------- 1


def test_lattice_points_are_nearest():
    rng = np.random.default_rng(0)
    x = rng.normal(size=(200, 8)) * 2
    p = lattice_dedup.decode(x)
    twice = np.rint(2 * p).astype(int)
    assert np.allclose(2 * p, twice) and all(len(set(r % 2)) == 1 for r in twice) and (p.sum(1) % 2 == 0).all()
    near = lattice_dedup.shortest_vectors()
    assert near.shape == (240, 8) and np.allclose((near**2).sum(1), 2)
    own = ((x - p) ** 2).sum(1)
    assert all(own[i] <= ((x[i] - p[i] - near) ** 2).sum(1).min() + 1e-9 for i in range(len(x))) and own.max() <= 1 + 1e-9


def test_linked_vectors_equal_brute_force(spark):
    rng = np.random.default_rng(5)
    rows, base = [], rng.normal(size=(12, 24))
    for i in range(160):
        v = base[i % 12] + rng.normal(size=24) * rng.choice([0.0, 0.05, 0.15, 1.0])
        rows.append((i, [float(x) for x in v], int(i % 3)))
    rows += [(200, rows[0][1], 0), (201, rows[0][1], None), (202, None, 1), (203, [0.0] * 24, 1), (204, [float("nan")] + [1.0] * 23, 1), (205, [None] + [1.0] * 23, 1), (206, [], 1), (207, [1.0, 0.0], 1), (208, [2.0, 0.0], 1), (None, rows[0][1], 0), rows[1], (209, [1e-320] * 24, 2), (210, [1e300] * 24, 2)]
    df = spark.createDataFrame(rows, "vec_id long, embedding array<double>, label int").withColumn("component", F.lit("clash"))
    got = {r.vec_id: (r.n_links, r.component_id, r.kept) for r in lattice_dedup.linked_vectors(df).collect()}
    ok = {}
    for i, v, lab in rows:
        if i is None or lab is None or not v or any(x is None or not math.isfinite(x) for x in v) or not any(v):
            continue
        u = np.array(v) / np.abs(v).max()
        ok[i] = (lab, u / np.linalg.norm(u))
    links = {i: {j for j in ok if j != i and ok[i][0] == ok[j][0] and len(ok[i][1]) == len(ok[j][1]) and ok[i][1] @ ok[j][1] >= 0.98} for i in ok}
    assert sum(map(len, links.values())) > 40
    for i in {r[0] for r in rows} - {None}:
        seen, todo = {i}, [i]
        while todo:
            for j in links.get(todo.pop(), ()):
                if j not in seen:
                    seen.add(j)
                    todo.append(j)
        assert got[i] == (len(links.get(i, ())), min(seen), min(seen) == i), i
    assert got[None] == (0, None, None)


@pytest.mark.parametrize("blocks", [1, 2, 3, 4])
def test_pairs_at_the_threshold_meet_and_others_hardly(blocks):
    rng = np.random.default_rng(blocks)
    least = math.ceil(lattice_dedup.SELECTIVITY ** (blocks - 0.5))
    assert lattice_dedup.plan_of(least) == (blocks, tables := 4 << (blocks - 1))
    for dim in (16, 64, 384):
        u = rng.standard_normal((600, dim))
        u /= np.linalg.norm(u, axis=1, keepdims=True)
        w = rng.standard_normal((600, dim))
        w -= (w * u).sum(1, keepdims=True) * u
        w /= np.linalg.norm(w, axis=1, keepdims=True)
        v = 0.98 * u + math.sqrt(1 - 0.98**2) * w
        met, chance = np.zeros(600, bool), 0
        for t in range(tables):
            a, b = (lattice_dedup.cells(x, t, blocks, lattice_dedup.PROBES, lattice_dedup.SCALE) for x in (u, v))
            met |= (a[:, :1] == b).any(1) | (b[:, :1] == a).any(1)
            other = np.roll(v, 1, 0)
            c = lattice_dedup.cells(other, t, blocks, lattice_dedup.PROBES, lattice_dedup.SCALE)
            chance += int((a[:, :1] == c).any(1).sum())
        assert met.mean() >= 0.98
        assert chance <= 600 * tables * 4 / lattice_dedup.SELECTIVITY**blocks + 3


def test_links_with_more_blocks(spark):
    """The plans of larger inputs find the links of the brute force as well."""
    rng = np.random.default_rng(8)
    base = rng.normal(size=(40, 48))
    vectors = [base[i % 40] + rng.normal(size=48) * rng.choice([0.02, 0.06, 0.1, 0.2]) for i in range(300)]
    unit = np.array([v / np.linalg.norm(v) for v in vectors])
    want = np.argwhere(np.triu(unit @ unit.T >= 0.98, 1))
    df = spark.createDataFrame([(i, [float(x) for x in v], 1) for i, v in enumerate(vectors)], "vec_id long, embedding array<double>, label int")
    for plan in ((2, 8), (3, 16)):
        got = sum(r.n_links for r in lattice_dedup.linked_vectors(df, plan=plan).collect()) / 2
        assert len(want) > 100 and 0.9 * len(want) <= got <= len(want)


# ---------------------------------------------------------------- 2


def test_context_tree_is_a_distribution_and_beats_the_base(spark, docs):
    df, rows = docs
    a = plain(context_tree.score(df, context_tree.fold() == context_tree.HELD))
    assert len(a) == len(rows)
    learn = [r for r in rows if zlib.crc32(str("" if r[0] is None else r[0]).encode()) % 5 != 1]
    c = Counter(w for r in learn for w in WORD.findall(low(r[1])))
    n, v = sum(c.values()) + len(learn), len(c) + 1
    want = Counter()
    for i, text, *_ in rows:
        t = WORD.findall(low(text))
        base = sum(math.log10((c[w] + 0.5) / (n + 0.5 * (v + 1))) for w in t) + math.log10((len(learn) + 0.5) / (n + 0.5 * (v + 1)))
        want[i, len(t) + 1, sum(c[w] > 0 for w in t) + 1, n, round(base, 6)] += 1
    assert Counter((r.doc_id, r.n_tokens, r.n_known, r.train_tokens, round(r.base_score, 6)) for r in a) == want
    assert all(r.score < 0 for r in a)


def test_chances_of_all_bytes_sum_to_one():
    stream = np.frombuffer(b"\n\nabab abac \nabcab \n", np.uint8)
    value = context_tree.grams(stream, 2)
    known, n = np.unique(value, return_counts=True)
    context = int(value[5]) >> 8
    every = np.array([(context << 8) | b for b in range(256)])
    all_grams = np.unique(np.concatenate([known, every]))
    counts = np.array([dict(zip(known.tolist(), n.tolist())).get(g, 0) for g in all_grams.tolist()])
    near = all_grams >> 16
    total, tops = 0.0, []
    for byte in np.unique(near):
        mine = near == byte
        chance, top = context_tree.weigh_subtree(all_grams[mine], counts[mine], 2)
        tops.append(top)
        if byte == context >> 8:
            own = np.isin(all_grams[mine], every)
            total = chance[own].prod(1).sum()
    assert total == pytest.approx(1.0)


def slow_ctw(data, ctx_of, depth):
    """Weighted probability of one binary sequence under contexts of up to `depth` symbols, by the recursion itself."""

    def kt(bits):
        p, n = 0.0, [0, 0]
        for b in bits:
            p += math.log((n[b] + 0.5) / (sum(n) + 1))
            n[b] += 1
        return p

    def weigh(ctx):
        bits = [b for c, b in data if ctx_of(c)[: len(ctx)] == ctx]
        own = kt(bits)
        if len(ctx) == depth:
            return own
        nexts = {ctx_of(c)[: len(ctx) + 1] for c, _ in data if ctx_of(c)[: len(ctx)] == ctx}
        return np.logaddexp(own, sum(weigh(x) for x in nexts)) - math.log(2)

    return weigh(())


def test_weighting_equals_the_recursion():
    rng = random.Random(3)
    text = bytes([10, 10, *(rng.choice(b"ab") for _ in range(40))])
    value = context_tree.grams(np.frombuffer(text, np.uint8), 2)
    g, n = np.unique(value, return_counts=True)
    near = g >> 16
    got = {}
    for byte in np.unique(near):
        _, (node, n0, n1, weighted) = context_tree.weigh_subtree(g[near == byte], n[near == byte], 2)
        got[int(byte)] = dict(zip(node.tolist(), weighted.tolist()))
    data = [((int(x) >> 16, (int(x) >> 8) & 255), int(x) & 255) for x in value]
    for byte in got:
        first_bits = [(c, b >> 7) for c, b in data if c[0] == byte]
        want = slow_ctw([((c[1],), b) for c, b in first_bits], lambda c: c, 1)
        assert got[byte][1] == pytest.approx(want)


def slow_scores(learned, texts, depth):
    """log10 chance of each text under the weighted tree, from counts in dictionaries and the mixture's recursion."""
    code = lambda t: b"".join(low(w).encode() + b" " for w in WORD.findall(t or "")) + b"\n"
    n = Counter()
    for t in learned:
        s = b"\n" * depth + code(t)
        for i in range(depth, len(s)):
            for k in range(8):
                for d in range(depth + 1):
                    n[s[i - d : i], (s[i] | 256) >> (8 - k), (s[i] >> (7 - k)) & 1] += 1
    inner = {}
    for c, node, _ in n:
        if c:
            inner.setdefault((c[1:], node), set()).add((c, node))

    def kt(c, node):
        a, b = n[c, node, 0], n[c, node, 1]
        return math.lgamma(a + 0.5) + math.lgamma(b + 0.5) - math.lgamma(a + b + 1) - math.log(math.pi)

    known = {}

    def weigh(c, node):
        if (c, node) not in known:
            known[c, node] = kt(c, node) if len(c) == depth else np.logaddexp(kt(c, node), sum(weigh(*x) for x in inner.get((c, node), ()))) - math.log(2)
        return known[c, node]

    def chance(s, i, k, d):
        c, node, bit = s[i - d : i], (s[i] | 256) >> (8 - k), (s[i] >> (7 - k)) & 1
        p = (n[c, node, bit] + 0.5) / (n[c, node, 0] + n[c, node, 1] + 1)
        if d == depth:
            return p
        own = math.exp(kt(c, node) - math.log(2) - weigh(c, node))
        return own * p + (1 - own) * chance(s, i, k, d + 1)

    out = []
    for t in texts:
        s = b"\n" * depth + code(t)
        out.append(sum(math.log10(chance(s, i, k, 0)) for i in range(depth, len(s)) for k in range(8)))
    return out


def test_scores_of_whole_texts_equal_the_slow_model(spark, docs):
    _, rows = docs
    some = [(i, (t or "")[:300] if t else t) for i, t, *_ in rows[:30] + rows[-12:] if t != LONG]
    df = spark.createDataFrame(some, "doc_id long, text string").withColumn("score", F.lit("clash")).withColumn("chunk", F.lit("clash"))
    got = sorted((str(r.doc_id), r.score) for r in context_tree.score(df, context_tree.fold() == context_tree.HELD).collect())
    learned = [t for i, t in some if zlib.crc32(str("" if i is None else i).encode()) % 5 != 1]
    want = sorted(zip((str(i) for i, _ in some), slow_scores(learned, [t for _, t in some], context_tree.DEPTH)))
    assert [g[0] for g in got] == [w[0] for w in want]
    assert [g[1] for g in got] == pytest.approx([w[1] for w in want], rel=1e-5)


# ---------------------------------------------------------------- 3

PATTERNS = [("email", r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+"), ("ip", r"[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)"), ("card", r"[0-9]([\x20-]?[0-9])+"), ("phone", r"\+[0-9][\x20().0-9-]+[0-9]")]


def luhn(digits):
    total = 0
    for i, c in enumerate(reversed(digits)):
        x = int(c) * (1 + i % 2)
        total += x - 9 * (x > 9)
    return total % 10 == 0


def base_spans(text):
    out = []
    for rank, (kind, pattern) in enumerate(PATTERNS):
        for m in re.finditer(pattern, text or ""):
            digits = re.sub("[^0-9]", "", m[0])
            if (kind == "ip" and any(int(x) > 255 for x in m[0].split("."))) or (kind == "card" and not (12 <= len(digits) <= 19 and luhn(digits))) or (kind == "phone" and not 9 <= len(digits) <= 15):
                continue
            out.append((m.start(), rank, f"{kind}:{m.start()}:{m.end()}"))
    return ",".join(x[2] for x in sorted(out))


def test_base_spans_equal_the_grammar(spark):
    rng = random.Random(1)
    texts = ["a@b.c%d@e.f", "x@y@z.com", "x@y_z@w.com", "1.2.3.4.5.6.7.8", "1.2.3.256 9.9.9.9", "4465758382889437", "4465 7583-8288 9437 1", "5 4465758382889437", "é😀 a@b.co 😀 10.0.0.1", "1" * 5000, "a." * 5000 + "@b.c", "+" + "1 " * 3000, "000.0255.1.1", "\u0001a@b.c\u0001 1.1.1.1", "", None]
    texts += ["".join(rng.choice(a) for _ in range(60)) for a in ("a1.@+- ()9%_é", "0123456789 -+.") for _ in range(700)]
    df = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    for r in df.select("doc_id", private_terms.joined(private_terms.base_spans(F.col("text"))).alias("s")).collect():
        assert (r.s or "") == base_spans(texts[r.doc_id]), texts[r.doc_id]


def test_revealing_terms_are_found_and_masked(spark):
    rng = random.Random(9)
    words = ["wort", "haus", "baum", "licht", "wasser", "stein", "feld", "berg"]
    fill = lambda n: " ".join(rng.choice(words) for _ in range(n))
    rows = [(i, f"{fill(30)} ask Zorbinski at zor@site.org or else {fill(30)}" if i < 4 else fill(60) + (" at or ask else" if i % 2 else "")) for i in range(60)]
    df = spark.createDataFrame(rows, "doc_id long, text string").withColumn("base_x", F.lit(1))
    out = private_terms.with_spans(df).select("doc_id", "text", private_terms.all_spans(F.col("base"), F.col("terms")).alias("s")).withColumn("clean", private_terms.sanitised(F.col("text"), F.col("s"))).collect()
    for r in out:
        kinds = {(x.kind, x.value) for x in r.s}
        assert kinds == ({("email", "zor@site.org"), ("term", "remove:Zorbinski")} if r.doc_id < 4 else set())
        assert ("Zorbinski" in r.clean, "[EMAIL]" in r.clean) == (False, r.doc_id < 4)


def test_terms_go_wherever_they_stand(spark):
    """A disclosing term is removed far from its entity, and in documents that do not hold the entity."""
    filler = "wort haus baum licht wasser stein feld berg "
    rows = [(i, f"{filler * 3}v{'abcd'[i]}xyz Zorbinski at zor@site.org {filler * 6} later Zorbinski spoke") for i in range(4)] + [(4, f"{filler} only Zorbinski here"), (5, f"{filler} at later spoke only here")] + [(6 + i, f"at later {filler * 20}") for i in range(20)]
    df = spark.createDataFrame([(*r, "b", "t", "k") for r in rows], "doc_id long, text string, base string, Terms string, text_key string")
    with pytest.raises(ValueError):
        private_terms.with_spans(df)
    for r in private_terms.stage(spark, df, "").collect():
        assert "zorbinski" not in r.text.lower() and ("[EMAIL]" in r.text) == (r.doc_id < 4) and (r.base, r.Terms, r.text_key) == ("b", "t", "k")
        assert r.doc_id < 5 or r.text == dict(rows)[r.doc_id]


def test_disclosure_equals_brute_force(spark):
    import regex

    rng = random.Random(31)
    people = [f"{a}{b}" for a in ("zor", "kel", "Mur") for b in ("binski", "dano", "vale")]
    fill = "wort haus baum licht wasser stein feld berg, no; a if x".split()
    texts = []
    for i in range(120):
        who = rng.choice(people)
        body = rng.choices(fill, k=rng.randint(2, 40))
        if i % 3:
            body[rng.randrange(len(body)) :] = [who, rng.choice(["at", "mail:", "x=" + who]), f"{who.lower()}@site.org", *rng.choices(fill + people[:2], k=rng.randint(0, 9))]
        texts.append(" ".join(body))
    texts += texts[:20] + [None, "", "x" * 500 + " a@b.co " + "y" * 200]
    contexts, runs = set(), Counter()
    for t in texts:
        runs.update(w.lower() for w in regex.findall(private_terms.TERM, t or ""))
        for kind_span in filter(None, base_spans(t).split(",")):
            _, start, end = kind_span.split(":")
            start, end = int(start), int(end)
            low_at = max(0, start - private_terms.REACH)
            before = [m for m in regex.finditer(private_terms.TERM, t[low_at:start]) if m.start() > 0 or low_at == 0]
            after = [m for m in regex.finditer(private_terms.TERM, t[end : end + private_terms.REACH]) if m.end() < private_terms.REACH]
            words = [m[0].lower() for m in before[::-1][: private_terms.NEAR] + after[: private_terms.NEAR]]
            contexts |= {(t[start:end].lower(), " ".join(words), w) for w in words}
    n_te = Counter((e, w) for e, _, w in contexts)
    n_e = Counter(e for e, _ in {(e, c) for e, c, _ in contexts})
    total, want = sum(runs.values()), {}
    for (e, w), n in n_te.items():
        if n >= private_terms.SUPPORT:
            share = math.log2(n * total / (max(n, runs[w]) * n_e[e])) / max(math.log2(total / n_e[e]), 1e-9)
            if share >= private_terms.GENERALISE:
                want[e, w] = round(share, 9)
    df = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    got = private_terms.revealing_terms(df, private_terms.entity_contexts(df)).collect()
    assert {(r.entity, r.term): round(r.disclosure, 9) for r in got} == want and len(want) > 4 and {r.action for r in got} == {"remove", "generalise"}
    gone = {w: max(r.action for r in got if r.term == w) for _, w in want}
    for r in private_terms.with_spans(df).select("doc_id", "terms").collect():
        spans = [(m.start(), m.end(), f"{gone[m[0].lower()]}:{m[0]}") for m in regex.finditer(private_terms.TERM, texts[r.doc_id] or "") if m[0].lower() in gone]
        assert [(x.start, x.end, x.value) for x in r.terms] == spans


def test_places_of_very_many_matches(spark):
    rng = random.Random(5)
    texts = ["é" + "".join(rng.choice(["a@b.co ", "é😀 ", "x "]) for _ in range(n)) for n in (0, 60, 126, 127, 128, 129, 300, 5000)] + ["1.2.3.4 " * 20_000]
    df = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    for r in df.select("doc_id", private_terms.joined(private_terms.base_spans(F.col("text"))).alias("s")).collect():
        assert r.s == base_spans(texts[r.doc_id])


def test_terms_glued_into_tokens_are_found(spark):
    rows = [(i, f"{'wort haus baum ' * 20}v{i} name:zorbinski,mail:zor@site.org;w{'abcdef'[i]}xyz") for i in range(6)]
    df = spark.createDataFrame(rows, "doc_id long, text string")
    for r in private_terms.with_spans(df).select("terms").collect():
        assert "remove:zorbinski" in {x.value for x in r.terms}


def test_private_terms_on_odd_rows(spark, docs, empty):
    df, rows = docs
    assert private_terms.with_spans(df).count() == len(rows)
    assert private_terms.stage(spark, df, "").columns == df.columns
    assert private_terms.with_spans(empty).count() == 0


# ---------------------------------------------------------------- 4


def test_repeats_equal_brute_force(spark, docs):
    df, rows = docs
    for window in (50, 7):
        least = {}
        words = [(2**63 - 1 if i is None else i, WORD.findall(t or "")) for i, t, *_ in rows]
        for i, w in words:
            for k in range(len(w) - window + 1):
                key = tuple(w[k : k + window])
                least[key] = min(i, least.get(key, i))
        want = Counter()
        for i, w in words:
            gone = [False] * len(w)
            for k in range(len(w) - window + 1):
                if least[tuple(w[k : k + window])] < i:
                    gone[k : k + window] = [True] * window
            kept = " ".join(x for x, g in zip(w, gone) if not g)
            want[i, len(w), sum(gone), hashlib.sha256(kept.encode()).hexdigest()] += 1
        got = Counter((2**63 - 1 if r.doc_id is None else r.doc_id, r.n_words, r.n_removed, r.kept_sha256) for r in substring.remove_repeats(df, window).collect())
        assert got == want


# ---------------------------------------------------------------- 5


def test_chain_learns_and_leaves_clean_rows(spark):
    rng = random.Random(8)
    words = ["".join(rng.choice("aeiourst") for _ in range(5)) for _ in range(80)]
    rows, labels = [], []
    for i in range(600):
        bad, poor = i % 6 == 0, i % 6 == 0 or i % 4 == 0
        text = rng.choices(words, k=30) + (["vilestem" + rng.choice("abcd") * 2] if bad else []) + (["###", "junk"] if poor else [])
        rng.shuffle(text)
        rows.append((i, " ".join(text), "x"))
        if i % 2 == 0 or i % 3 == 0:
            labels.append((i, int(poor), int(bad)))
    labels += [(1, None, 1), (7, 1, 0), (7, 0, 0), (None, 1, 1)]
    df = spark.createDataFrame([*rows, (900, None, "x"), (901, "", None), (None, "vilestema", None)], "doc_id long, text string, toxic string")
    lab = spark.createDataFrame(labels, "doc_id long, low_quality int, toxic int")
    model = toxicity.learn(df, lab)
    got = {r.doc_id: (r.p_low_quality, r.toxic) for r in toxicity.predict(df, model).collect()}
    held = [i for i in range(600) if not (i % 2 == 0 or i % 3 == 0)]
    assert all(not got[i][1] for i in held) and all(got[i][1] for i in range(0, 600, 6)) and not got[900][1] and not got[901][1]
    nothing = toxicity.learn(df.limit(0), lab)
    assert toxicity.predict(df.limit(0), nothing).count() == 0


# ---------------------------------------------------------------- 6


def water(sizes, weights, epochs=3):
    """Clamp and redistribute until nothing is above its cap."""
    total, capped = sum(sizes.values()), set()
    while True:
        rest = total - sum(epochs * sizes[s] for s in capped)
        share = sum(weights[s] for s in sizes if s not in capped)
        targets = {s: epochs * sizes[s] if s in capped else weights[s] * rest / share for s in sizes}
        over = {s for s in sizes if s not in capped and targets[s] > epochs * sizes[s] + 1e-9}
        if not over:
            return targets
        capped |= over


def test_mix_equals_the_loop(spark, docs):
    df, rows = docs
    sizes = Counter()
    for _, text, _, source, _ in rows:
        sizes[source] += len(WORD.findall(text or ""))
    order = sorted([s for s in sizes if s is not None]) + [None]
    weights = {s: 1 + k % 3 for k, s in enumerate(order)}
    out = mixing.mix(df, keep=["source"]).collect()
    again = mixing.mix(df.repartition(7), keep=["source"]).collect()
    assert Counter(map(str, out)) == Counter(map(str, again)) and len(out) == len(rows)
    want, taken, most = water(sizes, weights), Counter(), Counter()
    for r in out:
        assert r.target == pytest.approx(want[r.source]) and r.source_size == sizes[r.source] and r.taken <= 3 * r["size"]
        taken[r.source] += r.taken
        most[r.source] = max(most[r.source], r["size"])
    assert all(abs(taken[s] - want[s]) <= most[s] for s in sizes)


def test_water_fill_with_several_clamps(spark):
    sizes = {"a": 1, "b": 2, "c": 1000, "d": 0, "e": 400}
    weights = {"a": 1, "b": 3, "c": 1, "d": 2, "e": 5}
    df = spark.createDataFrame([(s, n, weights[s]) for s, n in sizes.items()], "source string, source_size long, weight long")
    got = {r.source: r.target for r in mixing.water_fill(df).collect()}
    assert got == pytest.approx(water(sizes, weights))


# ---------------------------------------------------------------- 7


def jaccard_truth(rows):
    sets = {}
    for i, text, *_ in rows:
        w = WORD.findall(low(text))
        if i is not None:
            sets[i] = frozenset(tuple(w[k : k + 5]) for k in range(len(w) - 4)) if len(w) >= 5 else frozenset([tuple(w)] if w else [])
    parent = {i: i for i in sets}

    def find(x):
        while parent[x] != x:
            x = parent[x]
        return x

    ids = sorted(sets)
    for x, a in enumerate(ids):
        for b in ids[:x]:
            common = len(sets[a] & sets[b])
            if sets[a] and sets[b] and 100 * common >= 80 * (len(sets[a]) + len(sets[b]) - common):
                p, q = sorted((find(a), find(b)))
                parent[q] = p
    return {i: (len(sets[i]), find(i)) for i in ids}


def test_near_duplicates_equal_brute_force(spark, docs):
    df, rows = docs
    got = {(r.doc_id, r.n_shingles, r.component_id) for r in jaccard.near_duplicates(df).collect() if r.doc_id is not None}
    assert got == {(i, *x) for i, x in jaccard_truth(rows).items()}


def test_near_duplicate_chains(spark):
    """Texts that drift word by word: neighbours link, ends do not, and shared passages link nothing."""
    rng = random.Random(21)
    words = [f"w{k}" for k in range(5000)]
    rows, body = [], rng.choices(words, k=120)
    for i in range(30):
        rows.append((i, " ".join(body)))
        body = list(body)
        for _ in range(rng.choice([1, 2, 4])):
            body[rng.randrange(len(body))] = rng.choice(words)
    passage = rng.choices(words, k=60)
    rows += [(100 + i, " ".join(passage + rng.choices(words, k=rng.choice([5, 12, 20, 60])))) for i in range(30)]
    rows += [(200 + i, " ".join(rng.choices(["a", "b"], k=rng.randint(1, 12)))) for i in range(60)]
    df = spark.createDataFrame(rows, "doc_id long, text string")
    got = {(r.doc_id, r.n_shingles, r.component_id) for r in jaccard.near_duplicates(df).collect()}
    assert got == {(i, *x) for i, x in jaccard_truth(rows).items()}


def test_clusters_of_near_copies(spark):
    """Clusters whose members resemble their hub from hardly to nearly: rounds of stars, the metric's bound and the last pairs."""
    rng = random.Random(17)
    words = [f"w{k}" for k in range(900)]
    rows = []
    for c in range(3):
        base = rng.choices(words, k=110)
        for i in range(60):
            body = list(base)
            for _ in range(rng.choice([1, 3, 6, 9, 14])):
                body[rng.randrange(len(body))] = rng.choice(words)
            rows.append((1000 * c + i, " ".join(body[: rng.choice([110, 110, 95])])))
    rng.shuffle(rows)
    df = spark.createDataFrame(rows, "doc_id long, text string")
    got = {(r.doc_id, r.n_shingles, r.component_id) for r in jaccard.near_duplicates(df).collect()}
    want = {(i, *x) for i, x in jaccard_truth(rows).items()}
    assert got == want and 20 < len({x[2] for x in want}) < 160


def test_similar_sets_share_a_signature():
    rng = np.random.default_rng(6)
    for size in (1, 2, 4, 5, 8, 12, 20, 33, 36, 50, 90, 200, 700):
        for _ in range(20):
            a = rng.integers(0, 2**63, size, dtype=np.uint64)
            common = math.ceil(0.8 * size)
            extra = rng.integers(0, min(size - common, (common * 5 - size * 4) // 4) + 1 if common * 5 >= size * 4 else 1)
            b = np.concatenate([a[:common], rng.integers(0, 2**63, extra, dtype=np.uint64)])
            i = common
            if 100 * i < 80 * (len(a) + len(b) - i):
                continue
            value = np.concatenate([np.sort(a), np.sort(b)])
            for part in (0.0, 0.1, 0.4, 0.9):
                heavy = jaccard.Heavy(value[rng.random(len(value)) < part])
                sig, which = jaccard.signatures(value, np.array([0, len(a), len(a) + len(b)]), 80, heavy)
                assert set(sig[which == 0].tolist()) & set(sig[which == 1].tolist())


def test_sketches_never_exceed_the_difference():
    rng = np.random.default_rng(7)
    for _ in range(50):
        a = rng.integers(0, 2**63, rng.integers(1, 900), dtype=np.uint64)
        b = np.concatenate([a[: rng.integers(0, len(a) + 1)], rng.integers(0, 2**63, rng.integers(1, 3000), dtype=np.uint64)])
        p, q = jaccard.parity(np.concatenate([a, b]), np.array([0, len(a), len(a) + len(b)]))
        differ = sum(int(x).bit_count() for x in (p ^ q).view(np.uint64))
        assert differ <= len(set(a.tolist()) ^ set(b.tolist())) and (len(b) > 600 or differ > 0)


# ---------------------------------------------------------------- 8


def test_automaton_accepts_exactly_the_substrings():
    text = b"abcbcabab"
    moves = language.suffix_automaton(text)

    def accepts(s):
        at = 0
        for c in s:
            if c not in moves[at]:
                return False
            at = moves[at][c]
        return True

    rng = random.Random(1)
    for _ in range(500):
        s = bytes(rng.choice(b"abc") for _ in range(rng.randint(1, 6)))
        assert accepts(s) == (s in text)


def test_phrases_are_longest_matches():
    refs = {"x": b"the cat sat on the mat", "y": b"der hund sass auf der matte"}
    model = language.parse_tables(refs)
    rng = random.Random(3)
    texts = ["the mat sat", "der matte hund", "zzz", "", refs["x"].decode() * 2] + ["".join(rng.choice("the cat der hund ") for _ in range(rng.randint(1, 60))).strip() for _ in range(60)]
    texts = [" ".join(t.split()) for t in texts]
    raw, offsets = language.folded_bytes(pa.array(texts))
    got = language.count_phrases(model, raw, offsets, 10_000)
    for segment in (1, 2, 3, 5):  # parses of segments are joined exactly
        assert (language.count_phrases(model, raw, offsets, segment) == got).all()
    for t, row in zip(texts, got):
        for lang, n in zip(model["langs"], row):
            want, phrase = (1, b"") if t else (0, b"")
            for c in t.encode():
                longer = phrase + bytes([c])
                if longer in refs[lang]:
                    phrase = longer
                else:
                    want += 1
                    phrase = bytes([c]) if bytes([c]) in refs[lang] else b""
            assert n == want


def test_languages_of_odd_rows(spark, docs, empty):
    df, rows = docs
    out = language.identify(df.select("doc_id", "text"), {"en": b"the cat sat", "de": b"der hund sass"}).collect()
    assert len(out) == len(rows) and all(0 <= r.score <= 1 for r in out)
    assert {r.lang_pred for r in out if r.doc_id in (100, 101, 102)} == {"und"}
    assert {r.lang_pred for r in language.identify(df.select("doc_id", "text"), {}).collect()} == {"und"}
    assert language.stage(spark, empty, "").count() == 0 and language.reference_texts(empty) == {}


def test_held_out_accuracy(spark):
    d = "/root/testdata/sf0.01"
    truth = {r.doc_id: r.lang for r in spark.read.parquet(f"{d}/documents.parquet").collect()}
    held = [r for r in language.query(spark, d).collect() if r.held_out]
    assert sum(r.lang_pred == truth[r.doc_id] for r in held) >= 0.98 * len(held)


# ---------------------------------------------------------------- 9


def test_licences_are_recognised_and_confirmed(spark, empty):
    lines = ["Released under the MIT License.", "Licensed under the Apache License, Version 2.0.", "Licensed under CC BY-NC 4.0.", "A fishing licence is needed here.", "nothing at all", None, "", "This work is licensed under the GNU General Public License, version 3.\nAnd more\n" + LONG]
    df = spark.createDataFrame(list(enumerate(lines)), "doc_id long, text string").withColumn("found", F.lit(1))
    got = {r.doc_id: [(x.family, x.confirmed) for x in r.found] for r in licences.classified(df).collect()}
    assert got == {0: [("MIT", True)], 1: [("Apache-2.0", True)], 2: [("CC-BY-NC-4.0", True)], 3: [("unknown", False)], 4: [], 5: [], 6: [], 7: [("GPL-3.0", True)]}
    assert licences.classified(empty).count() == 0


def test_every_notice_passes_the_cue(spark):
    texts = sorted({t for _, t in licences.notices()})
    assert all(re.search(licences.CUE, x) for t in texts for x in (t, t.lower(), t.replace(" ", "\n")))
    assert not re.search(licences.CUE, "er kam mit dem Zug")
    lines = {"Released under the GPLv3.": "GPL-3.0", "Released under the MIT.": "MIT", "Distributed under the terms of the Apache-2.0.": "Apache-2.0", "You may use this file under the MPL-2.0.": "MPL-2.0", "Released under the CC-BY-4.0.": "CC-BY-4.0"}
    df = spark.createDataFrame(list(enumerate(lines)), "doc_id long, text string")
    got = {r.doc_id: [(x.family, x.confirmed) for x in r.found] for r in licences.classified(df).collect()}
    assert got == {k: [(family, True)] for k, family in enumerate(lines.values())}


def test_wrapped_licences_are_confirmed(spark):
    import textwrap

    want, rows = {}, []
    for family, (passage, *_) in licences.PASSAGES.items():
        assert len(passage.split()) <= licences.REACH
        for width in (75, 40):
            for lead in ("", " * ", "# "):
                body = "\n".join(lead + line for line in textwrap.wrap(passage, width))
                rows += [body, f"Copyright 2020 the authors.\n\n{body}\n\nAnd more."]
                want[len(rows) - 2] = want[len(rows) - 1] = family
    rows += ["Released under the\nMIT License.", "Licensed under the MIT License.\nLicensed under the Apache License, Version 2.0.", "one\n\nA fishing licence\nis needed in this river.\n \ntwo"]
    df = spark.createDataFrame(list(enumerate(rows)), "doc_id long, text string").repartition(4)
    got = {r.doc_id: {x.family for x in r.found if x.confirmed} for r in licences.classified(df).collect()}
    assert {k: got[k] for k in want} == {k: {f} for k, f in want.items()}
    assert [got[k] for k in range(len(want), len(rows))] == [{"MIT"}, {"MIT", "Apache-2.0"}, set()]


def slow_scan(text, m):
    """The licence scan of one text in plain loops."""
    lines = (text or "").split("\n")
    wordy = [bool(re.search(licences.WORDY, x)) for x in lines]
    weights, by_para = m["weights"], {}
    for i in range(len(lines)):
        nxt = i + 1 < len(lines) and wordy[i + 1]
        if not wordy[i] or not re.search(licences.CUE, "\n".join(lines[i : i + 2]) if nxt else lines[i]):
            continue
        end = next((j for j in range(i, len(lines)) if not wordy[j]), len(lines))
        k, n = 0, 0
        for t in lines[i : min(end, i + licences.REACH + 1)]:
            if n >= licences.REACH:
                break
            n, k = n + (len(licences.words_of(t)) if k else 0), k + 1
        for size in dict.fromkeys([1, min(2, end - i), k]):
            if size == 1 and not re.search(licences.CUE, lines[i]):
                continue
            part = "\n".join(lines[i : i + size])
            grams = set(licences.grams_of(part))
            odds = [sum(w) / m["heat"] for w in zip(weights[""], *(weights[g] for g in grams if g in weights))]
            top = max(odds)
            chance = 1 / sum(math.exp(o - top) for o in odds)
            family = m["classes"][odds.index(top)] if chance >= licences.SURE else "unknown"
            line = f" {' '.join(licences.words_of(part))} "
            share = max([len(grams & set(t["grams"])) / len(t["grams"]) for t in licences.templates().get(family, []) if t["name"] in line], default=0.0)
            by_para.setdefault(sum(not w for w in wordy[:i]), []).append((i, i + size, family, chance, share))
    out = []
    for _, ps in sorted(by_para.items()):
        firm = sorted((p for p in ps if p[4] >= licences.CONFIRM), key=lambda p: (-p[4], p[1] - p[0], p[0]))
        first = {}
        for p in firm:
            first.setdefault(p[2], p)
        kept = {}
        for p in firm:
            if not any(q[2] != p[2] and q[4] > p[4] and q[0] < p[1] and p[0] < q[1] for q in first.values()):
                kept.setdefault(p[2], p)
        out += [(*p[:3], True) for p in kept.values()] or [(*min(ps, key=lambda p: (p[2] == "unknown", -p[3], p[0], p[1]))[:3], False)]
    return out


def test_scan_equals_plain_loops(spark):
    import textwrap

    rng = random.Random(41)
    pool = sorted({t for _, t in licences.notices()})
    noise = "the band played on a bridge near some old river with permission of nobody".split()
    texts = []
    for _ in range(150):
        lines = []
        for _ in range(rng.randint(1, 6)):
            kind = rng.random()
            lines += textwrap.wrap(rng.choice(pool), rng.choice([30, 60, 200])) if kind < 0.5 else [rng.choice(["", " \t", "***"])] if kind < 0.7 else [" ".join(rng.choices(noise, k=rng.randint(1, 30)))]
        texts.append("\n".join(lines))
    texts += ["Released under the MIT-style licence of the band.", None, "", "\n", "license", texts[0], "MIT\n" * 200]
    df = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string").withColumn("found", F.lit("clash")).withColumn("a.b", F.lit(1))
    got = {r.doc_id: [(x.line, x.stop, x.family, x.confirmed) for x in r.found] for r in licences.classified(df, keep=("doc_id", "a.b")).collect()}
    m = licences.model()
    assert got == {k: slow_scan(t, m) for k, t in enumerate(texts)}
    assert got[150] == [(0, 1, "unknown", False)]
    assert sum(x[3] for v in got.values() for x in v) > 100


def test_left_out_notices_are_not_learned(monkeypatch):
    """No copy of a text is on both sides of the calibration's split."""
    seen = []
    fit = licences.fit
    monkeypatch.setattr(licences, "fit", lambda rows, steps=80: (seen.append({t for _, t in rows}), fit(rows, 1))[1])
    licences.calibrated(licences.notices())
    assert len(seen) == 2 and not seen[0] & seen[1] and len(seen[0] | seen[1]) == len({t for _, t in licences.notices()})


# ---------------------------------------------------------------- 10


def test_masks_leave_each_position_out_once():
    assert all(len(m) == decontaminate.SPAN for m in decontaminate.MASKS)
    assert all(any(m[k] == "0" for m in decontaminate.MASKS) for k in range(decontaminate.SPAN))


def test_every_accepted_run_keeps_a_seed():
    """All placements of two to four substitutions in items of 12 to 20 words, and exact runs of ten words."""
    for size in (10, 11, *range(12, 21)):
        item = [f"w{k}" for k in range(size)]
        index = decontaminate.build_index([1], [" ".join(item)])
        texts = []
        for n in range(5):
            for gone in itertools.combinations(range(size), n):
                same = np.array([k not in gone for k in range(size)])
                if decontaminate.best_run(same) >= decontaminate.MIN_WORDS:
                    texts.append(" ".join(["x", "y", *(w if s else "other" for w, s in zip(item, same)), "z"]))
        words, first = decontaminate.word_hashes(pa.array(texts, pa.string()))
        got = decontaminate.matches(index, words, first)
        assert all(got.get((t, 0), (0, 0))[1] >= decontaminate.MIN_WORDS for t in range(len(texts))), size
    item = [f"w{k}" for k in range(40)]
    index = decontaminate.build_index([1], [" ".join(item)])
    words, first = decontaminate.word_hashes(pa.array([" ".join(["x"] * 5 + item[k : k + 10] + ["y"] * 5) for k in range(31)], pa.string()))
    assert all(decontaminate.matches(index, words, first)[t, 0][1] == 10 for t in range(31))


def test_hits_equal_brute_force(spark):
    """All alignments of all items, compared word by word, against seeds, diagonals and runs; repeated items and rows, ties."""
    rng = random.Random(14)
    words = [f"w{k}" for k in range(3000)]
    items = [(k, rng.choices(words, k=n)) for k, n in enumerate([5, 6, 7, 8, 9, 10, 11, 12, 14, 18, 25, 30] * 3)]
    items += [(900, items[8][1]), (901, items[3][1]), (4, items[4][1])]
    rows = []
    for i in range(260):
        body = rng.choices(words, k=rng.randint(0, 40))
        item = list(rng.choice(items)[1])
        for _ in range(rng.randint(0, 4)):
            item[rng.randrange(len(item))] = "other"
        cut = rng.choice([0, 0, 0, 1, 3])
        rows.append((i, " ".join(body[:10] + item[cut : len(item) - rng.choice([0, 0, cut])] + body[10:])))
    rows += rows[:5]
    bench = spark.createDataFrame([(k, " ".join(w)) for k, w in items], "item_id long, text string")
    df = spark.createDataFrame(rows, "doc_id long, text string").repartition(3)

    def best(same):
        runs = [(sum(1 if x else -decontaminate.MISS for x in same[i:j]), i, j) for i in range(len(same)) for j in range(i + 1, len(same) + 1)]
        top = max(runs)[0]
        starts_well = lambda i, j: all(sum(1 if x else -decontaminate.MISS for x in same[i:e]) > 0 for e in range(i + 1, j))
        return top, max(sum(same[i:j]) for score, i, j in runs if score == top and starts_well(i, j))

    want = []
    for i, text in rows:
        doc, hit = text.split(), set()
        for k, item in items:
            for d in range(-len(item) + 1, len(doc)):
                a, b = max(0, -d), min(len(item), len(doc) - d)
                same = [item[x] == doc[x + d] for x in range(a, b)]
                if sum(same) < 5:
                    continue
                n = len(item)
                if n < decontaminate.SPAN:
                    ok = b - a == n and sum(same) >= (n - 1 if n >= decontaminate.TOLERANT else n)
                else:
                    ok = best(same)[1] >= decontaminate.MIN_WORDS and best(same)[0] > 0
                if ok:
                    hit.add(k)
        want.append((i, tuple(sorted(hit))))
    got = [(r.doc_id, tuple(r["items"])) for r in decontaminate.contamination(df, bench).collect()]
    assert sorted(got) == sorted(want) and sum(bool(x) for _, x in want) > 100
    assert sorted(r.doc_id for r in decontaminate.contamination(df, bench.union(bench)).where("n_items > 0").collect()) == sorted(i for i, x in want if x)


def test_contamination_tolerates_substitutions(spark, docs, empty):
    rng = random.Random(12)
    words = ["".join(rng.choice("abcdefgh") for _ in range(6)) for _ in range(900)]
    items = [(k, " ".join(rng.choices(words, k=n)) + ".") for k, n in enumerate([30, 25, 40, 6])] + [(50, None), (51, ""), (52, "one two")]
    bench = spark.createDataFrame(items, "item_id long, text string")
    rows = []
    for k, text in items[:3]:
        w = text.split()
        swapped = [x if i % 9 != 4 else "other" for i, x in enumerate(w)]
        rows += [(10 * k, " ".join(rng.choices(words, k=50) + w + rng.choices(words, k=50))), (10 * k + 1, "Intro " + " ".join(swapped).upper()), (10 * k + 2, " ".join(w[5:20])), (10 * k + 3, " ".join(w[:5])), (10 * k + 4, " ".join(rng.choices(words, k=300)))]
    rows += [(90, "before " + items[3][1] + " after"), (91, None), (92, ""), (93, "one two")]
    df = spark.createDataFrame(rows, "doc_id long, text string").withColumn("items", F.lit("clash"))
    got = {r.doc_id: r["items"] for r in decontaminate.contamination(df, bench).collect()}
    for k in range(3):
        assert got[10 * k] == got[10 * k + 1] == got[10 * k + 2] == [k]
        assert got[10 * k + 3] == got[10 * k + 4] == []
    assert got[90] == [3] and got[91] == got[92] == got[93] == []
    assert decontaminate.contamination(df, bench.limit(0)).where("contaminated").count() == 0
    assert decontaminate.contamination(empty, bench).count() == 0


def test_best_run_is_the_best_segment():
    rng = random.Random(2)
    for _ in range(200):
        same = np.array([rng.random() < 0.6 for _ in range(rng.randint(1, 25))])
        best = max((sum(1 if x else -decontaminate.MISS for x in same[i:j]), 0) for i in range(len(same)) for j in range(i + 1, len(same) + 1))[0]
        run = decontaminate.best_run(same)
        assert (run > 0) == (best > 0) and run >= best


# ---------------------------------------------------------------- all


def test_clashing_columns_are_kept(spark, docs):
    """Stages keep extra columns that are called like their own; maps refuse to name two columns alike."""
    df, _ = docs
    names = ["score", "LANG_PRED", "items", "contaminated", "__text", "base", "terms", "text_key", "class", "n", "component_id", "a.b", "bucket", "digest", "size", "taken"]
    wide = df.withColumns({c: F.lit(f"own {c}") for c in names})
    kept = language.text_filter(wide, lambda: lambda texts: np.array([t is not None and len(t) > 20 for t in texts.to_pylist()], bool))
    for out in (kept, private_terms.stage(spark, wide, ""), jaccard.stage(spark, wide, "")):
        assert out.columns == wide.columns
        rows = out.collect()
        assert rows and all(r[c] == f"own {c}" for r in rows for c in names)
    mixed = mixing.mix(wide, keep=[c for c in wide.columns if c not in ("doc_id", "size", "taken")]).collect()
    assert len(mixed) == df.count() and all(r[c] == f"own {c}" for r in mixed for c in names if c not in ("size", "taken"))
    for refused in (lambda: language.identify(wide, {}, ["doc_id", "score"]), lambda: toxicity.predict(wide.withColumn("toxic", F.lit(1)), {"names": ["toxic"]}, ["toxic"])):
        with pytest.raises(ValueError):
            refused()


def test_empty_tables(spark, empty):
    assert context_tree.score(empty, context_tree.fold() == 1).count() == 0
    assert substring.remove_repeats(empty).count() == 0
    assert mixing.mix(empty).count() == 0
    assert jaccard.near_duplicates(empty).count() == 0
    assert lattice_dedup.linked_vectors(spark.createDataFrame([], "vec_id long, embedding array<float>, label int")).count() == 0
