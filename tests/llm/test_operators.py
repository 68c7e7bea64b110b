"""The training-data operators against brute force on small fixtures, with nulls, empty and long texts, ties and repeats."""

import collections
import hashlib
import itertools
import random
import re
import zlib

import numpy as np
import pytest

from crowdlink.llm import bag_minhash, bpe, cap_filters, chat, decontaminate, fm_index, line_dedup, lm_score, near_dup, personal_data, recurrent, toxicity, url_rules
from crowdlink.llm.registry import default_vocabulary

DOCS = "doc_id long, text string, doc string, id long, words string"
WORD = re.compile("[^\x00-\x2f\x3a-\x60\x7b-\x7f]+")


def docs_of(spark, texts):
    """Documents with extra columns whose names clash with inner ones."""
    return spark.createDataFrame([(k, t, "x", 7, None) for k, t in enumerate(texts)], DOCS)


def lowered(text):
    return "".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in text or "")


def words(text):
    return WORD.findall(lowered(text))


def sha(text):
    return hashlib.sha256(text.encode()).hexdigest()


# 1


def test_suffix_order_and_search():
    rng = np.random.default_rng(1)
    for _ in range(30):
        runs = [rng.integers(1, 4, rng.integers(1, 12)) for _ in range(rng.integers(1, 8))]
        text = np.concatenate([np.append(r, 0) for r in runs]).astype(np.int64)
        index = fm_index.FmIndex(text, 3, every=4)
        patterns = [p for n in (1, 2, 3, 4) for p in itertools.product((1, 2, 3), repeat=n)]
        rows, size = np.zeros((len(patterns), 4), np.int64), np.array([len(p) for p in patterns])
        for r, p in zip(rows, patterns, strict=True):
            r[: len(p)] = p
        low, high = index.search(rows, size)
        for p, a, z in zip(patterns, low, high, strict=True):
            expected = [k for k in range(len(text) - len(p) + 1) if tuple(text[k : k + len(p)]) == p]
            assert sorted(index.locate(np.arange(a, z)).tolist()) == expected


def contaminated(text, items, width=10):
    w, hit, found = words(text), set(), set()
    for item, t in items:
        x = words(t)
        for k in range(max(1, len(x) - width + 1) if x else 0):
            win = x[k : k + width]
            for i in range(len(w) - len(win) + 1):
                if w[i : i + len(win)] == win:
                    hit |= set(range(i, i + len(win)))
                    found.add(item)
    return len(w), len(hit), sorted(map(str, found))


def test_decontamination(spark, monkeypatch):
    rnd = random.Random(3)
    vocab = ["The", "of", "é", "x1", "And", "z", "die", "Ä"]
    say = lambda n: " ".join(rnd.choice(vocab) for _ in range(n))
    items = [(k, say(rnd.choice([3, 10, 14, 25]))) for k in range(12)] + [(90, None), (91, ""), (3, "one more text of item three"), (92, "!!")]
    texts = [None, "", "...", *(say(rnd.randint(0, 120)) for _ in range(60))] + [f"Intro, {items[1][1].upper()}! outro {items[1][1]}"] * 2 + [" ".join(t for _, t in items if t) * 40]
    bench = spark.createDataFrame(items, "item_id long, text string")
    got = {r.doc_id: r for r in decontaminate.report(decontaminate.find_spans(docs_of(spark, texts), bench)).collect()}
    for k, t in enumerate(texts):
        n, hit, found = contaminated(t, items)
        assert (got[k].n_words, got[k].n_hit, got[k].n_items, got[k].items_sha256, got[k].contaminated) == (n, hit, len(found), sha(",".join(found)), hit > 0)
    empty = decontaminate.find_spans(docs_of(spark, texts[:5]), bench.limit(0))
    assert {r.n_hit for r in decontaminate.report(empty).collect()} == {0}
    assert decontaminate.report(decontaminate.find_spans(docs_of(spark, texts).limit(0), bench)).count() == 0
    with monkeypatch.context() as m:  # many blocks of the benchmark, one pass for each, give the same
        m.setattr(decontaminate, "BLOCK_BYTES", 150)
        again = {r.doc_id: r for r in decontaminate.report(decontaminate.find_spans(docs_of(spark, texts), bench)).collect()}
    assert again == got
    cleaned = decontaminate.remove(docs_of(spark, texts), bench)
    assert cleaned.columns == ["doc_id", "text", "doc", "id", "words"]
    clean = {r.doc_id: r.text for r in cleaned.collect()}
    for k, t in enumerate(texts):
        n, hit, _ = contaminated(t, items)
        assert (clean[k] == t) if not hit else len(words(clean[k])) == n - hit


# 2


def near(a, b):
    if abs(len(a) - len(b)) > 1 or min(len(a), len(b)) < line_dedup.MIN_WORDS:
        return False
    if len(a) == len(b):
        return sum(x != y for x, y in zip(a, b, strict=True)) <= 1
    long, short = (a, b) if len(a) > len(b) else (b, a)
    return any(long[:k] + long[k + 1 :] == short for k in range(len(long)))


def test_line_dedup(spark):
    rnd = random.Random(4)
    base = [" ".join(rnd.choice("abcdefgh") * rnd.randint(1, 3) for _ in range(rnd.choice([1, 3, 8, 9, 12]))) for _ in range(25)]

    def edited(line):
        w = line.split(" ")
        k = rnd.randrange(len(w))
        return " ".join(rnd.choice([w[:k] + ["q"] + w[k + 1 :], w[:k] + w[k + 1 :] or ["r"], w[:k] + ["s"] + w[k:], w]))

    texts = ["\n".join(rnd.choice([edited(rnd.choice(base)), rnd.choice(base), "", "  "]) for _ in range(rnd.randint(0, 9))) for _ in range(60)] + [None, "", "\n\n"]
    df = docs_of(spark, texts)
    th = {r.doc_id: r.th for r in df.selectExpr("doc_id", "xxhash64(text) th").collect()}
    first = {}
    for k, t in sorted(enumerate(texts), key=lambda x: (x[0], th[x[0]])):
        for no, line in enumerate(t.split("\n") if t is not None else []):
            if line.strip(" "):
                first.setdefault(line.strip(" "), (k, no))
    gone = {a for a, b in itertools.permutations(first, 2) if first[b] < first[a] and near(a.split(" "), b.split(" "))}
    got = {r.doc_id: r for r in line_dedup.report(df).collect()}
    out = {r.doc_id: r.text for r in line_dedup.rewrite(df).collect()}
    for k, t in enumerate(texts):
        lines = t.split("\n") if t is not None else []
        kept = [no for no, x in enumerate(lines) if x.strip(" ") and first[x.strip(" ")] == (k, no) and x.strip(" ") not in gone]
        assert got[k].kept_lines == ",".join(map(str, kept)) and got[k].n_kept == len(kept)
        assert got[k].n_lines == sum(bool(x.strip(" ")) for x in lines)
        assert out[k] == (None if t is None else "\n".join(x for no, x in enumerate(lines) if no in kept or not x.strip(" ")))
    assert line_dedup.rewrite(df.limit(0)).count() == 0 and line_dedup.rewrite(df).columns == df.columns
    twice = line_dedup.report(df.union(df)).collect()
    assert collections.Counter(r.kept_lines for r in twice) == collections.Counter([r.kept_lines for r in got.values()] * 2)


# 3


def test_gradients_of_the_recurrent_model():
    model = recurrent.Recurrent.fresh(10, size=5, classes=3, seed=1)
    model.p = {k: v.astype(np.float64) for k, v in model.p.items()}
    rng = np.random.default_rng(0)
    tokens = rng.integers(0, 11, (6, 3)).astype(np.int32)
    own = np.array([[0, 1, 2]] * 3 + [[3, 1, 2]] * 3)

    before, opens = recurrent._before(tokens, own, 0, 6, 3, 0)
    assert [list(x) for x in opens] == [[True] * 3, [False] * 3, [False] * 3, [True, False, False], [False] * 3, [False] * 3]
    assert list(before[0]) == [0, 0, 0] and list(before[3]) == [0, tokens[2, 1], tokens[2, 2]]

    def forward():
        run = model._forward(before, opens, np.zeros((5, 3)))
        return run, -model.scores(run[-1].transpose(0, 2, 1).reshape(-1, 5), tokens.reshape(-1)).mean()

    grads = model._gradients(tokens, own, before, opens, forward()[0])
    for name in model.p:
        for _ in range(4):
            at = tuple(rng.integers(0, s) for s in model.p[name].shape)
            old = model.p[name][at]
            model.p[name][at] = old + 1e-4
            up = forward()[1]
            model.p[name][at] = old - 1e-4
            down = forward()[1]
            model.p[name][at] = old
            assert grads[name][at] == pytest.approx((up - down) / 2e-4, abs=2e-4)


def test_recurrent_probabilities_sum_to_one_and_state_is_carried():
    model = recurrent.Recurrent.fresh(10, size=6, classes=3)
    h = np.random.default_rng(0).standard_normal((1, 6)).astype(np.float32)
    assert np.exp(model.scores(np.repeat(h, 11, axis=0), np.arange(11))).sum() == pytest.approx(1, abs=1e-4)
    texts = [np.random.default_rng(k).integers(0, 11, n).astype(np.int32) for k, n in enumerate([1, 300, 7, 130])]
    together = model.score_texts(texts, 0)
    assert together == pytest.approx([model.score_texts([t], 0)[0] for t in texts], rel=1e-4)


def test_words_of_texts_equal_those_of_bytes():
    import pyarrow as pa

    rnd = random.Random(8)
    texts = [None, "", " ", "A\x1cB \u00a0É\tc\x0b\x0cD\r\n", "\u2003x", *("".join(rnd.choice("aB \n\u0130ß") for _ in range(rnd.randint(0, 30))) for _ in range(200))]
    expected = [(t or "").encode().lower().split() for t in texts]
    column = pa.array(["x y", *texts]).slice(1)
    words, sizes = lm_score.words_of(column)
    assert words.to_pylist() == [w for x in expected for w in x] and sizes.tolist() == [len(x) for x in expected]
    known = pa.array([b"a", b"\n"], pa.binary())
    numbers, ends = lm_score.with_ends(lm_score.numbered(words, known, 2), sizes, 1)
    assert numbers.tolist() == [k for x in expected for k in [*(0 if w == b"a" else 2 for w in x), 1]]
    assert all(numbers[ends] == 1) and len(ends) == len(texts)
    assert [t for _, p in lm_score.pieces(column) for t in p.to_pylist()] == texts


def test_sums_of_runs_and_scores_of_large_weights():
    rng = np.random.default_rng(4)
    size = np.array([1, 60, 2, 24, 25, 1, 23, 200])
    at = np.append(0, np.cumsum(size))
    rows = rng.standard_normal((at[-1], 5))
    by, sums = recurrent._sums(rows, at)
    assert sorted(by.tolist()) == list(range(len(size))) and sums == pytest.approx(np.add.reduceat(rows, at[:-1])[by])
    model = recurrent.Recurrent.fresh(10, size=6, classes=3)
    h = np.tanh(rng.standard_normal((1, 6))).astype(np.float32)
    for scale in (1, 300):  # without the greatest score taken away first, exponentials of the second would overflow
        model.p["c"] *= scale
        model.p["w"] *= scale
        assert np.exp(model.scores(np.repeat(h, 11, axis=0), np.arange(11))).sum() == pytest.approx(1, abs=1e-4)


def test_lm_scores(spark):
    rnd = random.Random(5)
    texts = [None, "", "A b", *(" ".join(rnd.choice("Abcdefg") for _ in range(rnd.randint(1, 40))) for _ in range(80)), "rare" + " x" * 3000, "  word\x0bsplit"]
    got = {r.id: r for r in lm_score.score(docs_of(spark, texts)).collect()}
    toks = {k: (t or "").encode().lower().split() + [b"\n"] for k, t in enumerate(texts)}
    counts = collections.Counter(w for k, x in toks.items() if zlib.crc32(str(k).encode()) % 7 != 2 for w in x)
    n, v = sum(counts.values()), len(counts)
    for k, x in toks.items():
        r = got[k]
        assert (r.n_tokens, r.n_known, r.train_tokens, r.held_out) == (len(x), sum(counts[w] > 0 for w in x), n, zlib.crc32(str(k).encode()) % 7 == 2)
        assert r.base_score == pytest.approx(sum(np.log10((counts[w] + 1) / (n + v + 1)) for w in x))
        assert np.isfinite(r.score) and r.score < 0
    assert lm_score.score(docs_of(spark, texts).limit(0)).count() == 0


def test_lm_learns_from_every_document(spark):
    from pyspark.sql import functions as F

    ids = [r.id for r in spark.range(2000).orderBy(F.xxhash64("id")).collect()]
    late = set(ids[1800:])  # beyond any sample of the first training documents

    def score_of(swapped):
        rows = [(k, "q p p p" if swapped and k in late else "p p p q", "x", 7, None) for k in range(2000)]
        held = min(k for k in range(2000) if k not in late and zlib.crc32(str(k).encode()) % 7 == 2)
        return lm_score.score(spark.createDataFrame(rows, DOCS)).where(f"id = {held}").first()

    plain, other = score_of(False), score_of(True)
    assert plain.base_score == other.base_score and plain.score != other.score


# 4


def test_url_rules(spark):
    urls = [None, "", "no scheme", "http://A.example.COM/en/x?y", "http://www.example.com/en/", "http://example.com", "https://b.net/es/1#a", "https://net/fr/", "http://x.org/", "http://ecom/", "://com/"]
    rules = spark.createDataFrame([("com", "/", "allow"), ("example.com", "/en/", "block"), ("www.example.com", "/en/", "allow"), ("net", "/es/", "block"), ("net", "/fr/", "block"), (None, "/", "block")], "host string, path string, verdict string")
    pages = spark.createDataFrame([(k, u, "z") for k, u in enumerate(urls)], "page_id long, url string, host string")
    got = {r.id: r for r in url_rules.judge(pages, rules).collect()}
    assert [got[k].rule for k in range(len(urls))] == [None, None, None, "example.com/en/", "www.example.com/en/", None, "net/es/", "net/fr/", None, None, "com/"]
    assert [got[k].verdict for k in (3, 4, 5, 6)] == ["block", "allow", "allow", "block"]
    assert got[0].host == "" and got[3].host == "a.example.com" and got[3].path == "/en/x"
    assert url_rules.judge(pages, rules.limit(0)).where("rule is not null").count() == 0
    assert url_rules.judge(pages.union(pages), rules).count() == 2 * len(urls)
    dealt = {r.id: r for r in url_rules.judge(pages, rules, small=0, salts=3).collect()}
    assert dealt == got and url_rules.judge(pages.limit(0), rules).count() == 0
    long = spark.createDataFrame([(0, "http://" + "a." * 50_000 + "example.com/en/" + "x" * 100_000)], "page_id long, url string")
    assert url_rules.judge(long, rules).first().rule == "example.com/en/"


# 5


def base_spans(x):
    digits = lambda s: re.sub("[^0-9]", "", s)

    def luhn(d):
        return sum((lambda n: n - 9 if n > 9 else n)(int(c) * (2 if i % 2 else 1)) for i, c in enumerate(reversed(d))) % 10 == 0

    kinds = [("email", r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+", lambda s: True), ("ip", r"[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)", lambda s: all(int(p) <= 255 for p in s.split("."))),
             ("card", r"[0-9]([\x20-]?[0-9])+", lambda s: 13 <= len(digits(s)) <= 19 and luhn(digits(s))), ("phone", r"\+[0-9][\x20().0-9-]+[0-9]", lambda s: 9 <= len(digits(s)) <= 15)]
    return [f"{k}:{m.start()}:{m.end()}" for k, r, ok in kinds for m in re.finditer(r, x) if ok(m[0])]


def test_personal_data(spark):
    rnd = random.Random(5)
    bits = ["4539 1488 0343 6467", "a@b.co", "x_a@b.c_d@e.f", "1.2.3.4", "1.2.3.4.5", "999.1.1.1", "0001.2.3.4", "+1 (988) 555-2485", "+123456789", "4111111111111111", "é@a.b", "12-34", "7", "call", "1.2.3.4a@b.c.d", "++1234567890", "𝒳"]
    texts = [None, "", *("".join(rnd.choice("0123456789 -.+@ab_é𝒳\n()") for _ in range(rnd.randint(0, 60))) for _ in range(200)), *(" ".join(rnd.choice(bits) for _ in range(rnd.randint(0, 12))) for _ in range(150)), "1." * 900]
    got = {r.doc_id: r for r in personal_data.report(personal_data.find(docs_of(spark, texts))).collect()}
    for k, t in enumerate(texts):
        spans = base_spans(t or "")
        assert got[k].base_sha256 == sha(",".join(spans)) and set(spans) <= set(got[k].spans.split(",")) | {""} or not spans
        assert [got[k].n_email, got[k].n_ip, got[k].n_card, got[k].n_phone] == [sum(s.startswith(p) for s in spans) for p in ("email", "ip", "card", "phone")]
    assert personal_data.find(docs_of(spark, texts).limit(0)).count() == 0


def test_contexts_find_unseen_identifiers(spark):
    texts = [f"reach me mailto user{k}@mail.example.com please reply" for k in range(8)] + ["reach me mailto hidden@localhost please reply", "version 3@home is out", "the year 1999 was fine"]
    got = {r.doc_id: r.spans for r in personal_data.report(personal_data.find(docs_of(spark, texts))).collect()}
    assert got[8] == "email:16:32" and got[9] == "" and got[10] == ""


def discovered(found, rounds, support=3, confident=0.8, accept=0.8):
    """The rounds by plain loops over rows (value, kind, before, behind)."""
    edges = {(v, side, w) for v, _, *words in found for side, w in zip(("before", "behind"), words, strict=True) if w}
    seeds = {(v, k): 1.0 for v, k, _, _ in found if k}
    held = {v for v, _ in seeds}
    sizes = collections.Counter(p for _, *p in ((v, (s, w)) for v, s, w in edges) for p in p)
    scores, trail = dict(seeds), []
    for _ in range(rounds):
        support_of = collections.Counter()
        for v, s, w in edges:
            for (value, kind), x in scores.items():
                if value == v:
                    support_of[s, w, kind] += x
        sure = {(s, w, k): x / sizes[s, w] for (s, w, k), x in support_of.items() if sizes[s, w] >= support and x >= support and x / sizes[s, w] >= confident}
        if not sure:
            break
        miss = {}
        for v, s, w in edges:
            for (a, b, k), c in sure.items():
                if (a, b) == (s, w) and v not in held:
                    miss[v, k] = miss.get((v, k), 1.0) * (1 - 0.95 * c)
        scores = seeds | {x: 1 - m for x, m in miss.items()}
        trail.append({x: round(v, 9) for x, v in scores.items()})
    new = {}
    for (v, k), x in sorted(scores.items(), key=lambda y: (y[1], y[0][1])):
        if (v not in held and x >= accept and re.match(personal_data.SHAPES[k], v)) or (v, k) in seeds and k == "secret":
            new[v] = k
    return new, trail


def test_rounds_reach_what_only_other_finds_lead_to(spark):
    rows = [(f"s{k}x@a.b", "email", "mail", None) for k in range(8)] + [(f"u{k}@one", None, "mail", "thanks") for k in range(1)]
    rows += [(f"u0@one", None, "cc", None), *((f"s{k}x@a.b", "email", "cc", None) for k in range(5)), ("u1@two", None, "cc", "bye")]
    rows += [(f"s{k}x@a.b", "email", None, "bye") for k in range(6)] + [("u1@two", None, "bcc", None), ("u1@two", None, None, "bye"), ("u2@three", None, None, "bye"), ("loose@end", None, "the", None), ("19 99", None, "bye", None)]
    df = spark.createDataFrame(rows, "value string, kind string, before string, behind string")
    for rounds in (1, 2, 3, 5):
        expected, trail = discovered(rows, rounds)
        assert {r.value: r.kind for r in personal_data.discover(df, rounds).collect()} == expected
    assert len({tuple(sorted(x.items())) for x in trail}) >= 3 and "u2@three" in expected  # three rounds change scores


def test_secrets_by_cues_and_contexts(spark):
    key = lambda k: hashlib.sha1(str(k).encode()).hexdigest()
    texts = [f'é some words token = "{key(k)}" and more' for k in range(9)] + [f'SHOUT TOKEN = "{key(77).upper()}"!! NOW', f"a commit {key(78)} is no secret", f'later "{key(3)}" again', f'token = "{key(5)}"', f'token = "{key(5)}"', "token = 1999", None, ""]
    df = docs_of(spark, texts)
    got = {r.doc_id: r for r in personal_data.report(personal_data.find(df.union(df.where("doc_id = 2")))).collect()}
    for k, t in enumerate(texts):
        at = [m.span() for m in re.finditer("[0-9a-fA-F]{40}", t or "") if "commit" not in t]
        assert got[k].spans == ",".join(f"secret:{a}:{b}" for a, b in at) and got[k].n_secret == got[k].n_added == len(at)
        assert got[k].base_sha256 == sha("")
    assert personal_data.report(personal_data.find(df.union(df.where("doc_id = 2")))).count() == len(texts) + 1


def test_very_long_texts_take_linear_time(spark):
    import time

    texts = ["a@b.co 1.2.3.4 x9 " * 60_000]
    began = time.perf_counter()
    r = personal_data.report(personal_data.find(docs_of(spark, texts))).first()
    assert (r.n_email, r.n_ip) == (60_000, 60_000) and time.perf_counter() - began < 60


# 6


def test_near_vectors(spark):
    rng = np.random.default_rng(6)
    centre = rng.standard_normal((8, 16))
    v = [(k, (centre[k % 8] + 0.06 * rng.standard_normal(16)).astype(np.float32).tolist(), int(k % 3)) for k in range(200)]
    v += [(300, v[5][1], v[5][2]), (301, [0.0] * 16, 1), (302, None, 1), (303, [1.0, None] + [0.0] * 14, 1), (304, [float("nan")] * 16, 1), (305, v[5][1], None), (306, [1.0, 2.0], 1), (307, (2 * np.array(v[5][1])).tolist(), v[5][2])]
    df = spark.createDataFrame([(*x, 9) for x in v], "vec_id long, embedding array<float>, label int, id int")
    got = {r.id: (r.n_links, r.component_id) for r in cap_filters.near_vectors(df).collect()}
    good = {i: (np.float32(e).astype(float), lab) for i, e, lab in v if lab is not None and e and all(x is not None for x in e) and np.isfinite(np.float32(e)).all() and any(e)}
    near_ = {i: [j for j in good if j != i and good[j][1] == good[i][1] and len(good[j][0]) == len(good[i][0]) and good[i][0] @ good[j][0] / np.linalg.norm(good[i][0]) / np.linalg.norm(good[j][0]) >= 0.98] for i in good}
    reach = {}
    for i in sorted(good):
        todo = [i]
        while todo:
            x = todo.pop()
            if x not in reach:
                reach[x] = i
                todo += near_[x]
    assert got == {i: (len(near_[i]), reach[i]) if i in good else (0, i) for i, _, _ in v}
    assert sum(n for n, _ in got.values()) > 500 and cap_filters.near_vectors(df.limit(0)).count() == 0


def test_blocks_of_a_large_bucket_join_a_chain(spark, monkeypatch):
    monkeypatch.setattr(cap_filters, "SIDE", 4)
    angle = [0.15 * k for k in range(30)]
    df = spark.createDataFrame([(k, [float(np.cos(a)), float(np.sin(a))], 1) for k, a in enumerate(angle)], "vec_id long, embedding array<float>, label int")
    got = {r.id: (r.n_links, r.component_id) for r in cap_filters.near_vectors(df).collect()}
    assert got == {k: (sum(abs(a - b) < 0.2 for b in angle) - 1, 0) for k, a in enumerate(angle)}


def test_decoding_lists_every_filter_above_the_cap():
    rng = np.random.default_rng(2)
    x = rng.standard_normal((50, 12))
    x /= np.linalg.norm(x, axis=1, keepdims=True)
    books = cap_filters.codebooks(12, 3, 8)
    row, code = cap_filters.decode(x, books, 0.35, 5)
    every = np.array([np.concatenate([b[i] for b, i in zip(books, c, strict=True)]) for c in itertools.product(range(8), repeat=3)])
    scores = x @ every.T
    for n in range(50):
        best = set(np.argsort(-scores[n])[:5].tolist()) | set(np.flatnonzero(scores[n] >= 0.35).tolist())
        assert set(code[row == n].tolist()) == best


# 7


def test_signatures_estimate_weighted_similarity():
    rng = np.random.default_rng(0)
    from crowdlink.llm.text import mix

    for top in (2, 5, 40):
        e = mix(rng.integers(0, 2**63, 200).astype(np.uint64))
        a = rng.integers(0, top, 200)
        b = np.where(rng.random(200) < 0.8, a, rng.integers(0, top, 200))
        s = bag_minhash.signatures(np.concatenate([e[a > 0], e[b > 0]]), np.concatenate([a[a > 0], b[b > 0]]), np.repeat([0, 1], [(a > 0).sum(), (b > 0).sum()]), 2, 4096)
        true = np.minimum(a, b).sum() / np.maximum(a, b).sum()
        assert abs((s[0] == s[1]).mean() - true) < 0.03


def shingle_classes(texts, least=0.8):
    bags = []
    for t in texts:
        w = words(t)
        bags.append(collections.Counter(tuple(w[k : k + 5]) for k in range(max(1, len(w) - 4))) if w else collections.Counter())
    parent = list(range(len(texts)))

    def root(x):
        while parent[x] != x:
            x = parent[x]
        return x

    for a, b in itertools.combinations(range(len(texts)), 2):
        if bags[a] and bags[b] and (bags[a] & bags[b]).total() >= least * (bags[a] | bags[b]).total():
            x, y = sorted((root(a), root(b)))
            parent[y] = x
    return [root(x) for x in range(len(texts))]


def test_near_duplicates(spark):
    rnd = random.Random(8)
    base = [[f"w{rnd.randrange(500)}" for _ in range(rnd.choice([4, 30, 90]))] for _ in range(12)]

    def edited(w, times):
        w = list(w)
        for _ in range(times):
            k = rnd.randrange(len(w))
            w[k : k + rnd.choice([0, 1, 2])] = [f"n{rnd.randrange(9999)}"]
        return " ".join(w)

    texts = [None, "", "...", "one two", "One, two!"] + [edited(rnd.choice(base), rnd.choice([0, 0, 1, 1, 2, 3])) for _ in range(150)] + [edited(base[1], 2) for _ in range(40)] + ["a b c d e " * 500]
    df = docs_of(spark, texts)
    got = {r.id: r.class_id for r in near_dup.classes(df).collect()}
    assert got == dict(enumerate(shingle_classes(texts)))
    kept = near_dup.keep_one(df.union(df))
    assert kept.columns == df.columns and sorted(r.doc_id for r in kept.collect()) == sorted(k for k, c in got.items() if k == c)
    assert near_dup.classes(df.limit(0)).count() == 0


# 8


def maximal(v, a, b):
    best = None
    for i in range(a, b):
        s = 0
        for j in range(i, b):
            s += v[j]
            if s > 0 and (best is None or s > best[2]):
                best = (i, j + 1, s)
    return [] if best is None else [*maximal(v, a, best[0]), best[:2], *maximal(v, best[1], b)]


def test_maximal_segments():
    rnd = random.Random(3)
    for _ in range(400):
        v = [rnd.choice([-3, -2, -1, 1, 2, 3, 5, -4]) + rnd.random() * 0.01 for _ in range(rnd.randint(0, 14))]
        assert [s[:2] for s in toxicity.segments(v)] == maximal(v, 0, len(v))
    import time

    for v in ([rnd.choice([-1.0, 1.0]) * rnd.random() for _ in range(1_000_000)], [1.0 - k / 2e6 if k % 2 else -1.0 + k / 1e6 for k in range(1_000_000)], [3.0 if k % 2 else -1.0 - k % 3 for k in range(1_000_000)]):
        began = time.perf_counter()
        toxicity.segments(v)
        assert time.perf_counter() - began < 4  # a second or so; twice the two seconds asked for, as tests share cores


def test_toxicity_held_out(spark):
    rnd = random.Random(9)
    texts, toxic = [], []
    for k in range(600):
        w = [f"c{rnd.randrange(200)}" for _ in range(rnd.randint(5, 60))]
        if k % 6 == 0:
            for _ in range(4):
                w.insert(rnd.randrange(len(w)), rnd.choice(["Foul", "nasty", "vile"]))
        texts.append(" ".join(w))
        toxic.append(int(k % 6 == 0))
    texts += [None, ""]
    df = docs_of(spark, texts)
    labels = spark.createDataFrame([(k, y) for k, y in enumerate(toxic)] + [(None, 1), (5, None), (9999, 1)], "doc_id long, toxic int")
    model = toxicity.fit(df, toxicity.training_rows(labels, lambda i: ~toxicity.held_out(i)))
    got = {r.doc_id: r for r in toxicity.report(toxicity.score(df, model)).collect()}
    held = [k for k in range(600) if zlib.crc32(str(k).encode()) % 4 == 2]
    assert all(got[k].held_out for k in held) and sum(r.held_out for r in got.values() if r.doc_id < 600) == len(held)
    assert np.mean([got[k].predicted == toxic[k] for k in held]) > 0.97
    assert got[600].score == got[601].score < 0.3
    left = toxicity.drop_toxic(df, model)
    assert left.columns == df.columns and {r.doc_id for r in left.collect()} == {k for k, r in got.items() if not r.predicted}
    untaught = toxicity.fit(df, toxicity.training_rows(labels.limit(0), lambda i: ~toxicity.held_out(i)))
    assert {r.predicted for r in toxicity.report(toxicity.score(df, untaught)).collect()} == {0}


# 9


def test_encoding_equals_the_library(spark):
    from tokenizers import Tokenizer

    t = Tokenizer.from_file(default_vocabulary())
    rnd = random.Random(1)
    texts = [None, "", "  \n", "<|startoftext|>Hello<|endoftext|> World", "ΣΑΣ Σ İstanbul ǅ", "don't I'LL we've ''s", "a" * 5000, "汉字 ab٣ ½   é é", *("".join(rnd.choice("abcdeÉß1 '<|>endoftext\n.!é汉́") for _ in range(rnd.randint(0, 80))) for _ in range(300))]
    got = {r.doc_id: r for r in bpe.digests(bpe.encode_texts(docs_of(spark, texts), default_vocabulary())).collect()}
    for k, x in enumerate(texts):
        ids = t.encode(x or "", add_special_tokens=False).ids
        assert (got[k].n_tokens, got[k].ids_sha256, got[k].decoded_sha256) == (len(ids), sha(" ".join(map(str, ids))), sha(t.decode(ids, skip_special_tokens=False)))


def test_pair_tree_root_is_the_least():
    rnd = random.Random(2)
    for _ in range(50):
        v = [rnd.randrange(1000) for _ in range(rnd.randint(1, 40))]
        tree = bpe.PairTree(list(v))
        for _ in range(60):
            k = rnd.randrange(len(v))
            v[k] = rnd.randrange(1000)
            tree.put(k, v[k])
            assert tree.nodes[1] == min(v)


# 10


def test_chat_round_trip(spark):
    rnd = random.Random(7)
    say = lambda: "".join(rnd.choice(["\\", "<", ">", "</turn>\n", "\\l", "\\b", "a", "é", "\n", "<assistant>\n", "𝒳"]) for _ in range(rnd.randint(0, 8)))
    rows = [(c, n, rnd.choice(["user", "assistant", "<x>", None, "system"]), rnd.choice([say(), say(), None])) for c in range(40) for n in range(rnd.randint(1, 60 if c == 3 else 6))]
    rows += [(50, None, "user", "first"), (50, 1, "assistant", "same"), (50, 1, "assistant", "same"), (None, 0, "assistant", "lost")]
    df = spark.createDataFrame([(*r, "z") for r in rows], "conv_id long, turn long, role string, text string, content string")
    from pyspark.sql import functions as F

    chats = chat.format_turns(df.withColumn("parts", chat.text_part(F.col("text"))))
    got = {r.conv_id: r for r in chat.digests(chats).collect()}
    grouped = collections.defaultdict(list)
    for c, n, role, text in rows:
        grouped[c].append((-1 if n is None else n, role or "", text or ""))
    assert set(got) == set(grouped)
    for c, turns in grouped.items():
        turns.sort()
        loss = "".join(x for _, role, x in turns if role == "assistant")
        r = got[c]
        assert r.n_turns == len(turns)
        assert (r.loss_chars, r.loss_sha256) == (len(loss), sha(loss))
        if not any("\\" in x or "<" in x or ">" in x for _, ro, x in turns for x in (ro, x)):
            assert r.turns_sha256 == sha("".join(f"{role}\n{x}\n" for _, role, x in turns))


def test_chat_parts_become_ordered_placeholders(spark):
    df = spark.sql("""SELECT 1L conv_id, 0L turn, 'user' role, array(named_struct('kind', 'text', 'text', 'see <b>', 'ref', cast(null as string), 'tokens', cast(null as int)),
        named_struct('kind', 'image', 'text', cast(null as string), 'ref', 'a.png', 'tokens', 77), named_struct('kind', 'audio', 'text', cast(null as string), 'ref', 'b.wav', 'tokens', cast(null as int)),
        named_struct('kind', 'document', 'text', cast(null as string), 'ref', cast(null as string), 'tokens', cast(null as int))) parts UNION ALL SELECT 1L, 1L, 'assistant', null""")
    r = chat.format_turns(df).first()
    assert r.formatted == "<user>\nsee \\lb\\g<image:1><audio:2><document:3></turn>\n<assistant>\n</turn>\n"
    assert [(a.turn_index, a.n, a.kind, a.ref, a.tokens) for a in r.attachments] == [(0, 1, "image", "a.png", 77), (0, 2, "audio", "b.wav", 128), (0, 3, "document", None, 512)]


def test_lm_learns_in_as_many_passes_at_any_size(spark, monkeypatch):
    passes = []
    monkeypatch.setattr(lm_score, "learn", lambda texts, of, model, n: passes.append(n))
    docs = spark.createDataFrame([(1, "a", False)], "id long, text string, held_out boolean")
    for c in (10, 5_000_000):
        lm_score.fit(docs, spark.createDataFrame([(b"a", c)], "word binary, c long"))
    assert passes[0] == passes[1]


def test_lm_learns_from_every_place_of_a_text(monkeypatch):
    model, seen, took = recurrent.Recurrent.fresh(10, size=6, classes=3), [], recurrent.Recurrent._gradients
    monkeypatch.setattr(recurrent.Recurrent, "_gradients", lambda self, piece, own, *rest: seen.append(piece[own >= 0]) or took(self, piece, own, *rest))
    texts = [np.random.default_rng(k).integers(0, 11, n).astype(np.int32) for k, n in enumerate([1, 300, 7, 130, 0])]
    model.train(texts, 0)
    assert np.bincount(np.concatenate(seen), minlength=11).tolist() == np.bincount(np.concatenate(texts), minlength=11).tolist()
