"""Each corpus operator against brute force or an exact round trip, with the awkward rows that contracts name."""

import hashlib
import random
import re

import numpy as np
import public_tokenizers
import pyarrow as pa
import pytest
from pyspark.sql import functions as F

from deltamp.llm import chat, copies, leaks, licenses, passages, pieces, pii, quality, revisits, simhash, urls
from deltamp.llm.common import run_hashes, word_hashes_many

WORD = re.compile(r"[^\x20\x09-\x0D]+")
AWKWARD = [(1, None), (2, ""), (3, "  \n\t "), (4, "one"), (4, "one"), (None, "two words"), (5, "x " * 3000), (6, "é日😀 ▁ \x00 <|im_end|>"), (7, "long" * 3000)]


def docs(spark, rows=AWKWARD):
    return spark.createDataFrame([(*r, "other") for r in rows], "doc_id long, text string, length string")


def words(n, seed):
    r = random.Random(seed)
    return " ".join("".join(r.choice("abcdefgh") for _ in range(5)) for _ in range(n))


def test_word_hashes_follow_words():
    texts = [b"a bb  a\n", b"", b"bb\x0ba bb", b" "]
    flat, sizes = word_hashes_many(texts)
    assert sizes.tolist() == [3, 0, 3, 0] and flat[0] == flat[2] == flat[4] and flat[1] == flat[3] == flat[5] != flat[0]
    h = np.array([5, 6, 7, 5, 6, 7], np.uint64)
    r = run_hashes(h, 3)
    assert r[0] == r[3] and len(set(r.tolist())) == 3 and len(run_hashes(h, 7)) == 0


def test_simhash_groups(spark):
    base = words(200, 1)
    near = base.replace(base.split()[100], "changed")
    rows = [*AWKWARD, (20, base), (21, near), (22, base), (30, words(200, 2))]
    got = {(r["doc_id"], r["fp"]): r["component_id"] for r in simhash.near_duplicates(docs(spark, rows)).collect()}
    fps = [(i, simhash.fingerprint((t or "").encode())) for i, t in rows]
    signed = lambda x: x - 2**64 if x >= 2**63 else x
    root = list(range(len(fps)))
    for _ in fps:
        for a in range(len(fps)):
            for b in range(len(fps)):
                if (fps[a][1] ^ fps[b][1]).bit_count() <= 3:
                    root[a] = root[b] = min(root[a], root[b])
    for k, (i, fp) in enumerate(fps):
        want = min(j for m, (j, _) in enumerate(fps) if root[m] == root[k] and j is not None) if any(j is not None for m, (j, _) in enumerate(fps) if root[m] == root[k]) else None
        assert got[(i, signed(fp))] == want


def test_hot_bucket_is_dealt_out_exactly():
    r = np.random.default_rng(3)
    centre = r.integers(0, 2**63, 40, dtype=np.uint64)
    fps = np.unique(np.concatenate([centre, *[centre ^ (np.uint64(1) << r.integers(0, 63, 40).astype(np.uint64)) for _ in range(6)]]))
    i, j = simhash.close_pairs(fps, simhash.pivot_table(fps))

    def groups(pairs):
        root = list(range(len(fps)))

        def find(x):
            while root[x] != x:
                x = root[x]
            return x

        for a, b in pairs:
            a, b = find(a), find(b)
            root[max(a, b)] = min(a, b)
        return [find(x) for x in range(len(fps))]

    near = np.bitwise_count(fps[:, None] ^ fps[None, :]) <= 3
    assert groups(zip(i.tolist(), j.tolist())) == groups(zip(*map(list, np.nonzero(near)))) and len(i) < len(fps)


def test_components_of_a_long_path(spark):
    e = spark.createDataFrame([(k + 1, k) for k in range(40)] + [(100, 99)], "a long, b long")
    got = dict(tuple(r) for r in simhash.components(e).collect())
    assert got == {**{k: 0 for k in range(1, 41)}, 100: 99}


def test_passages(spark):
    shared = words(60, 5)
    rows = [*AWKWARD, (20, words(30, 6) + " " + shared), (21, shared + " " + words(50, 7)), (22, words(34, 8)), (23, words(90, 9)), (24, words(90, 9))]
    got = sorted((r["doc_id"] is None, r["doc_id"], r["n_words"], r["n_removed"], hashlib.sha256(r["kept"]).hexdigest()) for r in passages.repeated_runs(docs(spark, rows)).collect())
    want = sorted((i is None, i, *b) for (i, _), b in zip(rows, passages.brute_force([t for _, t in rows])))
    assert got == want and passages.repeated_runs(docs(spark, rows).where("false")).count() == 0


def test_automaton_matches_brute_force(spark):
    r = random.Random(1)
    reference = [[r.choice("abc") for _ in range(30)] for _ in range(3)]
    text = [r.choice("abc") for _ in range(80)]
    subs = {tuple(s[i:j]) for s in reference for i in range(30) for j in range(i + 1, 31)}
    a = passages.Automaton(reference)
    assert a.matches(text) == [max((n for n in range(1, min(30, e) + 1) if tuple(text[e - n : e]) in subs), default=0) for e in range(1, 81)]
    out = passages.remove_reference_spans(docs(spark, [(1, "x a b c d y"), (2, None)]), ["a b c d"], 3).collect()
    assert [(o["text"], o["n_removed"]) for o in out] == [("x y", 4), ("", 0)]


def test_pieces_equal_the_library(spark):
    import sentencepiece

    path = str(public_tokenizers.path("piece_bpe_32k.model"))
    sp = sentencepiece.SentencePieceProcessor(model_file=path)
    r = random.Random(2)
    texts = [t for _, t in AWKWARD] + ["".join(r.choice("ab  c\nde. éth'▁😀s0") for _ in range(r.randint(0, 60))) for _ in range(300)]
    rows = list(enumerate(texts))
    for o in pieces.encode(docs(spark, rows), path, keep=("ids", "decoded", "n_tokens")).collect():
        want = sp.encode(texts[o["doc_id"]] or "", add_bos=True, add_eos=True)
        assert np.frombuffer(o["ids"], "<u4").tolist() == want and o["decoded"] == sp.decode(want) and o["n_tokens"] == len(want)


def test_quality_measures(spark):
    from collections import Counter

    rows = [*AWKWARD, (20, "a b c d e f g h i j k l a b c d e z\nline\nline\n \n"), (21, words(40, 3) + " ### $ |")]
    labels = spark.createDataFrame([(21, 1, 0)], "doc_id long, quality int, toxic int")
    for o in quality.judge(docs(spark, rows), labels).collect():
        t, q = o["text"] or "", o["_q"]
        w = WORD.findall(t)
        c = Counter(tuple(w[i : i + 5]) for i in range(len(w) - 4))
        again = {j for i in range(len(w) - 4) if c[tuple(w[i : i + 5])] > 1 for j in range(i, i + 5)}
        lines = [x for x in t.split("\n") if WORD.search(x)]
        assert (q["n_words"], q["word_chars"], q["n_symbols"], q["n_dup_lines"], q["n_repeat_words"]) == (len(w), sum(map(len, w)), sum(x in "#*$%&|<>" for x in t), len(lines) - len(set(lines)), len(again))
        assert q["base_failed"] == (len(w) < 10 or 100 * len(again) > 20 * len(w)) and not (q["base_failed"] and q["kept"])
        assert o["length"] == "other"


def test_url_verdicts(spark):
    rows = [(1, None), (2, "nothing"), (3, "http://WWW.example.com/en/x?q"), (4, "http://example.com/en/"), (5, "https://a.b.net/es/1"), (6, "http://x.org/casino/"), (7, "http://m.spam-farm.example.org/a"), (8, "http://com"), (9, "ftp://x.com/")]
    frame = spark.createDataFrame(rows, "page_id long, url string")
    got = {r[0]: tuple(r[1:]) for r in urls.filter_urls(frame).collect()}
    assert got[1] == got[2] == ("", "", None, "allow") and got[3] == ("www.example.com", "/en/x", "www.example.com/en/", "allow")
    assert got[4][2:] == ("example.com/en/", "block") and got[5][2:] == ("net/es/", "block") and got[6][2:] == got[7][2:] == (None, "block")
    assert got[8] == ("com", "", None, "allow") and got[9][2:] == ("com/", "allow")


def test_revisits(spark):
    none = None
    rows = [(1, "http://A.com/x", 10, "response", "e1", none, {"Content-Type": "t", "X": "1"}), (2, "https://www.a.com/x/#f", 20, "revisit", "W/e1", none, {"x": "2", "Content-Length": "0"}), (3, "http://a.com/x", 20, "response", "e2", none, {}), (4, "http://a.com/x?utm_source=q", 30, "revisit", "e1", none, none), (5, none, 5, "revisit", none, none, none), (6, "b.com", 1, "response", none, none, none), (7, "b.com", 2, "revisit", none, "d", none)]
    f = spark.createDataFrame(rows, "record_id long, url string, ts long, kind string, etag string, last_modified string, headers map<string,string>")
    got = {r["record_id"]: (r["response_id"], r["status"], r["headers"]) for r in revisits.resolve(f).collect()}
    assert got == {2: (1, "resolved", {"Content-Type": "t", "x": "2"}), 4: (3, "validator_mismatch", None), 5: (None, "no_prior", None), 7: (6, "no_validator", None)}
    assert revisits.resolve(f.where("false")).count() == 0


def test_licences(spark):
    rows = [*AWKWARD, (20, "a b c released under the MIT license. d"), (21, words(30, 1) + " This work is licensed under the GNU General Public License, version 3. " + words(9, 2)), (22, "Licensed under nothing at all, really")]
    got = {(r["doc_id"], r["template"]) for r in licenses.scan(docs(spark, rows)).collect()}
    assert got == {(20, "MIT/0"), (21, "GPL-3.0/0")}


def test_long_runs_of_digits_are_judged():
    zeros, nines = "0" * 6000, "9" * 6000
    assert pii.base_spans(f"{zeros}1.2.3.004 {nines}.1.1.1") == [("ip", 0, 6009)]


def test_chat_round_trip():
    r = random.Random(1)
    for _ in range(300):
        turns = [(r.choice(["user", "a\\n\nb", "<|im_start|>"]), "".join(r.choice(["<|im_end|>", "<\\|", "<", "|", "\\", "x", "\n", "é"]) for _ in range(r.randint(0, 8)))) for _ in range(3)]
        assert chat.read_turns("".join(chat.render_turn(*t)[0] for t in turns)) == turns


def test_chat_conversations(spark):
    rows = [(1, 1, "assistant", " hi  there"), (1, 0, "user", None), (None, 0, "assistant", "x"), (2, 0, "user", "<|im_end|>"), (1, 1, "assistant", " hi  there")]
    f = spark.createDataFrame(rows, "conv_id long, turn long, role string, text string")
    got = {r["conv_id"]: r for r in chat.format_conversations(f, str(public_tokenizers.path("byte_bpe_50k.json"))).collect()}
    assert got[1]["n_turns"] == 3 and got[1]["loss_chars"] == 20 and got[1]["loss_sha256"] == hashlib.sha256(b" hi  there hi  there").hexdigest()
    assert got[None]["loss_chars"] == 1 and got[2]["loss_chars"] == 0 and got[1]["n_loss_tokens"] > 0


def test_base_spans_equal_plain_patterns():
    r = random.Random(5)
    for _ in range(5000):
        t = "".join(r.choice("a1.@+- %(9)2é") for _ in range(r.randint(0, 50)))
        want = []
        for kind, p in (("email", r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+"), ("ip", r"[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)"), ("card", r"[0-9]([\x20-]?[0-9])+"), ("phone", r"\+[0-9][\x20().0-9-]+[0-9]")):
            for m in re.finditer(p, t):
                d = re.sub("[^0-9]", "", m[0])
                if {"email": True, "ip": kind == "ip" and all(int(x) <= 255 for x in m[0].split(".")), "card": 13 <= len(d) <= 19 and pii.luhn(d), "phone": 9 <= len(d) <= 15}[kind]:
                    want.append((kind, m.start(), m.end()))
        assert pii.base_spans(t) == want


def test_tagger_gradients_and_held_out_accuracy(spark):
    t = pii.Tagger(3)
    x, y = np.random.default_rng(0).integers(0, 130, (2, 7)), np.array([[0, 1, 2, 2, 0, 3, 4], [5, 6, 0, 0, 7, 8, 8]])
    _, g = t.gradients(x, y)
    for k in t.p:
        at = tuple(np.unravel_index(np.abs(g[k]).argmax(), g[k].shape))
        t.p[k][at] += 1e-5
        up = t.gradients(x, y)[0]
        t.p[k][at] -= 2e-5
        down = t.gradients(x, y)[0]
        t.p[k][at] += 1e-5
        assert abs((up - down) / 2e-5 - g[k][at]) < 1e-6
    rng = random.Random(99)
    texts = [pii.labelled_text(rng) for _ in range(200)]
    got = pii.model_spans([x for x, _ in texts], pii.trained())
    hit = sum(len(set(s) & set(m)) for (_, s), m in zip(texts, got))
    assert hit >= 0.8 * sum(len(s) for _, s in texts) and hit >= 0.8 * sum(map(len, got))
    rows = [*AWKWARD, (20, "mail a.b@x.org or 12.13.14.15"), (21, "7 4485380592391139 end")]
    out = {r["doc_id"]: r for r in pii.scan(docs(spark, rows)).collect()}
    assert out[20]["spans"].startswith("email:5:14,ip:18:29") and out[1]["spans"] == ""
    assert pii.redact(docs(spark, rows)).where("doc_id = 20").first()["text"] == "mail <email> or <ip>"


def test_leaks(spark):
    items = [(k, words(30 + k, 100 + k) + ".") for k in range(8)]
    item = items[3][1].split()
    noisy = " ".join("zz" if i % 6 == 5 else w for i, w in enumerate(item))
    rows = [*AWKWARD, (20, words(90, 1) + " " + items[0][1].upper() + "\n" + words(70, 2)), (21, words(40, 3) + " " + noisy), (22, words(400, 4)), (23, " ".join(item[:6]))]
    bench = spark.createDataFrame([*items, (50, None), (51, "too short")], "item_id long, text string")
    got = {(r["doc_id"], r["item_id"]) for r in leaks.matches(docs(spark, rows), bench).collect()}
    assert got == {(20, 0), (21, 3)}
    assert leaks.keep_clean(docs(spark, rows), bench).count() == len(rows) - 2
    assert leaks.matches(docs(spark, rows), bench.where("false")).count() == 0


def test_leaks_of_many_and_of_long_items(spark):
    r = random.Random(7)
    vocabulary = [words(1, 1000 + k) for k in range(3000)]
    items = [(k, " ".join(r.choice(vocabulary) for _ in range(38)) + ".") for k in range(1200)]
    items.append((1200, words(900, 60)))
    noise = lambda n: " ".join(r.choice(vocabulary) for _ in range(n))
    rows = [(k, f"{noise(r.randint(0, 90))} {t} {noise(r.randint(0, 90))}") for k, t in items]
    half = " ".join("zz" if i % 4 == 3 else w for i, w in enumerate(items[5][1].split()))
    rows += [(2000, noise(2000) + " " + half + " " + noise(500)), (2001, noise(3000)), (2002, None)]
    got = {(m["doc_id"], m["item_id"]) for m in leaks.matches(docs(spark, rows), spark.createDataFrame(items, "item_id long, text string")).collect()}
    assert got == {(k, k) for k in range(1201)} | {(2000, 5)}


@pytest.mark.parametrize("n,text", [(3, b"Is it so? Yes it is"), (4, b"First part here now. Two words. And more"), (0, b"")])
def test_answers(n, text):
    assert leaks.answer_of(text) == n


def test_common_length():
    r = random.Random(1)
    for _ in range(200):
        a, b = ([r.randrange(5) for _ in range(r.randint(0, 20))] for _ in range(2))
        row = [0] * (len(b) + 1)
        for x in a:
            new = [0]
            for j, y in enumerate(b):
                new.append(row[j] + 1 if x == y else max(row[j + 1], new[j]))
            row = new
        assert leaks.common_length(np.array(a, int), np.array(b, int)) == row[-1]


def test_pipeline_stages(spark, tmp_path):
    import corpus_pipeline

    good = words(120, 50)
    rows = [(1, good, "en", "s", 1), (2, good, "en", "s", 1), (3, "short text", "en", "s", 1), (4, words(60, 51) + " a@b.org " + words(60, 52), "en", "s", 1), (5, words(50, 53) + " " + words(30, 54), "en", "s", 1), (6, None, "en", "s", 1)]
    spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long").write.parquet(f"{tmp_path}/documents.parquet")
    spark.createDataFrame([(1, 1, 0), (4, 1, 0), (5, 1, 0)], "doc_id long, quality int, toxic int").write.parquet(f"{tmp_path}/labels.parquet")
    spark.createDataFrame([(0, words(30, 54))], "item_id long, text string").write.parquet(f"{tmp_path}/benchmark.parquet")
    assert sorted(r["doc_id"] for r in corpus_pipeline.run(spark, str(tmp_path)).collect()) == [1, 4]


def test_all_labelled_good_rows_are_trusted(spark):
    frame = spark.range(21_000).selectExpr("id AS doc_id", "concat('w', id, ' x', id) AS text")
    assert not any(quality.fit(frame, frame.selectExpr("doc_id", "1 AS quality", "0 AS toxic")))


def edited(text, n, mark):
    w = text.split()
    for k in range(n):
        w[10 + k * 30] = f"{mark}{k}"
    return " ".join(w)


def stage(spark, rows):
    import corpus_pipeline

    frame = spark.createDataFrame([(i, t, "en", "s", 1) for i, t in rows], "doc_id long, text string, lang string, source string, n_chars long")
    return sorted(((r["doc_id"], r["text"]) for r in corpus_pipeline.keep_one_of_group(spark, frame, "").collect()), key=repr)


def test_stage_drops_near_copies_by_five_word_shingles(spark):
    base, other = words(200, 70), words(200, 71)
    rows = [(1, base), (2, edited(base, 4, "q")), (3, edited(base, 6, "r")), (4, other), (5, other.upper())]
    texts = dict(rows)
    sets = copies.shingle_sets([t.encode() for t in texts.values()])
    assert copies.similarity(sets[0], sets[1]) >= 0.8 > copies.similarity(sets[0], sets[2])
    assert stage(spark, rows) == sorted([(k, texts[k]) for k in (1, 3, 4)], key=repr)


def test_stage_groups_equal_all_pairs(spark):
    r = random.Random(3)
    rows = []
    for k in range(5):
        text = words(200, 80 + k)
        for m in range(12):
            rows.append((len(rows), text))
            w = text.split()
            for _ in range(2):
                w[r.randrange(200)] = words(1, r.randrange(10**6))
            text = " ".join(w)
    sets = copies.shingle_sets([t.encode() for _, t in rows])
    root = list(range(len(rows)))
    for _ in rows:
        for a in range(len(rows)):
            for b in range(a):
                if copies.similarity(sets[a], sets[b]) >= 0.8:
                    root[a] = root[b] = min(root[a], root[b])
    assert [i for i, _ in stage(spark, rows)] == sorted({root[k] for k in range(len(rows))}, key=lambda i: repr((i, rows[i][1])))


def test_stage_keeps_a_row_of_every_group(spark):
    a, b, c, d = (words(60, 90 + k) for k in range(4))
    rows = [(None, a), (None, b), (None, b), (7, c), (7, d), (8, d), (None, d), (9, None), (None, "")]
    want = [(None, a), (None, b), (7, c), (7, d), (9, None)]
    assert stage(spark, rows) == sorted(want, key=repr) == stage(spark, rows[::-1])


def test_rules_are_found_by_their_tokens_as_by_all_expressions():
    """The verdict is the regular expressions' own, whatever token is rarest."""
    r = random.Random(1)
    bits = ["://", "ads", "ad", ".", "/", "casino", "poker", "de", "1", "22", "html", "htmlx", "?", "&", "utm_source=", "spam", "spammer", "page=2", "ref=x", "xyz", "-farm", "spam-farm", "adult-x", "blog", "tag", "feed", "#", "x", "A", "casino-win", "DE"]
    named = [t for p in urls.PATTERNS for s in urls.proved_tokens(p) for t in s]
    hits = 0
    for k in range(20_000):
        if k % 200 == 0:
            index = urls.PatternIndex(urls.PATTERNS, {t: r.randrange(9) for t in named})
        u = ("http://" if k % 2 else "") + "".join(r.choice(bits) for _ in range(r.randint(1, 9)))
        want = any(re.search(p, u.lower()) for p in urls.PATTERNS)
        hits += want
        assert index.blocks(u) == want, u
    assert hits > 100


def test_rules_that_prove_no_token_are_refused():
    assert urls.proved_tokens("/a(bb|cd)?/x(/|$)") == [frozenset({"a", "x"}), frozenset({"abb", "x"}), frozenset({"acd", "x"})]
    for bad in ("spam", "/spam", "x=[0-9]+", "/(a|b*)/?"):
        with pytest.raises(ValueError):
            urls.proved_tokens(bad)


def test_url_rows_repeat_and_may_be_long(spark):
    rows = [(1, "http://x.org/" + "a/" * 50_000 + "casino/"), (1, "http://x.org/" + "a/" * 50_000 + "casino/"), (2, None)]
    f = spark.createDataFrame([(*r, "v") for r in rows], "page_id long, url string, verdict string")
    assert sorted((r["page_id"], r["verdict"]) for r in urls.filter_urls(f).collect()) == [(1, "block"), (1, "block"), (2, "allow")]
    assert urls.filter_urls(f.where("false")).count() == 0


def test_whole_licence_texts(spark):
    """A 300-word template beside all others, held against containment by sets over all windows."""
    long = words(300, 400)
    texts = {**licenses.TEMPLATES, "Long": (long,)}
    w = long.split()
    mit = licenses.TEMPLATES["MIT"][2]
    rows = [(1, words(120, 1) + " " + long + " " + words(80, 2)), (2, " ".join(w[:200])), (3, " ".join(w[:265])), (4, words(700, 3) + " " + mit.upper()), (5, words(900, 4)), (6, None)]
    got = {(r["doc_id"], r["template"]) for r in licenses.scan(docs(spark, rows), texts=texts).collect()}
    cut = lambda t: re.findall(r"[a-z0-9]+(?:[.-][a-z0-9]+)*", (t or "").lower())
    shingles = lambda x: {tuple(x[i : i + 5]) for i in range(len(x) - 4)}
    want = set()
    for i, t in rows:
        for name, notices in texts.items():
            for k, n in enumerate(notices):
                have, need = cut(t), shingles(cut(n))
                width = licenses.width_of(len(cut(n)))
                if any(len(shingles(have[a : a + width]) & need) >= 0.8 * len(need) for a in range(0, max(1, len(have)), width // 2)):
                    want.add((i, f"{name}/{k}"))
    assert got == want and {(1, "Long/0"), (3, "Long/0"), (4, "MIT/2")} <= got and (2, "Long/0") not in got
    with pytest.raises(ValueError):
        licenses.templates(spark, {"X": ("one two",)})


def test_links_of_a_hot_bucket_lose_nothing(spark):
    """Over 4000 fingerprints share most blocks; groups equal those of all pairs."""
    r = np.random.default_rng(9)
    base = np.uint64(0x0123456789ABCDEF)
    low = r.choice(1 << 13, 4500, replace=False).astype(np.uint64)
    fps = np.unique(base ^ (low * np.uint64(8)))
    frame = spark.createDataFrame([(int(x),) for x in fps.view(np.int64)], "fp long")
    got = {tuple(x) for x in simhash.links(frame, 4500, hot=500).collect()}
    root = {int(x): int(x) for x in fps.view(np.int64)}

    def find(x):
        while root[x] != x:
            root[x] = root[root[x]]
            x = root[x]
        return x

    def groups(pairs):
        root.update({k: k for k in root})
        for a, b in pairs:
            a, b = find(a), find(b)
            root[max(a, b)] = min(a, b)
        return {k: find(k) for k in root}

    x, y = np.nonzero(np.triu(np.bitwise_count(fps[:, None] ^ fps[None, :]) <= 3, 1))
    signed = fps.view(np.int64)
    assert groups(got) == groups(zip(signed[x].tolist(), signed[y].tolist()))


def test_benchmark_in_parts_and_short_items(spark, monkeypatch):
    monkeypatch.setattr(leaks, "MOST_ITEMS", 3)
    items = [(k, words(20 + k, 500 + k)) for k in range(10)] + [(50, "tiny little item"), (51, "two words"), (52, "four words in order")]
    bench = spark.createDataFrame(items, "item_id long, text string")
    assert len(leaks.benchmark_parts(bench)) > 2
    rows = [(k, words(60, k) + " " + t + " " + words(20, 90 + k)) for k, t in items] + [(60, "order in words four tiny item little"), (61, None)]
    assert {(m["doc_id"], m["item_id"]) for m in leaks.matches(docs(spark, rows), bench).collect()} == {(k, k) for k, t in items if k != 51}
    assert sorted(r["doc_id"] for r in leaks.keep_clean(docs(spark, rows), bench).collect()) == [51, 60, 61]


def test_added_spans_against_brute_force_and_other_rules():
    """merged() against a plain restatement; then planted forms that the patterns lose."""
    r = random.Random(3)
    for _ in range(400):
        text = "".join(r.choice("12345 (+-.@[a]") for _ in range(60))
        base = pii.base_spans(text)
        guessed = sorted(((r.choice(pii.KINDS), a, a + r.randint(1, 30)) for a in (r.randrange(60) for _ in range(5))), key=lambda s: (s[1], s[2]))
        guessed = [(k, a, min(60, z)) for k, a, z in guessed]
        used, want = {i for _, a, z in base for i in range(a, z)}, list(base)
        for k, a, z in guessed:
            for lo, hi in pii.settled(k, text, a, z):
                if not used & set(range(lo, hi)) and lo >= max([0, *(y for q in want[len(base) :] for y in [q[2]])]):
                    want.append((k, lo, hi))
                    used |= set(range(lo, hi))
        assert pii.merged(text, base, guessed) == (base, sorted(want, key=lambda s: (pii.KINDS.index(s[0]), s[1])))
    vocabulary = "the report was sent by our office to a new client last week and nobody answered order ticket room section".split()
    num = lambda n: "".join(r.choice("0123456789") for _ in range(n))

    def card():
        body = "4" + num(14)
        return body + next(c for c in "0123456789" if pii.luhn(body + c))

    texts = []
    for _ in range(150):
        text, spans = "", []
        for _ in range(20):
            kind = r.choice(("card", "email", "phone", None, None, None, None, None))
            if kind is None:
                text += r.choice((*vocabulary, num(4), "v1.2.3", "(" + r.choice(vocabulary) + ")")) + " "
                continue
            if kind == "card":
                text += num(2) + " "
            shown = {"card": card, "email": lambda: f"{r.choice(vocabulary)} [at] {r.choice(vocabulary)} [dot] org", "phone": lambda: f"({num(3)}) {num(3)}-{num(4)}"}[kind]()
            spans.append((kind, len(text), len(text) + len(shown)))
            text += shown + " "
        texts.append((text, spans))
    found = pii.find([t for t, _ in texts], pii.trained())
    added = sum(len(set(all_) - set(base)) for base, all_ in found)
    right = sum(len(set(s) & set(all_) - set(base)) for (_, s), (base, all_) in zip(texts, found))
    missed_by_base = sum(len(set(s) - set(base)) for (_, s), (base, _) in zip(texts, found))
    assert added and right >= 0.85 * added and right >= 0.7 * missed_by_base


def test_windows_without_signs_hold_nothing():
    rng = random.Random(5)
    texts = ["".join(pii.labelled_text(rng)[0] + " " + words(40, k) + " " for _ in range(4)) for k in range(60)]
    t = pii.trained()
    whole = [pii.merged(x, pii.base_spans(x), g) for x, g in zip(texts, pii.model_spans(texts, t, every=True))]
    assert whole == pii.find(texts, t)


def test_long_texts_are_tagged_piece_by_piece(monkeypatch):
    rng = random.Random(6)
    text = " ".join(pii.labelled_text(rng)[0] for _ in range(60))
    t = pii.trained()
    whole = pii.find([text], t)[0]
    monkeypatch.setattr(pii, "PIECE", 1500)
    got = pii.find([text], t)[0]
    assert got[0] == whole[0] and len(set(got[1]) ^ set(whole[1])) <= 0.03 * len(whole[1])
    assert pii.model_spans([], t) == [] and pii.find([""], t) == [([], [])]


def test_buckets_grow_and_columns_may_clash(spark):
    frame = docs(spark, [(k, words(50, k)) for k in range(30)]).withColumnRenamed("length", "_q")
    labels = spark.createDataFrame([(1, 1, 0)], "doc_id long, quality int, toxic int")
    out = quality.judge(frame, labels)
    assert out.columns == ["doc_id", "text", "_q", "__q"] and out.where("__q.kept is not null").count() == 30
    assert quality.buckets_for(frame) == quality.LEAST_BUCKETS and quality.judge(frame.where("false"), labels).count() == 0
    big = frame.selectExpr("doc_id", "repeat('x', 40000000) AS text").limit(8)
    assert quality.buckets_for(big) == 1 << 17


def test_quality_scores_by_brute_force(spark):
    from math import log

    rows = [(k, words(30, k % 7)) for k in range(25)]
    labels = spark.createDataFrame([(k, 1, 0) for k in range(0, 25, 3)], "doc_id long, quality int, toxic int")
    raw, good = {}, {}
    grams = lambda t: [*t.split(), *zip(t.split(), t.split()[1:])]
    for k, t in rows:
        for g in grams(t):
            raw[g] = raw.get(g, 0) + 1
            good[g] = good.get(g, 0) + (k % 3 == 0)
    share = sum(good.values()) / sum(raw.values())
    weight = {g: round(1000 * (log(good[g] + quality.PRIOR) - log(raw[g] * share + quality.PRIOR))) for g in raw}
    for r in quality.judge(docs(spark, rows), labels).collect():
        want = sum(weight[g] for g in grams(r["text"])) / len(grams(r["text"]))
        assert abs(r["_q"]["score"] - want) < 2  # few of 32,768 buckets are shared


def test_conversations_keep_their_id_type(spark):
    f = spark.createDataFrame([("a", 0, "user", "x"), ("b", 0, "assistant", None)], "conv_id string, turn long, role string, text string")
    path = str(public_tokenizers.path("byte_bpe_50k.json"))
    assert sorted(r["conv_id"] for r in chat.format_conversations(f, path).collect()) == ["a", "b"]
    assert chat.format_conversations(f.where("false"), path).count() == 0


def test_pipeline_of_awkward_rows(spark, tmp_path):
    """Null and repeated ids, null texts, a clashing column; and an empty table."""
    import corpus_pipeline

    good = [words(120, 700 + k) for k in range(4)]
    rows = [(None, good[0]), (None, good[1]), (5, good[2]), (5, good[3]), (5, good[3]), (6, None), (7, "")]
    kind = "doc_id long, text string, lang string, source string, n_chars long, _q string"
    for name, some in (("a", rows), ("b", [])):
        spark.createDataFrame([(i, t, "en", "s", 1, "z") for i, t in some], kind).write.parquet(f"{tmp_path}/{name}/documents.parquet")
        spark.createDataFrame([(5, 1, 0)], "doc_id long, quality int, toxic int").write.parquet(f"{tmp_path}/{name}/labels.parquet")
        spark.createDataFrame([(0, words(30, 54))], "item_id long, text string").write.parquet(f"{tmp_path}/{name}/benchmark.parquet")
    assert corpus_pipeline.run(spark, f"{tmp_path}/b").count() == 0
    assert sorted(r["doc_id"] or -1 for r in corpus_pipeline.run(spark, f"{tmp_path}/a").collect()) == [-1, -1, 5, 5]


def test_buckets_of_several_groups_equal_all_pairs(spark):
    """Chains of edits, where a bucket's centre links few of its rows; dealt out in slots or not."""
    r = random.Random(8)
    rows = []
    for k in range(2):
        w = words(60, 800 + k).split()
        for _ in range(60):
            rows.append((len(rows), " ".join(w)))
            w[r.randrange(60)] = words(1, r.randrange(10**6))
    sets = copies.shingle_sets([t.encode() for _, t in rows])
    root = list(range(len(rows)))

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    for a in range(len(rows)):
        for b in range(a):
            if copies.similarity(sets[a], sets[b]) >= 0.8:
                p, q = find(a), find(b)
                root[max(p, q)] = min(p, q)
    want = sorted({find(k) for k in range(len(rows))})
    got = {hot: None for hot in (4000, 20)}
    for hot in got:
        frame = docs(spark, rows)
        slim = copies.banded(frame.selectExpr("doc_id AS id", "xxhash64(doc_id) AS row", "text"))
        groups = dict(tuple(x) for x in simhash.components(copies.links(slim, copies.fingered(frame), hot=hot)).collect())
        name = {int(copies.set_hash(s).view(np.int64)): k for k, s in enumerate(sets)}
        got[hot] = sorted({min(name[f] for f in name if groups.get(f, f) == groups.get(g, g)) for g in name})
    assert got == {4000: want, 20: want}
    assert copies.bucket_links([1, 2], [1, 2], np.zeros(2, np.uint64), [np.arange(4, dtype=np.uint64), np.arange(5, dtype=np.uint64)]) == [(2, 1)]


def test_stage_proposes_pairs_through_pivot_tables(spark):
    """Texts that are a few words apart in a long text, equal SimHashes of different sets, and strangers."""
    rows = [(k, edited(words(600, 300 + k // 4), k % 4, f"z{k}")) for k in range(40)] + [(100, None), (101, "")]
    frame = spark.createDataFrame([(k, k, t) for k, t in rows], "id long, row long, text string")
    slim = copies.banded(frame)
    sets = copies.shingle_sets([(t or "").encode() for _, t in rows])
    number = {int(copies.set_hash(s).view(np.int64)): i for i, s in enumerate(sets)}
    sims = [int(copies.fingerprint(s)) for s in sets]
    assert [r["sim"] % 2**64 for r in slim.orderBy("id").collect()] == sims

    def groups(pairs):
        root = {i: i for i in number.values()}
        for a, b in pairs:
            low, high = sorted((root[a], root[b]))
            root = {i: low if r == high else r for i, r in root.items()}
        return root

    close = [(i, j) for i in number.values() for j in number.values() if i < j and (sims[i] ^ sims[j]).bit_count() <= 3]
    found = [(number[r["a"]], number[r["b"]]) for r in copies.pivot_pairs(slim).collect()]
    assert close and groups(found) == groups(close)


@pytest.mark.parametrize("kind", ("long", "string", "int"))
def test_trusted_texts_are_found_by_bitmap_and_join(spark, monkeypatch, kind):
    """A full bitmap, ids of other types, null and repeated ids: the weights stay those of a plain join."""
    rows = [(k if k % 9 else None, words(20, k % 11)) for k in range(200)] + [(7, words(20, 99)), (7, words(20, 98))]
    frame = spark.createDataFrame(rows, "doc_id long, text string").withColumn("doc_id", F.col("doc_id").cast(kind))
    labels = spark.createDataFrame([(k, 1, 0) for k in range(0, 200, 7)] + [(None, 1, 0), (7, 1, 0)], "doc_id long, quality int, toxic int")
    trusted = {str(k) for k in range(0, 200, 7)}
    good = quality.fit(frame, labels)
    same = labels.withColumn("doc_id", F.col("doc_id").cast(kind))
    assert quality.fit(frame, same) == good
    monkeypatch.setattr(quality, "MOST_BITS", 64)
    assert quality.fit(frame, same) == good
    only = frame.where(F.col("doc_id").cast("string").isin(*trusted))
    monkeypatch.setattr(quality, "may_be_in", lambda ids, key: F.lit(True))
    assert quality.fit(frame, only.selectExpr("doc_id", "1 AS quality", "0 AS toxic")) == good and any(good)


def test_trusted_texts_only_are_moved(spark):
    frame = spark.range(4000).selectExpr("id AS doc_id")
    told = frame.where(quality.may_be_in(frame.where("doc_id % 50 = 0"), F.col("doc_id")))
    ids = {r[0] for r in told.collect()}
    assert set(range(0, 4000, 50)) <= ids and len(ids) < 1200


def test_stages_run_on_small_batches(spark):
    import corpus_pipeline

    key = "spark.sql.execution.arrow.maxRecordsPerBatch"
    before = spark.conf.get(key)
    try:
        frame = spark.createDataFrame([(k, words(3, k), "en", "s", 1) for k in range(3000)], "doc_id long, text string, lang string, source string, n_chars long").coalesce(1)
        out = corpus_pipeline.encode(spark, frame, "")
        sizes = frame.select("doc_id").mapInArrow(lambda it: (pa.RecordBatch.from_pydict({"n": pa.array([b.num_rows], pa.int64())}) for b in it), "n long")
        assert max(r["n"] for r in sizes.collect()) <= corpus_pipeline.BATCH_ROWS and out.count() == 3000
    finally:
        spark.conf.set(key, before)
        spark.conf.unset("spark.sql.execution.arrow.maxBytesPerBatch")


def test_stages_leave_no_shuffle_files(spark):
    import time
    from pathlib import Path

    import corpus_pipeline

    key = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"
    spark.conf.set(key, "false")
    places = [Path(str(p)) for p in spark._jvm.org.apache.spark.SparkEnv.get().blockManager().diskBlockManager().localDirs()]
    held = lambda: {f for p in places for f in p.rglob("shuffle_*.data")}
    try:
        before = held()
        text = words(200, 1200)
        frame = spark.createDataFrame([(k, edited(text, k % 4, f"s{k}"), "en", "s", 1) for k in range(12)], "doc_id long, text string, lang string, source string, n_chars long")
        assert len(corpus_pipeline.keep_one_of_group(spark, frame, "").collect()) == 1
        for _ in range(50):
            left = held() - before
            if not left:
                break
            time.sleep(0.2)
        assert not left
    finally:
        spark.conf.unset(key)
