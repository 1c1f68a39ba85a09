import hashlib
import math
import random
import re
from collections import Counter

import numpy as np
import pytest

from groupmatch.llm import bpe, curriculum, language, licences, ngram_jaccard, perplexity, secret_scan, urls, warc

WORD = re.compile(r"[^\x20\x09-\x0D]+")
ODD = [(None, None, None, None), (1, "", "en", "b"), (2, " \n\t ", None, None), (3, "word", "en", "a"), (3, "word", "en", "a"), (4, "é 字 😀\x00x " * 3000, "fr", "b")]


def table(spark, rows):
    # A column whose name is also one of the results.
    return spark.createDataFrame([(*r, 7) for r in rows], "doc_id long, text string, lang string, source string, n_words int")


def texts(seed=1, n=60):
    rng = random.Random(seed)
    base = [" ".join(rng.choice("alpha beta gamma delta the of one two".split()) + str(rng.randrange(40)) for _ in range(60)) for _ in range(n // 3)]
    out = []
    for i in range(n):
        words = base[i % len(base)].split()
        for _ in range(rng.randrange(4) if i >= len(base) else 0):
            words[rng.randrange(len(words))] = f"edit{rng.randrange(1000)}"
        out.append(" ".join(words))
    return out


def brute_components(rows, n, percent):
    low = str.maketrans({chr(c): chr(c + 32) for c in range(65, 91)})
    sets = []
    for _, t, *_ in rows:
        w = WORD.findall((t or "").translate(low))
        sets.append({tuple(w[k : k + n]) for k in range(max(1, len(w) - n + 1))} if w else set())
    root = list(range(len(rows)))

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    for i in range(len(rows)):
        for j in range(i):
            if sets[i] and sets[j] and 100 * len(sets[i] & sets[j]) >= percent * len(sets[i] | sets[j]):
                root[find(i)] = find(j)
    least = {}
    for i, r in enumerate(rows):
        if r[0] is not None:
            least[find(i)] = min(least.get(find(i), r[0]), r[0])
    return Counter((r[0], len(s), least.get(find(i))) for i, (r, s) in enumerate(zip(rows, sets)))


@pytest.mark.parametrize("percent, n", [(85, 4), (80, 5), (60, 2)])
def test_jaccard_equals_brute_force(spark, percent, n):
    rows = ODD + [(100 + i, t, "en", "a") for i, t in enumerate(texts(n))]
    got = ngram_jaccard.jaccard_components(table(spark, rows), n, percent, parts=3)
    assert Counter(map(tuple, got.collect())) == brute_components(rows, n, percent)


def test_jaccard_squares(spark, monkeypatch):
    """Large areas are cut into several squares without losing links."""
    monkeypatch.setattr(ngram_jaccard, "SIDE", 4)
    rows = [(i, t, "en", "a") for i, t in enumerate(texts(9, 90))]
    assert Counter(map(tuple, ngram_jaccard.jaccard_components(table(spark, rows), 3, 80, parts=2).collect())) == brute_components(rows, 3, 80)


def test_jaccard_keeps_one_and_empty_table(spark):
    rows = ODD + [(50, "a b c d e f g", "en", "a"), (51, "A B c d e f g", "en", "b")]
    kept = [r.doc_id for r in ngram_jaccard.keep_one(table(spark, rows)).collect()]
    assert sorted(k for k in kept if k) == [1, 2, 3, 4, 50] and None in kept
    assert ngram_jaccard.jaccard_components(table(spark, [])).count() == 0 and ngram_jaccard.keep_one(table(spark, [])).count() == 0


def test_jaccard_keeps_unlike_texts_of_one_number(spark):
    words = "a b c d e f g h i j".split()
    rows = [(1, " ".join(words), "en", "a"), (1, " ".join(reversed(words)), "en", "a"), (1, " ".join(words), "en", "b"), (None, " ".join(words), "en", "c"), (2, "z " * 9, "en", "a"), (2, "z " * 9, "en", "a"), (7, "", "en", "a"), (7, "", "en", "a")]
    kept = Counter((r.doc_id, r.text) for r in ngram_jaccard.keep_one(table(spark, rows)).collect())
    assert kept == {(1, rows[0][1]): 1, (1, rows[1][1]): 1, (2, "z " * 9): 1, (7, ""): 2}


def test_base_rules_equal_brute_force(spark):
    rng = random.Random(3)
    rows = ODD + [(10 + i, "\n".join(" ".join(rng.choice(["a", "b#", "é", "<x>"]) for _ in range(rng.randrange(9))) for _ in range(rng.randrange(1, 30))), rng.choice(["en", "fr", None]), "s") for i in range(80)]

    def brute(t):
        t = t or ""
        w = WORD.findall(t)
        grams = Counter(tuple(w[k : k + 5]) for k in range(len(w) - 4))
        cover = {k + j for k in range(len(w) - 4) if grams[tuple(w[k : k + 5])] > 1 for j in range(5)}
        seen, dup = set(), 0
        for line in t.split("\n"):
            dup += bool(WORD.search(line)) and line in seen
            seen.add(line)
        return len(w), sum(map(len, w)), sum(c in "#*$%&|<>" for c in t), dup, len(cover), len(w) < 10 or 100 * len(cover) > 20 * len(w)

    out = perplexity.judge(table(spark, rows)).collect()
    key = lambda r: (r[0] is None, r[0] or 0, repr(r))
    got = sorted(((r.doc_id, r.n_words, r.word_chars, r.n_symbols, r.n_dup_lines, r.n_repeat_words, r.base_failed) for r in out), key=key)
    assert got == sorted(((i, *brute(t)) for i, t, *_ in rows), key=key)
    assert not any(r.kept for r in out if r.base_failed)


def kneser_ney(texts, reach=5):
    """log p of every 5-gram's last character by modified Kneser-Ney, from the definitions."""
    pad = chr(perplexity.PAD)
    grams = Counter()
    for t in texts:
        s = pad * (reach - 1) + t + pad
        grams.update(s[k : k + reach] for k in range(len(s) - reach + 1))
    counts = {reach: grams}
    for k in range(reach - 1, 0, -1):
        counts[k] = Counter(g[1:] for g in counts[k + 1])
    lower = {"": 1.0 / len(counts[1])}
    for k in range(1, reach + 1):
        seen = Counter(counts[k].values())
        d = [0, 0.5, 0.5, 0.5]
        if seen[1] and seen[2]:
            y = seen[1] / (seen[1] + 2 * seen[2])
            d = [0] + [min(max(j - (j + 1) * y * seen[j + 1] / seen[j] if seen[j] else 0.5, 0.05), j - 0.05) for j in (1, 2, 3)]
        total, mass = Counter(), Counter()
        for g, n in counts[k].items():
            total[g[:-1]] += n
            mass[g[:-1]] += d[min(n, 3)]
        lower = {g: max(n - d[min(n, 3)], 0) / total[g[:-1]] + mass[g[:-1]] / total[g[:-1]] * lower[g[1:] if k > 1 else ""] for g, n in counts[k].items()}
    return {g: math.log(p) for g, p in lower.items()}


@pytest.mark.parametrize("broadcast_rows", [perplexity.BROADCAST_ROWS, 0])
def test_perplexity_equals_brute_force(spark, broadcast_rows):
    """Scores, both bounds and verdicts, with the model broadcast and with documents in chunks."""
    rng = random.Random(5)
    stock = {"en": "the cat sat on a mat while dogs ran far away from home".split(), "ru": "кот дом вода небо город снег 日本".split(), None: "x yy zzz".split()}
    rows = ODD + [(10 + i, " ".join(rng.choice(stock[x]) for _ in range(rng.randrange(10, 40))), x, "s") for i in range(90) for x in [rng.choice(list(stock))]]
    rows += [(500, "qzx#" * 30 + " q z x v k j p w g y", "en", "s"), (501, "on a mat " * 3 + "while dogs ran far", "en", "s"), rows[20]]
    got = perplexity.judge(table(spark, rows), 3.5, broadcast_rows=broadcast_rows).collect()
    assert len(got) == len(rows)
    by = {}
    for r in rows:
        by.setdefault(r[2] or "", []).append(r[1] or "")
    pad, scores = chr(perplexity.PAD), {}
    for lang, texts in by.items():
        log_p = kneser_ney([t for t in texts if t])
        for t in texts:
            s = pad * 4 + t + pad
            scores[lang, t] = -sum(log_p[s[k : k + 5]] for k in range(len(s) - 4)) / (len(s) - 4) if t else None
    bounds = {}
    for lang in by:
        cells = sorted(round(scores[lang, t] * 1000) for t in {r.text for r in got if (r.lang or "") == lang and not r.base_failed})
        if cells:
            m = cells[(len(cells) - 1) // 2]
            s = max(1.4826 * sorted(abs(c - m) for c in cells)[(len(cells) - 1) // 2], 2.0)
            bounds[lang] = ((m - 3.5 * s) / 1000, (m + 3.5 * s) / 1000)
    low = high = 0
    for r in got:
        want = scores[r.lang or "", r.text or ""]
        assert (r.log_ppl is None and want is None) or abs(r.log_ppl - want) < 1e-5
        a, b = bounds.get(r.lang or "", (-math.inf, math.inf))
        assert abs(r.lower - a) < 1e-6 or r.lower == a
        assert abs(r.upper - b) < 1e-6 or r.upper == b
        assert r.kept == (not r.base_failed and (want is None or a <= r.log_ppl <= b))
        low, high = low + (want is not None and want < a and not r.base_failed), high + (want is not None and want > b and not r.base_failed)
    assert high and perplexity.judge(table(spark, []), broadcast_rows=broadcast_rows).count() == 0


def test_reject_keeps_columns(spark):
    rows = ODD + [(10 + i, " ".join(random.Random(i).choices("one two three four five six seven".split(), k=12)), "en", "a") for i in range(20)]
    out = perplexity.reject(table(spark, rows))
    assert out.columns == ["doc_id", "text", "lang", "source", "n_words"] and {r.n_words for r in out.collect()} == {7}


def test_perplexity_rejects_gibberish(spark):
    rng = random.Random(1)
    plain = [(i, " ".join(rng.choice("the quick brown fox jumps over lazy dogs while birds sing songs at dawn".split()) for _ in range(40)) + f" {i}", "en", "s") for i in range(60)]
    bad = (999, " ".join("".join(rng.choice("xzqjkvwpç§€") for _ in range(9)) for _ in range(40)), "en", "s")
    kept = {r.doc_id for r in perplexity.reject(table(spark, [*plain, bad])).collect()}
    assert kept == set(range(60))


def test_perplexity_bands_reject_labelled_junk(spark):
    """Word lists and words with added symbols are outside the bands, prose with a good label is inside."""
    docs = spark.read.parquet("/root/testdata/sf0.01/documents.parquet").select("doc_id", "text", "lang")
    labels = spark.read.parquet("/root/testdata/sf0.01/labels.parquet").groupBy("doc_id").max("quality").toDF("doc_id", "quality")
    got = Counter((r.quality, r.kept) for r in perplexity.judge(docs).where("NOT base_failed AND lang = 'en'").join(labels, "doc_id").collect())
    assert got[0, False] >= 0.5 * (got[0, True] + got[0, False]) > 0
    assert got[1, False] <= 0.05 * got[1, True]


def test_perplexity_rejects_shuffled_words(spark):
    rng = random.Random(2)
    lines = ["the quick brown fox jumps over", "some lazy dogs sleep near houses", "while birds sing songs at dawn", "nobody listens to what we say", "rivers carry stones down into valleys", "an old man walks home slowly"]
    lines += ["children play games behind that wall", "their mother bakes bread every morning", "cold winds blow from northern mountains", "ships bring goods across wide oceans"]
    plain = [(i, " ".join(rng.sample(lines, 6)) + f" {i}", "en", "s") for i in range(80)]
    shuffled = []
    for i, text, *_ in plain[:3]:
        words = text.split()
        rng.shuffle(words)
        shuffled.append((900 + i, " ".join(words), "en", "s"))
    got = {r.doc_id: r for r in perplexity.judge(table(spark, [*plain, *shuffled])).collect()}
    assert all(got[r[0]].log_ppl > got[r[0]].upper for r in shuffled)
    assert sum(got[r[0]].kept for r in plain) >= 76


def test_perplexity_grows_with_scripts(spark):
    """Characters are not folded: letters 18 apart differ, each script gets entries, and probabilities sum to one."""
    grams = lambda texts: perplexity.count_grams(spark.createDataFrame([(0, "x", t) for t in texts], "chunk int, lang string, text string"))
    rng = random.Random(8)
    cyrillic = "".join(chr(0x430 + k % 32) for k in range(400))
    folded = "".join(chr(0x430 + k % 18) for k in range(400))
    assert grams([cyrillic]).count() > grams([folded]).count() and grams(["日本語 한국어 😀😁"]).count() == 11
    table_ = perplexity.train(grams([cyrillic, "ab ac ab ad"]))
    heads = Counter()
    for r in table_.collect():
        assert r.log_p < 0
        heads[r.gram[:4]] += np.exp(r.log_p)
    assert max(heads.values()) <= 1 + 1e-5
    plain = [(i, " ".join(rng.choice(["слово", "город", "вода", "земля", "небо", "река", "гора"]) for _ in range(40)) + f" {i}", "ru", "s") for i in range(60)]
    odd = (999, "".join(chr(ord(c) + 18) if "а" <= c <= "н" else c for c in plain[0][1]), "ru", "s")
    got = {r.doc_id: r.log_ppl for r in perplexity.judge(table(spark, [*plain, odd])).collect()}
    assert got[999] > got[0] + 0.02


def test_secrets(spark):
    key = "AKIA" + "Q7XZ2MPL9RT4WY6B"
    hexed = hashlib.sha1(b"x").hexdigest()
    common = "Zx9Lm2Qp7Rt4Vw8Ky3Nb6"
    odd = f"é token = '{common}' {key} password: abc, SECRET=\"{hexed}\" secret=token: abcdefgh"
    rows = ODD + [(10, odd, "en", "s1")] + [(20 + i, f"x token={common}", "en", f"s{i}") for i in range(4)] + [(30, "Ab3dEf7hIj1LmNo5PqRs9TuVwX2yZ4aB6", "en", "s9")]
    got = {r.doc_id: r for r in secret_scan.scan(table(spark, rows)).collect()}

    def spans(t):
        out = []
        for k, (name, pattern, group, least) in enumerate([("assign", secret_scan.ASSIGN, 2, 6), ("access", r"AKIA[A-Z0-9]+", 0, 20), ("hex", r"[0-9a-f]+", 0, 24)]):
            out += [(m.start(), k, name, m.end()) for m in re.finditer(pattern, t) if len(m[group]) >= least]
        return ",".join(f"{n}:{a}:{b}" for a, _, n, b in sorted(out))

    for i, t, *_ in rows:
        r, text = got[i], spans(t or "")
        assert r.base_sha256 == hashlib.sha256(text.encode()).hexdigest()
        if i != 30:
            assert r.spans == text
    assert got[30].spans == "live:0:33" and got[10].n_example == 1 and got[20].n_live == 0
    masked = {r.doc_id: r.text for r in secret_scan.mask(table(spark, rows)).collect()}
    assert key not in masked[10] and hexed not in masked[10] and common in masked[10] and masked[30] == secret_scan.MASK
    assert len(secret_scan.mask(table(spark, rows)).collect()) == len(rows) and secret_scan.scan(table(spark, [])).count() == 0


def test_short_secrets_are_masked(spark):
    """Owner-specific values go from six characters on and with few distinct characters; placeholders stay."""
    few = "abc123abc123abc123abc123"
    values = ["hunter2secret", "s3cr3t", few, "myexamplecode9"]
    kept = ["changeme", "xxxxxxxx", "your_api_key", "common7"]
    rows = [(i, f"a password: {v} b", "en", "s1") for i, v in enumerate(values + kept)] + [(20 + i, "password: common7", "en", f"t{i}") for i in range(3)]
    masked = {r.doc_id: r.text for r in secret_scan.mask(table(spark, rows)).collect()}
    assert all(masked[i] == f"a {secret_scan.MASK} b" for i in range(4))
    assert all(masked[4 + i] == f"a password: {v} b" for i, v in enumerate(kept))


def test_bpe_equals_library(spark):
    import public_tokenizers
    from tokenizers import Tokenizer

    path = public_tokenizers.path("byte_bpe_50k.json")
    tok = Tokenizer.from_file(path)
    rng = random.Random(2)
    pool = "ab cdé'ßstremvdl \n\t  .,!ⅷ9٣字　\x1c\x85😀\r"
    rows = ODD + [(10 + i, "".join(rng.choice(pool) for _ in range(rng.randrange(80))), "en", "a") for i in range(200)] + [(900, "a<|endoftext|> 's don't'll", "en", "a")]
    out = bpe.encode(table(spark, rows), path, lexicon_size=64).collect()
    assert len(out) == len(rows)
    for r in out:
        assert list(r.ids) == tok.encode(r.text or "", add_special_tokens=False).ids and r.n_tokens == len(r.ids) and r.n_words == 7
    digests = {r.doc_id: r for r in bpe.encode(table(spark, rows), path, digests=True).collect()}
    for i, t, *_ in rows:
        assert digests[i].decoded_sha256 == hashlib.sha256((t or "").encode()).hexdigest()
    assert bpe.encode(table(spark, []), path).count() == 0


def test_lexicon_shares_suffixes(tmp_path):
    import public_tokenizers

    v = bpe.Vocabulary(open(public_tokenizers.path("byte_bpe_50k.json"), "rb").read())
    words = [a + b for a in (b"walk", b"talk", b"stalk") for b in (b"ing", b"ed", b"s", b"")]
    block = bpe.compile_lexicon(words, v)
    place = tmp_path / "lexicon"
    place.write_bytes(block)
    lex = bpe.Lexicon.open(str(place))
    buffer = b"".join([*words, b"walkin"])
    lengths = np.array([len(w) for w in words] + [6])
    found = lex.find(buffer, np.concatenate(([0], np.cumsum(lengths)))[:-1], lengths)
    assert sorted(found[:-1]) == list(range(len(words))) and found[-1] == -1
    assert len(lex.final) < sum(map(len, words)) / 3


def test_mix(spark):
    rng = random.Random(4)
    rows = ODD + [(10 + i, " ".join("w" * rng.randrange(1, 60)), "en", rng.choice(["a", "a", "a", "b", "c", None])) for i in range(150)]
    out = curriculum.mix(table(spark, rows)).collect()
    assert len(out) == len(rows)
    size, target, taken = Counter(), {}, Counter()
    for r, (_, t, _, s) in zip(sorted(out, key=lambda r: (r.doc_id is None, r.doc_id or 0)), sorted(rows, key=lambda r: (r[0] is None, r[0] or 0))):
        assert r.size == len(WORD.findall(t or "")) and 0 <= r.taken <= 2 * r.size
        size[s] += r.size
        target[s] = r.target
        taken[s] += r.taken
    weight = dict(zip(sorted(size, key=lambda s: (s is None, s or "")), [3, 1, 2, 3]))
    level, total = 0.0, 1.5 * sum(size.values())
    for _ in range(20):
        full = {s for s in size if 2 * size[s] <= weight[s] * level}
        level = (total - sum(2 * size[s] for s in full)) / sum(weight[s] for s in size if s not in full)
    for s in size:
        assert abs(target[s] - min(2 * size[s], weight[s] * level)) < 1e-6 and abs(taken[s] - target[s]) <= 1
    again = {(r.doc_id, r.taken, r.position) for r in curriculum.mix(table(spark, rows).repartition(3)).collect()}
    assert again == {(r.doc_id, r.taken, r.position) for r in out}
    words = sum(len(WORD.findall(r.text)) for r in curriculum.train_order(table(spark, rows)).collect())
    assert words == sum(taken.values()) and curriculum.mix(table(spark, [])).count() == 0


def test_language(spark):
    rng = random.Random(6)
    stock = {"en": "the of and to in is that it was for".split(), "fr": "le la les de des une est dans pour qui".split()}
    rows = ODD[:3] + [(10 + i, " ".join(rng.choice(stock[x]) for _ in range(20)), x, "s") for i in range(200) for x in [rng.choice(["en", "fr"])]] + [(999, "123 !", "en", "s")]
    out = {r.doc_id: r for r in language.identify(table(spark, rows)).collect()}
    for i, t, x, _ in rows:
        if i is None or i < 10 or i == 999:
            assert out[i].lang_pred == "und" and out[i].score == 0.0
        else:
            assert out[i].lang_pred == x and 0 <= out[i].score <= 1
    assert language.identify(table(spark, [])).count() == 0


def test_licences(spark):
    text = licences.KNOWN["MIT"].upper().replace("YEAR HOLDER", "2020 SOMEBODY, INC.").replace("SUBLICENSE", "Sub-Licence")
    got = {r.doc_id: r.license_id for r in licences.scan(table(spark, [*ODD, (10, text, "en", "a"), (11, text + " but", "en", "a")])).collect()}
    assert got[10] == "MIT" and got[11] is None and got[None] is None


def test_urls(spark):
    rows = [(1, "http://Sub.Example.org/es/x"), (2, "http://example.org/en/12"), (3, "https://a.com/de/?q"), (4, "http://www.spam-farm.example.net/x/"), (5, None), (6, "nothing"), (7, "http://tionsh.example.net/en/404/#x"), (8, "http://tionsh.example.net/en/4045")]
    out = {r.page_id: r for r in urls.judge(spark.createDataFrame([(*r, "h", 1) for r in rows], "page_id long, url string, html string, host int")).collect()}
    assert [out[i].verdict for i in range(1, 9)] == ["block", "block", "block", "block", "allow", "allow", "block", "allow"]
    assert out[1].rule == "example.org/es/" and out[4].rule is None and out[5].host == "" and out[3].path == "/de/"
    keys = [f"k{i}" for i in range(1000)]
    bloom = urls.build_bloom(spark.createDataFrame([(k,) for k in keys], "key string"))
    assert bloom.may_hold(keys).all() and bloom.may_hold([f"z{i}" for i in range(1000)]).mean() < 0.05


def test_warc_round_trip(spark):
    rows = [(1, "http://a/", '<head><title>T &amp; x</title></head><p>One<br>two</p><script>no()</script><a href="/l?a=1&amp;b">L</a>'), (2, None, None), (3, "http://b/", "")]
    out = warc.build(spark.createDataFrame(rows, "page_id long, url string, html string")).collect()
    assert len(out) == 6
    for r in out:
        (heads, body), = warc.from_bytes(warc.to_bytes(r.asDict()))
        assert heads["WARC-Refers-To"] == r.refers_to and warc.digest(body) == heads["WARC-Block-Digest"] and body.decode() == r.content
    one = {r.record_type: r for r in out if r.page_id == 1}
    assert one["conversion"].content == "One\ntwo\nL" and "outlink: /l?a=1&b L a/@href" in one["metadata"].content and "title: T & x" in one["metadata"].content
    assert one["conversion"].refers_to == one["metadata"].refers_to and one["conversion"].record_id != one["metadata"].record_id


def test_warc_headers_stay_in_their_lines(spark):
    rows = [(1, "http://a/\r\nWARC-Type: x\r\n\r\n", "<p>x</p>", 5), (1, "http://a/\r\nWARC-Type: x\r\n\r\n", "<p>x</p>", 5), (2, "http://b/", "<p>" + "long " * 200_000 + "</p>", 6)]
    schema = "page_id long, url string, html string, record_type int"
    out = warc.build(spark.createDataFrame(rows, schema)).collect()
    assert len(out) == 6
    for r in out:
        # Read by hand: the head ends at the first empty line, each line has one name, the length is that of the body.
        raw = warc.to_bytes(r.asDict())
        head, _, rest = raw.partition(b"\r\n\r\n")
        lines = head.decode().split("\r\n")
        assert lines[0] == "WARC/1.1" and sum(x.startswith("WARC-Type: ") for x in lines) == 1
        size = int(next(x for x in lines if x.startswith("Content-Length: ")).split(": ")[1])
        assert rest[:size].decode() == r.content and rest[size:] == b"\r\n\r\n"
    assert warc.build(spark.createDataFrame([], schema)).count() == 0
    import gzip

    packed = warc.archives(warc.build(spark.createDataFrame(rows[2:], schema)), 2).collect()
    found = [x for r in packed for x in warc.from_bytes(gzip.decompress(bytes(r.archive)))]
    assert sum(r.records for r in packed) == len(found) == 2 and {h["WARC-Type"] for h, _ in found} == {"metadata", "conversion"}


def test_language_learns_rare_languages(spark):
    """A language of few rows among many is learned from all of them; repeated and long rows are judged each."""
    rng = random.Random(7)
    stock = {"en": "the of and to in is that it was for".split(), "de": "der die und das ist nicht ein mit auf zu".split()}
    rows = [(i, " ".join(rng.choice(stock["en"]) for _ in range(12)), "en", "s") for i in range(600)] + [(1000 + i, " ".join(rng.choice(stock["de"]) for _ in range(12)), "de", "s") for i in range(12)]
    rows += [rows[0], (5000, "und das ist nicht " * 30_000, None, "s")]
    out = language.identify(table(spark, rows), per_lang=100).collect()
    got = {r.doc_id: r.lang_pred for r in out}
    assert len(out) == len(rows) and got[5000] == "de" and all(got[1000 + i] == "de" for i in range(12))


def test_urls_of_odd_tables(spark):
    schema = "page_id long, url string, html string, host int"
    rows = [(1, "http://x.spam-farm.example.net/" + "a/" * 3000, "h", 1)] * 3 + [(None, None, None, None)]
    out = urls.judge(spark.createDataFrame(rows, schema)).collect()
    assert sorted((r.page_id or 0, r.verdict) for r in out) == [(0, "allow"), (1, "block"), (1, "block"), (1, "block")]
    assert urls.judge(spark.createDataFrame([], schema)).count() == 0


@pytest.mark.parametrize("name", [k for k in licences.KNOWN if "notice" not in k])
def test_licence_copies_match(spark, name):
    """Re-cased, re-wrapped and re-punctuated copies, with or without heading, with other copyright lines."""
    body = licences.KNOWN[name].split("\n\n", 1)[1]
    if body.lower().startswith("copyright"):
        body = body.split("\n\n", 1)[1]
    words = body.split()
    wrapped = "\n".join(" * " + " ".join(words[k : k + 9]) for k in range(0, len(words), 9))
    rows = [(1, body.upper(), "en", "a"), (2, "Copyright © 2019 A. Body\nAll rights reserved.\n\n" + wrapped, "en", "a"), (3, body.replace(",", " ,").replace('"', "\u201c"), "en", "a"), (4, body + " indeed", "en", "a"), (5, " ".join(words[:-1]), "en", "a")]
    got = {r.doc_id: r.license_id for r in licences.scan(table(spark, rows)).collect()}
    assert [got[i] for i in range(1, 6)] == [name, name, name, None, None]
    assert licences.scan(table(spark, [])).count() == 0
