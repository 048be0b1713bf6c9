"""Operators against brute force on small tables, with nulls, empty and long texts, ties and repeated rows."""

import html
import json
import re
import zlib
from collections import Counter

import numpy as np
import pytest
from pyspark.sql import functions as F

import corpus_pipeline
from turnstile_cover.llm import chat, html_extract, langid, lm, packing, pii
from turnstile_cover.llm import jaccard_join as joins
from turnstile_cover.llm.components import connected_components
from turnstile_cover.llm.decontam import decontaminate
from turnstile_cover.llm.quality import repetition
from turnstile_cover.llm.queries import OP10_SQL, QUERIES, table
from turnstile_cover.llm.substring_dedup import remove_repeats, repeated_spans

WORD = re.compile(r"[^\x20\x09-\x0D]+")
ALNUM = re.compile(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+")
ODD = [None, "", " \n\t ", "one", "a\nb\na\n", "é ü \U0001f600", "z " * 3000, "x y", "x y"]


def low(t):
    return re.sub("[A-Z]", lambda m: m[0].lower(), t or "")


def frame(spark, texts, first=0, extra=False):
    df = spark.createDataFrame([(first + i, t) for i, t in enumerate(texts)], "doc_id long, text string").repartition(3)
    return df.withColumns({"n_words": F.lit("clash"), "th": F.lit(1), "kept": F.lit("x"), "start": F.lit(0)}) if extra else df


@pytest.fixture(scope="module")
def docs(spark, sf):
    return [(r[0], r[1]) for r in table(spark, sf, "documents").where("doc_id < 400").select("doc_id", "text").collect()]


def texts_of(docs):
    return [t for _, t in docs] + ODD


def test_quality_counts(spark, docs):
    texts = texts_of(docs)
    got = {r["doc_id"]: r for r in repetition(frame(spark, texts, extra=True)).collect()}
    for i, t in enumerate(texts):
        w, lines, t = WORD.findall(t or ""), Counter(), t or ""
        dup = 0
        for line in t.split("\n"):
            if WORD.search(line):
                dup += lines[line] > 0
                lines[line] += 1
        grams = Counter(tuple(w[k : k + 3]) for k in range(len(w) - 2))
        inside = [any(grams[tuple(w[s : s + 3])] > 1 for s in range(max(0, k - 2), min(k, len(w) - 3) + 1)) for k in range(len(w))]
        r = got[i]
        assert (r["n_words"], r["word_chars"], r["n_symbols"], r["n_dup_lines"], r["n_repeat_words"]) == (len(w), sum(map(len, w)), len(re.findall(r"[#*$%&|<>]", t)), dup, sum(inside))
        assert r["base_failed"] == (len(w) < 50 or 100 * sum(inside) > 50 * len(w)) and not (r["kept"] and r["base_failed"])


def test_quality_rejects_labelled_junk(spark, sf):
    labels = spark.read.parquet(f"{sf}/labels.parquet").select("doc_id", "quality")
    got = repetition(table(spark, sf, "documents")).where("not base_failed").join(labels, "doc_id").groupBy("quality", "kept").count().collect()
    assert {(r["quality"], r["kept"]) for r in got} == {(0, False), (1, True)}
    words = " ".join(f"w{n}" for n in range(60))
    got = repetition(frame(spark, [words + " |" * 5, words + " |" * 30])).orderBy("doc_id").collect()
    assert [r["broken_rule"] for r in got] == [None, "symbols"]


@pytest.mark.parametrize("sizes", [{}, {"part_words": 4, "pass_parts": 1}, {"part_words": 4, "pass_parts": 2}])
def test_decontamination(spark, docs, sizes):
    items = [(1, "Aa bb cc dd ee ff gg hh ii jj kk"), (2, "bb cc dd ee ff gg hh ii jj kk ll"), (3, "short item"), (4, None), (5, "")]
    texts = texts_of(docs) + ["x aa bb cc dd ee ff gg hh ii jj y", "aa bb cc dd ee ff gg hh ii jj kk ll", "a short, ITEM here short"]
    bench = spark.createDataFrame(items, "item_id long, text string")
    got = {r["doc_id"]: r for r in decontaminate(frame(spark, texts, extra=True), bench, clean=True, **sizes).collect()}
    windows = {}
    for i, t in items:
        w = ALNUM.findall(low(t))
        for k in range(len(w) - min(10, len(w)) + 1 if w else 0):
            windows.setdefault(tuple(w[k : k + 10]), set()).add(str(i))
    for i, t in enumerate(texts):
        w, hit, found = ALNUM.findall(low(t)), set(), set()
        for size in {len(x) for x in windows}:
            for k in range(len(w) - size + 1):
                if tuple(w[k : k + size]) in windows:
                    hit |= set(range(k, k + size))
                    found |= windows[tuple(w[k : k + size])]
        assert (got[i]["n_words"], got[i]["n_hit"], sorted(got[i]["items"])) == (len(w), len(hit), sorted(found))
        assert ALNUM.findall(low(got[i]["text"])) == [x for k, x in enumerate(w) if k not in hit]


def brute_repeats(rows, window):
    first, words = {}, {i: (t or "").encode().split() for i, t in rows}
    for i in sorted(words):
        for k in range(len(words[i]) - window + 1):
            first.setdefault(tuple(words[i][k : k + window]), i)
    out = {}
    for i, w in words.items():
        gone = set()
        for k in range(len(w) - window + 1):
            if first[tuple(w[k : k + window])] < i:
                gone |= set(range(k, k + window))
        out[i] = (len(w), len(gone), b" ".join(x for k, x in enumerate(w) if k not in gone).decode())
    return out


def test_substring_dedup(spark, docs):
    rng = np.random.default_rng(1)
    base = [str(x) for x in rng.integers(0, 500, 400)]
    made = [" ".join(base), " ".join(base[:150] + ["cut"] + base[150:]), " ".join(["p"] * 60 + base[300:]), " ".join(["q"] * 200), " ".join(["q"] * 130)]
    rows = list(enumerate(texts_of(docs) + made + made))
    got = {r["doc_id"]: (r["n_words"], r["n_removed"], r["kept"]) for r in remove_repeats(frame(spark, [t for _, t in rows], extra=True)).collect()}
    assert got == brute_repeats(rows, 50)


def test_substring_dedup_graph(spark):
    """Paths end where texts part; few words, short windows, loops and repeated ids give many branches."""
    a, b, c = ([f"{x}{i}" for i in range(80)] for x in "abc")
    texts = [a + b, a + b, a + c, b[:70]]
    rows = spark.createDataFrame([(i, " ".join(t)) for i, t in enumerate(texts)], "doc_id long, text string")
    spans = sorted((r["doc_id"], r["start"], r["n"], r["origin"], r["pos"]) for r in repeated_spans(rows).collect())
    # the last window of a goes on with b or c; document 3 ends inside the path of b and starts none
    assert spans == [(1, 0, 31, 0, 0), (1, 31, 80, 0, 31), (2, 0, 31, 0, 0), (3, 0, 21, 0, 80)]

    rng = np.random.default_rng(7)
    made = [(int(i), " ".join(rng.choice(list("xyz"), rng.integers(0, 40)))) for i in rng.integers(0, 30, 60)]
    made += [(3, "x y " * 30), (40, "x y " * 30), (40, "z " * 90), (41, "z " * 30 + "y x " * 20)]
    window = 6
    first = {}
    for i, t in sorted(made):
        w = tuple(t.split())
        for k in range(len(w) - window + 1):
            first.setdefault(w[k : k + window], i)
    want = []
    for i, t in made:
        w = t.split()
        gone = {k + x for k in range(len(w) - window + 1) if first[tuple(w[k : k + window])] < i for x in range(window)}
        want.append((i, len(w), len(gone), " ".join(x for k, x in enumerate(w) if k not in gone)))
    got = remove_repeats(spark.createDataFrame(made, "doc_id long, text string"), window).collect()
    assert sorted((r["doc_id"], r["n_words"], r["n_removed"], r["kept"]) for r in got) == sorted(want)



def brute_components(rows, k, percent):
    sets = {}
    for i, t in rows:
        w = WORD.findall(low(t))
        sets[i] = {tuple(w[n : n + k]) for n in range(len(w) - k + 1)} if len(w) >= k else {tuple(w)} if w else set()
    up = {i: i for i in sets}

    def find(x):
        while up[x] != x:
            x = up[x]
        return x

    keys = sorted(sets)
    for n, i in enumerate(keys):
        for j in keys[:n]:
            both = len(sets[i] & sets[j])
            if both and 100 * both >= percent * len(sets[i] | sets[j]):
                a, b = find(i), find(j)
                up[max(a, b)] = min(a, b)
    return {i: (len(sets[i]), find(i)) for i in sets}


@pytest.mark.parametrize(("k", "percent", "size"), [(3, 90, 24 << 20), (5, 80, 20_000)])
def test_jaccard_join(spark, docs, monkeypatch, k, percent, size):
    monkeypatch.setattr(joins, "CHUNK_BYTES", size)
    rng, base = np.random.default_rng(2), [f"w{x}" for x in range(300)]
    made = []
    for _ in range(60):
        w = list(base)
        for at in rng.integers(0, 300, rng.integers(0, 12)):
            w[at] = f"e{rng.integers(10**6)}"
        made.append(" ".join(w))
    rows = list(enumerate(texts_of(docs)[:150] + ODD + made))
    got = {r["doc_id"]: (r["n_shingles"], r["component_id"]) for r in joins.near_duplicates(frame(spark, [t for _, t in rows], extra=True), k, percent).collect()}
    assert got == brute_components(rows, k, percent)


def test_jaccard_join_counts_keys_in_passes(spark, docs, monkeypatch):
    """A key goes through one of several shuffles; before, all keys of all sets went through one."""
    written, write = [], joins.materialize
    monkeypatch.setattr(joins, "materialize", lambda df, name: (written.append(name), write(df, name))[1])
    monkeypatch.setattr(joins, "KEYS_A_PASS", 4000, raising=False)
    rows = list(enumerate(texts_of(docs)[:60]))
    got = {r["doc_id"]: (r["n_shingles"], r["component_id"]) for r in joins.near_duplicates(frame(spark, [t for _, t in rows], extra=True), 5, 80).collect()}
    assert got == brute_components(rows, 5, 80) and 1 < written.count("join-heads") <= joins.MAX_PASSES


def test_packing_is_exact(spark, docs):
    import public_tokenizers
    from tokenizers import Tokenizer

    path = public_tokenizers.path("byte_bpe_50k.json")
    tok = Tokenizer.from_file(path)
    texts = texts_of(docs) + ["a  b ", " <|endoftext|> x", "tab\tand\n line", "word " * 5000]
    want = {i: np.array([*tok.encode(t or "", add_special_tokens=False).ids, 1], "<u4") for i, t in enumerate(texts)}
    pieces = packing.pack(frame(spark, texts, extra=True), path, public_tokenizers.path("byte_bpe_50k.tiktoken"), group_docs=64)
    place, used = Counter(), Counter()
    for r in sorted(pieces.collect(), key=lambda r: (r["doc_id"], r["start"])):
        part = want[r["doc_id"]][r["start"] : r["start"] + r["length"]]
        assert r["start"] == place[r["doc_id"]] and zlib.crc32(part.tobytes()) == r["ids_crc32"] and r["doc_tokens"] == len(want[r["doc_id"]])
        place[r["doc_id"]] += r["length"]
    assert all(place[i] == len(x) for i, x in want.items())
    for r in sorted(pieces.collect(), key=lambda r: (r["sequence_id"], r["offset"])):
        assert used[r["sequence_id"]] == r["offset"]
        used[r["sequence_id"]] += r["length"]
    assert max(used.values()) <= 2048 and packing.padding(pieces).first()["share"] < 0.05


def test_personal_data(spark, docs):
    rules = {"email": r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+", "ip": r"[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)", "card": r"[0-9]([\x20-]?[0-9])+", "phone": r"\+[0-9][\x20().0-9-]+[0-9]"}

    def ok(kind, m):
        d = re.sub("[^0-9]", "", m)
        luhn = sum((x * 2 - 9 if x > 4 else x * 2) if n % 2 else x for n, x in enumerate(map(int, reversed(d)))) % 10 == 0
        return {"email": True, "ip": all(int(x) <= 255 for x in m.split(".")) if kind == "ip" else True, "card": 16 <= len(d) <= 19 and luhn, "phone": 8 <= len(d) <= 15}[kind]

    odd = ["a@b.com_x@y.com x@y@z.com é\U0001f600 q@w.e..t", "1.2.3.4.5.6.7.8 999.1.1.1.1 001.002.3.4", "4111 1111 1111 1111 4111  1111 5555555555554444", "9" * 5000 + " 1" * 4000, "a." * 3000 + "@x.y", "+1 (383) 555-8961 +12"]
    texts = texts_of(docs) + odd + [f"{x} revealing person ann@x.org and {x}" for x in ("u", "v", "w", "t")]
    out = pii.sanitise(frame(spark, texts, extra=True))
    got = {r["doc_id"]: r for r in out.select("doc_id", pii.listed(tuple(pii.KINDS)).alias("base"), pii.listed((*pii.KINDS, "term")).alias("spans"), "text").collect()}
    for i, t in enumerate(texts):
        assert got[i]["base"] == ",".join(f"{k}:{m.start()}:{m.end()}" for k, x in rules.items() for m in re.finditer(x, t or "") if ok(k, m[0]))
    last = got[len(texts) - 1]
    assert "term" in last["spans"] and "revealing" not in last["text"] and "[EMAIL]" in last["text"]
    assert "term" not in got[0]["spans"]


def test_personal_data_in_long_texts(spark):
    """Tens of thousands of spans in one text, pieces across blocks, astral characters: as re places and writes them."""
    many = " \U0001f600 ".join(f"u{i}@x{i % 7}.org {i % 256}.2.3.4 é" for i in range(30_000))
    long = "é\U0001f600x " * 5000 + "a@b.org" + " y" * 9000 + " 1.2.3.4" + "z " * 4096
    edge = "x" * 4090 + " a@b.org" + "y" * 4093 + " 1.2.3.4 " + "z" * 8192
    texts = [many, long, edge, "a@b.org", "", None]
    out = pii.sanitise(spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string"), pii.DisclosureLimits(support=1 << 30))
    got = {r["doc_id"]: r for r in out.select("doc_id", pii.listed(("email", "ip")).alias("spans"), "text").collect()}
    email, ip = r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(?:\.[A-Za-z0-9-]+)+", r"[0-9]+\.[0-9]+\.[0-9]+\.[0-9]+"
    for i, t in enumerate(texts):
        assert got[i]["spans"] == ",".join(f"{k}:{m.start()}:{m.end()}" for k, p in (("email", email), ("ip", ip)) for m in re.finditer(p, t or ""))
        assert got[i]["text"] == re.sub(ip, "[IP]", re.sub(email, "[EMAIL]", t or ""))


def test_terms_outside_spans(spark):
    rng = np.random.default_rng(5)
    rows, want = [], []
    for i in range(60):
        n, m = (int(x) for x in rng.integers(0, (6, 900)[i % 2], 2))
        a, b = (sorted((int(s), int(s + e)) for s, e in zip(rng.integers(0, 8 * (n + m) + 9, k), rng.integers(1, 9, k), strict=True)) for k in (n, m))
        rows.append((i, [(s, e, "s") for s, e in a], [(s, e, "t") for s, e in b]))
        want.append([t for t in b if not any(s < t[1] and t[0] < e for s, e in a)])
    df = spark.createDataFrame(rows, f"i int, spans {pii.SPANS}, terms {pii.SPANS}")
    got = {r["i"]: [(x["start"], x["end"]) for x in r["o"]] for r in df.select("i", pii.outside(F.col("terms"), F.col("spans")).alias("o")).collect()}
    assert all(got[i] == w for i, w in enumerate(want))


def test_members(spark):
    keys = [int(k) for k in np.random.default_rng(3).integers(-(1 << 63), 1 << 63, 30_000)]
    of, rows = (spark.createDataFrame([(k,) for k in x], "k long") for x in (keys[:3000], keys))
    got = {r["k"]: r["member"] for r in pii.with_member(rows, "k", of).collect()}
    assert len(got) == 30_000 and all(got[k] for k in keys[:3000]) and sum(got.values()) < 3000 + 0.2 * 27_000
    assert not any(r["member"] for r in pii.with_member(rows, "k", of.limit(0)).collect())


def term_words(spark, texts, columns="doc_id long, text string"):
    """The term spans' words of each text."""
    rows = pii.sanitise(spark.createDataFrame(list(enumerate(texts)), columns)).select("doc_id", F.transform("term", lambda t: t["value"]).alias("w")).collect()
    return [r["w"] for r in sorted(rows)]


def test_terms_of_values_seen_once(spark):
    plain = [f"{c}{c}{c}{c} other words" for c in "abcdefghijklmnopqrst"]
    kind = [f"to mailbox {c}{c}{c}{c} {c}@{c}.org" for c in "uvwx"]  # four values and domains, each in one text
    got = term_words(spark, plain + kind)
    assert got == [[]] * len(plain) + [["mailbox"]] * len(kind)
    group = [f"to partner {x}@one.org" for x in "abc"] + [f"to else{x} {x}@{x}.net" for x in "klmno"]
    got = term_words(spark, plain + group)
    assert got[len(plain) :] == [["partner"]] * 3 + [[]] * 5


def test_terms_count_texts_and_reach_all(spark):
    plain = [f"noise{n} other words" for n in range(200)]
    three = [f"{x} revealing person{x} ann@x.org" for x in "uvw"]
    copies = term_words(spark, plain + three + three[:1] * 1000)
    assert copies[200:] == [["revealing"]] * 1003
    away = ["a revealing word", "ann@x.org" + " xyz" * 40 + " Revealing"]
    six = three + [f"{x} revealing person{x} ann@x.org" for x in "rst"]
    assert term_words(spark, plain + six + away)[200:] == [["revealing"]] * 7 + [["Revealing"]]
    edge = [f"revealing {x} ann@x.org {x} telling" for x in "uvw"]
    assert term_words(spark, plain + edge)[200:] == [["revealing", "telling"]] * 3
    cut = ["revealing" + f" {x}" + "!" * 74 + "ann@x.org" + "!" * 78 + "telling" for x in "uvw"]  # neither word is whole in the context
    assert term_words(spark, plain + cut)[200:] == [[]] * 3


def test_html(spark, sf):
    pages = table(spark, sf, "pages").limit(80)
    got = {r["page_id"]: r["text"] for r in html_extract.extract(pages).collect()}
    for r in pages.collect():
        inner = re.search(r"<article>(.*)</article>", r["html"], re.S)[1]
        blocks = [" ".join(html.unescape(re.sub(r"<[^>]*>", " ", b)).split()) for b in re.split(r"</?(?:p|h1)>", inner)]
        assert got[r["page_id"]] == "\n".join(b for b in blocks if b)
    odd = spark.createDataFrame([(1, None), (2, ""), (3, "<p"), (4, "plain"), (5, "<article><p>A &lt;b&gt;  c<div class='ad'>buy</div></article>")], "page_id long, html string")
    found = {r["page_id"]: r["text"] for r in html_extract.extract(odd, labelled=pages).collect()}
    assert found[1] == found[2] == "" and "A <b> c" in found[5] and "buy" not in found[5]


def test_language(spark, sf):
    docs = table(spark, sf, "documents")
    held = langid.fold("doc_id", 4) == 2
    model = langid.fit(docs.where(~held), max_rows=800)
    out = langid.identify(docs.where(held), model, keep=("lang",))
    assert out.where("lang = lang_pred").count() >= 0.97 * out.count()
    odd = {r["doc_id"]: r for r in langid.identify(frame(spark, ODD + ["123 !", "ñ"]), model).collect()}
    assert [odd[i]["lang_pred"] for i in (0, 1, 2, len(ODD))] == ["und"] * 4 and odd[len(ODD) + 1]["lang_pred"] != "und"
    assert langid.fit(docs.where("false")) is None and {r["lang_pred"] for r in langid.identify(frame(spark, ODD), None).collect()} == {"und"}


def test_language_model(spark, docs):
    texts = texts_of(docs)
    df = frame(spark, texts)
    train = df.where("doc_id % 10 <> 0")
    got = {r["doc_id"]: r for r in lm.score(df, train, lm.MaxEntSettings(head=300)).collect()}
    counts = Counter(w for i, t in enumerate(texts) if i % 10 for w in [*WORD.findall(low(t)), "\0"])
    n, v = sum(counts.values()), len(counts)
    for i, t in enumerate(texts):
        w = [*WORD.findall(low(t)), "\0"]
        base = sum(np.log10((counts[x] + 0.1) / (n + 0.1 * (v + 1))) for x in w)
        r = got[i]
        assert (r["n_tokens"], r["n_known"], r["train_tokens"]) == (len(w), sum(counts[x] > 0 for x in w), n) and abs(r["base_score"] - base) < 1e-6 * max(1, abs(base))
    again = {r["doc_id"]: r["score"] for r in lm.score(df.repartition(7), train.repartition(5), lm.MaxEntSettings(head=300)).collect()}
    assert max(abs(again[i] - r["score"]) for i, r in got.items()) < 1e-3
    empty = frame(spark, []).withColumns({"n_tokens": F.lit(1), "at": F.lit("x"), "shard": F.lit(2)})
    assert lm.score(empty, train).count() == 0 and lm.score(frame(spark, ["x y", "x y", "long " * 60_000], extra=True).withColumn("shard", F.lit("s")), train, keep=("shard",)).count() == 3
    none = lm.score(df, df.where("false")).collect()
    assert len(none) == len(texts) and all(r["n_known"] == 0 for r in none)


def test_chats(spark, sf):
    rows = [(1, 1, "assistant", 'x <tool_call>{"id":"b","name":"f","arguments":{"z":1,"a":"$a"}}</tool_call><tool_call>{"id":"a","name":"f","arguments":{"a":"q"}}</tool_call><tool_call>no</tool_call>'), (1, 2, "tool", '{"tool_call_id":"a","content":"42"}'), (1, 3, "tool", '{"tool_call_id":"zz"}'), (1, 4, None, None), (2, 0, "assistant", '<tool_call>{"id":"c","name":"g","arguments":{"a":"$d"}}</tool_call><tool_call>{"id":"d","name":"g","arguments":{"q":"$c"}}</tool_call>')]
    df = spark.createDataFrame(rows, "conv_id long, turn long, role string, text string")
    got = {(r["conv_id"], r["turn"]): r for r in chat.format_chats(df, {"g": {"a": ("integer", True)}}).collect()}
    calls = json.loads(got[1, 1]["line"])["tool_calls"]
    assert [(c["id"], c["depth"], c["result"]) for c in calls] == [("a", 0, "42"), ("b", 1, "")] and got[1, 1]["n_linked"] == 1
    assert [c["faults"] for c in json.loads(got[2, 0]["line"])["tool_calls"]] == [["type:a"], ["unknown:q", "missing:a"]] and got[1, 3]["is_orphan"]
    import duckdb

    con = duckdb.connect()
    con.execute(f"CREATE VIEW conversations AS SELECT * FROM '{sf}/conversations.parquet'")
    want = con.execute(OP10_SQL)
    assert sorted(map(tuple, QUERIES["op10_chat_formatting"](spark, sf).collect())) == sorted(want.fetchall())


def test_language_model_beats_counts_and_sums_to_one(spark, sf):
    df = table(spark, sf, "documents").select("doc_id", "text")
    held = langid.fold("doc_id", 10) == 0
    settings = lm.MaxEntSettings()
    score, base = lm.score(df.where(held), df.where(~held), settings).agg(F.sum("score"), F.sum("base_score")).first()
    assert 0 > score > 0.99 * base  # a hundredth better at least on rows that training did not see
    train = df.where("doc_id < 60")
    counts = lm.materialize(lm.word_counts(train, settings), "t")
    v, _ = lm.vocabulary(counts, settings)
    model = lm.MaxEnt(v, settings, lm.train(train, v, settings))
    words = sorted({w for r in train.collect() for w in WORD.findall(low(r["text"]))})
    assert len(words) + 1 == v.distinct
    unknown, fresh = {}, 0
    while len(unknown) < settings.suffix_classes:  # one unknown word of each class
        c = next(lm.chunks(lm.pa.array([f"q{fresh}zz{fresh * 7919 % 1000}"])))
        unknown.setdefault(int(lm.tokens(c, settings.suffix_classes)[1][0]), f"q{fresh}zz{fresh * 7919 % 1000}")
        fresh += 1
    history = f"{words[1]} {words[7]}"
    column, total = lm.pa.array([f"{history} {w}" for w in [*words, *unknown.values()]] + [history]), 0.0
    for c in lm.chunks(column):
        h, suffix, at = lm.tokens(c, settings.suffix_classes)
        logs, mass = model.log10_p(h, suffix, at)
        place = np.minimum(np.searchsorted(v.head, h), len(v.head) - 1)
        n = np.where(v.head[place] == h, v.head_n[place], 0)
        logs += np.where(np.isnan(mass), 0, np.log10(n + settings.smoothing) - np.nan_to_num(mass))
        total += float((10 ** logs[at[:-1] + 2]).sum())  # the third token: each word, an unknown one of each class, the end
    assert abs(total - 1) < 1e-3


def brute_chats(rows, schemas):
    """Linked messages by plain loops: (conv, turn, role) -> counts, orphan and the calls listed."""
    kinds = {"string": str, "integer": int, "number": (int, float), "boolean": bool, "object": dict, "array": list}
    convs, out = {}, []
    for c, t, role, text in rows:
        convs.setdefault(c, []).append((t, role or "", text or ""))
    for c, messages in convs.items():
        calls, results = {}, {}
        for t, role, text in sorted(set(messages), key=str):
            if role == "assistant":
                for place, body in enumerate(re.findall(r"(?s)<tool_call>(.*?)</tool_call>", text)):
                    try:
                        body = json.loads(body)
                    except ValueError:
                        continue
                    args = body.get("arguments", {})
                    calls.setdefault((t, text), []).append((place, body.get("id"), body.get("name"), args))
        for t, role, text in sorted(messages, key=lambda m: (m[0] is None, m[0] or 0)):
            if role == "tool" and "tool_call_id" in text:
                r = json.loads(text)
                results.setdefault(r["tool_call_id"], r.get("content"))
        ids = {i for cs in calls.values() for _, i, _, _ in cs if i}
        needs = {i: set() for i in ids}
        for cs in calls.values():
            for _, i, _, args in cs:
                if i:
                    needs[i] |= {x for x in re.findall(r'"\$([A-Za-z0-9_-]+)"', json.dumps(args)) if x in ids}
        depth = {}
        while new := {i: max((depth[n] for n in needs[i]), default=-1) + 1 for i in ids - set(depth) if needs[i] <= set(depth)}:
            depth |= new
        for t, role, text in messages:
            mine = sorted(calls.get((t, text), []) if role == "assistant" else [], key=lambda x: (depth.get(x[1], 2**31), x[0]))
            listed = []
            for _, i, name, args in mine:
                schema, faults = schemas.get(name), []
                if not isinstance(args, dict):
                    faults = ["not_json"]
                elif schema:
                    faults = [f"unknown:{k}" for k in sorted(set(args) - set(schema))]
                    for k, (kind, must) in sorted(schema.items()):
                        faults += [f"missing:{k}"] if must and k not in args else [f"type:{k}"] if k in args and not isinstance(args[k], kinds[kind]) else []
                listed.append((i or "", name or "", args, depth.get(i, -1), faults, results.get(i) or ""))
            orphan = role == "tool" and (json.loads(text).get("tool_call_id") if text.startswith("{") else None) not in ids
            out.append((c, t, role, text, len(listed), sum(i in results for i, *_ in listed), sum(bool(x[4]) for x in listed), orphan, listed))
    return out


def test_chats_equal_plain_loops(spark):
    call = lambda i, args, name="search": f'<tool_call>{json.dumps({"id": i, "name": name, "arguments": args})}</tool_call>'
    chain = "".join(call(f"k{n}", {"query": f"$k{n - 1}" if n else "q"}) for n in range(12))
    rows = [(1, 1, "assistant", "go " + chain[::1]), (1, 2, "tool", '{"tool_call_id":"k3","content":"3"}'), (1, 2, "tool", '{"tool_call_id":"k3","content":"3"}'), (1, 3, "tool", '{"tool_call_id":"gone"}'), (1, 4, "tool", "plain")]
    rows += [(2, 1, "assistant", call("a", {"query": "$b"}) + call("b", {"query": "$c"}) + call("c", {"query": "$a"}) + call("d", {"query": "$a"}) + call("e", {"limit": "x", "zz": 1}))]
    rows += [(3, 1, "assistant", call("a", "no json") + call("b", [1, 2]) + call(None, {"query": 5}) + "<tool_call>no</tool_call>")] * 2 + [(3, 1, "assistant", call("z", {"query": "other text"}))]
    rows += [(None, 1, "assistant", call("n", {"query": "q"}, "f")), (None, None, "tool", '{"tool_call_id":"n","content":"r"}'), (4, None, "assistant", call("m", {"query": None})), (5, 1, None, None), (5, 2, "user", ""), (5, 3, "user", "long " * 20_000)]
    schemas = {"search": {"query": ("string", True), "limit": ("integer", False)}}
    df = spark.createDataFrame(rows, "conv_id long, turn long, role string, text string").withColumns({"id": F.lit(9), "th": F.lit("x"), "calls": F.lit(1), "called": F.lit(0)})
    got = []
    for r in chat.format_chats(df, schemas).collect():
        line = json.loads(r["line"])
        assert json.dumps(line, sort_keys=True, separators=(",", ":"), ensure_ascii=False) == r["line"]
        listed = [(x["id"], x["name"], x["arguments"], x["depth"], x["faults"], x["result"]) for x in line["tool_calls"]]
        got.append((r["conv_id"], r["turn"], r["role"], line["content"], r["n_calls"], r["n_linked"], r["n_faulty"], r["is_orphan"], listed))
    assert sorted(got, key=str) == sorted(brute_chats(rows, schemas), key=str)
    assert chat.format_chats(df.where("false"), schemas).count() == 0


def test_html_learns_from_rare_marks_and_survives_depth(spark, sf):
    pages = table(spark, sf, "pages").where("page_id < 30").select("html")
    plain = spark.range(20_000).select(F.concat(F.lit("<div>page "), F.col("id").cast("string"), F.lit("</div>")).alias("html"))
    copies = pages.limit(1).crossJoin(spark.range(500).select(F.lit(1))).select("html")
    found = html_extract.training_pages(plain.union(pages).union(copies), 200, 100_000)
    assert len(found) == len(set(found)) == pages.distinct().count()
    blocks = html_extract.blocks_of("<div>a" * 30_000)
    assert len(blocks) == 30_000 and len({id(n.up) for n in (blocks[0].path, blocks[-1].path)}) == 2
    assert all(html_extract.Features().vector(b) for b in blocks[::5000])
    assert [b.text for b in html_extract.blocks_of("<a" * 50_000 + " x")] != [] and html_extract.blocks_of("<p>x<!--" + "y>" * 10)[0].text == "x"
    odd = spark.createDataFrame([(1, "u", "<div>a" * 8000), (1, "u", "<div>a" * 8000)], "page_id long, url string, html string").withColumns({"text": F.lit(3), "n_main": F.lit("q")})
    assert html_extract.extract(odd, labelled=pages).count() == 2 and html_extract.extract(odd.where("false")).count() == 0


def test_language_sample_takes_copies_once(spark):
    base = [(f"alpha beta gamma {n}", "aa") for n in range(60)] + [(f"uno dos tres {n}", "bb") for n in range(60)]
    long = [(f"kuku mumu lulu {n} " * 3000, "cc") for n in range(6)]
    rows = base + long + base[:1] * 3000
    df = spark.createDataFrame(rows, "text string, lang string").repartition(5).withColumns({"h": F.lit(1), "at": F.lit("x"), "long": F.lit(0)})
    seen = []
    model = langid.fit(df, max_rows=90, min_rows=10, ftrl=type("Spy", (langid.Ftrl,), {"fit": lambda self, r, y, c: (seen.append(Counter(y)), langid.Ftrl.fit(self, r, y, c))[1]})())
    assert model.languages == ["aa", "bb", "cc"] and seen[0] == {0: 24, 1: 24, 2: 5}  # of 30, 30 and 6, a fifth is held back
    ask = spark.createDataFrame([(1, "mumu kuku"), (2, "alpha gamma"), (2, "alpha gamma"), (3, "dos uno " * 50_000)], "doc_id long, text string").withColumns({"score": F.lit("x"), "lang_pred": F.lit(1)})
    assert sorted(r["lang_pred"] for r in langid.identify(ask, model).select("lang_pred").collect()) == ["aa", "aa", "bb", "cc"]
    assert langid.identify(ask.where("false"), model).count() == 0


def test_pipeline_stages(spark, sf):
    docs, kept = table(spark, sf, "documents").where("doc_id < 200"), []
    for name, stage in corpus_pipeline.STAGES[:-1]:
        docs = stage(spark, docs, sf)
        assert tuple(docs.columns) == corpus_pipeline.COLUMNS
        docs = corpus_pipeline.materialize(docs, name)
        kept.append(docs.count())
    assert kept == sorted(kept, reverse=True) and 0 < kept[-1] < 200
    assert corpus_pipeline.STAGES[-1][1](spark, docs, sf).select("doc_id").distinct().count() == kept[-1]


def test_empty_tables(spark):
    empty = spark.createDataFrame([], "doc_id long, text string")
    bench = spark.createDataFrame([], "item_id long, text string")
    assert repetition(empty).count() == decontaminate(empty, bench).count() == remove_repeats(empty).count() == joins.near_duplicates(empty).count() == pii.sanitise(empty).count() == lm.score(empty, empty).count() == 0


def test_group_sums_equal_plain_sums():
    r = np.random.default_rng(0)
    for n, kinds in ((1, 1), (7, 3), (600, 40), (600, 1), (600, 10_000)):
        rows, keys, index = r.normal(size=(n, 5)), np.sort(r.integers(0, kinds, 3 * n)), r.integers(0, n, 3 * n)
        first = np.flatnonzero(np.concatenate(([True], keys[1:] != keys[:-1])))
        want = [rows[part].sum(0) for part in np.split(index, first[1:])]
        assert np.allclose(lm.group_sums(rows, index, first, np.diff(np.append(first, len(keys)))), want)


def test_components_equal_union_find(spark):
    r = np.random.default_rng(3)
    chain = [(i, i + 1) for i in range(60)]
    spread = [(int(a) + 100, int(b) + 100) for a, b in r.integers(0, 300, (220, 2))]
    zigzag = [(500, 590), (590, 510), (510, 580), (580, 505), (700, 701), (701, 700), (710, 710), (None, 720)]
    parent: dict[int, int] = {}

    def find(x):
        while parent.setdefault(x, x) != x:
            x = parent[x]
        return x

    for a, b in chain + spread + zigzag[:-2]:
        if a != b:
            p, q = find(a), find(b)
            parent[max(p, q)] = min(p, q)
    edges = spark.createDataFrame(chain + spread + zigzag, "a long, b long")
    assert {(x, c) for x, c in connected_components(edges).collect()} == {(x, find(x)) for x in list(parent)}
    assert connected_components(edges.where("false")).count() == 0


def test_bitmap_of_many_hashes_lets_few_others_pass(spark):
    from turnstile_cover.llm import bitfilter

    rng = np.random.default_rng(3)
    inside, others = (rng.integers(-(1 << 62), 1 << 62, 100_000) for _ in range(2))
    held = bitfilter.build(spark.createDataFrame([(int(x),) for x in inside], "k long"), "k", each=10, max_bits=20, places=4)
    assert held.holds(inside).all() and held.holds(others).mean() < 0.03
    full = bitfilter.build(spark.createDataFrame([(int(x),) for x in inside], "k long"), "k", each=10, max_bits=16, places=4)
    assert full.places == 1 and full.holds(inside).all()


def test_jaccard_join_leaves_only_what_its_result_reads(spark):
    from turnstile_cover.operators import checkpoints

    at = checkpoints.mark()
    words = "a b c d e f g h i j k l m n o p q r s t u v w x y z".split()
    texts = [" ".join(words[i:] + words[:i]) for i in (0, 0, 1, 1, 5)]
    out = joins.near_duplicates(spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string"), 3, 80)
    names = {p.rsplit("/", 1)[-1].rsplit("-", 5)[0] for p in checkpoints._written[at:]}
    assert "join-heads" not in names and "join-members" not in names
    assert {r["doc_id"]: r["component_id"] for r in out.collect()}[1] == 0
