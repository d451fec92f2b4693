"""Small fixtures for the ten operators: odd rows, ties, repeats, empty tables, clashing columns; brute-force versions."""

import base64
import collections
import hashlib
import re
import zlib

import numpy as np
import pytest
from pyspark.sql import functions as F

from dyntri.llm import arrow_text, chat_format, context_mixing, decontaminate, html_extract, line_dedup, mixing, ngram_join, quality, storage, token_files, warc

WORD = re.compile(r"[^\x20\x09-\x0D]+")
DOCS = "doc_id long, text string, source string, n_words string, _kept string, size string"
LONG = " ".join(f"w{i % 977}x{i % 31}" for i in range(30_000))
COPY = " ".join(f"near{i}" for i in range(60))
ROWS = [
    (1, "Alpha beta gamma delta epsilon zeta eta theta iota kappa lambda\nsecond line here", "a"), (2, None, None), (3, "", "a"), (4, " \t\x0b\n ", "b"), (5, LONG, "a"), (6, COPY, "b"), (7, COPY + " tail", "b"),
    (8, COPY.upper().replace(" ", "\n"), None), (9, "one two", "c"), (10, "one two", "c"), (10, "one two", "c"), (None, "one two", "c"), (11, "ÄÖ ünïcode 日本語 \U0001f600 x", "a"), (12, "spam spam spam spam spam spam spam spam spam spam spam spam", "a"),
]


@pytest.fixture(scope="module")
def docs(spark):
    return spark.createDataFrame([(i, t, s, "clash", "clash", "clash") for i, t, s in ROWS], DOCS)


@pytest.fixture(scope="module")
def none(spark):
    return spark.createDataFrame([], DOCS)


def low(t):
    return re.sub("[A-Z]", lambda m: m[0].lower(), t or "")


# ------------------------------------------------------------------ 1


def test_chat_round_trip_and_mask(spark):
    texts = ["</s>[INST] ok [/INST]", "a\\b <\\s> [\\\\INST] [ROLE] x [TEXT] y", "", None, "<<SYS>> <</SYS>>", "[\\/INST] [INS T] <s><s>", "\U0001f600 [/ROLE]", "x" * 20000]
    roles = ["user", "assistant", "system", "tool", None, "[ROLE] odd [TEXT]", "assistant", "user"]
    rows = [(1, i, r, t) for i, (r, t) in enumerate(zip(roles, texts))] + [(2, 0, "user", "a"), (2, 0, "user", "a"), (None, 0, "user", "n")]
    table = spark.createDataFrame(rows, "conv_id long, turn long, role string, text string")
    made = chat_format.formatted(chat_format.turns_of_table(table))
    got = {r.conv_id: r for r in made.select("conv_id", "formatted", chat_format.read_back(F.col("formatted")).alias("turns"), chat_format.loss_text(F.col("formatted"), F.col("loss_spans")).alias("loss")).collect()}
    assert [(t.role, t.text) for t in got[1].turns] == [(r or "", t or "") for r, t in zip(roles, texts)]
    assert got[1].loss == texts[1] + texts[6]
    assert len(got[2].turns) == 2 and got[None].turns[0].text == "n"
    assert chat_format.turns_of_table(table.limit(0)).count() == 0


def test_layouts_by_fingerprint(spark):
    records = [
        '{"messages":[{"role":"human","content":"hi"},{"role":"gpt","content":"yo"}]}', '{"conversations":[{"from":"human","value":"hi"},{"from":"gpt","value":"yo"}]}', '{"output":"yo","instruction":"hi"}',
        '{"prompt":"hi","completion":"yo"}', '{"question":"hi","answer":"yo"}', '{"instruction":"hi","input":"","output":"yo"}', '{"strange":1}', "no json", None,
    ]
    df = spark.createDataFrame([(i, r) for i, r in enumerate(records)], "id long, record string")
    got = [r.turns and [(t.role, t.text) for t in r.turns] for r in chat_format.turns_of_json(df).orderBy("id").collect()]
    assert got == [[("user", "hi"), ("assistant", "yo")]] * 6 + [None] * 3
    assert chat_format.schema_paths(df.schema) == ("id", "record")
    with pytest.raises(ValueError):
        chat_format.turns_of_table(df)


# ------------------------------------------------------------------ 2


def brute_components(rows, size, percent):
    sets = []
    for _, t in rows:
        w = WORD.findall(low(t))
        sets.append({tuple(w[i : i + size]) for i in range(len(w) - size + 1)} or ({tuple(w)} if w else set()))
    ids = [i for i, _ in rows]
    reach = {i: i for i in ids}

    def root(x):
        while reach[x] != x:
            x = reach[x]
        return x

    for a in range(len(rows)):
        for b in range(a):
            both = len(sets[a] & sets[b])
            if both and 100 * both >= percent * (len(sets[a]) + len(sets[b]) - both):
                x, y = sorted((root(ids[a]), root(ids[b])))
                reach[y] = x
    return sorted((i, len(s), root(i)) for i, s in zip(ids, sets))


def test_ngram_join_equals_brute_force(spark):
    rng = np.random.default_rng(7)
    words = [f"v{i}" for i in range(400)]
    rows, base = [], [[words[k] for k in rng.integers(0, 400, n)] for n in (5, 30, 120, 200)]
    for i in range(160):
        w = list(base[i % 4])
        for _ in range(rng.integers(0, 5)):
            w[rng.integers(0, len(w))] = f"u{rng.integers(0, 10**6)}"
        if i % 11 == 0:
            w = w[: len(w) - len(w) // 8]
        rows.append((i, (" " if i % 2 else "\n").join(w)))
    rows += [(200, None), (201, ""), (202, " \n"), (203, "a b"), (204, "A b"), (205, "a b c"), (206, LONG), (207, LONG + " z")]
    df = spark.createDataFrame(rows, "doc_id long, text string")
    for size, percent in ((4, 85), (5, 80)):
        got = sorted(map(tuple, ngram_join.join_components(df, size, percent).collect()))
        assert got == brute_components(rows, size, percent)


def test_ngram_join_odd_rows(docs, none):
    got = ngram_join.join_components(docs).collect()
    assert len(got) == len(ROWS)
    by = {r.doc_id: r for r in got}
    assert by[7].component_id == 6 and by[8].component_id == 6 and by[10].component_id == 9 and by[3].component_id == 3 and by[5].n_shingles > 1000
    assert ngram_join.join_components(none).count() == 0
    kept = [r.doc_id for r in ngram_join.one_per_component(docs).select("doc_id").collect()]
    assert sorted(kept, key=str) == sorted([1, 2, 3, 4, 5, 6, 9, 11, 12], key=str)


# ------------------------------------------------------------------ 3


def test_warc_round_trip_and_lookup(spark, tmp_path):
    rows = [(1, "http://a.example/x", "<p>é\r\n\r\nWARC/1.1</p>"), (2, "http://www.b.example:8080/?q=1", "<p>é\r\n\r\nWARC/1.1</p>"), (3, None, None), (4, "", ""), (5, "http://a.example/x", "z" * 300_000), (6, "bad\nurl", "y"), (None, "http://c.example", "y"), (7, "http://a.example/x", "y"), (8, "a\tb\x01c\u2028d", "q"), (9, "a", "r"), (10, "a\x01", "s")]
    rows += [(100 + i, "http://a.example/x", f"n{i}") for i in range(9)]
    pages = spark.createDataFrame(rows, "page_id long, url string, html string").repartition(3)
    archives, index = storage.fresh_path(spark, "a"), storage.fresh_path(spark, "i")
    warc.write_archives(pages, archives)
    warc.write_index(spark, archives, index, block_lines=2)
    got = warc.read_captures(spark, archives, index, pages.select("url")).collect()
    assert len(got) == len(rows)
    some = spark.createDataFrame([("http://a.example/x",), ("http://a.example/x",), ("http://nowhere.example/",), (None,)], "url string")
    assert sorted(r.page_id for r in warc.read_captures(spark, archives, index, some).collect()) == [1, 3, 4, 5, 7, *range(100, 109)]
    assert warc.read_captures(spark, archives, index, some.limit(0)).count() == 0
    by = {r.page_id: r for r in got}
    for i, _, h in rows:
        b = (h or "").encode()
        assert (by[i].payload_bytes, by[i].payload_digest) == (len(b), base64.b32encode(hashlib.sha1(b).digest()).decode())
    assert [by[i].record_type for i in (1, 2, 3, 4, 5, 6, 7)] == ["response", "revisit", "response", "revisit", "response", "response", "revisit"]
    assert (by[2].refers_to, by[4].refers_to, by[7].refers_to, by[1].refers_to) == (1, 3, 6, None)
    look = warc.CaptureIndex(spark, index)
    lines = look.captures("http://a.example/x")
    assert [x["page_id"] for x in lines] == [1, 5, 7, *range(100, 109)] and [x["page_id"] for x in look.captures(rows[8][1])] == [8] and look.captures("http://nowhere.example/") == []
    assert look.read(lines[0])[1].decode() == rows[0][2]
    warc.write_archives(pages.limit(0), empty := storage.fresh_path(spark, "e"))
    assert storage.read_blobs(spark, empty).count() == 0
    warc.write_index(spark, empty, nothing := storage.fresh_path(spark, "n"))
    assert warc.read_captures(spark, empty, nothing, pages.select("url")).count() == 0 and warc.CaptureIndex(spark, nothing).captures(None) == []
    assert warc.surt("http://User@www.B.example:80/p?q#f") == "example,b,www)/p?q"


# ------------------------------------------------------------------ 4


def brute_quality(t):
    t = t or ""
    w = WORD.findall(t)
    g = collections.Counter(tuple(w[i : i + 5]) for i in range(len(w) - 4))
    cover = {i + k for i in range(len(w) - 4) if g[tuple(w[i : i + 5])] > 1 for k in range(5)}
    lines = [x for x in t.split("\n") if WORD.search(x)]
    return len(w), sum(map(len, w)), len(re.findall(r"[#*$%&|<>]", t)), len(lines) - len(set(lines)), len(cover), len(w) < 10 or 100 * len(cover) > 20 * len(w)


def test_quality_measures_and_verdicts(spark, docs, none):
    rows = storage.saved(quality.measured(docs), "m")
    for r in rows.select("text", "_q.*").collect():
        assert (r.n_words, r.word_chars, r.n_symbols, r.n_dup_lines, r.n_repeat_words, r.base_failed) == brute_quality(r.text)
    assert quality.judged(rows, quality.host_verdicts(rows)).count() == len(ROWS)
    kept = {r.doc_id for r in quality.kept_rows(docs).collect()}
    assert kept >= {1, 6} and not kept & {2, 3, 4, 9, 12}
    assert quality.kept_rows(docs).columns == docs.columns and quality.kept_rows(none).count() == 0


def test_bad_hosts_get_less_room(spark):
    clean = " ".join(f"word{i}" for i in range(40))
    some = clean + " " + "#" * 10  # a severity above 1, below 2
    rows = [(i, clean if i % 100 else some, "good") for i in range(400)] + [(1000 + i, some if i % 4 else clean, "bad") for i in range(400)]
    df = spark.createDataFrame(rows, "doc_id long, text string, source string")
    kept = {r.doc_id for r in quality.kept_rows(df).select("doc_id").collect()}
    assert kept == {i for i, _, s in rows if s == "good"} | {i for i, t, s in rows if s == "bad" and t == clean}


# ------------------------------------------------------------------ 5


def test_html_extraction():
    page = """<html><head><title>T</title><style>p{}</style></head><body><header>Site</header><nav><li>m1<li>m2</nav><div class="cookie-notice">We use</div>
    <article><header><h1>Head &amp; title</h1></header><p>One <b>bold</b>&nbsp;text<br>more<p>Two &lt;x&gt;<script>var t="</p>";</script><ul><li>i1<li>i2</ul><div class="ad">buy</div>
    <aside>side</aside><form>f</form><!-- c --><section id="comments"><p>nice</p></section></article><footer>&copy;</footer></body></html>"""
    assert html_extract.main_text(page) == "Head & title\n\nOne bold text more\n\nTwo <x>\n\ni1\n\ni2"
    for odd in ("", "<", "a < b", "<p", "<div><div>", "</p></p>", "<article></article>", "<p>x</b></i>", "<" * 500, "<b>" * 3000 + "x"):
        assert isinstance(html_extract.main_text(odd), str)


def test_wrapper_induction(spark):
    def page(i):
        return f"<body><div class=top><span>Daily Planet</span></div><div class=story><p>Report {i} about {i * 7}</p><p>{'x' * (i % 5 + 1)} end</p></div><div class=bottom>All rights reserved</div></body>"

    rows = [(i, f"http://Host.example/{i}", page(i)) for i in range(40)] + [(100, "http://lone.example/", page(3)), (101, None, None), (102, "x", "")]
    got = {r.page_id: r.text for r in html_extract.extracted(spark.createDataFrame(rows, "page_id long, url string, html string")).collect()}
    assert len(got) == len(rows)
    assert all(got[i] == f"Report {i} about {i * 7}\n\n{'x' * (i % 5 + 1)} end" for i in range(40))
    assert "Daily Planet" in got[100] and got[101] == "" and got[102] == ""
    a, b = html_extract.parse("<div><p>a<p>b</div>"), html_extract.parse("<div><p>a<p>c<p>b</div>")
    assert [(x.text, y.text) for x, y in html_extract.matched(a, b)[1] if x.text] == [("b", "b"), ("a", "a")]


def test_wrappers_of_all_pages(spark):
    def one(i):
        return f"<body><div class=top><span>Daily Planet</span></div><div class=story><p>Report {i}</p></div></body>"

    def two(i):
        return f"<body><section><p>Evening Star</p></section><section class=piece><h2>Piece {i}</h2></section></body>"

    copy = "<body><div class=story><p>The same article</p></div></body>"
    rows = [(i, "http://two.example/", one(i) if i % 2 else two(i)) for i in range(40)] + [(100 + i, "http://copies.example/", copy) for i in range(30)] + [(130, "http://copies.example/", one(130))]
    rows += [(200, "http://again.example/", one(200))] * 8 + [(210 + i, "http://near.example/", f"<body><main><p>One article</p></main><i>{i}</i></body>") for i in range(9)]
    got = {r.page_id: r.text for r in html_extract.extracted(spark.createDataFrame(rows, "page_id long, url string, html string")).collect()}
    assert all(got[i] == (f"Report {i}" if i % 2 else f"Piece {i}") for i in range(40))
    assert all(got[100 + i] == "The same article" for i in range(30)) and got[200] == "Daily Planet\n\nReport 200"
    assert all(got[210 + i] == "One article" for i in range(9))


# ------------------------------------------------------------------ 6


def test_mixing_targets_and_takings(spark, docs, none):
    rng = np.random.default_rng(3)
    rows = [(int(i), " ".join(["w"] * int(rng.integers(0, 60))), f"s{i % 7}" if i % 9 else None) for i in range(600)] + [(5, "w w w", "s5"), (5, "w w w", "s5"), (9000, "w " * 5000, "s1")]
    df = spark.createDataFrame(rows, "doc_id long, text string, source string")
    got = mixing.mix(df, block_words=64)[0].toPandas()
    again = mixing.mix(df.repartition(5), block_words=64)[0].toPandas()
    order = ["doc_id", "source", "size", "taken"]
    assert got.sort_values(order)[order].reset_index(drop=True).equals(again.sort_values(order)[order].reset_index(drop=True))
    sizes = collections.Counter()
    for _, t, s in rows:
        sizes[s] += len(t.split())
    names = sorted([s for s in sizes if s]) + [None]
    want, weight = dict.fromkeys(names, 0.0), {s: (5, 2, 1)[i % 3] for i, s in enumerate(names)}
    left, live = 1.5 * sum(sizes.values()), set(names)
    while left > 1e-9 and live:
        total = sum(weight[s] for s in live)
        share, left = left, 0.0
        for s in sorted(live, key=str):
            want[s] += share * weight[s] / total
            if want[s] >= 2 * sizes[s]:
                left += want[s] - 2 * sizes[s]
                want[s] = 2.0 * sizes[s]
                live.discard(s)
    for s, part in got.groupby("source", dropna=False):
        s = s if isinstance(s, str) else None
        assert abs(part.target.iloc[0] - want[s]) < 1e-6 and abs(part.taken.sum() - want[s]) <= 1 and part.source_size.iloc[0] == sizes[s]
    assert (got.taken <= 2 * got["size"]).all() and len(got) == len(rows)
    assert mixing.mix(none)[0].count() == 0 and mixing.mix(docs)[0].count() == len(ROWS)
    assert mixing.mixed_rows(docs).columns == docs.columns


def test_schedule_is_balanced_everywhere(spark):
    goals = spark.createDataFrame([("a", 50_000.0), ("b", 20_000.0), ("c", 10_000.0)], "source string, target double")
    slots = mixing.schedule(goals, 10).orderBy("time").toPandas()
    assert len(slots) == 8000 and slots.time.is_unique
    for n in (800, 1600, 4000):
        part = slots.head(n).source.value_counts()
        assert abs(part["a"] / n - 0.625) < 0.02 and abs(part["c"] / n - 0.125) < 0.02
    assert (slots.sort_values("time").groupby("source")["rank"].diff().dropna() == 1).all()


# ------------------------------------------------------------------ 7


def test_lm_counts_and_scores(spark, docs, none):
    rng = np.random.default_rng(1)
    vocabulary = ["the", "cat", "sat", "mat", "running", "jumped", "house."]
    rows = [(int(i), " ".join(rng.choice(vocabulary, int(rng.integers(3, 40))))) for i in range(120)] + [(500, None), (501, ""), (502, "unseen zebra"), (None, "the cat")]
    df = spark.createDataFrame(rows, "doc_id long, text string")
    got = context_mixing.scored(df, frequent=3).collect()
    words = [WORD.findall(low(t)) + [None] for _, t in rows]
    held = [i is not None and zlib.crc32(str(i).encode()) % 5 == 1 for i, _ in rows]
    c = collections.Counter(w for ws, h in zip(words, held) if not h for w in ws)
    n, v = sum(c.values()), len(c)
    by = {r.doc_id: r for r in got}
    assert len(got) == len(rows)
    for (i, _), ws, h in zip(rows, words, held):
        r = by[i]
        assert (r.held_out, r.n_tokens, r.n_known, r.train_tokens) == (h, len(ws), sum(w in c for w in ws), n)
        assert abs(r.base_score - sum(np.log10((c[w] + 0.5) / (n + 0.5 * (v + 1))) for w in ws)) < 1e-8
        assert r.score < 0 and r.bits_per_byte > 0
    likely, odd = by[1], by[502]
    assert likely.score / likely.n_tokens > odd.score / odd.n_tokens
    assert context_mixing.scored(none).count() == 0 and context_mixing.scored(docs).count() == len(ROWS)


def test_mixing_learns_from_all_pairs(spark):
    words = sorted(f"word{k % 9}{k}".encode() for k in range(400))
    c = 1 + np.arange(400) ** 2
    pairs = spark.createDataFrame([(bytearray(w[:6]), bytearray(w), k % 3, int(n), 6) for k, (w, n) in enumerate(zip(words, c))], context_mixing.PAIRS).repartition(5, "grp").sortWithinPartitions("grp", "word", "class")
    bits = context_mixing.table_bits(400)
    tables = context_mixing.context_counts(pairs, bits)
    model = context_mixing.fresh_model(bits, *tables)
    sent = spark.sparkContext.broadcast(tables)
    import pyarrow as pa

    own = context_mixing.edges(pa.array(words, pa.binary()), np.arange(400) % 3, c, np.full(400, 6))
    for kernel in (context_mixing.weight_sums, context_mixing.map_sums):
        assert np.allclose(context_mixing.summed(pairs, kernel, model, sent), kernel(model, own))
    sums = context_mixing.summed(pairs, context_mixing.map_sums, model, sent)
    assert sums[1].sum() == sum((len(w) + 1) * 8 * int(n) for w, n in zip(words, c))  # no pair is left out, no count is capped
    first = np.abs(context_mixing.weight_sums(model, own)[:, : context_mixing.INPUTS]).sum()
    for _ in range(8):
        model.weights = context_mixing.stepped(model.weights, context_mixing.summed(pairs, context_mixing.weight_sums, model, sent))
    assert np.abs(context_mixing.weight_sums(model, own)[:, : context_mixing.INPUTS]).sum() < first / 2


def test_words_are_a_probability_in_groups_of_any_size(spark, monkeypatch):
    """All words of a class together have a probability of 1 at most, whatever groups they lie in; words that share a beginning share its decisions."""
    rng = np.random.default_rng(2)
    syllables = ["tion", "ing", "an", "re", "st", "le"]
    words = sorted({"".join(rng.choice(syllables, 5)) for _ in range(500)})
    pairs = spark.createDataFrame([(bytearray(w.encode()), k % 2, 1 + k % 4) for k, w in enumerate(words)], "word binary, class int, c long")
    for most in (200_000, 40, 3):
        monkeypatch.setattr(context_mixing, "GROUP_WORDS", most)
        grouped = storage.saved(context_mixing.grouped_pairs(pairs), "g")
        assert grouped.count() == len(words) and grouped.groupBy("grp").count().agg(F.max("count")).first()[0] <= max(most, 1) or most > 40
        bits = context_mixing.table_bits(len(words))
        tables = context_mixing.context_counts(grouped, bits)
        got = context_mixing.scored_pairs(grouped, context_mixing.fresh_model(bits, *tables), spark.sparkContext.broadcast(tables)).collect()
        assert len(got) == len(words) and sum(r["first"] for r in got) == len(words) and sum(10**r.score for r in got) <= 2.001


def test_classes_of_texts(spark):
    rng = np.random.default_rng(4)
    tongues = [["the", "of", "and", "to", "in", "is"], ["der", "die", "und", "von", "zu", "mit"]]
    rows = [(i, " ".join(rng.choice(tongues[i % 2], 30))) for i in range(200)]
    found = context_mixing.text_classes(spark.createDataFrame(rows, "doc_id long, text string"))
    data = np.frombuffer("the of a und der die nothing known".encode(), np.uint8)
    starts, ends, _ = arrow_text.word_spans(data, np.array([0, len(data)]), arrow_text.word_table())
    kinds = found.of(data, starts, ends, np.array([2, 4, 2]))
    assert found.odds.shape == (12, 2) and kinds[0] != kinds[1] and kinds[2] == 0


# ------------------------------------------------------------------ 8


@pytest.mark.parametrize("values", [[], [0] * 1000, [2**64 - 1, 0, 2**60, 2**60 - 1], list(range(5000)), [2**i for i in range(64)] * 20])
def test_simple8b_round_trip(values):
    x = np.array(values, np.uint64)
    words, blocks, literals = token_files.pack(x)
    assert np.array_equal(token_files.unpack(words, literals), x) and len(blocks) == -(-len(x) // token_files.BLOCK_IDS)


def test_token_files(spark, docs, none):
    import public_tokenizers
    from tokenizers import Tokenizer

    path = public_tokenizers.path("word_bpe_49k.json")
    tok = Tokenizer.from_file(path)
    token_files.write_token_files(docs, out := storage.fresh_path(spark, "t"), path, segment_ids=2000)
    got = token_files.token_digests(spark, out).orderBy("start").collect()
    rows = sorted(ROWS, key=lambda r: (r[0] is not None, r[0] or 0))
    start = 0
    assert len(got) == len(rows)
    for r, (i, t, _) in zip(got, rows):
        ids = np.array(tok.encode(t or "", add_special_tokens=False).ids + [2], np.uint32)
        assert (r.doc_id, r.start, r.n_tokens, r.ids_crc32) == (i, start, len(ids), zlib.crc32(ids.tobytes()))
        start += len(ids)
    whole = {r.doc_id: r.ids for r in token_files.read_token_files(spark, out).collect()}
    assert whole[9] == tok.encode("one two", add_special_tokens=False).ids + [2]
    token_files.write_token_files(none, out := storage.fresh_path(spark, "t"), path)
    assert token_files.token_digests(spark, out).count() == 0
    ids = np.arange(3000, dtype=np.uint32) % 700
    segment = token_files.write_segment(np.arange(3), np.zeros(3), np.array([1000, 0, 2000]), ids)
    assert [len(token_files.read_document(segment, k)) for k in range(3)] == [1000, 0, 2000] and np.array_equal(token_files.read_document(segment, 2), ids[1000:])


# ------------------------------------------------------------------ 9


def test_line_dedup(spark, docs, none):
    passage = "this passage has more than ten words and it stands in several documents at once"
    rows = [(1, f"first own line of words\n{passage}\nlast own line"), (2, f"other own line of words\n  {passage}\nother end"), (3, passage), (3, passage), (4, "short line\nshort line"), (5, "short line"), (6, f"{passage} tail"), (None, passage), (7, None), (8, f"x y\n{passage}\nz\n{passage}")]
    df = spark.createDataFrame(rows, "doc_id long, text string").withColumn("n_lines", F.lit("clash"))
    got = sorted(((r.doc_id, r.text, len(r.removed_lines)) for r in line_dedup.deduplicated(df).collect()), key=str)
    want = [(1, rows[0][1], 0), (2, "other own line of words\nother end", 1), (3, "", 1), (3, "", 1), (4, rows[4][1], 0), (5, "short line", 0), (6, rows[6][1], 0), (None, passage, 0), (7, None, 0), (8, f"x y\nz\n{passage}", 1)]
    assert got == sorted(want, key=str)
    assert line_dedup.deduplicated(none).count() == 0 and line_dedup.deduplicated(docs).count() == len(ROWS)
    assert line_dedup.aligned([1, 2, 3, 4, 5], [9, 2, 3, 8, 5, 1]) == [(1, 3), (4, 5)]


def common_words(a, b):
    """The most words of a block of adjacent lines that two texts share, lines without words passed over."""
    a, b = ([x.strip() for x in t.split("\n") if x.strip()] for t in (a, b))
    best, last = 0, [0] * (len(b) + 1)
    for x in a:
        last = [0] + [last[j] + len(x.split()) if x == y else 0 for j, y in enumerate(b)]
        best = max(best, *last)
    return best


def test_line_dedup_loses_no_repeat(spark):
    def line(k, n):
        return " ".join(f"l{k}w{i}" for i in range(n))

    verse = [line(k, 3) for k in range(20)]
    passage = [line(100 + k, 8) for k in range(8)]
    rows = [(k, f"own {k} text\n{x}\nend {k}") for k, x in enumerate(passage)]  # every line of the passage alone in an earlier document
    rows += [
        (20, "start of twenty\n" + "\n".join(passage)), (21, "\n".join(passage) + "\nend of twenty-one"),
        (22, "\n".join(["a head", *verse, "a tail"])), (23, "\n\n".join(["other head", *verse, "other tail"])), (24, line(200, 6)), (25, f"x\n{line(200, 6)}\ny"),
        (26, "\n".join([*verse[10:], "mid", *verse[:10]])), (27, "\n".join([*passage, "again", *passage])),
        (28, "\n".join(line(300 + k, 9) for k in range(4))), (29, "\n".join(line(300 + k, 9) for k in (3, 2, 1, 0))),
    ]
    got = {r.doc_id: r.text for r in line_dedup.deduplicated(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    assert [got[k] for k in range(8)] == [t for _, t in rows[:8]] and got[22] == rows[10][1] and got[24] == rows[12][1] and got[28] == rows[16][1]
    assert got[20] == "start of twenty" and got[21] == "end of twenty-one" and got[23].split() == ["other", "head", "other", "tail"]
    assert got[25] == "x\ny" and got[26] == "mid" and got[29] == "" and got[27] == "again\n" + "\n".join(passage)


def test_line_dedup_aligns_again(spark):
    import random

    rng = random.Random(5)
    pool = [" ".join(f"p{k}w{i}" for i in range(rng.choice([1, 2, 3, 4, 5, 7, 12]))) for k in range(40)]
    texts = []
    for k in range(60):
        lines = [f"own {k}"]
        for _ in range(rng.randint(1, 6)):
            at = rng.randrange(40)
            lines += pool[at:at + rng.randint(1, 25)] * rng.randint(1, 3) + [""] * rng.randint(0, 2)
        texts.append("\n".join(lines))
    got = {r.doc_id: r.text for r in line_dedup.deduplicated(spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")).collect()}
    assert max(common_words(texts[a], texts[b]) for a in range(60) for b in range(a)) >= 50
    assert max(common_words(got[a], got[b]) for a in range(60) for b in range(a)) < 50
    assert got[0] == texts[0] and all(f"own {k}" in got[k] for k in got)


# ------------------------------------------------------------------ clashing names

CLASH = "_q _w _l _h _n _g _s _p _kept _key _key1 _key2 _hash _copies _copy _id _first _gone _version text_ ranges_ row key1 key2 row_hash copies node id gone version none n_hit spans item_ids host allowed component_id".split()


@pytest.mark.parametrize("empty", [False, True])
def test_rows_keep_columns_of_any_name(spark, docs, empty):
    bench = spark.createDataFrame([(1, "no such words here")], "item_id long, text string")
    wide = docs.select("doc_id", "text", "source", *[F.concat(F.lit(f"{c}:"), F.coalesce(F.col("doc_id").cast("string"), F.lit("-"))).alias(c) for c in CLASH])
    wide = wide.limit(0) if empty else wide
    for f in (quality.kept_rows, mixing.mixed_rows, ngram_join.one_per_component, lambda d: decontaminate.clean(d, bench), lambda d: line_dedup.deduplicated(d).drop("n_lines", "removed_lines")):
        out = f(wide)
        assert out.columns == wide.columns
        got = out.collect()
        assert bool(got) != empty and all(r[c] == f"{c}:{'-' if r.doc_id is None else r.doc_id}" for r in got for c in CLASH)


def test_rows_that_share_an_id_are_not_lost(spark):
    def text(k):
        return " ".join(f"t{k}w{i}" for i in range(40))

    rows = [(7, text(1)), (7, text(2)), (7, text(2)), (3, text(1) + " x"), (None, text(3)), (None, text(2) + " y"), (9, None), (9, "")]
    for order in (rows, rows[::-1]):
        got = ngram_join.one_per_component(spark.createDataFrame(order, "doc_id long, text string").repartition(3), 5, 80).collect()
        assert sorted(map(tuple, got), key=str) == sorted([(3, text(1) + " x"), (7, text(2)), (None, text(3)), (9, None), (9, "")], key=str)


# ------------------------------------------------------------------ 10


def test_decontamination(spark, docs, none):
    items = [(1, "alpha beta gamma delta epsilon zeta eta theta iota kappa"), (2, "One, two!"), (3, ""), (4, None), (20, "one two"), (5, "Ünïcode 日本語")]
    bench = spark.createDataFrame(items, "item_id long, text string")
    for block in (8_000_000, 20):  # one automaton, and several in turn
        got = decontaminate.scan(docs, bench, window=10, block_bytes=block).collect()
        assert len(got) == len(ROWS)
        by = {r.doc_id: r for r in got}
        assert (by[1].n_words, by[1].n_hit, by[1].item_ids) == (14, 10, ["1"])
        assert by[1].text[by[1].spans[0].start : by[1].spans[0].end] == "Alpha beta gamma delta epsilon zeta eta theta iota kappa"
        assert by[9].item_ids == ["2", "20"] and by[2].n_words == 0 and by[6].n_hit == 0
        assert by[11].text[by[11].spans[0].start : by[11].spans[0].end] == "ünïcode 日本語" if by[11].spans else True
    assert {r.doc_id for r in decontaminate.clean(docs, bench).select("doc_id").collect()} >= {2, 3, 4, 5, 6, 7, 8, 12}
    assert decontaminate.scan(none, bench).count() == 0 and decontaminate.scan(docs, bench.limit(0)).agg(F.sum("n_hit")).first()[0] == 0


def test_long_items_in_parts(spark, monkeypatch):
    words = [f"q{k}z" for k in range(300)]
    item = spark.createDataFrame([(1, " ".join(words).upper()), (2, "short, one")], "item_id long, text string")
    docs = spark.createDataFrame([(k, " ".join(["x", *words[a:b], "y", "short one"])) for k, (a, b) in enumerate([(0, 9), (0, 10), (95, 130), (290, 300), (0, 300)])], "doc_id long, text string")
    want = sorted(map(str, decontaminate.digest(decontaminate.scan(docs, item)).collect()))
    monkeypatch.setattr(decontaminate, "PART_WORDS", 25)
    for block in (10**6, 200):
        assert sorted(map(str, decontaminate.digest(decontaminate.scan(docs, item, block_bytes=block)).collect())) == want


def test_words_of_a_piece():
    data = np.frombuffer(b"ab  cd" + b"ef" + b"" + b" x", np.uint8)
    starts, ends, counts = arrow_text.word_spans(data, np.array([0, 6, 8, 8, 10]), arrow_text.word_table())
    assert counts.tolist() == [2, 1, 0, 1] and [bytes(data[a:b]) for a, b in zip(starts, ends)] == [b"ab", b"cd", b"ef", b"x"]


def test_words_in_blocks_and_tables_in_few_bytes(spark):
    """Short words as integers and hashes in blocks agree with bytes; a table's row goes in the bytes that its largest number needs, and sums are whole."""
    words = [b"A", b"abcdefg", b"abcdefgh", b"abcdefghi", b"Abcdefghijklmnopqr", b"abcdefghijklmnopqs", b"abcdefghijklmnopqrs", b"z"]
    data = np.frombuffer(b" ".join(words), np.uint8)
    starts, ends, _ = arrow_text.word_spans(data, np.array([0, len(data)]), arrow_text.word_table())
    keys = context_mixing.short_keys(data, starts, ends).tolist()
    assert keys == [int.from_bytes(w.lower(), "little") if len(w) < 8 else 0 for w in words]
    hashes = arrow_text.block_hashes(arrow_text.lowered(data), starts, ends).tolist()
    for w, h in zip(words, hashes):  # wherever a word stands
        alone = np.frombuffer(b"xx " + w + b"zz", np.uint8)
        assert arrow_text.block_hashes(arrow_text.lowered(alone), np.array([3]), np.array([3 + len(w)])).tolist() == [h]
    assert len(set(hashes)) == len(words)
    values = np.array([[0, 0], [7, 255], [0, 256], [1 << 31, 3], [1 << 40, 1]], np.int64)

    def send(batches):
        for _ in batches:
            yield from context_mixing._sent(values)

    for tasks in (3, 70):
        parts = spark.range(0, tasks, 1, tasks).mapInArrow(send, context_mixing.SENT)
        assert {r["size"] for r in parts.collect()} == {1, 2, 4, 8}
        got = dict(context_mixing._merged(parts, tasks, lambda x, y: x + y, lambda x: x))
        assert {k: v.tolist() for k, v in got.items()} == {k: (values[k] * tasks).tolist() for k in range(1, 5)}


def test_words_before_count_and_leave_a_probability(spark):
    """Texts of the same words score by their order; after any words before, all words together have the probability that they have alone."""
    rng = np.random.default_rng(5)
    follows = {"a": "bc", "b": "cd", "c": "de", "d": "ea", "e": "ab"}
    rows = []
    for i in range(300):
        words = ["a"]
        for _ in range(20):
            words.append(str(rng.choice(list(follows[words[-1]]), p=[0.8, 0.2])))
        rows.append((i, " ".join(words)))
    df = spark.createDataFrame(rows, "doc_id long, text string").withColumn("held_out", context_mixing.held_out())
    classes, pairs, _ = context_mixing.learned(df)
    n_pairs = pairs.count()
    before = context_mixing.words_before(df, classes, pairs, n_pairs)
    q = {r.key: r.score for r in pairs.collect()}
    for start in ("", "a", "a b", "e a", "c c", "a b c d"):
        total, alone = 0.0, 0.0
        for word in ("a", "b", "c", "d", "e", None):
            text = " ".join([*start.split(), *([word] if word else [])])
            import pyarrow as pa

            (x,) = context_mixing._words(pa.array([text]), classes)
            keys, _, at = context_mixing._tokens(x)
            log, open_ = before.of(keys, at, x.own)
            k = len(start.split())
            own = q[int(keys.view(np.int64)[k])]
            total, alone = total + 10 ** (log[k] + own * open_[k]), alone + 10**own
        # what words never seen have alone goes down by what the calls take
        assert alone - 1e-6 <= total <= 1 + 1e-6
    # which places of a text a slot remembers doesn't depend on partitions
    other = context_mixing.word_tables(df.repartition(7), classes, before.bits)
    assert all((np.array(a) == np.array(b)).all() for a, b in zip(context_mixing.word_tables(df, classes, before.bits), other))
    held = [i for i in range(1000, 1100) if zlib.crc32(str(i).encode()) % 5 == 1][:2]
    both = spark.createDataFrame([*rows, (held[0], "a b c d e a b c d e"), (held[1], "e d c b a e d c b a")], "doc_id long, text string")
    got = {r.doc_id: r.score for r in context_mixing.scored(both, frequent=3).where(F.col("doc_id") >= 1000).collect()}
    assert got[held[0]] > got[held[1]] + 3
