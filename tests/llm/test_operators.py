"""Operators on small inputs: brute force, ties, nulls, empty and long texts, repeated rows, clashing columns."""

import random
import re
from collections import Counter

import numpy as np
import pyarrow as pa
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st
from pyspark.sql import functions as F

from evencube.llm import bytegrams, bytescan, decontam, graph, langid, licenses, neardup, packing, quality, tokencount, topk, toxicity, urlfilter

UP = str.maketrans("ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")
PATTERNS = {"alnum": (bytescan.ALNUM, re.compile(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+")), "solid": (bytescan.NON_SPACE, re.compile(r"[^\x20\x09-\x0D]+"))}
EDGE = ["", None, " ", "\n\n", "a", "A b", "é", "中文 字", "😀x", "word " * 30_000, "x" * 100_000, "tab\tand\x00nul", "'s it's 12"]


def frame(spark, texts, **more):
    rows = [(k, t, *(v[k] for v in more.values())) for k, t in enumerate(texts)]
    kinds = "".join(f", {n} {'string' if isinstance(next((x for x in v if x is not None), ''), str) else 'int'}" for n, v in more.items())
    return spark.createDataFrame(rows, "doc_id long, text string" + kinds)


# scanning


@settings(max_examples=80, deadline=None)
@given(st.lists(st.one_of(st.none(), st.text(max_size=40)), max_size=12), st.sampled_from(sorted(PATTERNS)), st.integers(1, 60))
def test_words_are_those_of_the_pattern(texts, kind, limit):
    table, pattern = PATTERNS[kind]
    column, got = pa.array(texts, pa.string()), []
    for part in bytescan.slices(column, limit):
        words, data = bytescan.scan(part, table), bytescan.LOWER[part.data]
        raw = [data[a:b].tobytes().decode() for a, b in zip(words.start, words.end)]
        assert [bytescan.word_hash(w) for w in raw] == words.hash.tolist()
        got += [raw[a:b] for a, b in zip(words.bounds[:-1], words.bounds[1:])]
    assert got == [pattern.findall((t or "").translate(UP)) for t in texts]


def test_shingles_are_sets():
    column = pa.array(["a b c a b c", "a b", "", "x"], pa.string())
    (part,) = bytescan.slices(column)
    row, _ = bytescan.shingles(bytescan.scan(part, bytescan.NON_SPACE), 3)
    assert np.bincount(row, minlength=4).tolist() == [3, 1, 0, 1]


def test_sliced_columns_keep_their_rows():
    column = pa.array(["zero", "one", None, "three"], pa.string()).slice(1)
    (part,) = bytescan.slices(column)
    assert bytescan.scan(part, bytescan.ALNUM).counts.tolist() == [1, 0, 1]


# url filter


RULES = [urlfilter.Rule("block", "net", "/"), urlfilter.Rule("allow", "example.net", "/en/"), urlfilter.Rule("block", "a.b", ""), urlfilter.Rule("allow", "a.b", "/x"), urlfilter.Rule("allow", "a.b", ""), urlfilter.Rule("block", "c.d", "/p/q")]


def test_url_rules(spark):
    urls = ["http://Example.NET/en/1?x#y", "https://w.example.net/de/", "http://net", "http://xnet/", "a.b/x", None, "", "ftp://a.b", "ftp://s.a.b/xyz", "http://c.d/p/qr", "http://c.d/p", "x://y://net/", "http://net/\nz", "http://a..net/"]
    rows = spark.createDataFrame([(k, u, "kept") for k, u in enumerate(urls)], "page_id long, url string, rule string")
    got = {r.page_id: r for r in urlfilter.judge_urls(rows, RULES).collect()}

    def brute(url):
        host, path = "", ""
        if url and "://" in url:
            rest = url.split("://", 1)[1]
            host = re.split(r"[/?#]", rest)[0]
            path = re.split(r"[?#]", rest[len(host) :])[0]
            host = host.translate(UP)
        fits = [r for r in RULES if ("." + host).endswith("." + r.host) and path.startswith(r.path)]
        best = max(fits, key=lambda r: (r.host.count("."), len(r.path), r.verdict == "block"), default=None)
        return host, path, best.name if best else None, best.verdict if best else "allow"

    for k, u in enumerate(urls):
        assert (got[k].host, got[k].path, got[k].rule, got[k].verdict) == brute(u), u
    assert urlfilter.judge_urls(rows.limit(0), RULES).count() == 0
    with pytest.raises(ValueError):
        urlfilter.judge_urls(rows, RULES, default="maybe")


# decontamination


@settings(max_examples=60, deadline=None)
@given(st.lists(st.lists(st.sampled_from("abc"), max_size=30), max_size=6), st.lists(st.lists(st.sampled_from("abc"), max_size=9), max_size=6), st.integers(1, 4))
def test_search_by_brute_force(texts, items, window):
    tables = decontam.compile_tables(pa.array([" ".join(i) for i in items], pa.string()), window)
    names = np.array([f"i{k}" for k in range(len(items))], object)
    counts, spans, found = decontam.search(pa.array([" ".join(t) for t in texts], pa.string()), tables, names)
    for t, n, s, f in zip(texts, counts.to_pylist(), spans.to_pylist(), found.to_pylist()):
        hit, who = set(), set()
        for k, item in enumerate(items):
            m = min(window, len(item))
            for i in range(len(item) - m + 1 if m else 0):
                for at in range(len(t) - m + 1):
                    if t[at : at + m] == item[i : i + m]:
                        hit |= set(range(at, at + m))
                        who.add(f"i{k}")
        assert n == len(t) and set(f) == who
        assert {p for x in s for p in range(x["first"], x["last"] + 1)} == hit


def test_long_rows_are_walked_in_lanes(spark):
    text = " ".join(["filler"] * 3000 + list("abcdefghij") + ["filler"] * 500)
    items = spark.createDataFrame([(7, "A b c d e f g h i J"), (8, None), (None, "filler filler"), (9, "")], "item_id long, text string")
    docs = frame(spark, [text, None, "nothing here", "a b c"], hit_spans=["x"] * 4)
    got = {r.doc_id: r for r in decontam.find_contamination(docs, items).collect()}
    assert got[0].item_ids == ["7"] and got[0].n_words == 3510 and got[1].n_words == 0 and got[1].item_ids == [] and got[3].item_ids == []
    n = decontam.find_contamination(docs, items).select("doc_id", decontam.hit_count(F.col("hit_spans")).alias("n")).where("doc_id = 0").first().n
    assert n == 3510  # the unnamed item marks the filler
    assert decontam.find_contamination(docs.limit(0), items).count() == 0
    assert decontam.find_contamination(docs, items.limit(0)).where(F.size("hit_spans") > 0).count() == 0


def test_many_pattern_tables_give_the_same(spark, monkeypatch):
    r = random.Random(1)
    word = lambda: r.choice("abcdefgh")
    items = spark.createDataFrame([(k, " ".join(word() for _ in range(r.randrange(0, 9)))) for k in range(40)], "item_id long, text string")
    docs = frame(spark, [" ".join(word() for _ in range(60)) for _ in range(30)])
    whole = {x.doc_id: (x.item_ids, x.n) for x in decontam.find_contamination(docs, items, window=4).select("*", decontam.hit_count(F.col("hit_spans")).alias("n")).collect()}
    monkeypatch.setattr(decontam, "BLOCK_BYTES", 100)
    parts = {x.doc_id: (x.item_ids, x.n) for x in decontam.find_contamination(docs, items, window=4).select("*", decontam.hit_count(F.col("hit_spans")).alias("n")).collect()}
    assert whole == parts


# licences


@settings(max_examples=60, deadline=None)
@given(st.lists(st.lists(st.integers(0, 3), min_size=1, max_size=12), min_size=1, max_size=4), st.lists(st.integers(0, 4), max_size=40))
def test_matching_statistics_by_brute_force(templates, text):
    a = licenses.SuffixAutomaton()
    for k, t in enumerate(templates):
        a.add(k, t)
    a.close()
    lengths, states = a.statistics(text)
    holds = lambda piece: any(t[i : i + len(piece)] == piece for t in templates for i in range(len(t) - len(piece) + 1))
    for i, (size, state) in enumerate(zip(lengths, states)):
        want = max(k for k in range(i + 2) if k == 0 or holds(text[i + 1 - k : i + 1]))
        assert size == want
        for template, at in a.ends[state].items() if size else ():
            assert templates[template][at - size + 1 : at + 1] == text[i + 1 - size : i + 1]


def test_licence_spans(spark):
    mit = licenses.TEMPLATES["mit"]
    cut = mit.replace("free of charge, ", "free of any charge at all, ")
    texts = [f"intro words. {mit} tail", f"intro. {cut} tail", "permission is hereby", None, "", "UNDER the\nMIT license under the mit license", "cc by nc by nc", "apache license version 2 " * 3]
    got = {r.doc_id: r for r in licenses.scan_licences(frame(spark, texts, labels=["x"] * len(texts))).collect()}
    assert got[0].labels == ["mit"] and got[0].coverage == 1 and (got[0].spans[0].first, got[0].spans[0].last) == (2, 2 + len(mit.split()) - 1)
    assert got[1].labels == ["mit"] and 0.8 < got[1].coverage < 1
    assert got[2].labels == [] and got[2].coverage < licenses.MIN_COVER
    for k in (3, 4):
        assert (got[k].n_words, got[k].n_places, got[k].first_word, got[k].labels, got[k].coverage) == (0, 0, None, [], 0.0)
    assert (got[5].n_places, got[5].first_word, got[5].last_word, got[5].phrase_labels) == (2, 0, 4, ["mit"])
    assert got[6].n_places == 1 and got[7].n_places == 3 and got[7].last_word == 8
    assert licenses.scan_licences(frame(spark, texts).limit(0)).count() == 0


# token counts


PIECES = [" ", "  ", "\n", "a", "the", "é", "▁", "\x00", "<s>", "①", "\t", " x", "\n\n", "中", "😀", "12", "...", " \n", "\n ", " " * 17, "aaa", "abba"]


def piece_model():
    import public_tokenizers
    import sentencepiece

    path = public_tokenizers.path("piece_bpe_32k.model")
    return path, sentencepiece.SentencePieceProcessor(model_file=path)


def test_compiled_counts_agree_with_the_library(monkeypatch):
    (path, library), r = piece_model(), random.Random(2)
    compiled = tokencount.compile_model(path)
    texts = [t or "" for t in EDGE] + ["".join(r.choices(PIECES, k=r.randrange(1, 30))) for _ in range(3000)]
    want = [len(x) for x in library.encode(texts)]
    assert tokencount.TokenCounter(compiled).counts(texts) == want
    monkeypatch.setattr(tokencount, "MAX_ARCS", 50)
    monkeypatch.setattr("evencube.llm.merges.MAX_PAIRS", 20)
    assert tokencount.TokenCounter(compiled).counts(texts[13:400]) == want[13:400]


def test_transducer_by_naive_merges(monkeypatch):
    """Against merging the best pair, leftmost first, until none is left; strings read side by side and alone."""
    from evencube.llm import merges

    r, made = random.Random(8), 0
    for _ in range(60):
        letters = "abc"[: r.randrange(1, 4)]
        pieces, known = [], set(letters)
        while len(pieces) < 12:
            p = "".join(r.choices(sorted(known), k=2))
            if len(p) > 1 and p not in known:
                known.add(p)
                pieces.append(p)
            elif r.random() < 0.05:
                break
        rank = {p: k for k, p in enumerate(pieces)}
        texts = ["".join(r.choices(letters + "?é", weights=[9] * len(letters) + [1, 1], k=r.randrange(1, 30))) for _ in range(200)]
        try:
            machine = merges.Transducer(list(letters), pieces)
        except ValueError:  # no trained vocabulary has later pieces inside earlier ones
            continue
        made += 1
        parts = [merges._merged(t, rank, len(pieces)) for t in texts]
        want = [sum(len(x.encode()) if x in "?é" else 1 for x in p) for p in parts]
        for limit in (0, 64):
            monkeypatch.setattr(merges, "SIDE_BY_SIDE", limit)
            count, alone = machine.counts(texts)
            assert count.tolist() == want and alone.tolist() == [len(p[0]) == 1 for p in parts]
    assert made > 20


def test_chunk_maps_agree_wherever_texts_are_cut():
    (path, library), r = piece_model(), random.Random(5)
    counter = tokencount.TokenCounter(tokencount.compile_model(path))
    for _ in range(400):
        text = "".join(r.choices(PIECES, k=r.randrange(1, 30)))
        raw, size = tokencount.SPACE + text.replace(" ", tokencount.SPACE), r.randrange(1, 9)
        maps = [counter.chunk_map(raw[k : k + size]) for k in range(0, len(raw), size)]
        assert counter.long(maps) == len(library.encode(text))


def test_token_count_edges(spark, monkeypatch):
    """Null, empty, repeated, long rows (cut over tasks), clashing names and empty tables."""
    path, library = piece_model()
    monkeypatch.setattr(tokencount, "CHUNK_CHARS", 500)
    monkeypatch.setattr(tokencount, "LONG_CHARS", 2000)
    texts = [*EDGE, "two rows", "two rows", "one  line\n" * 1000, "one  line\n" * 1000]
    docs = frame(spark, texts, n_tokens=["x"] * len(texts), row=["y"] * len(texts)).withColumn("a.b", F.lit(None).cast("string"))
    got = tokencount.count_tokens(docs, path)
    assert got.columns == ["doc_id", "text", "row", "a.b", "n_bytes", "n_tokens", "over_limit"]
    rows = {r.doc_id: r for r in got.collect()}
    assert len(rows) == len(texts)
    for k, t in enumerate(texts):
        n = len(library.encode(t or ""))
        assert (rows[k].text, rows[k].row, rows[k].n_bytes, rows[k].n_tokens, rows[k].over_limit) == (t, "y", len((t or "").encode()), n, n > 4096)
    assert tokencount.count_tokens(docs.limit(0), path).count() == 0


def test_state_maps_compose_associatively():
    count = len
    maps = [tokencount.StateMap("a", 1, "b"), tokencount.StateMap("cd", 0, None), tokencount.StateMap("", 4, "x"), tokencount.StateMap("y", 0, "")]
    c = lambda a, b: tokencount.compose(a, b, count)
    assert c(c(maps[0], maps[1]), c(maps[2], maps[3])) == c(maps[0], c(maps[1], c(maps[2], maps[3]))) == tokencount.scan_maps(maps, count)


# packing


def test_ids_agree_with_the_library():
    import public_tokenizers
    from tokenizers import Tokenizer

    path = public_tokenizers.path("word_bpe_49k.json")
    library, encoder, r = Tokenizer.from_file(path), packing.PieceEncoder(path), random.Random(3)
    parts = [" ", "\n", "a", "B", "the", "'s", "'", "É", "ß", "×", "İ", "Σ", "<|endoftext|>", "<|", "12", "²", "...", "!!", "中", "😀", "\t", "\x1c", "e\u0301", "ŉ", "ſ", "'LL", "_", "Ÿ", "\x00", "Ⅷ"]
    texts = [t or "" for t in EDGE] + ["".join(r.choices(parts, k=r.randrange(0, 25))) for _ in range(4000)]
    assert encoder.encode(texts) == [np.array(x.ids, "<u4").tobytes() for x in library.encode_batch(texts, add_special_tokens=False)]


@settings(max_examples=60, deadline=None)
@given(st.lists(st.integers(1, 100), max_size=60), st.integers(100, 300))
def test_windows_hold_everything(sizes, capacity):
    at = packing.pack_group(sizes, capacity)
    sums = np.bincount(at, sizes) if len(sizes) else np.zeros(0)
    assert len(at) == len(sizes) and (sums <= capacity).all()


def test_differencing_evens_out():
    r = np.random.default_rng(0)
    sizes = r.integers(50, 1024, 800).tolist()
    at, fullest = packing.difference(sizes, 100)
    sums = np.bincount(at, sizes, 100)
    assert fullest == sums.max() and sums.max() - sums.min() < 60


def test_cuts_cover():
    for n in (1, 5, 4095, 4096, 4097, 9000, 20_000):
        got = packing.cuts(n)
        assert [a for a, _ in got] == np.cumsum([0, *(m for _, m in got)])[:-1].tolist() and sum(m for _, m in got) == n
        assert all(m == 4096 or m <= packing.PIECE for _, m in got)


def test_packing_edges(spark):
    import public_tokenizers

    path = public_tokenizers.path("word_bpe_49k.json")
    rows = spark.createDataFrame([(1, None), (1, None), (None, "a b"), (2, "word " * 9000)], "doc_id long, text string")
    got = packing.pack(rows, path).toPandas()
    assert len(got[got.doc_id == 1]) == 2 and (got[got.doc_id == 1].length == 1).all() and got.doc_id.isna().sum() == 1
    assert got[got.doc_id == 2].length.sum() == 9001 and got.groupby("sequence_id").length.sum().max() <= 4096
    assert packing.pack(rows.limit(0), path).count() == 0
    with pytest.raises(ValueError):
        packing.pack(rows, path, piece=0)


# near duplicates and components


@pytest.mark.parametrize("edges", [1 << 18, 5])
def test_components_by_brute_force(spark, monkeypatch, edges):
    monkeypatch.setattr(graph, "EDGES", edges)
    r = random.Random(4)
    for n, m in ((40, 30), (200, 150), (60, 59)):
        edges = [(r.randrange(n), r.randrange(n)) for _ in range(m)] if m != 59 else [(k, k + 1) for k in range(59)]
        got = {x.node: x.component for x in graph.components(spark.createDataFrame(edges + [(None, 1)], "a long, b long")).collect()}
        root = {k: k for k in range(n)}

        def find(i):
            while root[i] != i:
                i = root[i]
            return i

        for a, b in edges:
            x, y = find(a), find(b)
            root[max(x, y)] = min(x, y)
        assert got == {k: find(k) for e in edges if e[0] != e[1] for k in e}
    assert graph.components(spark.createDataFrame([], "a long, b long")).count() == 0


def test_hot_keys_are_joined_apart(spark):
    rows = spark.createDataFrame([(1, k) for k in range(600)] + [(2, 7), (3, 8), (None, 9)], "a long, x long")
    values = rows.groupBy("a").count().withColumnRenamed("count", "n").where("a <> 3").withColumn("low", F.col("a") * 10)
    got = graph.join_split(rows, values, ["a"], "n", rows.count())
    assert sorted((r.a, r.x, r.low) for r in got.collect()) == [(1, k, 10) for k in range(600)] + [(2, 7, 20)]


def test_boilerplate_is_hardly_compared(spark, monkeypatch):
    counted, confirmed = [], neardup._confirmed

    def watch(pairs, sets, percent):
        counted.append(pairs.count())
        return confirmed(pairs, sets, percent)

    monkeypatch.setattr(neardup, "_confirmed", watch)
    same = " ".join(f"s{k}" for k in range(60))
    texts = [same + " " + " ".join(f"x{r}_{k}" for k in range(60)) for r in range(3000)]
    got = neardup.near_duplicates(frame(spark, texts)).toPandas()
    assert got.kept.all() and sum(counted) < 50_000


def test_many_copies_of_one_id(spark):
    base = [f"w{k}" for k in range(30)]
    rows = spark.range(20_000).select(F.lit(7).cast("long").alias("doc_id"), F.lit(" ".join(base)).alias("text"))
    more = [(3, " ".join(base[:-1] + ["x"])), (7, "quite another text of one id"), (9, "quite another text of one id"), (5, "alone")]
    got = neardup.near_duplicates(rows.unionByName(spark.createDataFrame(more, "doc_id long, text string"))).groupBy("doc_id", "component_id", "kept").count().collect()
    assert sorted((r.doc_id, r.component_id, r.kept, r["count"]) for r in got) == [(3, 3, True, 1), (5, 5, True, 1), (7, 3, False, 20_001), (9, 3, False, 1)]


def test_half_keys():
    for s in (0.5, 0.8, 0.85):
        m = neardup.half_keys(s)
        assert 2 * (1 - s**neardup.HASHES) ** m <= neardup.MISS
    assert neardup.half_keys(1.0) == 1


def test_near_duplicate_edges(spark):
    base = [f"w{k}" for k in range(60)]
    other = base[:-1] + ["changed"]
    far = base[:30] + [f"v{k}" for k in range(30)]
    texts = [" ".join(base), " ".join(other), " ".join(base).upper(), " ".join(far), None, "", "one two", "ONE  two", "one"]
    rows = frame(spark, texts, kept=["x"] * len(texts)).unionByName(spark.createDataFrame([(None, " ".join(base), "y"), (3, " ".join(far), "z")], "doc_id long, text string, kept string"))
    got = neardup.near_duplicates(rows, words=5, percent=80).toPandas()
    by = got.dropna(subset=["doc_id"]).drop_duplicates().set_index("doc_id")
    assert by.component_id.to_dict() == {0: 0, 1: 0, 2: 0, 3: 3, 4: 4, 5: 5, 6: 6, 7: 6, 8: 8}
    assert by.n_shingles.to_dict() == {0: 56, 1: 56, 2: 56, 3: 56, 4: 0, 5: 0, 6: 1, 7: 1, 8: 1}
    assert by.kept.sum() == 6 and len(got) == len(texts) + 2
    lost = got[got.doc_id.isna()].iloc[0]
    assert np.isnan(lost.component_id) and not lost.kept
    assert neardup.near_duplicates(rows.limit(0)).count() == 0


@pytest.mark.parametrize("limits", [{}, {"SMALL": 1, "TILE": 8, "COLUMNS": 50}, {"SMALL": 60, "HUB_ROWS": 3}])
def test_large_families_are_linked(spark, monkeypatch, limits):
    for name, value in limits.items():
        monkeypatch.setattr(neardup, name, value)
    r, base = random.Random(5), [f"w{k}" for k in range(120)]
    texts = []
    for k in range(60):
        w = list(base)
        for _ in range(r.randrange(0, 12)):
            w[r.randrange(len(w))] = f"x{k}_{r.randrange(1000)}"
        texts.append(" ".join(w))
    got = neardup.near_duplicates(frame(spark, texts), words=3, percent=85).toPandas().set_index("doc_id").component_id
    sets = [{tuple(t.split()[k : k + 3]) for k in range(118)} for t in texts]
    root = list(range(60))

    def find(i):
        while root[i] != i:
            i = root[i]
        return i

    for i in range(60):
        for j in range(i):
            both = len(sets[i] & sets[j])
            if 100 * both >= 85 * len(sets[i] | sets[j]):
                a, b = find(i), find(j)
                root[max(a, b)] = min(a, b)
    assert got.to_dict() == {k: find(k) for k in range(60)}


# top-k


def test_search_group_by_brute_force(monkeypatch):
    monkeypatch.setattr(topk, "BUCKET_ROWS", 40)
    r = np.random.default_rng(0)
    for trial in range(40):
        d, n = int(r.integers(1, 6)), int(r.integers(5, 300))
        c = np.floor(r.normal(size=(n, d)) * np.exp(r.normal(size=(n, 1)) * r.choice([0, 0.5, 2])) * r.choice([3, 20, 64]))
        c = c[r.integers(0, 3, n)] if trial % 3 == 0 else np.abs(c) if trial % 5 == 0 else c
        ids = np.arange(n)
        x, got_ids, score = topk.search_group(c[:20], ids[:20], c, ids, 7)
        s = c[:20] @ c.T
        for k in range(min(20, n)):
            want = sorted(((-s[k, j], j) for j in range(n) if j != k))[:7]
            assert list(zip(got_ids[x == k], score[x == k])) == [(j, -v) for v, j in want]


def exact_scores(rows):
    whole = {i: [int(np.floor(64 * x)) for x in v] for i, v in rows}
    clip = lambda x: max(1 - (1 << 63), min((1 << 63) - 1, x))
    return {q: sorted((-clip(sum(x * y for x, y in zip(whole[q], whole[i]))), i) for i in whole if i != q) for q in whole if q % 20 == 0}


@pytest.mark.parametrize("size", [0, 20, 40, 60])
def test_products_are_exact(spark, monkeypatch, size):
    """Components up to 2**40 give products beyond what doubles hold, 2**60 beyond 64 bits."""
    monkeypatch.setattr(topk, "GROUP_ROWS", 30)
    monkeypatch.setattr(topk, "BLOCK_ROWS", 2)
    r = np.random.default_rng(size)
    rows = [(k, [float(x) for x in r.integers(-(1 << 20), 1 << 20, 6) * 2.0 ** (size - 20 - (k % 3) * 9)]) for k in range(120)]
    got = topk.top_products(topk.scaled_vectors(spark.createDataFrame(rows, "vec_id long, embedding array<double>")), F.col("vec_id") % 20 == 0, 5).collect()
    want = exact_scores(rows)
    assert sorted((x.query_id, x["rank"], x.vec_id, x.score) for x in got) == [(q, n + 1, i, -v) for q in sorted(want) for n, (v, i) in enumerate(want[q][:5])]


def test_short_vectors_are_not_sent(spark, monkeypatch):
    monkeypatch.setattr(topk, "GROUP_ROWS", 25)
    monkeypatch.setattr(topk, "BLOCK_ROWS", 2)
    sent, plain = [], topk._round

    def watch(asked, right, reach, start, stop, k):
        sent.append(asked.count() * (stop - start))
        return plain(asked, right, reach, start, stop, k)

    monkeypatch.setattr(topk, "_round", watch)
    r = np.random.default_rng(7)
    rows = [(k, [float(x) for x in r.normal(size=4) * 2.0 ** (-(k % 40) / 3)]) for k in range(600)]
    got = topk.top_products(topk.scaled_vectors(spark.createDataFrame(rows, "vec_id long, embedding array<double>")), F.col("vec_id") % 20 == 0, 5).collect()
    want = exact_scores(rows)
    assert sorted((x.query_id, x["rank"], x.vec_id, x.score) for x in got) == [(q, n + 1, i, -v) for q in sorted(want) for n, (v, i) in enumerate(want[q][:5])]
    assert sum(sent) < 0.6 * 30 * 24


def test_vector_edges(spark, monkeypatch):
    monkeypatch.setattr(topk, "GROUP_ROWS", 3)
    monkeypatch.setattr(topk, "BLOCK_ROWS", 1)
    nan, inf = float("nan"), float("inf")
    rows = [(0, [1.0, 0.5]), (0, [1.0, 0.5]), (1, [1.0, 0.5]), (2, None), (3, [nan, 1.0]), (4, [inf, 1.0]), (5, [None, 1.0]), (6, []), (7, [0.0, 0.0]), (8, [-1.0, 1.0]), (20, [0.25, 0.25]), (None, [1.0, 1.0]), (9, [1.0, 1.0, 1.0]), (10, [1.0, 0.5]), (10, [1.0, 0.5])]
    table = spark.createDataFrame(rows, "vec_id long, embedding array<float>")
    got = topk.top_products(topk.scaled_vectors(table), F.col("vec_id") % 20 == 0, 4).collect()
    by = {q: [(r.rank, r.vec_id, r.score) for r in sorted(got, key=lambda r: r.rank) if r.query_id == q] for q in (0, 20)}
    assert by[0] == [(1, 1, 5120), (2, 10, 5120), (3, 10, 5120), (4, 20, 1536)]
    assert by[20][:2] == [(1, 0, 1536), (2, 0, 1536)] and {r.query_id for r in got} == {0, 20}
    assert topk.top_products(topk.scaled_vectors(table.limit(0)), F.col("vec_id") % 20 == 0).count() == 0


# classifiers


def test_many_tries_give_the_same(spark, monkeypatch):
    r = random.Random(4)
    hosts, paths = ["net", "a.net", "b.a.net", "org", ""], ["", "/", "/x", "/x/", "/x/y", "/z"]
    rules = [urlfilter.Rule(r.choice(["allow", "block"]), r.choice(hosts), r.choice(paths)) for _ in range(25)]
    urls = [(k, f"http://{r.choice(['net', 'c.a.net', 'b.a.net', 'x.org', 'other.de'])}{r.choice(['', '/', '/x', '/xy', '/x/y/z', '/z?q'])}", "mine") for k in range(200)]
    pages = spark.createDataFrame(urls, "page_id long, url string, judged0 string")
    one = urlfilter.judge_urls(pages, rules).collect()
    monkeypatch.setattr(urlfilter, "MAX_RULE_CHARS", 9)
    assert len(urlfilter._blocks(rules)) > 3 and sorted(urlfilter.judge_urls(pages, rules).collect(), key=str) == sorted(one, key=str)


def test_training_step_by_step():
    """Weights and scores against the update rule, one coordinate at a time in plain Python."""
    r = random.Random(9)
    texts = [" ".join(r.choices(["bad", "good", "worse", "fine", "thing"], k=6)) for _ in range(40)]
    labels = np.array([float("bad" in t.split()) for t in texts])
    how = toxicity.Ftrl(alpha=0.5, beta=1.0, l1=0.3, l2=0.1, epochs=2, min_texts=3)
    key, weight, bias = toxicity.train(pa.array(texts), labels, how)
    sets = [set(toxicity.features(next(bytescan.slices(pa.array([t]))))[1].tolist()) for t in texts]
    held = Counter(f for s in sets for f in s)
    known = {f for f, n in held.items() if n >= 3}
    z, n = Counter(), Counter()

    def w(f):
        edge = 0.0 if f is None else how.l1
        if abs(z[f]) <= edge:
            return 0.0
        return -(z[f] - (edge if z[f] > 0 else -edge)) / ((how.beta + n[f] ** 0.5) / how.alpha + how.l2)

    for _ in range(how.epochs):
        for s, label in zip(sets, labels):
            on = [*(s & known), None]
            g = 1 / (1 + np.exp(-sum(w(f) for f in on))) - label
            for f, old in [(f, w(f)) for f in on]:
                z[f] += g - ((n[f] + g * g) ** 0.5 - n[f] ** 0.5) / how.alpha * old
                n[f] += g * g
    assert bias == pytest.approx(w(None)) and dict(zip(key.tolist(), weight)) == pytest.approx({f: w(f) for f in known if w(f)})
    model = toxicity.ToxicityModel(key, weight, bias)
    score, _ = model.scorer()(pa.array(texts[:9]))
    assert np.allclose(score.to_numpy(), [1 / (1 + np.exp(-sum(w(f) for f in [*(s & known), None]))) for s in sets[:9]], atol=1e-6)


def test_repeated_rows_train_once(spark):
    docs = frame(spark, [("nasty word " if k % 2 == 0 else "kind word ") + f"t{k}" for k in range(60)])
    labels = spark.createDataFrame([(k, int(k % 2 == 0)) for k in range(60)], "doc_id long, toxic int")
    one = toxicity.fit_toxicity(docs, labels)
    many = toxicity.fit_toxicity(docs.unionByName(docs.where("doc_id < 3").crossJoin(spark.range(200)).drop("id")), labels.unionByName(labels))
    assert np.array_equal(one.key, many.key) and np.allclose(one.weight, many.weight)


def test_repeated_rows_are_judged_alike(spark):
    """Rows of one id and text, many times over, in the operators that judge row by row."""
    docs = frame(spark, ["under the mit license and more words to find here", "the house and the garden are here", None], lang=["en", "en", None])
    twice = docs.unionByName(docs)
    items = spark.createDataFrame([(1, "the house and the garden"), (1, "the house and the garden"), (2, None)], "item_id int, text string")
    pages = spark.createDataFrame([(1, "http://a.net/x", "own"), (1, "http://a.net/x", "own"), (2, None, "own")], "page_id long, url string, __judged string")
    profiles = langid.fit_profiles(docs)
    for result, keys in (
        (licenses.scan_licences(twice), ["doc_id"]),
        (decontam.find_contamination(twice, items), ["doc_id"]),
        (langid.predict_language(twice, profiles), ["doc_id"]),
        (urlfilter.judge_urls(pages, [urlfilter.Rule("block", "net", "/")]), ["page_id"]),
    ):
        rows = [tuple(str(x) for x in r) for r in result.collect()]
        assert len(rows) in (6, 3) and len(set(rows)) == (3 if keys == ["doc_id"] else 2)
        assert result.limit(0).count() == 0


def test_toxicity_edges(spark):
    labels = spark.createDataFrame([(k, int(k % 2 == 0)) for k in range(60)] + [(99, None), (None, 1)], "doc_id long, toxic int")
    texts = [("nasty word here " if k % 2 == 0 else "kind word here ") + f"t{k}" for k in range(60)]
    docs = frame(spark, texts, score=["x"] * 60)
    model = toxicity.fit_toxicity(docs, labels)
    got = {r.doc_id: r for r in toxicity.score_toxicity(docs, model).collect()}
    assert got[0].predicted == 1 and got[1].predicted == 0
    odd = toxicity.score_toxicity(frame(spark, EDGE), model).collect()
    assert len(odd) == len(EDGE) and all(0 <= r.score <= 1 for r in odd) and len({r.score for r in odd if not r.text}) == 1
    plain = toxicity.fit_toxicity(docs, labels.limit(0))
    assert {r.score for r in toxicity.score_toxicity(docs, plain).collect()} == {0.5}
    assert toxicity.score_toxicity(docs.limit(0), model).count() == 0
    again = toxicity.fit_toxicity(docs.repartition(5), labels.repartition(3))
    assert np.array_equal(again.key, model.key) and np.allclose(again.weight, model.weight)


def test_quality_edges(spark):
    good = [f"the quick brown fox number {k} jumps over the lazy dog again and again" for k in range(40)]
    docs = frame(spark, good + ["##@@!!zz" * 40, None, ""], lang=["en"] * 40 + [None, None, "en"], kept=["x"] * 43)
    labels = spark.createDataFrame([(k, 1) for k in range(40)] + [(None, 1), (41, None)], "doc_id long, quality int")
    got = {r.doc_id: r for r in quality.score_quality(docs, quality.fit_quality(docs, labels)).collect()}
    assert all(got[k].kept for k in range(40)) and not got[40].kept
    assert got[41].kept and got[42].kept and got[41].perplexity is None
    none = quality.fit_quality(docs, labels.limit(0))
    assert quality.score_quality(docs, none).where("kept").count() == 43
    assert quality.score_quality(docs.limit(0), none).count() == 0
    long = quality.score_quality(frame(spark, EDGE, lang=["en"] * len(EDGE)), quality.fit_quality(docs, labels))
    assert long.count() == len(EDGE)


def byte_model(texts):
    """Probability of a gram's last byte from plain dictionaries."""
    counts = {6: Counter(g for t in texts for w in [b"\0" * 5 + t.lower().encode() + b"\0"] for g in (w[k : k + 6] for k in range(len(w) - 5)))}
    for k in range(5, 0, -1):
        counts[k] = Counter(g[1:] for g in counts[k + 1])
    cuts = {k: bytegrams.discounts(np.array([sum(v == x for v in n.values()) for x in (1, 2, 3, 4)])) for k, n in counts.items()}

    def p(gram):
        k = len(gram)
        if not k:
            return 1 / 256
        same = [v for g, v in counts[k].items() if g[:-1] == gram[:-1]]
        if not same:
            return p(gram[1:])
        n, cut = counts[k][gram], lambda v: min(v, cuts[k][min(v, 3) - 1]) if v else 0
        return (n - cut(n)) / sum(same) + sum(map(cut, same)) / sum(same) * p(gram[1:])

    return p, counts[6]


@pytest.mark.parametrize("limits", [{}, {"BLOCK_BYTES": 1000, "SHARDS": 2}])
def test_byte_model_by_hand(spark, monkeypatch, limits):
    """Whole-document losses of either fold against plain dictionaries, in one block and in several."""
    for name, value in limits.items():
        monkeypatch.setattr(quality, name, value)
    good = [[f"The cat {k} sat on the mat", f"a dog ate {k * k} cakes", "é is a letter of the cat", "aaaa aaab"] for k in range(6)]
    good = sorted({t for g in good for t in g})
    docs = frame(spark, [*good, "the dog sat on é", "zzz", ""], lang=["en"] * (len(good) + 3))
    labels = spark.createDataFrame([(k, 1) for k in range(len(good))], "doc_id long, quality int")
    monkeypatch.setattr(quality, "MIN_TEXTS", 2)
    got = quality.score_quality(docs, quality.fit_quality(docs, labels)).withColumn("fold", F.pmod(F.xxhash64("text"), F.lit(2))).collect()
    of = {r.text: r.fold for r in got}
    models = [byte_model([t for t in good if of[t] != f]) for f in (0, 1)]
    for r in got:
        w, (p, _) = b"\0" * 5 + r.text.lower().encode() + b"\0", models[r.fold]
        want = -sum(np.log(p(w[k : k + 6])) for k in range(len(w) - 5)) if r.text else 0
        assert r.loss == pytest.approx(want, rel=1e-5) and r.symbols == (len(w) - 5 if r.text else 0)
        assert r.perplexity is None if not r.text else r.perplexity == pytest.approx(np.exp(want / r.symbols), rel=1e-5)


def test_what_the_model_gathers_is_open(spark):
    """Whole words count: known words in another order score worse."""
    good = [" ".join(f"w{(k * 7 + j) % 50}" for j in range(60)) for k in range(60)]
    shuffled = " ".join(f"w{(j * j * 11 + 3 * j) % 50}" for j in range(60))
    docs = frame(spark, [*good, shuffled], lang=["en"] * 61)
    got = {r.doc_id: r for r in quality.score_quality(docs, quality.fit_quality(docs, spark.createDataFrame([(k, 1) for k in range(60)], "doc_id long, quality int"))).collect()}
    assert got[60].perplexity > 5 * max(got[k].perplexity for k in range(60))


def test_more_than_64_languages_have_models_of_their_own(spark):
    texts, langs = [], []
    for k in range(66):
        texts += [f"lang{k} has a word{j % 5} of its own{k}" for j in range(20)]
        langs += [f"l{k}"] * 20
    docs = frame(spark, texts, lang=langs)
    got = quality.score_quality(docs, quality.fit_quality(docs, spark.createDataFrame([(k, 1) for k in range(len(texts))], "doc_id long, quality int")))
    assert {r.model for r in got.select("model").distinct().collect()} == {f"l{k}" for k in range(66)}


def test_language_edges(spark):
    docs = frame(spark, ["the house and the garden"] * 3 + ["das haus und der garten"] * 3 + ["nothing"], lang=["en"] * 3 + ["de"] * 3 + [None])
    profiles = langid.fit_profiles(docs)
    got = {r.doc_id: r for r in langid.predict_language(frame(spark, ["the garden", "der garten", None, "123 !!", "中文", ""], lang_pred=["x"] * 6), profiles).collect()}
    assert got[0].lang_pred == "en" and got[1].lang_pred == "de"
    assert [got[k].lang_pred for k in (2, 3, 5)] == ["und"] * 3 and got[4].lang_pred in ("en", "de")
    assert all(0 <= r.score <= 1 for r in got.values())
    empty = langid.fit_profiles(docs.limit(0))
    assert {r.lang_pred for r in langid.predict_language(docs, empty).collect()} == {"und"}
    assert langid.predict_language(docs.limit(0), profiles).count() == 0


def test_predictions_equal_those_of_bundled_vectors():
    """Products from the table against document vectors bundled one by one, and the documents' cosines."""
    texts = {"a": ["the house and the garden", "a house"], "b": ["das haus und der garten", "ein haus"], "c": ["la maison et le jardin"]}
    vectors = langid.symbol_vectors(8192, 1)

    def codes(text):
        return langid.trigrams(next(bytescan.slices(pa.array([text]))))[1]

    counts = [np.unique(np.concatenate([codes(t) for t in of]), return_counts=True) for of in texts.values()]
    profile = np.stack([sum(n / c[1].sum() * langid.bind(np.array([g]), vectors)[0].astype(float) for g, n in zip(*c)) for c in counts])
    profile -= profile.mean(axis=0)
    profile /= np.linalg.norm(profile, axis=1, keepdims=True)
    every = np.unique(np.concatenate([c[0] for c in counts]))
    made = langid.Profiles(list(texts), langid.prototypes(langid.bundle(counts, vectors)), every, vectors)
    for g in every[:20]:
        assert np.allclose(made.table[:, g], profile @ langid.bind(np.array([g]), vectors)[0], atol=1e-3)
    for text in ("the garden", "der garten", "le jardin", "house haus maison", "quite other words"):
        known = codes(text)[np.isin(codes(text), every)]
        document = langid.bind(codes(text), vectors).astype(float).sum(axis=0)
        inside = langid.bind(known, vectors).astype(float).sum(axis=0) if len(known) else np.zeros(8192)
        want = profile @ inside / np.linalg.norm(document)
        got = made.cosines(next(bytescan.slices(pa.array([text]))))[0]
        # a document's length is taken from quasi-orthogonality
        assert np.allclose(got, want, rtol=0.1, atol=0.01)
        if len(known):
            assert got.argmax() == want.argmax()


def test_seventy_languages(spark, monkeypatch):
    words = [f"{chr(97 + k % 26)}{chr(97 + k // 26)}x{chr(97 + (k * 7) % 26)}zq{chr(97 + (k * 11) % 26)}" for k in range(70)]
    docs = frame(spark, [f"{w} {w} {w}" for w in words] * 2, lang=[f"l{k:02}" for k in range(70)] * 2)
    profiles = langid.fit_profiles(docs)
    assert [len(p.names) for p in profiles] == [64, 6]
    got = {r.doc_id: r.lang_pred for r in langid.predict_language(docs, profiles).collect()}
    assert got == {k: f"l{k % 70:02}" for k in range(140)}
    monkeypatch.setattr(langid, "BLOCK_LANGUAGES", 7)
    again = {r.doc_id: r.lang_pred for r in langid.predict_language(docs, langid.fit_profiles(docs)).collect()}
    assert again == got


def test_many_items_compile_in_bounded_memory():
    import pickle
    import time

    r = np.random.default_rng(2)
    words = np.array([f"w{k}" for k in range(50_000)])
    texts = pa.array([" ".join(words[r.integers(0, len(words), 200)]) for _ in range(2000)])
    began = time.time()
    tables = decontam.compile_tables(texts, 10)
    assert len(pickle.dumps(tables)) < 15 * texts.nbytes and time.time() - began < 20
