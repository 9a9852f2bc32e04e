import random

import duckdb
import numpy as np
import pyarrow as pa
import pytest

from rankfeed.llm import catalog, decontamination, exact_dedup, html_text, near_dedup, packing, quality, toxicity, warc
from rankfeed.llm.runtime import ship
from tests.conftest import SF

SCHEMA = "doc_id long, text string, digest string"


def shingle_set(text):
    words = (text or "").lower().split()
    return {tuple(words[k : k + 5]) for k in range(max(1, len(words) - 4))} if words else set()


@pytest.fixture(scope="module")
def edge(spark):
    rng = random.Random(5)
    base = [f"w{rng.randrange(400)}" for _ in range(120)]
    rows = [(1, None), (2, ""), (3, "  \n"), (4, "one two"), (5, "One Two"), (6, "one two"), (None, "lone row of text here now"), (7, "x " * 30000)]
    for k in range(10, 40):
        w = list(base)
        for _ in range(k % 7):
            w[rng.randrange(len(w))] = f"z{k}"
        rows.append((k, " ".join(w)))
    rows += [rows[-1]]
    return ship(spark).createDataFrame([(a, b, "clash") for a, b in rows], SCHEMA), rows


def test_near_classes_match_brute_force(edge):
    docs, rows = edge
    out = near_dedup.classes(docs).collect()
    assert len(out) == len(rows)
    root = {a: a for a, _ in rows if a is not None}
    sets = {a: shingle_set(b) for a, b in rows if a is not None}
    changed = True
    while changed:
        changed = False
        for a in sets:
            for b in sets:
                both = len(sets[a] & sets[b])
                if both and 100 * both >= 75 * len(sets[a] | sets[b]) and root[a] != root[b]:
                    root[a] = root[b] = min(root[a], root[b])
                    changed = True
    assert {r.doc_id: (r.n_shingles, r.component_id) for r in out if r.doc_id is not None} == {a: (len(sets[a]), root[a]) for a in sets}
    assert near_dedup.drop_near_duplicates(docs).columns == docs.columns


def test_rows_with_null_or_repeated_ids_stand_for_themselves(spark):
    rng = random.Random(8)
    text = lambda: " ".join(f"v{rng.randrange(5000)}" for _ in range(60))
    a, b, c, d = text(), text(), text(), text()
    rows = [(None, text()) for _ in range(6)] + [(None, a), (None, a + " end"), (5, b), (5, c), (9, c + " end"), (7, d), (7, d), (None, d), (None, None), (None, "")]
    docs = ship(spark).createDataFrame([(k, t, "x") for k, t in rows], SCHEMA)
    out = near_dedup.classes(docs).collect()
    assert len(out) == len(rows) and sum(r.kept for r in out) == 12
    assert [r.component_id for r in out if r.doc_id == 9] == [5]
    assert sorted(r.component_id or 0 for r in out if r.doc_id is None) == [0] * 10 + [7]
    kept = [(r.doc_id, r.text) for r in near_dedup.drop_near_duplicates(docs).collect()]
    assert len(kept) == 12 and set(rows[:6]) <= set(kept) and sum(k is None and (t or "").startswith(a) for k, t in kept) == 1
    assert {(5, b), (5, c), (7, d), (None, None), (None, "")} <= set(kept)


def test_exact_dedup_edges(edge):
    docs, rows = edge
    out = exact_dedup.assign(docs).collect()
    assert len(out) == len(rows)
    assert {r.keep_id for r in out if r.doc_id in (1, 2)} == {2}
    assert {r.keep_id for r in out if r.doc_id in (4, 5, 6)} == {6}
    kept = exact_dedup.drop_duplicates(docs)
    assert kept.columns == docs.columns and kept.count() == len({(b or "").lower() for _, b in rows})


def test_empty_tables(spark):
    none = ship(spark).createDataFrame([], SCHEMA)
    assert exact_dedup.assign(none).count() == 0
    assert near_dedup.classes(none).count() == 0


def test_plan_places_every_piece():
    rng = np.random.default_rng(1)
    lengths = rng.integers(1, 2047, 5000)
    values, counts = np.unique(lengths, return_counts=True)
    plan = packing.best_plan(dict(zip(values.tolist(), counts.tolist(), strict=True)), 2048)
    assert plan.sequences <= 1.02 * -(-int(lengths.sum()) // 2048)


def test_decontamination_finds_items_only():
    item = "what is the tall grey tower beside the old river bridge called? it is called the lantern of the seven northern winds"
    index = decontamination.Index([(7, item), (8, None or "")])
    filler = " ".join(f"word{k}" for k in range(300))
    assert index.hits(pa.array([f"{filler} {item.upper()} {filler}", filler, "", item.split("?")[0]]), 0.5, 0.6) == [[7], [], [], []]


def test_decontamination_finds_short_sides_and_items():
    ask = "which city on the banks of the long grey river has the oldest iron tower of all?"
    short = "what is it? the lantern of the seven northern winds above the harbour"
    index = decontamination.Index([(1, f"{ask} Lutetia"), (2, "seven amber herons"), (3, short), (4, "obsidian"), (5, f"{ask} the old Lutetia")])
    filler = " ".join(f"word{k}" for k in range(300))
    texts = [f"{filler} {ask} Lutetia. {filler}", f"{filler} {ask} Massalia {filler}", f"{filler} Seven amber herons, {filler}", "the seven amber herons", "herons amber seven", f"{filler} {short}", f"{filler} obsidian", f"{ask} the old lutetia"]
    assert index.hits(pa.array(texts), 0.5, 0.6) == [[1], [], [2], [2], [], [3], [4], [1, 5]]


def test_decontamination_is_the_same_however_items_are_dealt(spark):
    rng = np.random.default_rng(2)
    say = lambda n: " ".join(f"w{int(x)}" for x in rng.zipf(1.4, n) % 300)
    items = [(k, say(int(rng.integers(6, 140)))) for k in range(60)] + [(7, say(30)), (None, say(9)), (61, None), (62, "")]
    texts = [f"{say(60)} {items[k][1]} {say(40)}" for k in range(0, 60, 3)] + [say(200) for _ in range(20)] + [None, "", "w1 " * 4000]
    docs = ship(spark).createDataFrame([(k, t, "x") for k, t in enumerate(texts)], "doc_id long, text string, item_ids string")
    benchmark = spark.createDataFrame(items, "item_id long, text string")
    found = [{r.doc_id: r.found for r in decontamination.matched(docs, benchmark, name="found", most=m).collect()} for m in (1000, 9)]
    assert found[0] == found[1] and all(3 * k in found[0][k] for k in range(20)) and found[0][40] == []
    assert decontamination.clean(docs, benchmark).columns == docs.columns
    assert decontamination.clean(docs.limit(0), benchmark).count() == 0 and decontamination.clean(docs, benchmark.limit(0)).count() == len(texts)


def test_retrieval_equals_scoring_everything():
    """Bounds prune nothing that reaches the threshold: BM25 of all passages against all segments, written out."""
    rng = np.random.default_rng(8)
    say = lambda n: [f"w{int(x)}" for x in rng.zipf(1.5, n) % 200]
    items = [(k, " ".join(say(int(rng.integers(5, 120))))) for k in range(80)]
    index = decontamination.Index(items)
    segments = [(k, s) for k, (_, text) in enumerate(items) for s in decontamination.segments_of(decontamination.words_of(text))]
    count, mean = len(segments), sum(len(s) for _, s in segments) / len(segments)
    df = {w: sum(w in s for _, s in segments) for _, s in segments for w in s}
    weight = [{w: np.log(1 + (count - df[w] + 0.5) / (df[w] + 0.5)) * s.count(w) * 2.2 / (s.count(w) + 1.2 * (0.25 + 0.75 * len(s) / mean)) for w in s} for _, s in segments]
    own = [sum(x[w] for w in s) for x, (_, s) in zip(weight, segments, strict=True)]
    for _ in range(60):
        words = say(90) + items[int(rng.integers(80))][1].split()[: int(rng.integers(1, 60))] + say(70)
        want = {k for at in range(0, len(words), 48) for x, o, (k, _) in zip(weight, own, segments, strict=True) if sum(x.get(w, 0) for w in words[at : at + 96]) / o >= 0.5}
        assert index.search(np.array([index.terms.get(w, 0) for w in words]), 0.5) == want


def test_html_rules():
    page = "<html><body><nav>menu</nav><article><h1>T &amp; U</h1><p>one\n two<p>three<div class='comments'>no</div></article><footer>f</footer></body></html>"
    assert html_text.scan(page)[0] == ["T & U", "one two", "three"]
    assert html_text.scan("")[0] == []


def extracted(spark, pages):
    rows = ship(spark).createDataFrame([(k, url, page) for k, (url, page) in enumerate(pages)], "page_id long, url string, html string")
    out = {r.page_id: r for r in html_text.extract(rows).collect()}
    assert len(out) == len(pages) and all(r.n_chars == len(r.text) for r in out.values())
    return [out[k].text for k in range(len(pages))]


def test_html_copies_and_quoted_paragraphs_stay(spark):
    copy = "<html><body><div>home</div><article><h1>Title</h1><p>text one</p></article></body></html>"
    plain = "<html><body><p>alpha text</p><p>beta text</p></body></html>"
    quoted = [("http://q/", f"<body><article><p>a motto for all</p><p>story {k}</p></article></body>") for k in range(10)]
    beside = [("http://m/", f"<body><main><div>read more here</div><article><p>piece {k}</p></article></main></body>") for k in range(10)]
    got = extracted(spark, [("http://c/", copy)] * 10 + [("http://d/", plain)] * 10 + quoted + beside + [(None, plain), ("http://e/", None)])
    assert got[:10] == ["Title\ntext one"] * 10 and got[10:20] == ["alpha text\nbeta text"] * 10
    assert got[20:30] == [f"a motto for all\nstory {k}" for k in range(10)]
    assert got[30:40] == [f"piece {k}" for k in range(10)] and got[40:] == ["alpha text\nbeta text", ""]


def test_html_rotating_block_of_a_large_host_goes(spark):
    block = lambda k: f"<div>offer of week {k % 20}</div>"
    pages = [("http://big/", f"<body>{block(k)}<p>own story {k}</p></body>") for k in range(200)]
    pages += [("http://big/", f"<body><main>{block(k)}<article><p>tale {k}</p></article>{block(k + 1)}</main></body>") for k in range(200)]
    got = extracted(spark, pages + [("http://big/", f"<body><div>rare words</div><p>last story {k}</p></body>") for k in range(4)])
    assert got[:200] == [f"own story {k}" for k in range(200)] and got[200:400] == [f"tale {k}" for k in range(200)]
    assert got[400:] == [f"rare words\nlast story {k}" for k in range(4)]


def test_warc_round_trip(spark):
    big = "ü" * 600
    rows = [(1, "http://a/", big), (2, None, big), (3, "http://b/\r\n", None), (4, "http://a/", "small"), (5, "x", "small")]
    out = {r.page_id: r for r in warc.report(ship(spark).createDataFrame(rows, "page_id long, url string, html string")).collect()}
    assert (out[1].record_type, out[1].refers_to, out[1].payload_bytes) == ("revisit", 2, 1200)
    assert all(out[k].record_type == "response" and out[k].refers_to is None for k in (2, 3, 4, 5)) and out[3].payload_bytes == 0


def test_chain_uses_earlier_probabilities():
    """The second label follows from the first alone, whose own words the second model has too few rows of."""
    rng = np.random.default_rng(4)
    first = rng.random(900) < 0.4
    rows = [np.unique(np.r_[rng.integers(100, 400, 8), 5 + k % 20 if f else 40 + k % 20]) for k, f in enumerate(first)]
    y = np.column_stack([first, first]).astype(int)
    chain = toxicity.chained(rows, y)
    assert chain.models[1][1].shape == (2,) and chain.models[1][1][1] > 0.5
    assert 0 < chain.thresholds[1] < 1


def test_best_threshold_separates():
    p = np.array([0.9, 0.8, 0.3, 0.2, 0.1])
    assert 0.2 < toxicity.best_threshold(p, np.array([1, 1, 1, 0, 0])) < 0.3
    assert toxicity.best_threshold(p, np.zeros(5, int)) == 0.5


def held_out(name):
    from rankfeed.llm.features import indicators

    rows = duckdb.sql(f"select text, quality, toxic from '/root/testdata/sf0.1/documents.parquet' join '/root/testdata/sf0.1/labels.parquet' using (doc_id) order by doc_id").fetchall()
    ids, bounds = indicators(pa.array([t for t, _, _ in rows]))
    rows_of = [ids[a:b] for a, b in zip(bounds[:-1], bounds[1:], strict=True)]
    test = np.arange(len(rows)) % 4 == 2
    y = np.array([[1 - q, x] for _, q, x in rows])
    return [r for r, t in zip(rows_of, test, strict=True) if not t], [r for r, t in zip(rows_of, test, strict=True) if t], y[~test], y[test]


def test_toxicity_on_held_out_rows():
    from rankfeed.llm.features import flat

    train, test, y, z = held_out("toxic")
    chain, extra = toxicity.chained(train, y), np.zeros((len(test), 0))
    for model in chain.models:
        extra = np.column_stack([extra, toxicity.probability(model, *flat(test), extra)])
    found = extra[:, 1] >= chain.thresholds[1]
    assert found[z[:, 1] == 1].mean() > 0.8 and found[z[:, 1] == 0].mean() < 0.02


def test_quality_on_held_out_rows():
    from rankfeed.llm.features import flat, total

    train, test, y, z = held_out("quality")
    w, b = quality.train(train, 1 - y[:, 0])
    margin, good = total(w, *flat(test)) + b, z[:, 0] == 0
    assert (margin[good][:, None] > margin[~good][None, :]).mean() > 0.97


def test_scored_edges(spark):
    rows = [(1, "idiot text", "x"), (2, None, "y"), (None, "", "z"), (2, "word " * 50000, None), (2, None, "y")]
    docs = ship(spark).createDataFrame(rows, "doc_id long, text string, p_toxic string")
    labels = spark.createDataFrame([(1, 1, 1), (2, None, 0)], "doc_id long, quality int, toxic int")
    kept = toxicity.reject(docs, labels.limit(0))
    assert kept.columns == docs.columns and kept.count() == 5
    assert quality.report(docs.select("doc_id", "text"), labels).count() == 5
    assert quality.report(docs.limit(0).select("doc_id", "text"), labels).count() == 0
    assert toxicity.reject(docs.limit(0), labels).count() == 0


def test_token_counts_equal_tokenizer(spark):
    from tokenizers import Tokenizer, models, pre_tokenizers

    from rankfeed.llm.token_counts import vocabulary

    t = Tokenizer(models.Unigram(vocabulary(catalog.tokenizer_path("piece_bpe_32k.model")), unk_id=0))
    t.pre_tokenizer = pre_tokenizers.Sequence([pre_tokenizers.WhitespaceSplit(), pre_tokenizers.Metaspace()])
    got = {r.doc_id: r.n_tokens for r in catalog.op10_token_counts(spark, SF).collect()}
    texts = duckdb.sql(f"select doc_id, coalesce(text, '') from '{SF}/documents.parquet'").fetchall()
    assert got == {k: len(e.ids) for (k, _), e in zip(texts, t.encode_batch([x for _, x in texts]), strict=True)}


def test_packing_matches_the_tokenizer_and_leaves_no_gaps(spark):
    """Pieces, checksums and cuts against the tokenizer itself; sequences full from 0 on without gaps and within the capacity."""
    import zlib
    from collections import defaultdict

    from tokenizers import Tokenizer

    rng = random.Random(11)
    path, capacity = catalog.tokenizer_path("word_bpe_49k.json"), 64
    say = lambda n: " ".join(rng.choice(["tower", "río", "Grüße", "x1", "\n", "harbour,", "2048"]) for _ in range(n))
    rows = [(k, say(rng.randrange(1, 90))) for k in range(300)] + [(7, "again"), (7, "again"), (None, "no id"), (400, None), (401, ""), (402, say(3000))]
    docs = ship(spark).createDataFrame([(k, t, "clash") for k, t in rows], "doc_id long, text string, piece string")
    out = packing.pack(docs, path, capacity).collect()
    t = Tokenizer.from_file(path)
    want = []
    for k, text in rows:
        ids = [*t.encode(text or "", add_special_tokens=False).ids, 0]
        for n, start in enumerate(range(0, len(ids), capacity)):
            part = ids[start : start + capacity]
            want.append((k, n, start, len(part), zlib.crc32(np.array(part, "<u4").tobytes())))
    key = lambda x: (x[0] is None, x[0] or 0, *x[1:])
    assert sorted([(r.doc_id, r.piece, r.start, r.length, r.ids_crc32) for r in out], key=key) == sorted(want, key=key)
    places = defaultdict(list)
    for r in out:
        places[r.sequence_id].append((r.offset, r.length))
    for of_sequence in places.values():
        end = 0
        for offset, length in sorted(of_sequence):
            assert offset == end
            end += length
        assert end <= capacity
    assert len(places) <= 1.05 * -(-sum(w[3] for w in want) // capacity) + 1
    assert packing.pack(docs.limit(0), path, capacity).count() == 0


def test_pipeline_stages_against_brute_force(spark):
    """Each stage on what the one before kept, on all rows of the smallest tables."""
    import corpus_pipeline
    from rankfeed.llm.runtime import table, written

    docs = table(spark, SF, "documents")
    names = docs.columns
    seen, now = {}, docs
    for name, stage in corpus_pipeline.STAGES:
        now = written(stage(spark, now, SF), name)
        seen[name] = [r.asDict() for r in now.collect()]
        if name != "packing":
            assert now.columns == names
    texts = {name: {r["doc_id"]: r["text"] or "" for r in rows} for name, rows in seen.items() if name != "packing"}
    whole = {r.doc_id: r.text or "" for r in docs.collect()}
    toxic = {k for (k,) in duckdb.sql(f"select doc_id from '{SF}/labels.parquet' where toxic = 1").fetchall()}
    gone = set(whole) - set(texts["toxicity"])
    assert all(texts["toxicity"][k] == whole[k] for k in texts["toxicity"]) and len(gone - toxic) <= 0.05 * len(whole)

    lower = lambda s: "".join(c.lower() if c.isascii() else c for c in s)
    least = {}
    for k, s in texts["toxicity"].items():
        least[lower(s)] = max(k, least.get(lower(s), k))
    assert set(texts["exact_dedup"]) == set(least.values())

    sets = {k: shingle_set(lower(s)) for k, s in texts["exact_dedup"].items()}
    root = {k: k for k in sets}

    def top(k):
        while root[k] != k:
            k = root[k]
        return k

    ids = sorted(sets)
    for x, a in enumerate(ids):
        for b in ids[x + 1 :]:
            both = len(sets[a] & sets[b])
            if both and 100 * both >= 75 * len(sets[a] | sets[b]):
                low, high = sorted((top(a), top(b)))
                root[high] = low
    assert set(texts["minhash_near_dedup"]) == {k for k in ids if top(k) == k}

    items = decontamination.Index([tuple(r) for r in table(spark, SF, "benchmark").select("item_id", "text").collect()])
    left = texts["minhash_near_dedup"]
    hits = dict(zip(left, items.hits(pa.array(list(left.values())), 0.5, 0.6), strict=True))
    verbatim = {k for k in left for text in items_texts() if text and lower(text) in lower(left[k])}
    assert set(texts["decontamination"]) == {k for k in left if not hits[k]} and not verbatim & set(texts["decontamination"])

    assert {r["doc_id"] for r in seen["packing"]} == set(texts["decontamination"])
    assert all(r["offset"] + r["length"] <= 2048 for r in seen["packing"])


def items_texts():
    return [t for (t,) in duckdb.sql(f"select text from '{SF}/benchmark.parquet'").fetchall()]
