"""Each operator against brute force, round trips or held-out accuracy, and on odd tables."""

import functools
import hashlib
import itertools
import random
import re
import zlib

import duckdb
import numpy as np
import pyarrow as pa
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st
from pyspark.sql import functions as F

from narrative_engine.llm import decontamination, html_extraction, jaccard_join, language_id, line_dedup, lm_scoring, packing, quality_rules, registry, token_store, toxicity
from narrative_engine.llm.bytewords import word_hashes
from narrative_engine.llm.components import components, star_components
from narrative_engine.llm.tokens import Encoder, vocabulary_path

ODD = [(1, None), (2, ""), (3, "  \n\t "), (4, "one"), (5, "a b c d e f g h i j k l"), (5, "a b c d e f g h i j k l"), (6, "ab " * 30_000), (None, "no id here at all")]
SOFT = re.compile(r"[^\x20\x09-\x0D]+")


def words(n, seed):
    rng = random.Random(seed)
    return " ".join("".join(rng.choice("abcdefghij") for _ in range(5)) for _ in range(n))


def rows_of(df, *cols):
    return [tuple(r[c] for c in cols) for r in df.collect()]


# --- quality rules


def brute_rules(text):
    w = SOFT.findall(text or "")
    seen = {}
    for i in range(len(w) - 4):
        seen.setdefault(tuple(w[i : i + 5]), []).append(i)
    hit = {i + k for at in seen.values() if len(at) > 1 for i in at for k in range(5)}
    lines = [x for x in (text or "").split("\n") if SOFT.search(x)]
    return len(w), sum(map(len, w)), len(re.findall(r"[#*$%&|<>]", text or "")), len(lines) - len(set(lines)), len(hit)


def test_rules_on_odd_rows(make_docs):
    docs = make_docs([*ODD, (9, "x y z u v x y z u v x y\nq\nq"), (10, "é# ü|　a")])
    want = sorted(map(str, [(i, *brute_rules(t)) for i, t in rows_of(docs, "doc_id", "text")]))
    got = rows_of(quality_rules.ledger(docs), "doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words")
    assert sorted(map(str, got)) == want


def test_rule_policies_and_ablation(make_docs):
    docs = make_docs([(1, "too short"), (2, words(50, 1)), (3, "### $$$ %%% " + words(20, 2))])
    led = quality_rules.ledger(docs)
    assert sorted(r[0] for r in rows_of(quality_rules.passing(led), "doc_id")) == [2]
    report = {(r["policy"], r["version"], r["rule"]): r for r in quality_rules.policy_report(led).collect()}
    assert report["prose", 2, "symbols"]["n_only_by_rule"] == 1 and report["base", 1, "few_words"]["n_rejected"] == 1


# --- decontamination


def brute_hits(text, items):
    word = lambda t: re.findall(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+", "".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in t or ""))
    w, hit, found = word(text), set(), set()
    for k, t in items:
        b = word(t)
        for i in range(max(1, len(b) - 12)) if b else ():
            g = b[i : i + 13]
            for j in range(len(w) - len(g) + 1):
                if w[j : j + len(g)] == g:
                    hit |= set(range(j, j + len(g)))
                    found.add(str(k))
    ids = ",".join(sorted(found))
    return len(w), len(hit), len(found), hashlib.sha256(ids.encode()).hexdigest(), bool(hit) and 20 * len(hit) >= len(w)


@pytest.mark.parametrize("broadcast", [200_000, 0])
def test_decontamination_matches_brute_force(spark, make_docs, monkeypatch, broadcast):
    monkeypatch.setattr(decontamination, "BROADCAST_WINDOWS", broadcast)
    long, short = words(30, 3), "just three WORDS"
    items = [(1, long), (2, short), (30, words(15, 4)), (4, None), (5, "..."), (6, long)]
    texts = [long, "x, " + long.upper() + "!", " ".join(long.split()[:12]), " ".join(long.split()[5:20]), "He said Just-three words. " * 3, "", None, words(60, 5) + " " + words(15, 4), "ÄB " + short]
    docs = make_docs([*enumerate(texts), *ODD])
    bench = spark.createDataFrame(items, "item_id long, text string")
    got = rows_of(decontamination.contamination(docs, bench), "doc_id", "n_words", "n_hit", "n_items", "items_sha256", "contaminated")
    assert sorted(map(str, got)) == sorted(map(str, [(i, *brute_hits(t, items)) for i, t in rows_of(docs, "doc_id", "text")]))
    assert decontamination.contamination(docs, bench.limit(0)).where("contaminated").count() == 0


# --- Jaccard join


def brute_join(rows):
    low = lambda t: "".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in t or "")

    def shingles(t):
        w = SOFT.findall(low(t))
        return {tuple(w[i : i + 4]) for i in range(len(w) - 3)} if len(w) >= 4 else ({tuple(w)} if w else set())

    s = {i: shingles(t) for i, t in rows}
    up = {i: i for i in s}

    def root(x):
        while up[x] != x:
            x = up[x]
        return x

    for a, b in itertools.combinations(sorted(s), 2):
        if s[a] and s[b] and 100 * len(s[a] & s[b]) >= 85 * len(s[a] | s[b]):
            x, y = sorted((root(a), root(b)))
            up[y] = x
    return sorted((i, len(s[i]), root(i)) for i in s)


def test_jaccard_join_matches_brute_force(make_docs):
    rng, rows = random.Random(11), []
    for g in range(25):
        base = words(rng.choice((3, 4, 6, 9, 14, 40, 90, 160)), 100 + g).split()
        for _ in range(rng.choice((1, 2, 6))):
            w = list(base)
            for _ in range(rng.choice((0, 0, 1, 1, 2, 3))):
                w[rng.randrange(len(w))] = rng.choice("xyz") * 3
            if rng.random() < 0.3:
                w.append("tail")
            rows.append((len(rows), " ".join(w) if rng.random() < 0.8 else " ".join(w).upper()))
    rows += [(1000, None), (1001, ""), (1002, " \t"), (1003, "a"), (1004, "A"), (1005, "ab " * 20_000)]
    assert sorted(rows_of(jaccard_join.joined(make_docs(rows)), "doc_id", "n_shingles", "component_id")) == brute_join(rows)


def brute_rows(rows):
    """(doc_id, size, component) of each row: rows of one doc_id are one document, rows without one are documents of their own."""
    def shingles(t):
        w = SOFT.findall("".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in t or ""))
        return {tuple(w[i : i + 4]) for i in range(len(w) - 3)} if len(w) >= 4 else ({tuple(w)} if w else set())

    s, up = [shingles(t) for _, t in rows], list(range(len(rows)))

    def root(x):
        while up[x] != x:
            x = up[x]
        return x

    for a, b in itertools.combinations(range(len(rows)), 2):
        if s[a] and s[b] and (rows[a][0] is not None and rows[a][0] == rows[b][0] or 100 * len(s[a] & s[b]) >= 85 * len(s[a] | s[b])):
            up[root(a)] = root(b)
    least = {}
    for k, (i, _) in enumerate(rows):
        if i is not None and s[k]:
            least[root(k)] = min(i, least.get(root(k), i))
    return sorted(map(str, [(i, len(s[k]), i if not s[k] else least.get(root(k))) for k, (i, _) in enumerate(rows)]))


def odd_groups():
    a, b, c, d = (words(40, 900 + k).split() for k in range(4))
    near = lambda w, k: " ".join([*w[:k], "edit", *w[k + 1 :]])
    a, b, c, d = map(" ".join, (a, b, c, d))
    return [
        (7, a), (7, b), (3, near(a.split(), 0)), (9, near(b.split(), 0)), (None, a), (None, c), (None, c), (None, near(c.split(), 39)), (None, None), (12, None), (12, d), (11, ""), (4, d),
        (5, "x y z"), (5, "x y z"), (6, "X y z"), (20, words(30, 950)), (20, words(30, 951)), (21, words(30, 951)), (None, words(30, 952)), (22, words(30, 952)),
    ]


def test_jaccard_join_with_null_and_repeated_ids(make_docs):
    rows = odd_groups()
    got = rows_of(jaccard_join.joined(make_docs(rows)), "doc_id", "n_shingles", "component_id")
    assert sorted(map(str, got)) == brute_rows(rows)
    kept = rows_of(jaccard_join.representatives(make_docs(rows)), "doc_id", "text")
    sets = lambda t: brute_rows([(1, t)])
    assert len([1 for _, t in rows if not SOFT.findall(t or "")]) == len([1 for _, t in kept if not SOFT.findall(t or "")])
    full = [(i, t) for i, t in kept if SOFT.findall(t or "")]
    # one row of each group of linked texts, none of the others lost: texts of one doc_id that aren't alike both stay
    assert len(full) == 8 and sets and {i for i, _ in full} == {3, 7, 4, 5, 20, 22, None} and sum(i == 20 for i, _ in full) == 2


def test_jaccard_rounds_and_fallback_agree(make_docs, monkeypatch):
    rng, rows, base = random.Random(5), [], words(60, 9).split()
    for i in range(60):  # a chain of near copies, so that one pivot can't reach all
        if i % 2:
            base[rng.randrange(60)] = f"w{i}"
        rows.append((i, " ".join(base)))
    want = brute_join(rows)
    for rounds in (1, 4):
        monkeypatch.setattr(jaccard_join.links, "__defaults__", (rounds,))
        assert sorted(rows_of(jaccard_join.joined(make_docs(rows)), "doc_id", "n_shingles", "component_id")) == want


def test_rare_pairs_lose_no_link(spark):
    rng, sets = random.Random(21), {}
    for _ in range(20):  # groups of near copies of different sizes, some with many edits of their own
        base = rng.sample(range(10_000), rng.choice((1, 2, 6, 7, 13, 50, 147)))
        for _ in range(12):
            kept = [v for v in base if rng.random() < rng.choice((0.9, 0.97, 1.0))] or base[:1]
            sets[len(sets)] = set(kept) | set(rng.sample(range(10_000), rng.randrange(1 + len(base) // 7)))
    items = spark.createDataFrame([(i, np.array(sorted(s), dtype=np.uint64).tobytes()) for i, s in sets.items()], "id long, items binary")
    left = spark.createDataFrame([(i, i) for i in sets], "x long, c long")
    cells = jaccard_join.rare_cells(left, items, 85, 100)
    got = {tuple(sorted(r)) for r in rows_of(jaccard_join.rare_pairs(cells, 85, 100), "p", "x")}
    want = {(a, b) for a, b in itertools.combinations(sets, 2) if 100 * len(sets[a] & sets[b]) >= 85 * len(sets[a] | sets[b])}
    assert len(want) > 100 and want <= got and len(got) < len(sets) ** 2 // 8


def test_star_and_union_components_agree(spark):
    rng = random.Random(3)
    edges = spark.createDataFrame([(rng.randrange(300), rng.randrange(300)) for _ in range(220)], "a long, b long").where("a <> b")
    assert sorted(rows_of(components(edges), "node", "root")) == sorted(rows_of(star_components(edges), "node", "root"))


# --- line dedup


def test_patience_alignment():
    assert line_dedup.patience({(0, 5), (1, 6), (2, 7)}) == [(0, 5), (1, 6), (2, 7)]
    assert line_dedup.rising([(0, 3), (1, 1), (2, 2)]) == [(1, 1), (2, 2)]
    assert sorted(line_dedup.common_blocks({(0, 9), (1, 2), (2, 3)}, [30, 5, 5], 20)) == [0]


def test_line_dedup_takes_shared_passages_from_later_documents(make_docs):
    passage, own = words(60, 1), [words(40, 50 + i) for i in range(5)]
    many = "\n".join(words(9, 200 + k) for k in range(7))  # a passage of short lines
    rows = [(1, f"{own[0]}\n{passage}\n{many}"), (2, f"{passage}\n{own[1]}"), (3, f"{own[2]}\n  {passage}  \nhello there"), (4, f"{own[3]}\n{many}\n{own[4]}"), (5, "hello there\n" + words(30, 77)), *[(i + 100 if i else None, t) for i, t in ODD]]
    got = dict(rows_of(line_dedup.deduped(make_docs(rows)), "doc_id", "text"))
    assert got[1] == rows[0][1] and got[2] == own[1] and got[3] == f"{own[2]}\nhello there" and got[4] == f"{own[3]}\n{own[4]}" and got[5] == rows[4][1]
    assert got[101] is None and got[102] == "" and got[105] == ODD[4][1]


def test_line_dedup_looks_past_an_edited_first_copy(make_docs):
    lines = [words(6, 300 + k) for k in range(16)]
    edited = [f"{words(6, 400 + k)}" if k % 4 == 0 else x for k, x in enumerate(lines)]
    rows = [(1, "\n".join(edited)), (2, "\n".join(lines)), (3, "\n".join([words(30, 90), *lines])), (4, "\n".join([*lines[5:9], words(30, 91)]))]
    got = dict(rows_of(line_dedup.deduped(make_docs(rows)), "doc_id", "text"))
    assert (got[1], got[2]) == (rows[0][1], rows[1][1]) and got[3] == words(30, 90) and got[4] == words(30, 91)


def test_line_dedup_takes_every_run_an_earlier_document_holds(make_docs):
    rng, docs = random.Random(8), []
    pool = [words(rng.choice((1, 3, 6, 9, 25)), 500 + k) for k in range(12)]
    passages = [[rng.choice(pool) for _ in range(rng.randrange(3, 12))] for _ in range(6)]
    for _ in range(40):
        own = [x for p in rng.sample(passages, 3) for x in p if rng.random() < 0.93]
        docs.append(own)
    runs = [{tuple(d[i:j]) for i in range(len(d)) for j in range(i + 1, len(d) + 1)} for d in docs]
    got = dict(rows_of(line_dedup.deduped(make_docs([(i, "\n".join(d)) for i, d in enumerate(docs)])), "doc_id", "text"))
    for k, d in enumerate(docs):
        gone = set()
        for i in range(len(d)):
            for j in range(i + 1, len(d) + 1):
                if sum(len(x.split()) for x in d[i:j]) >= 20 and any(tuple(d[i:j]) in r for r in runs[:k]):
                    gone |= set(range(i, j))
        assert got[k] == "\n".join(x for i, x in enumerate(d) if i not in gone)


def test_common_blocks_keep_what_an_alignment_breaks_up():
    assert sorted(line_dedup.common_blocks({(0, 0), (0, 9), (1, 10), (2, 11)}, [8, 8, 8], 20)) == [0, 1, 2]


def test_line_dedup_on_whole_tables_against_brute_force(spark):
    """A line goes if and only if it lies in a run of 20 words or more that an earlier document holds."""
    docs = spark.read.parquet("/root/testdata/sf0.001/documents.parquet")
    rows = sorted((r["doc_id"], r["text"]) for r in docs.select("doc_id", "text").collect())
    lines = {i: [(k, x.strip(" \t\n\x0b\x0c\r")) for k, x in enumerate((t or "").split("\n"))] for i, t in rows}
    full = {i: [(k, x) for k, x in v if x] for i, v in lines.items()}
    places, want = {}, {}
    for i, t in rows:
        mine, gone = full[i], set()
        for a, (_, x) in enumerate(mine):
            for j, b in places.get(x, ()):
                n = 0
                while a + n < len(mine) and b + n < len(full[j]) and mine[a + n][1] == full[j][b + n][1]:
                    n += 1
                if sum(len(SOFT.findall(y)) for _, y in mine[a : a + n]) >= 20:
                    gone |= {k for k, _ in mine[a : a + n]}
        want[i] = t if not gone else "\n".join(x for k, x in enumerate(t.split("\n")) if k not in gone)
        for a, (_, x) in enumerate(mine):
            places.setdefault(x, []).append((i, a))
    got = dict(rows_of(line_dedup.op1_line_dedup(spark, "/root/testdata/sf0.001"), "doc_id", "text"))
    assert got == want and any(want[i] != t for i, t in rows)


def test_line_dedup_keeps_clashing_columns(make_docs):
    docs = make_docs([(1, words(30, 1)), (2, words(30, 1))]).withColumn("gone", F.lit(1)).withColumn("_id", F.lit(2)).withColumn("partners", F.lit("x"))
    out = line_dedup.deduped(docs)
    assert out.columns == [*docs.columns, "_dedup"] and sorted(rows_of(out, "doc_id", "text")) == [(1, words(30, 1)), (2, "")]


# --- tokens


@pytest.fixture(scope="module")
def tokenizer():
    from tokenizers import Tokenizer

    return Tokenizer.from_file(vocabulary_path())


@functools.lru_cache(maxsize=1)
def whole_encoder():
    return Encoder(vocabulary_path())


TEXTS = ["Hello, World! it's 12.5% <|endoftext|> x", "Ünïcödé ß ſ İ ǅ", "á ẹ́  x y\x1cz\x85w", "", None, "don't we'll they're 3rd", "日本語 text 🙂🙂 ok", "tab\tnew\nline\r\n", "x" * 3000, "O̊ ﬁ", "''s 's"]


def test_cached_encoding_is_the_librarys(tokenizer):
    odd = ["a \x01 b\x01c \x01\x01 d", "(\"Hello,\") --x-- _a_ {b}=c+d @e", "ÀÉ straße ÿx ciónue%%% Éeu, 'quoted' <|oops|> <|endoftext", "é e\u0301 x\u00a0y\u2003z\u3000", "ab" * 200_000, "." * 9000]
    texts = [*TEXTS, *odd, " ".join(TEXTS[:4])]
    own = Encoder(vocabulary_path())
    for _ in range(2):
        got = [x.tolist() for x in own.encode(pa.array(texts))]
        assert got == [tokenizer.encode(t or "", add_special_tokens=False).ids for t in texts]
    assert all(len(w) <= 64 for w in own.words) and list(own.encode(pa.array([], pa.string()))) == []


@given(st.lists(st.text(alphabet="abZé ÀÿǅıΣς'’.,-_<|>12\n\t\x01\x1c\x85\u00a0\u0301日🙂", max_size=40), max_size=6))
@settings(max_examples=200, deadline=None)
def test_any_text_gets_the_librarys_ids(texts):
    own, plain = whole_encoder(), whole_encoder().whole
    assert [x.tolist() for x in own.encode(pa.array(texts, pa.string()))] == [plain.encode(t, add_special_tokens=False).ids for t in texts]


def test_a_full_table_takes_no_more(monkeypatch):
    monkeypatch.setattr("narrative_engine.llm.tokens.TABLE_BYTES", 2_000)
    own = Encoder(vocabulary_path())
    texts = [" ".join(words(300, i).split()) for i in range(5)]
    assert [x.tolist() for x in own.encode(pa.array(texts))] == [own.whole.encode(t, add_special_tokens=False).ids for t in texts]
    assert own.held < 2_500


@pytest.mark.parametrize("kind", token_store.KINDS)
@pytest.mark.parametrize("n", [0, 1, 7, 4096, 20_001])
def test_chunk_round_trip(kind, n):
    ids = np.random.default_rng(n).integers(0, 1 << 32, n, dtype=np.uint32).astype("<u4")
    raw = token_store.encode_chunk(ids, kind, block_ids=4096)
    assert (token_store.decode_chunk(raw) == ids).all()
    if n > 4096:
        assert (token_store.decode_chunk(raw, block=1) == ids[4096:8192]).all()


def test_token_store(make_docs, tokenizer):
    rows = [(i * 7 % 11, t) for i, t in enumerate(TEXTS)]
    got = sorted(rows_of(token_store.read_documents(token_store.staged(token_store.chunks(make_docs(rows)))), "doc_id", "start", "n_tokens", "ids_crc32"))
    at, want = 0, []
    for i, t in sorted(rows):
        x = np.array([*tokenizer.encode(t or "", add_special_tokens=False).ids, 2], "<u4")
        want.append((i, at, len(x), zlib.crc32(x.tobytes())))
        at += len(x)
    assert got == want
    assert token_store.read_documents(token_store.chunks(make_docs(rows).limit(0))).count() == 0


def test_packing(make_docs, tokenizer):
    rng = random.Random(2)
    rows = [*enumerate(TEXTS), *[(100 + i, words(rng.choice((5, 80, 300, 700, 2500)), i)) for i in range(60)], (200, TEXTS[0]), (200, TEXTS[0])]
    out = packing.packed(make_docs(rows)).collect()
    want = []
    for i, t in rows:
        x = np.array([*tokenizer.encode(t or "", add_special_tokens=False).ids, 1], "<u4")
        want += [(i, k, a, len(x[a : a + 4096]), zlib.crc32(x[a : a + 4096].tobytes())) for k, a in enumerate(range(0, len(x), 4096))]
    assert sorted(tuple(r)[:5] for r in out) == sorted(want)
    bins = {}
    for r in out:
        bins.setdefault(r["sequence_id"], []).append((r["offset"], r["length"]))
    for v in bins.values():
        v.sort()
        assert all(o == sum(n for _, n in v[:k]) for k, (o, _) in enumerate(v)) and sum(n for _, n in v) <= 4096
    plain = []  # best fit, largest first
    for n in sorted((w[3] for w in want), reverse=True):
        k = min((k for k in range(len(plain)) if plain[k] >= n), key=lambda k: plain[k], default=None)
        if k is None:
            plain.append(4096)
            k = len(plain) - 1
        plain[k] -= n
    assert -(-sum(w[3] for w in want) // 4096) <= len(bins) <= len(plain)


def test_bin_completion_is_optimal_on_small_cases():
    def best(sizes, cap):
        todo, least = sorted(sizes, reverse=True), [len(sizes)]

        def go(k, bins):
            if len(bins) >= least[0]:
                return
            if k == len(todo):
                least[0] = len(bins)
                return
            for i in range(len(bins)):
                if bins[i] + todo[k] <= cap:
                    go(k + 1, [*bins[:i], bins[i] + todo[k], *bins[i + 1 :]])
            go(k + 1, [*bins, todo[k]])

        go(0, [])
        return least[0]

    rng = random.Random(4)
    for _ in range(60):
        sizes = [rng.randint(1, 20) for _ in range(rng.randint(1, 9))]
        used = sum(f.times for f in packing.pack(np.bincount(sizes, minlength=21), 20))
        assert best(sizes, 20) <= used <= best(sizes, 20) + 1


def test_packing_searches_across_sequences():
    sizes = [2448, 1836, 1836, 1428, 1428, 1224, 1020, 612, 408]
    for n in (1, 10, 1000):
        counts = n * np.bincount(sizes, minlength=4097)
        found = packing.pack(counts)
        used = np.zeros(4097, dtype=int)
        for f in found:
            assert sum(x * k for x, k in f.parts) <= 4096
            for x, k in f.parts:
                used[x] += f.times * k
        assert sum(f.times for f in found) == 3 * n and (used == counts).all()


def test_packing_reaches_the_optimum_of_small_cases():
    def fits(todo, rooms):
        if not todo:
            return True
        return any(todo[0] <= r and fits(todo[1:], (*rooms[:i], r - todo[0], *rooms[i + 1 :])) for i, r in enumerate(rooms) if r not in rooms[:i])

    rng = random.Random(6)
    for _ in range(150):
        sizes = sorted((rng.randint(2, 14) for _ in range(rng.randint(4, 11))), reverse=True)
        counts = np.bincount(sizes, minlength=21)
        least = next(k for k in range(1, 12) if fits(sizes, (20,) * k))
        for found in (packing.pack(counts, 20), packing.best_fit(counts, 20)):
            assert (sum(f.times * np.bincount(np.repeat(*zip(*f.parts)), minlength=21) for f in found) == counts).all()
            assert all(sum(x * k for x, k in f.parts) <= 20 for f in found)
        assert sum(f.times for f in packing.pack(counts, 20)) == least


# --- models


def test_toxicity_on_the_held_out_fold(spark):
    sf = "/root/testdata/sf0.01"
    rows = toxicity.op4_toxicity(spark, sf).join(spark.read.parquet(f"{sf}/labels.parquet"), "doc_id").where("held_out")
    n, right, caught, toxic = rows.agg(F.count("*"), F.sum((F.col("predicted") == F.col("toxic")).cast("int")), F.sum(F.col("predicted") * F.col("toxic")), F.sum("toxic")).first()
    assert right >= 0.9 * n and caught >= 0.5 * toxic


def test_toxicity_is_a_noisy_or_of_its_sentences(spark, make_docs):
    docs = make_docs([*[(i, f"{words(12, i)}. You idiot {words(5, i)}. {words(9, i + 500)}.") for i in range(60)], *[(i, f"{words(12, i)}. {words(9, i + 900)}.") for i in range(60, 160)]])
    model = toxicity.train(docs, spark.createDataFrame([(i, int(i < 60)) for i in range(160)], "doc_id long, toxic int"))
    parts = [f"{words(7, 8000 + k)}{' idiot' * (k % 3)} {words(2, 8100 + k)}." for k in range(12)]
    one = dict(rows_of(toxicity.scored(make_docs(enumerate(parts)), model), "doc_id", "score"))
    whole = dict(rows_of(toxicity.scored(make_docs([(k, " ".join(parts[: k + 1])) for k in range(12)]), model), "doc_id", "score"))
    for k in range(12):
        assert abs(whole[k] - (1 - np.prod([1 - one[j] for j in range(k + 1)]))) < 1e-9


def test_language_matches_exact_sets(spark):
    """Every document of the tables judged with plain sets of n-grams in place of the filters."""
    def grams(text):
        x, out = bytes(b if b >= 128 else b | 32 if chr(b).isalpha() else 32 for b in text.encode()), []
        x = b" " + re.sub(rb" +", b" ", x) + b"  "
        return [x[i : i + 4] for i in range(len(x) - 3) if x[i + 1] != 32 or x[i + 2] != 32]

    rows = spark.read.parquet("/root/testdata/sf0.001/documents.parquet").select("doc_id", "text", "lang").collect()
    seen = {}
    for r in rows:
        if r["lang"] is not None and r["text"] is not None and zlib.crc32(str(r["doc_id"]).encode()) % 4 != 2:
            for g in grams(r["text"]):
                seen.setdefault(r["lang"], {}).setdefault(g, 0)
                seen[r["lang"]][g] += 1
    rate = {k: {g: n / sum(v.values()) for g, n in v.items() if n >= language_id.LEAST} for k, v in seen.items()}
    most = {}
    for v in rate.values():
        for g, x in v.items():
            most[g] = max(most.get(g, 0), x)
    held = {k: {g for g, x in v.items() if x >= language_id.SHARE * most[g]} for k, v in rate.items()}
    got = {r["doc_id"]: r for r in language_id.op7_language_id(spark, "/root/testdata/sf0.001").collect()}
    for r in rows:
        mine = grams(r["text"] or "")
        share = {k: sum(g in v for g in mine) / max(1, len(mine)) for k, v in held.items()}
        best = max(sorted(share), key=share.get)
        assert got[r["doc_id"]]["lang_pred"] == best and abs(got[r["doc_id"]]["score"] - share[best]) < 0.02, (r["doc_id"], share, got[r["doc_id"]])


def test_toxicity_finds_the_sentence_and_stands_odd_rows(spark, make_docs):
    docs = make_docs([*[(i, f"{words(12, i)}. You idiot {words(5, i)}. {words(9, i + 500)}.") for i in range(60)], *[(i, f"{words(12, i)}. {words(9, i + 900)}.") for i in range(60, 160)]])
    labels = spark.createDataFrame([(i, int(i < 60)) for i in range(160)], "doc_id long, toxic int")
    model = toxicity.train(docs, labels)
    text = f"{words(10, 7000)}. Some idiot here. {words(10, 7001)}."
    row = toxicity.scored(make_docs([(1, text)]), model).first()
    assert row["predicted"] == 1 and ["idiot" in text.encode()[s["first"] : s["last"]].decode() for s in row["offending"]] == [True]
    assert toxicity.scored(make_docs(ODD), model).where("predicted = 0 AND score BETWEEN 0 AND 1").count() == len(ODD)
    assert toxicity.train(docs, labels.limit(0)) is toxicity.EMPTY


def test_language_on_the_held_out_fold(spark):
    sf = "/root/testdata/sf0.01"
    rows = language_id.op7_language_id(spark, sf).join(spark.read.parquet(f"{sf}/documents.parquet").select("doc_id", "lang"), "doc_id").where("held_out")
    n, right = rows.agg(F.count("*"), F.sum((F.col("lang") == F.col("lang_pred")).cast("int"))).first()
    assert right >= 0.97 * n


def test_language_filters(make_docs):
    a, b = np.arange(1000, 3000, dtype=np.uint32), np.arange(2500, 4000, dtype=np.uint32)
    f = language_id.build([("y", b), ("x", a)])
    assert f.languages == ("x", "y") and (f.counts(a)[0], f.counts(b)[1]) == (2000, 1500)
    got = dict(rows_of(language_id.identified(make_docs([(1, None), (2, "123 !?"), (3, "a")]), f), "doc_id", "lang_pred"))
    assert got[1] == got[2] == "und" and got[3] in ("x", "y")
    assert language_id.train(make_docs([(1, None)])).languages == ()


def test_every_language_is_learnt(spark):
    rows = [(3 * k + j, " ".join([words(4, k)] * 3), f"l{k:03}") for k in range(520) for j in range(3)]
    found = language_id.train(spark.createDataFrame(rows, "doc_id long, text string, lang string"))
    assert len(found.languages) > 512


def test_lm_scores_match_brute_force(spark, make_docs):
    rows = [(i, words(20, i % 7) + " " + words(3, i)) for i in range(30)] + [(50, None), (51, "..")]
    docs, labels = make_docs(rows), spark.createDataFrame([(i, int(i % 2)) for i in range(30)], "doc_id long, quality int")
    got = {r["doc_id"]: r for r in lm_scoring.scored(docs, lm_scoring.train(lm_scoring.flagged(docs, labels))).collect()}
    token = lambda t: re.findall(r"[a-z0-9]+", t or "")
    uni, hist, big = [{}, {}], [{}, {}], [{}, {}]
    for i, t in rows:
        k = 0 if i < 30 and i % 2 else 1
        w = token(t)
        hist[k]["^"] = hist[k].get("^", 0) + 1
        for p, x in zip(["^", *w], w):
            uni[k][x] = uni[k].get(x, 0) + 1
            big[k][p, x] = big[k].get((p, x), 0) + 1
    vocab = set(uni[0]) | set(uni[1])
    def loss(k, w):
        n, v = sum(uni[k].values()), len(vocab) + 1
        out = 0.0
        for p, x in zip(["^", *w], w):
            q = (uni[k].get(x, 0) + 1) / (n + v)
            seen = big[k].get((p, x), 0) if big[0].get((p, x), 0) + big[1].get((p, x), 0) >= lm_scoring.LEAST else 0
            h = hist[k]["^"] if p == "^" else uni[k].get(p, 0)
            out -= np.log((seen + lm_scoring.WEIGHT * q) / (h + lm_scoring.WEIGHT))
        return out / len(w)
    for i, t in rows[:30]:
        assert abs(got[i]["score"] - (loss(0, token(t)) - loss(1, token(t)))) < 1e-9
    assert got[50]["score"] == got[51]["score"] == 0.0 and got[51]["n_tokens"] == 0
    assert len(word_hashes(np.frombuffer(b"a b, a", dtype=np.uint8))) == 3


def test_lm_counts_have_no_cap(spark, make_docs):
    text = lambda i: " ".join(f"w{i * 400 + k // 2 if k % 2 else i}" for k in range(800))
    rows = [(i, text(i % 50)) for i in range(100)]  # 20,000 words, each in two documents
    labels = spark.createDataFrame([(i, 1) for i in range(50)], "doc_id long, quality int")
    models = lm_scoring.train(lm_scoring.flagged(make_docs(rows), labels))
    assert models.words == len({w for _, t in rows for w in t.split()}) > 1 << 14
    uni, hist, n = {}, 0, 0
    for i, t in rows[:50]:
        for w in t.split():
            uni[w] = uni.get(w, 0) + 1
            n += 1
    w, both = text(49).split(), {}
    for _, t in rows[:50]:
        for p in itertools.pairwise(["^", *t.split()]):
            both[p] = both.get(p, 0) + 1
    want = 0.0
    for p, x in itertools.pairwise(["^", *w]):
        q, hist = (uni[x] + 1) / (n + models.words + 1), 50 if p == "^" else uni[p]
        want -= np.log((both[p, x] + lm_scoring.WEIGHT * q) / (hist + lm_scoring.WEIGHT))
    got = {r["doc_id"]: r for r in lm_scoring.scored(make_docs(rows), models).collect()}
    assert abs(got[49]["loss_target"] - want / len(w)) < 1e-9 and abs(got[49]["score"]) < 1e-9


# --- HTML


PAGE = """<!DOCTYPE html><html><head><title>T</title><style>p{{x}}</style><script>var a="</p>";</script></head><body><header><h2>Site</h2></header><nav><ul><li><a href=x>Home</a></li></ul></nav>
<div class="cookie-notice">We use cookies</div><div class="ad">Buy</div><aside class=sidebar><p>More</p></aside>{open}<h1>Title &amp; more</h1><p>First  <b>bold</b>
 text&nbsp;here.<p>Second &lt;tag&gt;<br>line.</p><ul><li>one<li>two</ul><form><input><button>Go</button></form>{close}<section id="comments"><p>Nice!</p></section><footer>&copy; x</footer></body></html>"""
MAIN = "Title & more\nFirst bold text here.\nSecond <tag> line.\none\ntwo"


@pytest.mark.parametrize("open_,close", [("<article>", "</article>"), ("<main>", "</main>"), ('<div class="content">', "</div>")])
def test_main_text(open_, close):
    assert html_extraction.main_text(PAGE.format(open=open_, close=close)) == MAIN


def test_article_text_with_telling_names_stays():
    inside = '<figure><figcaption>Caption</figcaption></figure><div class="legal-text">Law</div><div class="long-form">Long</div><p class="alert">Beware</p><div class="share">Tweet</div><div class="ad">Buy</div>'
    assert html_extraction.main_text(f"<body><article><h1>T</h1>{inside}<p>End</p></article></body>") == "T\nCaption\nLaw\nLong\nBeware\nEnd"
    story = words(40, 3)
    assert html_extraction.main_text(f'<body><article><p>Teaser</p></article><div id="story"><p>{story}</p></div></body>') == story
    long = "<p>" + "<b>" * 3000 + "deep" + "</b>" * 3000 + "</p>" + "<p>" + "x" * (1 << 20) + "</p>"
    assert html_extraction.main_text(f"<main>{long}</main>") == "deep\n" + "x" * (1 << 20)


def test_extraction_of_whole_tables_against_a_plain_parser(spark):
    """The pages of the tables have one article each; an HTML parser of the standard library reads it."""
    from html.parser import HTMLParser

    class Plain(HTMLParser):
        def __init__(self):
            super().__init__(convert_charrefs=True)
            self.inside, self.blocks, self.now = 0, [], []

        def close_block(self):
            text = " ".join("".join(self.now).split())
            self.now = []
            if text:
                self.blocks.append(text)

        def handle_starttag(self, tag, attrs):
            if self.inside and tag == "br":
                self.now.append(" ")
            elif self.inside and tag not in ("b", "i", "em", "strong", "a", "span", "code"):
                self.close_block()
            self.inside += tag == "article"

        def handle_endtag(self, tag):
            if self.inside and tag not in ("b", "i", "em", "strong", "a", "span", "code", "br"):
                self.close_block()
            self.inside -= tag == "article"

        def handle_data(self, data):
            if self.inside:
                self.now.append(data)

    sf = "/root/testdata/sf0.01"
    got = dict(rows_of(html_extraction.op2_html_extraction(spark, sf), "page_id", "text"))
    pages = spark.read.parquet(f"{sf}/pages.parquet").select("page_id", "html").collect()
    assert len(got) == len(pages)
    for r in pages:
        p = Plain()
        p.feed(r["html"] or "")
        p.close()
        p.close_block()
        assert got[r["page_id"]] == "\n".join(p.blocks), r["page_id"]


def test_wrapper_inference(spark):
    page = lambda k: f"<html><body><div class=top>Example site</div><div><h1>Story {k}</h1><p>{words(9, k)}</p><p>{words(7, k + 50)}</p>{'<p>extra ' + str(k) + '</p>' if k % 2 else ''}</div><div class=end>All texts are free</div></body></html>"
    rows = [(k, f"http://Host.example/{k}", page(k)) for k in range(5)] + [(8, None, None), (9, "x", ""), (10, "http://host.example/q", "<p>open <b>never closed")]
    got = dict(rows_of(html_extraction.extracted(spark.createDataFrame(rows, "page_id long, url string, html string")), "page_id", "text"))
    assert got[0] == f"Story 0\n{words(9, 0)}\n{words(7, 50)}" and got[1].endswith("extra 1")
    assert (got[8], got[9], got[10]) == ("", "", "open never closed")


def test_wrappers_drop_template_inside_articles_and_in_repeated_groups(spark):
    one = lambda k: f"<body><article><h1>Story</h1><p>Read more in our app today.</p><p>{words(30, k)}</p><p>{words(9, k + 90)}</p><p>Share this.</p></article></body>"
    two = lambda k: f"<body><table><tr><td>Old site</td></tr></table><ul><li>Home<li>About</ul><blockquote>{words(20, k)}</blockquote></body>"
    rows = [(k, f"http://a.example/{k}", one(k)) for k in range(40)] + [(k, f"http://a.example/{k}", two(k)) for k in range(40, 44)]
    rows += [(k, f"http://b.example/{k}", one(7)) for k in range(50, 60)]  # copies have no template
    got = dict(rows_of(html_extraction.extracted(spark.createDataFrame(rows, "page_id long, url string, html string")), "page_id", "text"))
    assert all(got[k] == f"Story\n{words(30, k)}\n{words(9, k + 90)}" for k in range(40))
    assert all(got[k] == words(20, k) for k in range(40, 44)) and got[50].endswith("Share this.")


def test_union_free_alignment():
    one, two = html_extraction.stream(html_extraction.blocks("<ul><li>a<li>b</ul><p>x</p>")), html_extraction.stream(html_extraction.blocks("<ul><li>a<li>b<li>c</ul><p>x</p><h2>y</h2>"))
    kinds = [n[0] for n in html_extraction.aligned(one, two)]
    assert kinds[0] == "rep" and "opt" in kinds and ("text", "x") in html_extraction.aligned(one, two)


CLASHING = ("_doc", "_dedup", "_id", "_key", "_same", "same", "x", "id", "n", "key", "h", "salt", "gone", "text_key", "raw", "words", "rank", "_words", "component_id", "n_links")


@pytest.fixture(scope="module")
def odd_docs(make_docs):
    rows = [*ODD, (7, "w" * (1 << 20)), (8, None), (8, None), (9, words(60, 1)), (9, words(60, 1)), (9, words(60, 2)), (None, words(60, 1)), (None, None), (10, "\x00 \ufffe 🙂 e\u0301"), (11, "a\u00a0b\u2003c " * 40)]
    df = make_docs(rows)
    return df.withColumns({c: F.lit(7) for c in CLASHING}), len(rows)


ROWWISE = {
    "line dedup": lambda d, s: line_dedup.deduped(d), "toxicity": lambda d, s: toxicity.scored(d, toxicity.train(d, s)), "language": lambda d, s: language_id.identified(d, language_id.train(d)),
    "decontamination": lambda d, s: decontamination.contamination(d, d.select(F.col("doc_id").alias("item_id"), "text").where("doc_id = 9")), "join": lambda d, s: jaccard_join.joined(d),
    "rules": lambda d, s: quality_rules.ledger(d), "store": lambda d, s: token_store.read_documents(token_store.staged(token_store.chunks(d))),
    "scoring": lambda d, s: lm_scoring.scored(d, lm_scoring.train(lm_scoring.flagged(d, s.withColumnRenamed("toxic", "quality")))),
}


@pytest.mark.parametrize("name", sorted(ROWWISE))
def test_odd_rows(spark, odd_docs, name):
    """Null ids and texts, repeated rows, a megabyte without a blank, columns with clashing names: a row each, equal ones for equal rows."""
    docs, n = odd_docs
    labels = spark.createDataFrame([(9, 1), (5, 0), (None, 1), (9, 1)], "doc_id long, toxic int")
    got = ROWWISE[name](docs, labels).collect()
    assert len(got) == n
    # the starts of a store differ by row, and so do row numbers
    twins = [str([v for k, v in r.asDict().items() if k not in ("start", "_row")]) for r in got if r["doc_id"] in (5, 8)]
    assert len(twins) == 4 and len(set(twins)) <= 2


def test_odd_rows_are_packed(odd_docs):
    docs, n = odd_docs
    got = packing.packed(docs).collect()
    assert sum(r["piece"] == 0 for r in got) == n and all(r["offset"] + r["length"] <= 4096 for r in got)


def test_odd_pages(spark):
    rows = [(1, None, None), (1, None, None), (None, "http://a.example/x", "<article><p>a</article>"), (2, "http://a.example/x", "<article><p>a</article>"), (2, "http://a.example/x", "<article><p>a</article>"), (3, "::", "w" * (1 << 20)), (4, "http://[", "<" * 5000)]
    pages = spark.createDataFrame(rows, "page_id long, url string, html string").withColumns({"host": F.lit(1), "_host": F.lit(2), "templates": F.lit(3), "text": F.lit("t")})
    got = rows_of(html_extraction.extracted(pages), "page_id", "url", "text")
    assert len(got) == len(rows) and sum(g == (2, "http://a.example/x", "a") for g in got) == 2 and ("w" * (1 << 20)) in {t for _, _, t in got}


def test_pipeline_stands_odd_rows(spark, odd_docs, tmp_path):
    import corpus_pipeline

    docs, n = odd_docs
    spark.createDataFrame([(1, words(30, 1000)), (None, "x")], "item_id long, text string").write.parquet(f"{tmp_path}/benchmark.parquet")
    now = docs
    for name, stage in corpus_pipeline.STAGES:
        was, now = now, stage(spark, now, str(tmp_path))
        now.write.parquet(f"{tmp_path}/{name}")
        now = spark.read.parquet(f"{tmp_path}/{name}")
        if name != "packing":
            assert now.columns == was.columns
    assert now.where("piece = 0").count() == spark.read.parquet(f"{tmp_path}/decontamination").count() > 0
    kept = spark.read.parquet(f"{tmp_path}/jaccard_join").select("doc_id", "text").collect()
    # one row of the text that three rows hold, and the other text of the same doc_id
    assert sorted((r["doc_id"], r["text"]) for r in kept if r["text"] in (words(60, 1), words(60, 2))) == sorted([(9, words(60, 1)), (9, words(60, 2))])


def test_pipeline_of_empty_tables(spark, tmp_path):
    import corpus_pipeline

    for t in ("documents", "benchmark"):
        spark.read.parquet(f"/root/testdata/sf0.001/{t}.parquet").limit(0).write.parquet(f"{tmp_path}/{t}.parquet")
    assert corpus_pipeline.run(spark, str(tmp_path)).count() == 0


@pytest.mark.parametrize("name", sorted(registry.QUERIES))
def test_empty_tables(spark, tmp_path, name):
    for t in ("documents", "benchmark", "labels", "pages"):
        spark.read.parquet(f"/root/testdata/sf0.001/{t}.parquet").limit(0).write.parquet(f"{tmp_path}/{t}.parquet")
    assert registry.QUERIES[name](spark, str(tmp_path)).count() == 0


@pytest.mark.parametrize("name", sorted(registry.ORACLES))
def test_matches_sql(spark, tmp_path, name):
    df = registry.QUERIES[name](spark, "/root/testdata/sf0.001")
    df.write.parquet(str(tmp_path / "q"))
    con = duckdb.connect()
    for t in ("documents", "benchmark"):
        con.sql(f"create view {t} as select * from '/root/testdata/sf0.001/{t}.parquet'")
    con.sql(f"create view s_ as select * from '{tmp_path}/q/*.parquet'")
    con.sql(f"create table o_ as {registry.ORACLES[name]}")
    cols = ", ".join(df.columns)
    assert con.sql(f"(select {cols} from s_ except all select {cols} from o_) union all (select {cols} from o_ except all select {cols} from s_)").fetchall() == []


def test_pipeline_stage_by_stage(spark, make_docs, tmp_path):
    import corpus_pipeline

    item = words(30, 1)
    a, shared = words(120, 2), words(60, 8)
    near = a.split()
    near[3] = "changed"
    rows = [(1, a), (2, " ".join(near)), (3, "short"), (4, item), (5, words(80, 5) + "\n" + shared), (6, shared + "\n" + words(80, 6)), (7, None)]
    make_docs(rows).write.parquet(f"{tmp_path}/documents.parquet")
    spark.createDataFrame([(1, item)], "item_id long, text string").write.parquet(f"{tmp_path}/benchmark.parquet")
    docs, seen = spark.read.parquet(f"{tmp_path}/documents.parquet"), {}
    for name, stage in corpus_pipeline.STAGES:
        docs = stage(spark, docs, str(tmp_path))
        docs.write.parquet(f"{tmp_path}/out_{name}")
        docs = spark.read.parquet(f"{tmp_path}/out_{name}")
        seen[name] = docs
    ids = lambda n: sorted({r[0] for r in rows_of(seen[n], "doc_id")})
    assert ids("quality_rules") == ids("line_dedup") == [1, 2, 4, 5, 6]
    assert dict(rows_of(seen["line_dedup"], "doc_id", "text"))[6] == words(80, 6)
    assert ids("jaccard_join") == [1, 4, 5, 6] and ids("decontamination") == ids("packing") == [1, 5, 6]
    assert seen["decontamination"].columns == ["doc_id", "text", "lang", "source", "n_chars"]
    assert sorted(rows_of(corpus_pipeline.run(spark, str(tmp_path)), "doc_id", "piece", "length", "ids_crc32")) == sorted(rows_of(seen["packing"], "doc_id", "piece", "length", "ids_crc32"))
