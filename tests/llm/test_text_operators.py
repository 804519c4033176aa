"""Line dedup, mixing, SimHash, BPE and chat formatting against brute force, with odd inputs."""

from __future__ import annotations

import hashlib
import random
import re

import numpy as np
import pytest
import xxhash
from tokenizers import Tokenizer

from sitemine.llm import bpe, chat_format, components, line_dedup, mixing, simhash

DOCS = "doc_id long, text string, lang string, source string, n_lines long, ids string, hit_id int, dup_id int"


def docs(spark, rows):
    return spark.createDataFrame([(i, t, "en", s, 7, "x", 1, 2) for i, t, s in rows], DOCS)


ODD = [(1, None, "a"), (2, "", None), (3, " \t\n", "b"), (4, "one", "a"), (4, "one", "a"), (None, "no id\nline", "a"), (5, "\n".join(["Same line "] * 3), "b"), (6, "x" * 50_000, "b")]


class TestLineDedup:
    def brute(self, rows, min_docs):
        blanks = " \t\n\x0b\x0c\r"
        key = lambda line: "".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in line.strip(blanks))
        seen = {}
        for _, t, _ in rows:
            for k in {key(x) for x in (t or "").split("\n")} - {""}:
                seen[k] = seen.get(k, 0) + 1
        out = []
        for i, t, _ in rows:
            lines = (t or "").split("\n")
            kept = [x for x in lines if seen.get(key(x), 0) < min_docs]
            out.append((i, len(lines), len(lines) - len(kept), "\n".join(kept)))
        return out

    def test_against_brute_force(self, spark):
        rng = random.Random(1)
        pool = ["Alpha", " alpha\t", "BETA", "beta ", "", "  ", "Ünïcode", "ÜNÏCODE", "gamma delta", "\x0bgamma delta"]
        rows = ODD + [(100 + i, "\n".join(rng.choices(pool + [f"own {i}"], k=rng.randint(1, 8))), "a") for i in range(40)]
        got = line_dedup.drop_frequent_lines(docs(spark, rows), min_docs=4)
        assert "n_lines_" in got.columns and got.columns[:8] == DOCS.replace(" long", "").replace(" string", "").replace(" int", "").split(", ")
        got = [(r.doc_id, r.n_lines_, r.n_dropped, r.text) for r in got.collect()]
        assert sorted(got, key=str) == sorted(self.brute(rows, 4), key=str)

    @pytest.mark.parametrize("limit", [10**6, 0])
    def test_many_lines_with_many_hits(self, spark, monkeypatch, limit):
        """Long documents of lines that all drop, or every other one, and one id with two texts; with and without a broadcast."""
        monkeypatch.setattr(line_dedup, "HIT_ROWS", limit)
        rows = [(i, "\n".join(f"line {j}" if j % 2 or i < 4 else f"own {i} {j}" for j in range(20_000)), "a") for i in range(6)]
        rows += [(5, "line 1\nother", "b"), (None, "line 3\nline 5\nkept", "b"), (None, "kept", "b")]
        got = line_dedup.drop_frequent_lines(docs(spark, rows), min_docs=5)
        got = [(r.doc_id, r.n_lines_, r.n_dropped, r.text) for r in got.collect()]
        assert sorted(got, key=str) == sorted(self.brute(rows, 5), key=str)

    def test_empty(self, spark):
        assert line_dedup.drop_frequent_lines(docs(spark, [])).count() == 0


class TestMixing:
    def test_water_filling_and_repetitions(self, spark):
        rng = random.Random(2)
        rows = [(i, "w " * rng.randint(1, 40), s) for i, s in enumerate(["a"] * 300 + ["b"] * 20 + ["c"] * 100 + [None] * 30)] + [(900, None, "a"), (901, "", "z")]
        df = docs(spark, rows)
        got = mixing.mix(df).collect()
        sizes = {}
        for _, t, s in rows:
            sizes[s] = sizes.get(s, 0) + len(re.findall(r"[^\x20\x09-\x0D]+", t or ""))
        names = sorted((s for s in sizes if s is not None), key=lambda s: s) + [None]
        weight = {s: (3, 1, 2)[i % 3] for i, s in enumerate(names)}
        total, target, free = 1.5 * sum(sizes.values()), {}, set(names)
        while True:  # the loop that the window sums replace
            level = (total - sum(target.values())) / sum(weight[s] for s in free)
            over = {s for s in free if level * weight[s] >= 2 * sizes[s]}
            if not over:
                break
            target |= {s: 2.0 * sizes[s] for s in over}
            free -= over
        target |= {s: level * weight[s] for s in free}
        taken = {}
        for r in got:
            assert r.mix_target == pytest.approx(target[r.source]) and r.mix_source_size == sizes[r.source] and r.mix_times <= 2
            taken[r.source] = taken.get(r.source, 0) + r.mix_times * r.mix_size
        assert all(abs(taken[s] - target[s]) <= 40 for s in names)
        again = mixing.mix(df.repartition(7)).collect()
        assert sorted((str(r.doc_id), r.mix_times) for r in got) == sorted((str(r.doc_id), r.mix_times) for r in again)
        assert mixing.repeat_rows(mixing.mix(df)).count() == sum(r.mix_times for r in got)

    def test_odd_rows_and_empty(self, spark):
        assert mixing.mix(docs(spark, ODD)).count() == len(ODD)
        assert mixing.mix(docs(spark, [])).count() == 0
        assert {r.mix_times for r in mixing.mix(docs(spark, [(1, None, None), (2, " ", "a")])).collect()} == {0}


def brute_fingerprint(text, shingle=4):
    words = [w for w in re.split(r"[\x20\x09-\x0D]+", "".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in text or "")) if w]
    if not words:
        return 0
    parts = [" ".join(words[i : i + shingle]) for i in range(max(1, len(words) - shingle + 1))]
    h = [xxhash.xxh64_intdigest(p.encode(), 42) for p in parts]
    return sum(1 << b for b in range(64) if 2 * sum(x >> b & 1 for x in h) > len(h))


class TestSimhash:
    def test_fingerprints_and_components(self, spark):
        rng = random.Random(3)
        vocabulary = [f"w{i}" for i in range(50)] + ["É", "ÀB"]
        base = [" ".join(rng.choices(vocabulary, k=rng.randint(1, 120))) for _ in range(60)]
        rows = [(i, t, "a") for i, t in enumerate(base)]
        for i in range(120):
            words = rng.choice(base).split()
            words[rng.randrange(len(words))] = rng.choice(vocabulary)
            rows.append((1000 + i, " ".join(words).upper() if i % 3 == 0 else "\t".join(words), "b"))
        rows += [(2000, None, "a"), (2001, "", "a"), (2002, " \n", "a"), (7, rows[7][1], "a")]
        got = simhash.near_duplicates(docs(spark, rows)).collect()
        prints = {i: brute_fingerprint(t) for i, t, _ in rows}
        ids = sorted(prints)
        low = {i: i for i in ids}
        changed = True
        while changed:
            changed = False
            for a in ids:
                for b in ids:
                    if (prints[a] ^ prints[b]).bit_count() <= 4 and low[b] < low[a]:
                        low[a], changed = low[b], True
        assert len(got) == len(rows)
        for r in got:
            assert r.fingerprint % 2**64 == prints[r.id] and r.component_id == low[r.id], r

    def test_every_link_of_four_bits_shares_a_key(self):
        rng = random.Random(4)
        keys = simhash.exact_keys(4)
        for _ in range(3000):
            a = rng.getrandbits(64)
            b = a
            for bit in rng.sample(range(64), 4):
                b ^= 1 << bit
            x, y = a.to_bytes(8, "little"), b.to_bytes(8, "little")
            assert any(all(x[p] == y[p] for p in k) for k in keys)

    def test_hot_bucket_is_split_and_whole(self, spark, monkeypatch):
        rng = random.Random(5)
        near = [rng.getrandbits(64)] * 600
        prints = [p ^ (1 << rng.randrange(64)) ^ (1 << rng.randrange(64)) for p in near]
        nodes = spark.createDataFrame([(i, p - 2**64 if p >= 2**63 else p) for i, p in enumerate(prints)], "node long, w0 long").dropDuplicates(["w0"])
        real = simhash.deal
        monkeypatch.setattr(simhash, "deal", lambda *a, **k: real(*a, **k, block_rows=256))
        links = simhash.bucket_links(nodes, simhash.exact_keys(4), 4, 4)
        assert components.connected_components(links).select("component").distinct().count() == 1

    def test_similar_texts_and_stage(self, spark):
        rng = random.Random(6)
        word = lambda: "".join(rng.choices("abcdefghij", k=6))
        base = [[word() for _ in range(300)] for _ in range(30)]
        rows = [(i, " ".join(w), "a") for i, w in enumerate(base)]
        for i, w in enumerate(base):
            w = list(w)
            w[150] = word()
            rows.append((100 + i, " ".join(w), "b"))
        got = {r.id: r.component_id for r in simhash.similar_texts(docs(spark, rows)).collect()}
        assert all(got[100 + i] == i and got[i] == i for i in range(30))
        kept = simhash.drop_near_duplicates(docs(spark, rows + [(None, "lonely words here", "a"), (0, rows[0][1], "a")]))
        assert kept.columns == docs(spark, []).columns
        assert sorted(r.doc_id for r in kept.collect() if r.doc_id is not None) == list(range(30))
        assert kept.where("doc_id is null").count() == 1

    def test_pairs_inside_a_loose_family_are_found(self, spark):
        rng = random.Random(8)
        word = lambda: "".join(rng.choices("abcdefghij", k=6))
        shared = [word() for _ in range(235)]
        rows = []
        for i in range(200):  # Jaccard about 0.63 to each other, a near copy of each at 0.86
            own = [word() for _ in range(65)]
            rows += [(i, " ".join(shared + own), "a"), (1000 + i, " ".join(shared + own[:-22] + [word() for _ in range(22)]), "a")]
        got = {r.id: r.component_id for r in simhash.similar_texts(docs(spark, rows)).collect()}
        assert all(got[i] == i for i in range(200)) and all(got[1000 + i] in (i, 1000 + i) for i in range(200))
        assert sum(got[1000 + i] == i for i in range(200)) >= 199

    def test_similar_texts_are_those_of_exact_jaccard(self, spark):
        rng = random.Random(10)
        word = lambda: "".join(rng.choices("abcdefghij", k=6))
        rows, want = [], {}
        for i in range(400):  # even numbers at 0.8 to 0.82, odd ones at 0.77 to 0.8; every fourth text is short
            n = rng.randint(5, 30) if i % 4 > 1 else rng.randint(150, 300)
            base = [word() for _ in range(n + 4)]
            low, high = (0.8, 0.82) if i % 2 == 0 else (0.77, 0.7999)
            more = max((k for k in range(n) if low <= n / (n + k) <= high), default=0 if i % 2 == 0 else n)
            rows += [(i, " ".join(base), "a"), (1000 + i, " ".join(base + [word() for _ in range(more)]), "a")]
            want |= {i: i, 1000 + i: i if i % 2 == 0 else 1000 + i}
        got = {r.id: r.component_id for r in simhash.similar_texts(docs(spark, rows)).collect()}
        assert sum(got[k] != want[k] for k in want if k % 2) == 0
        assert sum(got[k] != want[k] for k in want) <= 1

    def test_a_loose_neighbour_does_not_hide_a_link(self, spark):
        rng = random.Random(9)
        far, near = ([rng.getrandbits(63) for _ in range(4)] for _ in range(2))
        prints = [(1, [5, 6], *far), (2, [5, 7], *near), (3, [5, 8], near[0] ^ 1, *near[1:]), (4, [9], *near)]
        nodes = spark.createDataFrame(prints, "node long, keys array<long>, " + ", ".join(f"w{i} long" for i in range(4)))
        assert {(r.a, r.b) for r in simhash.family_links(nodes, 60).collect()} == {(3, 2)}

    def test_pairs_of_too_few_shared_positional_bytes_leave(self, spark):
        octets = [bytes(range(1, 65)), bytes([1, 2]) + bytes(62), bytes([1, 2, 3]) + bytes(61)]
        nodes = spark.createDataFrame([(i, [5], bytearray(o), 1, 2, 3, 4) for i, o in enumerate(octets)], "node long, keys array<long>, octets binary, " + ", ".join(f"w{i} long" for i in range(4)))
        assert {(r.a, r.b) for r in simhash.family_links(nodes.where("node < 2"), 60).collect()} == set()
        assert {(r.a, r.b) for r in simhash.family_links(nodes, 60).collect()} == {(2, 0)}

    @pytest.mark.parametrize("measure", ["jaccard", "cosine"])
    def test_tally_keeps_similar_pairs_and_drops_others(self, measure):
        """Of pairs just at the threshold every one that meets passes the tally of positional bytes; unrelated sets share too few."""
        rng = np.random.default_rng(13)
        ratio, passed = simhash.size_ratio(0.8, measure), []
        for n in (33, 60, 130, 193, 300, 760, 3100):
            for turn in range(60):
                smaller = n if turn % 2 else round(n * (1 + ratio) / 2)
                need = 0.8 / 1.8 * (n + smaller) if measure == "jaccard" else 0.8 * (n * smaller) ** 0.5
                shared = min(smaller, int(need) + 1)
                made = np.unique(rng.integers(0, 2**64, 2 * n + smaller, np.uint64))
                rng.shuffle(made)
                a, b, c = np.sort(made[:n]), np.sort(np.concatenate([made[:shared], made[n : n + smaller - shared]])), np.sort(made[n + smaller :])
                x, y, z = (simhash.position_filings(s, ratio) for s in (a, b, c))
                met = [simhash.enough_shared(p, q) for k, p in x for m, q in y if np.intersect1d(k, m).size]
                assert met and all(met), (n, turn)
                passed += [simhash.enough_shared(p, q) for (_, p), (_, q) in zip(x, z, strict=True)]
        assert np.mean(passed) < 0.02

    @pytest.mark.parametrize("measure", ["jaccard", "cosine"])
    def test_similar_pairs_meet_whatever_their_size(self, measure):
        """Brute force of the index: of pairs just at the threshold nearly all share a key, at every size and size ratio."""
        rng = np.random.default_rng(11)
        ratio = simhash.size_ratio(0.8, measure)
        for n in (33, 60, 130, 185, 193, 300, 500, 760, 770, 2000, 3100, 12_000):
            met = 0
            for turn in range(60):
                smaller = n if turn % 2 else round(n * (1 + ratio) / 2)
                need = 0.8 / 1.8 * (n + smaller) if measure == "jaccard" else 0.8 * (n * smaller) ** 0.5
                shared = min(smaller, int(need) + 1)
                made = np.unique(rng.integers(0, 2**64, n + smaller, np.uint64))
                a, b = np.sort(made[:n]), np.sort(np.concatenate([made[:shared], made[n : n + smaller - shared]]))
                met += bool(np.intersect1d(simhash.position_keys(a, ratio), simhash.position_keys(b, ratio)).size)
            assert met == 60, (measure, n, met)

    def test_cosine_families(self, spark):
        rng = random.Random(12)
        word = lambda: "".join(rng.choices("abcdefghij", k=6))
        rows, sets = [], {}
        for i in range(120):  # copies with words changed, at cosines from about 0.6 to 0.95
            base = [word() for _ in range(rng.choice([20, 60, 150, 400, 900]))]
            near = [w if rng.random() > rng.choice([0.01, 0.03, 0.05, 0.08]) else word() for w in base]
            rows += [(i, " ".join(base), "a"), (1000 + i, " ".join(near), "a")]
        for i, t, _ in rows:
            w = t.split()
            sets[i] = {tuple(w[j : j + 5]) for j in range(len(w) - 4)}
        got = {r.id: r.component_id for r in simhash.similar_texts(docs(spark, rows), measure="cosine").collect()}
        for i in range(120):
            a, b = sets[i], sets[1000 + i]
            assert (got[1000 + i] == i) == (len(a & b) / (len(a) * len(b)) ** 0.5 >= 0.8), i

    def test_odd_rows_and_empty(self, spark):
        got = simhash.near_duplicates(docs(spark, ODD)).collect()
        assert len(got) == len(ODD)
        blank = [r for r in got if r.fingerprint == 0]
        assert {r.id for r in blank} == {1, 2, 3} and {r.component_id for r in blank} == {1}
        assert simhash.near_duplicates(docs(spark, [])).count() == 0
        assert simhash.drop_near_duplicates(docs(spark, [])).count() == 0


class TestComponents:
    def test_random_graphs(self, spark):
        rng = random.Random(7)
        for n, m in ((30, 20), (60, 50), (80, 200)):
            links = [(rng.randrange(n), rng.randrange(n)) for _ in range(m)] + [(None, 3), (4, 4)]
            low = {i: i for i in range(n)}
            for _ in range(n):
                for a, b in links:
                    if a is not None:
                        low[a] = low[b] = min(low[a], low[b])
            got = {r.node: r.component for r in components.connected_components(spark.createDataFrame(links, "a long, b long")).collect()}
            touched = {x for a, b in links if a is not None and a != b for x in (a, b)}
            assert got == {x: low[x] for x in touched}

    def test_long_chain_and_empty(self, spark):
        chain = spark.range(200).selectExpr("id as a", "id + 1 as b")
        assert {r.component for r in components.connected_components(chain).collect()} == {0}
        assert components.connected_components(spark.createDataFrame([], "a long, b long")).count() == 0


@pytest.fixture(scope="module")
def library():
    return Tokenizer.from_file(bpe.default_path())


class TestBpe:
    ALPHABET = [*"abcdefthinger  '''\n!?.,-12é", "the", "ing", "'s", "'re", "Σ", "İ", "é", "漢字", "<|endoftext|>", "😀", "\x85", " ", "²", "ª", "ß", "́", "ſ"]

    def texts(self, n):
        rng = random.Random(8)
        for i in range(n):
            yield "".join(rng.choices(["th", "e", "in", "g", "er", "the"], k=rng.randint(1, 900))) if i % 3 == 0 else "".join(rng.choices(self.ALPHABET, k=rng.randint(0, 60)))

    def test_whole_texts_and_pieces_equal_the_library(self, library):
        own = bpe.load(bpe.default_path())
        for text in self.texts(1200):
            want = library.encode(text, add_special_tokens=False).ids
            assert own.encode_all([text])[0].tolist() == want
            for size in (5, 64, 301):
                got = []
                for segment, special in own.segments(text):
                    got += [special] if special >= 0 else own.tree([own.piece(segment[i : i + size]) for i in range(0, len(segment), size)]).tolist()
                assert got == want, (size, text)
            assert own.decode(want) == library.decode(want, skip_special_tokens=False)

    def test_frames(self, spark, library):
        rows = ODD + [(100 + i, t, "a") for i, t in enumerate(self.texts(40))] + [(200, "unsplit" * 3000 + "<|endoftext|>" + "A b" * 10, "b")]
        want = sorted((str(i), library.encode(t or "", add_special_tokens=False).ids) for i, t, _ in rows)
        for piece in (100, 65_536):
            got = bpe.encode(docs(spark, rows), piece=piece)
            assert "ids_" in got.columns and "text" not in got.columns
            assert sorted((str(r.doc_id), list(r.ids_)) for r in got.collect()) == want
        told = bpe.decode(bpe.encode(docs(spark, rows)), ids="ids_").collect()
        assert all(r.decoded == library.decode(r.ids_, skip_special_tokens=False) for r in told)
        assert bpe.encode(docs(spark, [])).count() == 0


class TestChat:
    def test_round_trip(self):
        rng = random.Random(9)
        parts = ["<s>", "</s>", "[INST]", "[/INST]", "\\", "\n", "a", " ", "<", "s>", "[", "]"]
        for _ in range(4000):
            turns = [("".join(rng.choices(parts, k=rng.randint(0, 3))), "".join(rng.choices(parts, k=rng.randint(0, 6)))) for _ in range(rng.randint(0, 4))]
            text, spans = chat_format.render(turns)
            assert chat_format.parse(text) == turns
            assert [chat_format.unescape(text[a:b]) for a, b in spans] == [t for _, t in turns]

    def test_outside_the_grammar(self):
        for bad in ("x", "<s>", "<s>[INST]user\n[/INST]\nhi</s>", "<s>[INST]user\n[/INST]\nhi\n</s>x"):
            with pytest.raises(chat_format.GrammarError):
                chat_format.parse(bad)

    def test_frame(self, spark):
        rows = [(1, 1, "assistant", "b", 9), (1, 0, "user", None, 9), (1, 1, "assistant", "a", 9), (None, None, None, "x\\", 9), (2, 0, "assistant", "</s>" * 2000, 9)]
        got = {r.conv_id: r for r in chat_format.read_back(chat_format.format_conversations(spark.createDataFrame(rows, "conv_id long, turn long, role string, text string, formatted int"))).collect()}
        sha = lambda t: hashlib.sha256(t.encode()).hexdigest()
        assert got[1].turns_sha256 == sha("user\n\nassistant\na\nassistant\nb\n") and got[1].loss_sha256 == sha("ab") and got[1].loss_chars == 2
        assert got[None].turns_sha256 == sha("\nx\\\n") and got[None].loss_chars == 0
        assert got[2].loss_sha256 == sha("</s>" * 2000)
        lone = spark.createDataFrame([(None, 1, "user", "a", 9), (None, 2, "assistant", "</s>" * 50_000, 9)], "conv_id long, turn long, role string, text string, formatted int")
        assert sorted((r.conv_id, r.n_turns, r.loss_chars) for r in chat_format.read_back(chat_format.format_conversations(lone)).collect()) == [(None, 1, 0), (None, 1, 200_000)]
        assert chat_format.format_conversations(spark.createDataFrame([], "conv_id long, turn long, role string, text string")).count() == 0


def test_no_python_on_the_native_path(spark):
    plan = mixing.mix(docs(spark, ODD))._jdf.queryExecution().toString()
    assert not re.search("Python|Pandas|Arrow", plan)


def test_short_integer_ids(spark):
    rows = spark.createDataFrame([(1, "a b c d e f"), (2, "a b c d e f"), (3, "x")], "doc_id int, text string")
    assert {r.id: r.component_id for r in simhash.near_duplicates(rows).collect()} == {1: 1, 2: 1, 3: 3}
    assert sorted(r.doc_id for r in simhash.drop_near_duplicates(rows).collect()) == [1, 3]
