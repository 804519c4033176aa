"""Audio, embeddings, URL rules, quality, language and the pipeline, with odd inputs."""

from __future__ import annotations

import hashlib
import itertools
import math
import random
import re
import struct
import zlib
from collections import Counter

import numpy as np
import pytest
from pyspark.sql import functions as F

from sitemine.llm import embedding_dedup, language_id, mpeg_audio, quality_lm, url_rules


class TestAudio:
    def test_round_trip(self):
        rng = random.Random(1)
        for n in (0, 1, 575, 576, 577, 5000, 200_000):
            content = rng.randbytes(n)
            data = mpeg_audio.store(content)
            audio = mpeg_audio.parse(data)
            assert mpeg_audio.payload_of(data, audio) == mpeg_audio.pad(content)
            assert audio.frames * 576 == len(mpeg_audio.pad(content)) == audio.samples and audio.duration == audio.samples / 16000
            assert (audio.bad_crc, audio.junk, audio.resyncs, audio.vbr, audio.vbr_frames) == (0, 0, 0, "Info", audio.frames)
            assert audio.tags["TXXX"] == f"content_bytes={n}"

    def test_false_syncs_in_the_payload(self):
        content = b"\xff\xf2\xd8\xc0" * 5000
        data = mpeg_audio.store(content)
        assert mpeg_audio.payload_of(data, mpeg_audio.parse(data)) == mpeg_audio.pad(content)

    def test_resynchronises_and_counts_damage(self):
        data = mpeg_audio.store(b"sound" * 1000)
        whole = mpeg_audio.parse(data)
        start = int(whole.offsets[2])
        audio = mpeg_audio.parse(data[:start] + b"junk\xff\xfb\x90\x00junk" + data[start:])
        assert audio.frames == whole.frames and audio.junk == 12 and audio.resyncs == 1
        broken = bytearray(data)
        broken[start + 8] ^= 1
        assert mpeg_audio.parse(bytes(broken)).bad_crc == 1
        cut = mpeg_audio.parse(data[:-100])
        assert cut.frames == whole.frames - 1 and cut.junk == 548

    def test_other_streams(self):
        # MPEG-1 Layer III, 128 kbit/s, 44.1 kHz stereo, with and without padding, and an ID3v1 tag
        frame = lambda padded: struct.pack(">I", 0xFFFB9000 | padded << 9) + bytes(417 + padded - 4)
        tag = b"TAG" + b"title".ljust(30, b"\0") + bytes(95)
        audio = mpeg_audio.parse(b"".join(frame(i % 2) for i in range(10)) + tag)
        assert audio.frames == 10 and audio.samples == 11520 and audio.head.rate == 44100 and audio.tags["id3v1.title"] == "title"
        assert audio.offsets.tolist() == [417 * i + i // 2 for i in range(10)]
        xing = bytearray(frame(0))
        xing[36:48] = b"Xing" + struct.pack(">II", 1, 77)
        audio = mpeg_audio.parse(bytes(xing) + frame(0) * 3)
        assert (audio.vbr, audio.vbr_frames, audio.frames) == ("Xing", 77, 3)
        xing[36:164] = b"Xing" + struct.pack(">III", 15, 3, 4 * 417) + bytes(range(0, 200, 2)) + struct.pack(">I", 57) + bytes(8)
        audio = mpeg_audio.parse(bytes(xing) + frame(0) * 3)
        assert audio.vbr_quality == 57 and audio.vbr_seek == [2 * i * 4 * 417 // 256 for i in range(100)]
        vbri = bytearray(frame(0))
        vbri[36:54] = b"VBRI" + bytes(4) + struct.pack(">HII", 80, 1234, 5)
        vbri[54:70] = struct.pack(">HHHH", 4, 3, 2, 7) + struct.pack(">HHHH", 10, 20, 30, 40)
        audio = mpeg_audio.parse(bytes(vbri) + frame(0) * 2)
        assert (audio.vbr, audio.vbr_bytes, audio.vbr_frames, audio.vbr_quality, audio.vbr_seek) == ("VBRI", 1234, 5, 80, [30, 90, 180, 300])
        for nothing in (b"", b"\xff", b"no audio here", bytes(1000), b"\xff" * 1000):
            assert mpeg_audio.parse(nothing).frames == 0

    @staticmethod
    def crc_of_bits(bits):
        """CRC-16 bit by bit over a list of bits."""
        crc = 0xFFFF
        for bit in bits:
            top = crc >> 15
            crc = crc << 1 & 0xFFFF
            if top != bit:
                crc ^= 0x8005
        return crc

    def test_checksums_of_layers_one_and_two(self):
        rng = random.Random(4)
        bits_of = lambda raw: [b >> i & 1 for b in raw for i in range(7, -1, -1)]
        # (header, size, bits of each allocation in stream order, channels that each stands for)
        cases = [
            (0xFFFE9000 | 3 << 6, 12 * 288000 // 44100 * 4, [4] * 32, [1] * 32),  # layer I, mono
            (0xFFFE9000, 12 * 288000 // 44100 * 4, [4] * 64, [1] * 64),  # layer I, stereo
            (0xFFFE9050, 12 * 288000 // 44100 * 4, [4] * (2 * 8 + 24), [1] * 16 + [2] * 24),  # layer I, joint stereo from subband 8
            (0xFFFC90C0, 144 * 160000 // 44100, [4] * 11 + [3] * 12 + [2] * 7, [1] * 30),  # layer II, mono at 160
            (0xFFFC9000, 144 * 160000 // 44100, [4] * 22 + [3] * 24 + [2] * 8, [1] * 54),  # layer II, stereo at 80 a channel
            (0xFFFC1840, 144 * 32000 // 32000, [4] * 4 + [3] * 4 + [3] * 8, [1] * 8 + [2] * 8),  # layer II, 16 a channel at 32 kHz, joint from subband 4
            (0xFFF490C0, 144 * 80000 // 22050, [4] * 4 + [3] * 7 + [2] * 19, [1] * 30),  # layer II of MPEG-2
        ]
        for word, size, widths, channels in cases:
            body = bytearray(rng.randbytes(size - 6))
            bits, at, more = bits_of(body), 0, 0
            for width, n in zip(widths, channels, strict=True):
                more += 2 * n * any(bits[at : at + width]) if word >> 17 & 3 == 2 else 0
                at += width
            head = word.to_bytes(4, "big")
            crc = self.crc_of_bits(bits_of(head[2:]) + bits[: at + more])
            frame = head + crc.to_bytes(2, "big") + bytes(body)
            audio = mpeg_audio.parse(frame * 3)
            assert (audio.frames, audio.checked, audio.bad_crc, audio.junk) == (3, 3, 0, 0), hex(word)
            broken = bytearray(frame)
            broken[4] ^= 1
            assert mpeg_audio.parse(bytes(broken) + frame * 2).bad_crc == 1

    def test_an_independent_reader(self):
        """The stored bytes taken apart by fixed offsets and bitwise checks, without the parser."""
        content = "Töne ".encode() * 700
        data = mpeg_audio.store(content)
        tag = data[6] << 21 | data[7] << 14 | data[8] << 7 | data[9]
        assert data[:6] == b"ID3\x03\0\0" and (len(data) - 10 - tag) % 648 == 0
        frames = [data[i : i + 648] for i in range(10 + tag, len(data), 648)]
        for f in frames:
            head = int.from_bytes(f[:4], "big")
            # sync, MPEG-2, layer III, protected, 144 kbit/s, 16 kHz, no padding, mono
            assert (head >> 20, head >> 19 & 1, head >> 17 & 3, head >> 16 & 1, head >> 12 & 15, head >> 10 & 3, head >> 9 & 1, head >> 6 & 3) == (0xFFF, 0, 1, 0, 13, 2, 0, 3)
            bits = [b >> i & 1 for b in f[2:4] + f[6:15] for i in range(7, -1, -1)]
            assert self.crc_of_bits(bits) == int.from_bytes(f[4:6], "big")
        assert frames[0][15:31] == b"Info" + struct.pack(">III", 7, len(frames) - 1, 648 * len(frames))
        assert b"".join(f[15:591] for f in frames[1:]) == content + b"\xff" * (-len(content) % 576)
        assert mpeg_audio.parse(data).offsets.tolist() == [10 + tag + 648 * i for i in range(1, len(frames))]

    def test_crc_known_value(self):
        # CRC-16 with polynomial 0x8005, start 0xFFFF, not reflected: published check value of "123456789"
        assert mpeg_audio.crc16(b"123456789") == 0xAEE7

    def test_frame(self, spark):
        rows = [(1, "text é", 5), (1, "text é", 5), (2, None, 6), (3, "", 7), (None, "x" * 100_000, 8)]
        df = spark.createDataFrame(rows, "doc_id long, text string, frames int")
        one, two = (sorted(map(str, d.collect())) for d in (mpeg_audio.measure(mpeg_audio.add_audio(df)), mpeg_audio.store_and_measure(df)))
        assert one == two
        got = mpeg_audio.store_and_measure(df)
        assert "frames_" in got.columns
        for r in got.collect():
            text = dict((i, t) for i, t, _ in rows)[r.doc_id]
            assert bytes(r.payload) == mpeg_audio.pad((text or "").encode()) and r.content_bytes == len((text or "").encode())
            assert r.media_sha256 == hashlib.sha256(mpeg_audio.store((text or "").encode())).hexdigest()
        assert mpeg_audio.store_and_measure(df.limit(0)).count() == 0

    def test_text_that_looks_like_a_tag(self):
        for content in (b"a" * 505 + b"TAG" + b"b" * 68, b"x" * (576 + 505) + b"TAG tail"):
            data = mpeg_audio.store(content)
            assert data[-128:-125] == b"TAG"
            audio = mpeg_audio.parse(data)
            assert mpeg_audio.payload_of(data, audio) == mpeg_audio.pad(content) and audio.junk == 0
            tagged = mpeg_audio.parse(data + b"TAG" + b"title".ljust(125, b"\0"))
            assert tagged.tags["id3v1.title"] == "title" and tagged.junk == 0 and tagged.frames == audio.frames


class TestEmbeddings:
    def brute(self, rows, threshold=0.9):
        ok = lambda v: v and all(x is not None and math.isfinite(x) for x in v) and any(v)
        cos = lambda a, b: sum(x * y for x, y in zip(a, b)) / math.sqrt(sum(x * x for x in a) * sum(y * y for y in b))
        n = len(rows)
        links = [[j for j in range(n) if j != i and ok(rows[i][1]) and ok(rows[j][1]) and len(rows[i][1]) == len(rows[j][1]) and cos(rows[i][1], rows[j][1]) >= threshold] for i in range(n)]
        low = [r[0] for r in rows]
        for _ in range(n):
            for i in range(n):
                for j in links[i]:
                    low[i] = low[j] = min(low[i], low[j])
        return sorted((rows[i][0], len(links[i]), low[i], low[i] == rows[i][0]) for i in range(n))

    def test_against_brute_force(self, spark):
        rng = np.random.default_rng(2)
        base = rng.normal(size=(40, 16))
        rows = [(i, base[i].tolist()) for i in range(40)]
        for i in range(120):
            rows.append((100 + i, (base[i % 12] + rng.normal(size=16) * rng.choice([0.02, 0.15, 0.3])).tolist()))
        rows += [(300 + i, rows[100][1]) for i in range(30)] + [(400, (2 * np.array(rows[100][1])).tolist())]
        rows += [(500, None), (501, []), (502, [0.0] * 16), (503, [float("nan")] * 16), (504, [None] + [1.0] * 15), (505, [float("inf")] * 16), (506, [1.0, 0.0]), (507, [2.0, 0.0]), (508, [1e300] * 16)]
        df = spark.createDataFrame([(i, v, "x") for i, v in rows], "vec_id long, embedding array<double>, n_links string")
        got = embedding_dedup.near_duplicates(df).collect()
        assert sorted((r.vec_id, r.n_links, r.component_id, r.kept) for r in got) == self.brute(rows[:-1] + [(508, [1.0] * 16)])

    def test_hot_bucket_in_blocks(self, spark, monkeypatch):
        rng = np.random.default_rng(3)
        center = rng.normal(size=8)
        rows = [(i, (center + rng.normal(size=8) * 0.02).astype(np.float32).tolist()) for i in range(700)]
        monkeypatch.setattr(embedding_dedup, "BLOCK_ROWS", 256)
        got = embedding_dedup.near_duplicates(spark.createDataFrame(rows, "vec_id long, embedding array<float>")).collect()
        assert all(r.n_links == 699 and r.component_id == 0 for r in got)

    def test_empty(self, spark):
        assert embedding_dedup.near_duplicates(spark.createDataFrame([], "vec_id long, embedding array<float>")).count() == 0


class TestUrlRules:
    def test_fixed_rules(self, spark):
        want = {
            "https://a.example.org/es/1": ("a.example.org", "/es/1", "example.org/es/", "block"),
            "https://EXAMPLE.org/en/19?q=/es/": ("example.org", "/en/19", "example.org/en/1", "block"),
            "http://example.org/en/2": ("example.org", "/en/2", "org/", "allow"),
            "http://notexample.org/es/": ("notexample.org", "/es/", "org/", "allow"),
            "http://x.com/fr/1#top": ("x.com", "/fr/1", "com/fr/", "allow"),
            "http://x.com/de/": ("x.com", "/de/", "com/de/", "block"),
            "http://x.com/frx": ("x.com", "/frx", None, "allow"),
            "http://x.org": ("x.org", "", None, "allow"),
            "http://x.org?a=b/c": ("x.org", "", None, "allow"),
            "no scheme": ("", "", None, "allow"),
            None: ("", "", None, "allow"),
            "": ("", "", None, "allow"),
            "http://É.com/a\nb": ("É.com", "/a\nb", None, "allow"),
        }
        rows = [(i, u, "host") for i, u in enumerate(want)]
        rules = url_rules.mine_rules(spark.createDataFrame([], "url string, bad boolean"))
        got = url_rules.judge(spark.createDataFrame(rows + rows[:1], "page_id long, url string, host string"), rules).collect()
        assert len(got) == len(rows) + 1
        assert {r.url: (r.host_, r.path, r.rule, r.verdict) for r in got} == want and {r.host for r in got} == {"host"}

    def test_templates_are_mined_as_one_token(self, spark):
        """Tokens that always stand together, or everywhere, do not multiply rules."""
        path = "/".join(f"part{i}" for i in range(16))
        urls = [(f"http://shop.net/{path}/item{'/x/y/z' if i % 4 == 0 else ''}?a=1&b=2", i % 4 == 0) for i in range(80)] + [("http://far.net/", None), ("http://shop.net/99999999999999999999", None)]
        rules = url_rules.mine_rules(spark.createDataFrame(urls, "url string, bad boolean"), min_support=0.01, min_count=1).collect()
        assert [(r.tokens, r.confidence, r.support) for r in rules] == [(["path=x"], 1.0, 0.25)]
        pages = spark.createDataFrame([("http://a.net/en/12345678901234567890/x",), ("http://a.net/en/1234567890123456789",), ("http://a.net/en/7",), (None,)], "url string")
        labels = spark.createDataFrame([(1234567890123456789, 0, 0), (7, 1, 0), (7, 1, 1)], "doc_id long, quality int, toxic int")
        assert sorted((r.url[-3:], r.bad) for r in url_rules.labelled_pages(pages, labels).collect()) == [("789", True), ("n/7", False), ("n/7", True)]

    def test_mined_rules_against_brute_force(self, spark):
        rng = random.Random(4)
        urls = []
        for i in range(400):
            host, lang, key = rng.choice(["pills", "news", "blog"]), rng.choice(["en", "de"]), rng.choice(["", "?ref=x"])
            bad = (host == "pills" and lang == "en") or rng.random() < 0.1
            urls.append((f"http://{host}.site.net/{lang}/{i}{key}", bad))
        df = spark.createDataFrame([*urls, ("http://a.b/c", None), (None, True)], "url string, bad boolean")
        rules = url_rules.mine_rules(df, min_support=0.05, min_confidence=0.8, min_count=1)
        tokens = {r.url: frozenset(r.t) for r in df.where("url is not null").select("url", url_rules.url_tokens(F.col("url")).alias("t")).collect()}
        seen = [(tokens[u], b) for u, b in urls] + [(frozenset(), True)]
        found = {}
        for size in range(1, 6):
            for some in {c for t, b in seen if b for c in itertools.combinations(sorted(t), size)}:
                fit = [b for t, b in seen if t.issuperset(some)]
                if sum(fit) >= 0.05 * 400 and sum(fit) / len(fit) >= 0.8:
                    found[frozenset(some)] = sum(fit) / len(fit)
        kept = {s for s, c in found.items() if not any(o < s and found[o] >= c for o in found)}
        assert {frozenset(r.tokens) for r in rules.collect()} == kept and kept
        verdicts = {r.url: r.verdict for r in url_rules.judge(df, rules, fixed=()).collect()}
        assert all((verdicts[u] == "block") == any(s <= tokens[u] for s in found) for u, _ in urls)

    def test_native(self, spark):
        rules = url_rules.mine_rules(spark.createDataFrame([("http://a.b/c", True)] * 30, "url string, bad boolean"))
        plan = url_rules.judge(spark.createDataFrame([(1, "http://a.b/c")], "page_id long, url string"), rules)._jdf.queryExecution().toString()
        assert not re.search("MapInArrow|Pandas|PythonUDF|ArrowEval", plan)


PROSE = {"en": "the quick brown fox jumps over that lazy dog while rain falls", "de": "der schnelle braune fuchs springt über den faulen hund während", "fr": "le renard brun rapide saute par dessus le chien paresseux où"}


def prose(rng, lang, n):
    return " ".join(rng.choices(PROSE[lang].split(), k=n)).capitalize() + "."


class TestQuality:
    def rows(self):
        rng = random.Random(5)
        good = [(i, prose(rng, rng.choice(list(PROSE)), rng.randint(5, 80))) for i in range(300)]
        lang = lambda t: next(k for k, v in PROSE.items() if t.lower().split()[0].strip(".") in v.split())
        rows = [(i, t, lang(t)) for i, t in good]
        junk = [(1000 + i, " ".join(f"{w}###$$%{i}" for w in prose(rng, "en", 30).split()), "en") for i in range(40)]
        return rows, junk

    def test_keeps_clean_and_rejects_junk(self, spark):
        rows, junk = self.rows()
        odd = [(2000, None, "en"), (2001, "", None), (None, *rows[7][1:]), (2002, "the fox", "xx"), (2003, "z" * 200_000, "en"), (3, rows[3][1], rows[3][2])]
        docs = spark.createDataFrame([(*r, "x") for r in rows + junk + odd], "doc_id long, text string, lang string, keep string")
        labels = spark.createDataFrame([(i, 1, 0) for i, _, _ in rows[:200]] + [(i, 0, 0) for i, _, _ in junk[:10]] + [(None, 1, 0), (5, None, None)], "doc_id long, quality int, toxic int")
        told = {r.id: r for r in quality_lm.judge(docs, labels).collect()}
        assert sum(told[i].keep for i, _, _ in rows) >= len(rows) - 3
        assert not any(told[i].keep for i, _, _ in junk)
        assert told[2000].keep and told[2001].keep and told[None].keep and not told[2003].keep and told[2002].model == "*"
        kept = quality_lm.keep_good(docs, labels)
        assert kept.columns == docs.columns and kept.where("doc_id >= 1000 and doc_id < 1100").count() == 0 and kept.where("doc_id is null").count() == 1

    def brute(self, texts):
        """Kneser-Ney written out over strings: p(gram) of any four points, edges as None."""
        top = Counter(g for t in texts for x in [[None] * 3 + list(t) + [None]] for g in zip(x, x[1:], x[2:], x[3:], strict=False))
        levels = [top]
        while len(next(iter(levels[-1]))) > 1:
            levels.append(Counter(g[1:] for g in levels[-1]))
        levels = [(c, self.discount(c)) for c in reversed(levels)]
        floor = 1 / (len(levels[0][0]) + 1)
        totals = []
        for c, d in levels:
            total, freed = Counter(), Counter()
            for g, n in c.items():
                total[g[:-1]] += n
                freed[g[:-1]] += d[min(n, 3)]
            totals.append((total, freed))

        def p(gram):
            out = floor
            for k, ((c, d), (total, freed)) in enumerate(zip(levels, totals, strict=True), 1):
                end = gram[-k:]
                if end[:-1] in total:
                    n = c.get(end, 0)
                    out = ((n - d[min(n, 3)]) if n else 0) / total[end[:-1]] + freed[end[:-1]] / total[end[:-1]] * out
            return out

        return p, sorted({g[0] for g in levels[0][0]}, key=str)

    @staticmethod
    def discount(counts):
        k = Counter(counts.values())
        y = k[1] / (k[1] + 2 * k[2]) if k[1] + 2 * k[2] else 0
        raw = [(i - (i + 1) * y * k[i + 1] / k[i]) if k[i] and k[1] + 2 * k[2] else -1 for i in (1, 2, 3)]
        return [0.0, *(r if 0 < r < i else 0.5 for i, r in enumerate(raw, 1))]

    def test_probabilities_and_sums_are_those_of_the_formula(self, spark):
        rows, junk = self.rows()
        trusted = [(i, t, lang, i % 2) for i, t, lang in rows[:80]]
        good = spark.createDataFrame(trusted, "id long, text string, lang string, half int")
        languages = quality_lm.languages_of(good)
        assert languages == sorted(PROSE)
        counts = quality_lm.count_grams(good, languages, gather=500)  # many small additions
        model = quality_lm.kneser_ney(counts)
        point = lambda c: quality_lm.EDGE if c is None else ord(c)
        truth = {}
        for place, name in enumerate([*languages, None]):
            for half in (0, 1):
                truth[2 * place + half] = self.brute([t for _, t, lang, h in trusted if h == half and lang == (name or lang)])
        for number, (p, alphabet) in truth.items():
            contexts = [(None, None, None), ("t", "h", "e"), ("q", "q", "q"), ("e", " ", None)]
            assert all(sum(p((*c, x)) for x in alphabet) + p((*c, "unknown")) == pytest.approx(1) for c in contexts)
            asked = [(*c, x) for c in contexts for x in [*alphabet, "☃"]]
            frame = spark.createDataFrame([(number, point(a) << 42 | point(b) << 21 | point(c), point(d)) for a, b, c, d in asked], "number long, context long, point long")
            got = {(r.context, r.point): r.p for r in quality_lm.probabilities(frame, model).collect()}
            for a, b, c, d in asked:
                assert got[point(a) << 42 | point(b) << 21 | point(c), point(d)] == pytest.approx(p((a, b, c, d)), rel=1e-9)
        mixed = [*trusted, *((i, t, lang, i % 2) for i, t, lang in junk), (9000, "no such language ☃", "xx", 0), (9001, None, "en", 1), (9002, "", None, 0), (3, trusted[3][1], trusted[3][2], 1)]
        docs = spark.createDataFrame(mixed, good.schema).repartition(5)
        ways = [sorted(map(tuple, quality_lm.score(docs, model, languages, table_rows=n).collect())) for n in (10**6, 0)]
        assert len(ways[0]) == len(ways[1]) == len(mixed)
        for a, b in zip(*ways, strict=True):
            assert a[:3] == b[:3] and (a[3:] == b[3:] or a[3:] == pytest.approx(b[3:], rel=1e-9))
        told = {r[0]: r for r in ways[0]}
        for i, t, lang, half in mixed:
            if not t:
                assert told[i][2] == 0 and told[i][3] is None
                continue
            p = truth[2 * (languages.index(lang) if lang in languages else 3) + 1 - half][0]
            x = [None] * 3 + list(t) + [None]
            cost = -np.mean([np.log(p(g)) for g in zip(x, x[1:], x[2:], x[3:], strict=False)])
            pairs, firsts = Counter(zip([None, *t], [*t, None], strict=True)), Counter([None, *t])
            own = -sum(n * np.log(n / firsts[g[0]]) for g, n in pairs.items()) / (len(t) + 1)
            assert told[i][2:] == pytest.approx((len(t) + 1, np.exp(cost), np.exp(own)), rel=1e-9)

    def test_long_texts_in_chunks(self, monkeypatch):
        rng = np.random.default_rng(3)
        points = rng.integers(97, 105, 5000)
        whole, own = list(quality_lm.grams(points)), quality_lm.own_cost(points)
        monkeypatch.setattr(quality_lm, "CHUNK", 700)
        parts = list(quality_lm.grams(points))
        assert len(whole) == 1 and len(parts) == 8 and quality_lm.own_cost(points) == pytest.approx(own)
        assert all((np.concatenate([p[i] for p in parts]) == whole[0][i]).all() for i in (0, 1))

    def test_thresholds_and_keep(self, spark, monkeypatch):
        """Quantiles by language and band written out, and what they keep."""
        monkeypatch.setattr(quality_lm, "MIN_BAND", 20)
        monkeypatch.setattr(quality_lm.thresholds, "__defaults__", (20,))
        rows, junk = self.rows()
        docs = spark.createDataFrame(rows + junk, "doc_id long, text string, lang string")
        labels = spark.createDataFrame([(i, 1, 0) for i, _, _ in rows[:200]], "doc_id long, quality int, toxic int")
        told = quality_lm.judge(docs, labels, quantile=0.9).collect()
        trusted = {i for i, _, _ in rows[:200]}
        size = {i: len(t) + 1 for i, t, _ in rows + junk}
        band = lambda r: min(max(int(np.log2(size[r.id])), 5), 14)
        for r in told:
            peers = [x for x in told if x.id in trusted and x.model == r.model]
            near = [x for x in peers if band(x) == band(r)]
            rank = lambda values, q: sorted(values)[max(0, int(np.ceil(q * len(values) - 1e-9)) - 1)]
            limit = rank([x.perplexity for x in (near if len(near) >= 20 else peers)], 0.9)
            least = rank([x.own_perplexity for x in near], 0.1) if len(near) >= 20 else None
            assert (r.threshold, r.least_own) == (limit, least)
            assert r.keep == (r.perplexity <= limit and (least is None or r.own_perplexity >= least))
        assert {r.keep for r in told} == {True, False}

    def test_without_trusted_or_rows(self, spark):
        docs = spark.createDataFrame([(1, "a", "en")], "doc_id long, text string, lang string")
        none = spark.createDataFrame([], "doc_id long, quality int, toxic int")
        assert quality_lm.judge(docs, none).first().keep and quality_lm.keep_good(docs, none).count() == 1
        assert quality_lm.judge(docs.limit(0), none).count() == 0


class TestLanguage:
    def test_held_out_accuracy_and_odd_rows(self, spark):
        rng = random.Random(6)
        rows = []
        for i in range(240):
            lang = rng.choice(list(PROSE))
            rows.append((i, prose(rng, lang, rng.randint(3, 60)), lang, 0.5))
        odd = [(1000, None, "en", 0.1), (1001, "", None, 0.1), (1002, "123 !? ²", "en", 0.1), (None, PROSE["de"], "de", 0.1), (1003, PROSE["fr"] * 3000, None, 0.1), (5, *rows[5][1:])]
        df = spark.createDataFrame(rows + odd, "doc_id long, text string, lang string, score double")
        model = language_id.train(df)
        assert model.languages == ["de", "en", "fr"]
        got = language_id.predict(df, model)
        assert {"lang_pred", "score_"} <= set(got.columns) and got.count() == len(rows) + len(odd)
        told = got.withColumn("held", language_id.held_out(F.col("doc_id"))).collect()
        test = [r for r in told if r.held and r.doc_id < 1000]
        assert len(test) > 30 and sum(r.lang_pred == r.lang for r in test) >= 0.97 * len(test)
        by = {r.doc_id: r for r in told}
        assert [by[i].lang_pred for i in (1000, 1001, 1002)] == ["und"] * 3 and by[None].lang_pred == "de" and by[1003].lang_pred == "fr"
        assert all(0 <= r.score_ <= 1 for r in told)

    def test_score_is_the_kernel_model(self, spark):
        """Kernels, Nyström map and ridge regression written out over sets of strings."""
        rng = random.Random(7)
        train = [(i, prose(rng, lang, 12), lang) for i, lang in enumerate(["en", "de", "fr"] * 14)]
        asked = [(1000 + i, prose(rng, lang, 9), None) for i, lang in enumerate(["en", "de", "fr", "de"])] + [(2000, "łódź 東京 ß", None)]
        df = spark.createDataFrame(train + asked, "doc_id long, text string, lang string")
        marks, ridge = 10, 0.02
        model = language_id.train(df, landmarks=marks, ridge=ridge)
        grams = lambda t: {t.lower()[i : i + n] for n in (1, 2, 3) for i in range(len(t) - n + 1)}
        kernel = lambda a, b: len(grams(a) & grams(b)) / math.sqrt(len(grams(a)) * len(grams(b)))
        sample = [(r["rank"], r.turn, r.lang, r.text) for r in language_id.sample_rows(df, id_col="doc_id", text="text", lang="lang", max_rows=2000).collect()]
        learned = [i for i, _, _ in train if zlib.crc32(str(i).encode()) % 4 != 2]
        assert sorted(t for *_, t in sample) == sorted(t for i, t, _ in train if i in learned)
        landmarks = [t for *_, t in sorted(sample)[:marks]]
        k_mm = np.array([[kernel(a, b) for b in landmarks] for a in landmarks])
        k_nm = np.array([[kernel(t, b) for b in landmarks] for *_, t in sample])
        languages = sorted({lang for _, _, lang, _ in sample})
        y = np.array([[1.0 if lang == name else -1.0 for name in languages] for _, _, lang, _ in sample])
        # ridge regression on Nyström features z = k_m K_mm^(-1/2), solved for weights on the kernels themselves
        w = np.linalg.solve(k_nm.T @ k_nm + ridge * len(sample) * k_mm, k_nm.T @ y)
        want = np.array([[kernel(t, b) for b in landmarks] for _, t, _ in asked]) @ w
        got = language_id.Scorer(model).scores([t for _, t, _ in asked])
        assert model.languages == languages and got == pytest.approx(want, rel=1e-3, abs=1e-4)
        told = {r.doc_id: r for r in language_id.predict(df, model).collect()}
        for (i, _, _), values in zip(asked, want, strict=True):
            assert told[i].lang_pred == languages[int(values.argmax())]
            assert told[i].score == pytest.approx(min(1, max(0, (1 + values.max()) / 2)), abs=1e-3)

    def test_long_texts_in_chunks(self, monkeypatch):
        text = "".join(random.Random(9).choices("abcdefß東", k=3000))
        whole = language_id.ngrams(text)
        monkeypatch.setattr(language_id, "CHUNK", 250)
        assert (language_id.ngrams(text) == whole).all() and len(whole) == len({text[i : i + n] for n in (1, 2, 3) for i in range(len(text) - n + 1)})

    def test_nothing_to_learn(self, spark):
        df = spark.createDataFrame([(1, "words", None)], "doc_id long, text string, lang string")
        assert language_id.predict(df, language_id.train(df)).first().lang_pred == "und"
        assert language_id.predict(df.limit(0), language_id.train(df.limit(0))).count() == 0


def test_pipeline(spark, sf):
    """Each stage keeps its promise on what its predecessor kept."""
    pipeline = pytest.importorskip("corpus_pipeline")
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    columns = docs.columns
    seen = []
    for name, stage in pipeline.STAGES:
        out = stage(spark, docs, sf).cache()
        seen.append(out.count())
        if name != "bpe":
            assert out.columns == columns
        if name == "line_dedup":
            counts = {}
            for r in docs.collect():
                for key in {x.strip(" \t\n\x0b\x0c\r").lower() for x in r.text.split("\n")} - {""}:
                    counts[key] = counts.get(key, 0) + 1
            for r in out.collect():
                assert all(counts.get(x.strip(" \t\n\x0b\x0c\r").lower(), 0) < 10 for x in r.text.split("\n")) and r.n_chars == len(r.text)
        if name == "simhash_near_dedup":
            assert out.select("doc_id").distinct().count() == seen[-1] < seen[-2]
        docs = out
    assert seen[0] >= seen[1] >= seen[2] and seen[3] == seen[4]
    assert pipeline.run(spark, sf).count() == seen[-1]
    labels = spark.read.parquet(f"{sf}/labels.parquet").where("quality = 1 and toxic = 0")
    first = pipeline.STAGES[0][1](spark, spark.read.parquet(f"{sf}/documents.parquet"), sf)
    assert first.join(labels, "doc_id").count() >= 0.99 * labels.count()
