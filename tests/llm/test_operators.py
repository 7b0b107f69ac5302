"""Each operator against brute force on small texts with nulls, empties, ties, repeats and clashing columns."""

import hashlib
import zlib

import numpy as np
import pyarrow as pa
import pytest

from pathwindow.llm import decontaminate, embeddings, lines, packing, pii, quality, simhash, suffixes, token_counts, toxicity
from pathwindow.llm.oracles import ORACLES
from pathwindow.llm.tokens import Encoder

LONG = " ".join(f"word{i % 97} tail{i % 31}" for i in range(6000))
TEXTS = [None, "", " ", "The same line of text here\nand one more line", "the same line of TEXT here\n\nother words", LONG, LONG + " end", "x" * 450, "x" * 450, "a  b \n c <|endoftext|> é😀", "mail me at a.b@example.org or +1 202 555 0147, 10.0.0.255"]
SCHEMA = "doc_id long, text string, node long, shard int, n int, length long"


@pytest.fixture(scope="module")
def docs(spark):
    return spark.createDataFrame([(i, t, 1, 2, 3, 4) for i, t in enumerate(TEXTS)] + [(3, TEXTS[3], 1, 2, 3, 4)], SCHEMA)


@pytest.fixture(scope="module")
def none(docs):
    return docs.where("doc_id < 0")


def test_simhash(docs, none):
    rows = {r.doc_id: r for r in simhash.digest(simhash.near_duplicates(docs)).collect()}
    prints = {i: simhash.fingerprint(simhash.shingle_hashes(t or "")) for i, t in enumerate(TEXTS)}
    assert {i: r.fingerprint for i, r in rows.items()} == {i: f"{p:016x}" for i, p in prints.items()}
    ids = list(prints)
    group = {i: i for i in ids}
    for _ in ids:
        for i in ids:
            for j in ids:
                if (prints[i] ^ prints[j]).bit_count() <= 3:
                    group[i] = group[j] = min(group[i], group[j])
    assert {i: r.component_id for i, r in rows.items()} == group
    assert simhash.near_duplicates(none).count() == 0


def test_simhash_trees_lose_no_link(spark):
    rng = np.random.default_rng(2)
    base = rng.integers(0, 1 << 63, 3000, dtype=np.uint64)
    near = base[:500] ^ (np.uint64(1) << rng.integers(0, 63, 500).astype(np.uint64)) ^ (np.uint64(1) << rng.integers(0, 63, 500).astype(np.uint64))
    fps = np.unique(np.concatenate([base, near]))
    frame = spark.createDataFrame([(int(f), 0, i) for i, f in enumerate(fps.view(np.int64))], "fp long, n int, node long")
    pairs = np.argwhere(np.triu(np.bitwise_count(fps[:, None] ^ fps[None, :]) <= 3, 1))
    found = simhash.link_fingerprints(frame, shard=128).collect()
    join = lambda links: simhash._roots(len(fps), np.array([p[0] for p in links]), np.array([p[1] for p in links])).tolist()
    assert join(found) == join(pairs)


def test_packing(docs, none):
    rows = packing.pack(docs).collect()
    whole, want = _whole_tokenizer(), []
    for i, t in [*enumerate(TEXTS), (3, TEXTS[3])]:
        ids = np.array([*whole.encode(t or "", add_special_tokens=False).ids, 0], "<u4")
        start = 0
        for piece, length in enumerate([n for n in [len(ids) % 2048] if n] + [2048] * (len(ids) // 2048)):
            want.append((i, piece, start, length, zlib.crc32(ids[start : start + length].tobytes())))
            start += length
    assert sorted((r.doc_id, r.piece, r.start, r.length, r.ids_crc32) for r in rows) == sorted(want)
    by: dict = {}
    for r in rows:
        by.setdefault(r.sequence_id, []).append((r.offset, r.length))
    for slots in by.values():
        at = 0
        for offset, length in sorted(slots):
            assert offset == at
            at += length
        assert at <= 2048
    assert packing.pack(none).count() == 0


def test_packing_plan_places_every_rank_once():
    rng = np.random.default_rng(1)
    counts = {int(k): int(n) for k, n in zip(rng.choice(np.arange(1, 2049), 300, False), rng.integers(1, 40, 300), strict=True)}
    plan = packing.Plan(counts)
    length = np.repeat(list(counts), list(counts.values()))
    rank = np.concatenate([np.arange(n) for n in counts.values()])
    bins, offset = plan.place(length, rank)
    order = np.lexsort([offset, bins])
    b, o, n = bins[order], offset[order], length[order]
    same = b[1:] == b[:-1]
    assert (o[1:][same] == (o + n)[:-1][same]).all() and (o[1:][~same] == 0).all() and (o + n).max() <= 2048
    assert plan.bins >= -(-int(length.sum()) // 2048) and plan.bins <= 1.1 * length.sum() / 2048 + 2


def test_ids_equal_the_whole_text_tokenizer(docs):
    import public_tokenizers
    from tokenizers import Tokenizer

    whole = Tokenizer.from_file(public_tokenizers.path("byte_bpe_50k.json"))
    coder = Encoder()
    for t in [*TEXTS, "  lead", "trail ", "tab\tin", "a\n b", "x \n y", "don't  stop", "a <|endoftext|> b", "<|endoftext|><|endoftext|>x  <|endoftext|>", "<|endof text|>"]:
        assert np.frombuffer(coder.ids(t or ""), "<u4").tolist() == whole.encode(t or "", add_special_tokens=False).ids


def test_token_counts_after_edits():
    coder = Encoder()
    text = LONG[:3000]
    tree = token_counts.TokenTree(text, coder, size=4)
    for start, end, new in ((0, 5, "new start"), (100, 100, " "), (700, 900, ""), (50, 51, "\n\n x"), (10**6, 10**6, " end")):
        a = min(start, len(text))
        text = text[:a] + new + text[max(a, min(end, len(text))) :]
        tree.edit(start, end, new)
        assert tree.text() == text and tree.tokens == coder.count(text)


def _whole_tokenizer():
    import public_tokenizers
    from tokenizers import Tokenizer

    return Tokenizer.from_file(public_tokenizers.path("byte_bpe_50k.json"))


def test_token_trees_stay_exact_under_random_edits():
    coder, rng, whole = Encoder(), np.random.default_rng(7), _whole_tokenizer()
    bits = ["one", " two", "  ", "\n", " <|endoftext|>", "<|endoftext|>", "three ", "", "é😀", " a b c d e f g h i j k l m", "\t x"]
    for _ in range(40):
        text = "".join(rng.choice(bits, rng.integers(0, 30)))
        tree = token_counts.TokenTree(text, coder, size=2)
        for _ in range(12):
            a = int(rng.integers(0, len(text) + 2))
            b, new = a + int(rng.integers(0, 12)), str(rng.choice(bits))
            text = text[:a] + new + text[max(min(a, len(text)), b) :]
            tree.edit(a, b, new)
            assert tree.text() == text and tree.chars == len(text) and tree.tokens == len(whole.encode(text, add_special_tokens=False).ids)


def test_edits_encode_only_what_they_touch():
    coder = Encoder()
    words = [f"word{i % 997}" for i in range(20_000)]
    text = " ".join(words)
    for step in (20, 60):
        edits, at = [], 0
        for i, w in enumerate(words):
            if i % step == 0:
                edits.append((at, at + len(w), "[name]"))
            at += len(w) + 1
        for order in (edits[::-1], sorted(edits, key=lambda e: e[0] * 7919 % 10007)):
            tree = token_counts.TokenTree(text, coder)
            leaf = max(map(len, tree.leaves))
            moved = 0
            for a, b, new in order:
                shift = sum(len(n) - (y - x) for x, y, n in order[:moved] if x < a)
                tree.edit(a + shift, b + shift, new)
                moved += 1
            assert tree.encoded <= 2 * len(edits) * leaf and len(tree.leaves) >= len(words) // 64


def test_token_counts(spark, docs, none):
    whole = _whole_tokenizer()
    edits = lambda t: [(0, 3, "X y"), (len(t) // 2, len(t) // 2 + 9, ""), (10**9, 10**9, " tail")] if t else []

    def after(t):
        for a, b, new in edits(t):
            t = t[: min(a, len(t))] + new + t[min(b, len(t)) :]
        return t

    n = lambda t: len(whole.encode(t, add_special_tokens=False).ids)
    rows = sorted((r.doc_id, r.n_tokens, r.n_edits, r.n_tokens_after) for r in token_counts.count_tokens(docs, edits).collect())
    assert rows == sorted((i, n(t or ""), len(edits(t or "")), n(after(t or ""))) for i, t in [*enumerate(TEXTS), (3, TEXTS[3])])
    assert token_counts.count_tokens(none).count() == 0
    for r in token_counts.count_tokens(docs).collect():
        t = TEXTS[r.doc_id] or ""
        for a, b, new in token_counts.redactions(t):
            t = t[:a] + new + t[b:]
        assert r.n_tokens_after == n(t)


def test_embeddings(spark):
    rng = np.random.default_rng(4)
    base = rng.normal(size=(40, 64))
    v = np.concatenate([base, base[:20] + 0.15 * rng.normal(size=(20, 64)), base[:3]]).astype(np.float32)
    rows = [(i, x.tolist(), i % 2 if i < 60 else (i - 60) % 2) for i, x in enumerate(v)]
    rows += [(100, None, 1), (101, [0.0] * 64, 1), (102, [float("nan")] * 64, 1), (103, v[0].tolist(), None), (104, [], 0)]
    out = {r.vec_id: r for r in embeddings.near_duplicates(spark.createDataFrame(rows, "vec_id long, embedding array<float>, label int")).collect()}
    e = v.astype(float)
    e /= np.linalg.norm(e, axis=1, keepdims=True)
    label = np.array([r[2] for r in rows[: len(v)]])
    linked = (e @ e.T >= 0.93) & (label[:, None] == label[None, :])
    assert [out[i].n_links for i in range(len(v))] == (linked.sum(axis=1) - 1).tolist()
    assert all(out[i].n_links == 0 and out[i].kept and out[i].component_id == i for i in range(100, 105))


def test_e8_decoding_is_nearest():
    y = np.random.default_rng(0).normal(size=(200, 8)) * 2
    point = embeddings.decode(y)
    near = point[:, None, :] + embeddings.NEAREST[None, :, :]
    assert (((y - point) ** 2).sum(1) <= ((y[:, None, :] - near) ** 2).sum(2).min(1) + 1e-9).all()


def _repeats(raws):
    count: dict = {}
    for r in raws:
        for i in range(len(r) - 199):
            count[r[i : i + 200]] = count.get(r[i : i + 200], 0) + 1
    for r in raws:
        gone = np.zeros(len(r), bool)
        for i in range(len(r) - 199):
            if count[r[i : i + 200]] > 1:
                gone[i : i + 200] = True
        yield hashlib.sha256(bytes(np.frombuffer(r, np.uint8)[~gone])).hexdigest(), int(gone.sum())


def test_suffixes(spark, none):
    rng = np.random.default_rng(3)
    pool = ["".join(rng.choice(list("abcd é"), 150)) for _ in range(6)]
    texts = ["".join(pool[k] for k in rng.integers(0, 6, 5)) for _ in range(30)] + [None, "", "short", "x" * 450, pool[0] + "1" + pool[1]]
    frame = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    want = dict(enumerate(_repeats([(t or "").encode() for t in texts])))
    for hot in (suffixes.HOT, 1):
        assert {r.doc_id: (r.kept_sha256, r.n_removed) for r in suffixes.remove_repeats(frame, hot=hot).collect()} == want
    assert suffixes.remove_repeats(none).count() == 0


def test_difference_cover():
    cover = suffixes.difference_cover(57)
    assert {(a - b) % 57 for a in cover for b in cover} == set(range(57)) and len(cover) <= 12


def test_decontamination(spark, none):
    item = " ".join(f"w{i}" for i in range(20))
    bench = spark.createDataFrame([("1", item), ("2", "Short one"), ("3", None), ("4", "!!")], "item_id string, text string")
    rows = [(0, "x " + item.upper() + " y"), (1, "a short, ONE b"), (2, None), (3, " ".join(f"w{i}" for i in range(12))), (4, " ".join(f"w{i}" for i in range(13)) + " z" * 400)]
    out = {r.doc_id: r for r in decontaminate.find_contamination(spark.createDataFrame(rows, "doc_id long, text string"), bench).collect()}
    assert (out[0].n_hit, out[0].n_items, out[0].contaminated) == (20, 1, True)
    assert (out[1].n_hit, out[1].contaminated, out[2].n_words, out[3].n_hit) == (2, True, 0, 0)
    assert (out[4].n_hit, out[4].contaminated) == (13, False)


def test_decontamination_counts_items_without_an_id(spark):
    words = " ".join(f"w{i}" for i in range(15))
    bench = spark.createDataFrame([(None, words), ("2", "other words")], "item_id string, text string")
    docs = spark.createDataFrame([(0, words), (1, "clean"), (2, words + " other words")], "doc_id long, text string")
    out = {r.doc_id: (r.n_hit, r.n_items, r["items"], r.contaminated) for r in decontaminate.find_contamination(docs, bench).collect()}
    assert out == {0: (15, 1, [], True), 1: (0, 0, [], False), 2: (17, 2, ["2"], True)}
    assert [r.doc_id for r in decontaminate.keep_clean(docs, bench).collect()] == [1]
    duckdb = pytest.importorskip("duckdb").connect()
    for name, frame in (("documents", docs), ("benchmark", bench)):
        duckdb.register(name, pa.table({c: [r[c] for r in frame.collect()] for c in frame.columns}))
    want = sorted(duckdb.sql(ORACLES["op5_decontaminate"]).fetchall())
    for limit in (decontaminate.GROUP_BYTES, 20):  # in one pass, and item by item
        rows = decontaminate.digest(decontaminate.find_contamination(docs, bench, group_bytes=limit)).drop("runs").collect()
        assert sorted(map(tuple, rows)) == want
        assert [r.doc_id for r in decontaminate.keep_clean(docs, bench, group_bytes=limit).collect()] == [1]


def test_lines(docs, none):
    gone = {(r.doc, r.line) for r in lines.removed_lines(docs).collect()}
    assert gone >= {(4, 0), (8, 0)} and (3, 0) not in gone and not any(d in (0, 1, 2) for d, _ in gone)
    assert lines.removed_lines(none).count() == 0


def test_lines_of_null_and_repeated_ids_are_kept_apart(spark):
    same = "one line that many documents have\nand this one"
    rows = [(None, "alpha beta gamma\n" + same), (None, "delta epsilon\nzeta eta theta"), (None, "iota kappa\nand this one\nlambda"), (5, "mu nu xi\nzeta eta theta"), (5, "omikron pi\nrho sigma"), (5, "omikron pi\nrho sigma"), (6, "tau\n" + same)]
    frame = spark.createDataFrame(rows, "doc_id long, text string")
    removed = lines.removed_lines(frame)
    left = [r.text for r in lines.rewrite(frame, removed).collect()]
    found = [w for t in left for w in t.split("\n") if w]
    kinds = {w for _, t in rows for w in t.split("\n")}
    assert set(found) == kinds and {w for w in kinds if found.count(w) > 1} == {"omikron pi", "rho sigma"}
    assert {"mu nu xi", "omikron pi\nrho sigma", "tau"} <= set(left) and left.count("omikron pi\nrho sigma") == 2
    out = lines.digest(frame, removed).collect()
    assert len(out) == len(rows) and sum(r.n_removed for r in out) == 4 and {r.removed for r in out if r.doc_id == 6} == {"1,2"}


def _removed_by_brute_force(rows, threshold=0.8):
    """Every line of (doc, text) that has an earlier line of a similarity of at least the threshold."""
    every = [(d, k, lines.words_of(line)) for d, t in rows for k, line in enumerate((t or "").split("\n")) if line.split()]
    gone = set()
    for i, (d, k, s) in enumerate(every):
        if any(len(s & t) >= threshold * len(s | t) - 1e-9 for _, _, t in every[:i]):
            gone.add((d, k))
    return gone


@pytest.mark.parametrize("sizes", [{}, {"crowd": 8, "group": 6}])
def test_lines_equal_brute_force(spark, sizes):
    """With sizes: very frequent words and large groups, at the size of a test."""
    rng = np.random.default_rng(8)
    common, rare = [f"the{i}" for i in range(12)], [f"rare{i}word" for i in range(400)]
    families = [[*rng.choice(rare, rng.integers(0, 30), False), *rng.choice(common, rng.integers(1, 10), False)] for _ in range(25)]
    rows = []
    for d in range(70):
        made = []
        for _ in range(rng.integers(0, 5)):
            words = list(families[rng.integers(0, len(families))])
            for _ in range(rng.integers(0, 4)):
                at = rng.integers(0, len(words) + 1)
                words[at : at + rng.integers(0, 2)] = [str(rng.choice(rare))]
            rng.shuffle(words)
            made.append(" ".join(words) + ["", " ", "\t", " \r"][rng.integers(0, 4)])
        rows.append((d, "\n".join(made) if made else [None, "", " \n "][d % 3]))
    rows.append((70, "one " * 70_000 + "\n" + " ".join(f"very{i}" for i in range(3_000)) + "\n" + " ".join(f"very{i}" for i in range(40, 3_000)) + "\none"))
    frame = spark.createDataFrame(rows, "doc_id long, text string")
    assert {(r.doc, r.line) for r in lines.removed_lines(frame, **sizes).collect()} == _removed_by_brute_force(rows)


def _line_rows():
    """Near copies and copies of some families of lines, dealt over many documents, some of whose words only change places."""
    rng = np.random.default_rng(21)
    families = [[f"fam{f}word{i}" for i in range(12)] for f in range(6)]
    rows = []
    for d in range(60):
        words = list(families[d % 6])
        if d % 4 == 3:
            words[int(rng.integers(0, 12))] = f"own{d}"
        rng.shuffle(words)
        rows.append((d, " ".join(words) + f"\nline of {d} alone"))
    return rows


@pytest.mark.parametrize("bits", [64, 1])
def test_lines_whose_hashes_clash_are_proved_by_words(spark, bits):
    """With one bit nearly all sets have equal hashes, which their words disprove: every set then meets all others."""
    rows = _line_rows()
    frame = spark.createDataFrame(rows, "doc_id long, text string")
    assert {(r.doc, r.line) for r in lines.removed_lines(frame, bits=bits).collect()} == _removed_by_brute_force(rows)


def test_copies_of_a_line_meet_others_once():
    """Of a set's copies the first alone is proposed to near lines by the prefix words; the whole set's hash proposes the copies."""
    n, size = 500, 10
    token, doc = np.repeat(np.arange(1, 4, dtype=np.int64) << 56, n), np.tile(np.arange(n), 3)
    whole = np.where(doc % 100 == 7, doc + 1, 77)  # five near lines among copies
    columns = [token, doc, np.zeros(3 * n, np.int64), np.zeros(3 * n, np.int32), np.full(3 * n, size << 32), np.where(whole == 77, 0, 1 << doc // 100), np.zeros(3 * n, np.int64), whole]
    found = lines._Meetings(columns, lines.THRESHOLD, lines.CROWD, lines.GROUP).rows().to_pylist()
    pairs = {(r["doc"], r["ydoc"]) for r in found if r["kind"] == lines.PAIR}
    assert {x for x, _ in pairs} == {7, 107, 207, 307, 407} and (7, 0) in pairs
    assert len(found) <= 3 * (5 * 2 + 6)


def test_packed_postings_come_back_whole():
    rng = np.random.default_rng(3)
    columns = [rng.integers(-(1 << 62), 1 << 62, 5_000) for _ in lines.POSTING]
    columns[3] = rng.integers(0, 1 << 30, 5_000).astype(np.int32)
    columns[0][:700] = 77
    packed = lines._packed(columns, 300)
    part, rows = packed.column(0).to_pylist(), packed.column(1).to_pylist()
    assert part == sorted(set(part)) and 200 < len(part) <= 300
    back = lines._unpacked(rows)
    assert sorted(zip(*(c.tolist() for c in back))) == sorted(zip(*(c.tolist() for c in columns)))
    assert sum(77 in lines._unpacked([r])[0] for r in rows) == 1
    assert all(len(c) == 0 for c in lines._unpacked(lines._packed([c[:0] for c in columns], 300).column(1).to_pylist() or [b""]))


def test_personal_data():
    found = {k: v for k, v in pii.base_spans(TEXTS[-1]).items()}
    assert [TEXTS[-1][a:b] for a, b in found["email"]] == ["a.b@example.org"] and len(found["ip"]) == 1 and len(found["phone"]) == 1
    assert pii.luhn("4111111111111111") and pii.mod97("GB82WEST12345698765432")
    assert pii.base_spans("card 4111 1111-1111 1111")["card"] == [(5, 24)] and not pii.base_spans("1.2.3.256")["ip"]
    assert [k for _, _, k, _ in pii.spans_of("iban GB82 WEST 1234 5698 7654 32")].count("iban") == 1
    key = "04dbebab91ab85687d33eeaaf9ac699e1188f962"
    assert [(k, f'token = "{key}"'[a:b]) for a, b, k, _ in pii.spans_of(f'token = "{key}"') if k == "secret"] == [("secret", key)]
    assert not any(k == "secret" for t in ("token: aaaaaaaaaaaaaaaa", "the secret of success", "password = changechange", "token = see1") for *_, k, _ in pii.spans_of(t))
    import re

    wild = "a@b.c_d@e.f @x a@@b.c " + "9" * 5000 + " 1.2.3.4.5.6.7.8 " + "q" * 5000 + "@z.y"
    assert pii.base_spans(wild)["email"] == [m.span() for m in re.finditer(r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+", wild)]


def _base_by_regex(text):
    import re

    kinds = {
        "email": r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+", "ip": r"[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)",
        "card": r"[0-9]([\x20-]?[0-9])+", "phone": r"\+[0-9][\x20().0-9-]+[0-9]",
    }

    def good(kind, t):
        digits = [int(c) for c in t if c in "0123456789"]
        if kind == "ip":
            return all(int(p) <= 255 for p in t.split("."))
        if kind == "card":
            twice = [d if i % 2 == 0 else d * 2 - 9 * (d > 4) for i, d in enumerate(reversed(digits))]
            return 12 <= len(digits) <= 19 and sum(twice) % 10 == 0
        return kind != "phone" or 9 <= len(digits) <= 15

    spans = [(m.start(), k, m.end(), kind) for k, (kind, p) in enumerate(kinds.items()) for m in re.finditer(p, text) if good(kind, m.group())]
    return [(kind, a, b) for a, _, b, kind in sorted(spans)]


def test_personal_data_equals_brute_force(spark, docs, none):
    rng = np.random.default_rng(12)
    bits = ["a.b@c.de", "x@y", "10.0.0.1", "999.1.1.1", "4111 1111 1111 1111", "4111111111111112", "+1 (202) 555-0147", "+49 30", " ", ", ", "é", "😀", ".", "-", "1", "@", "+", "\n", "378282246310005"]
    texts = [*TEXTS, *("".join(rng.choice(bits, rng.integers(1, 40))) for _ in range(300))]
    frame = spark.createDataFrame([(i, t, "c") for i, t in enumerate(texts)], "doc_id long, text string, spans string")
    out = {r.doc_id: r for r in pii.digest(pii.find_personal_data(frame)).collect()}
    for i, t in enumerate(texts):
        want = _base_by_regex(t or "")
        told = ",".join(f"{k}:{a}:{b}" for k, a, b in want)
        assert out[i].base_sha256 == hashlib.sha256(told.encode()).hexdigest()
        assert [out[i][f"n_{k}"] for k in ("email", "ip", "card", "phone")] == [sum(w[0] == k for w in want) for k in ("email", "ip", "card", "phone")]
        assert set(told.split(",")) <= set(out[i].spans.split(","))
    assert pii.find_personal_data(none).count() == 0


def test_held_out_labels_never_reach_a_model(spark):
    rng = np.random.default_rng(3)
    bad, good = ["vile", "hate", "awful", "filth"], ["calm", "kind", "note", "page", "tree", "river"]
    texts = [" ".join(rng.choice(bad if i % 3 == 0 and k % 2 else good, 1)[0] for k in range(20)) for i in range(240)]
    docs = spark.createDataFrame([(i, t, 0.5) for i, t in enumerate(texts)], "doc_id long, text string, score double")
    fold = lambda i, n: zlib.crc32(str(i).encode()) % n
    label = lambda flip: spark.createDataFrame([(i, int((i % 3 != 0) != (flip and fold(i, 5) == 0)), int((i % 3 == 0) != (flip and fold(i, 4) == 2))) for i in range(240)], "doc_id long, quality int, toxic int")
    told = []
    for flip in (False, True):
        labels = label(flip)
        model = toxicity.fit(docs, labels, held_out=toxicity.held_out("doc_id"))
        toxic = {r.doc_id: (r.held_out, r.score, r.predicted) for r in toxicity.digest(toxicity.score(docs, model)).collect()}
        fine = {r.doc_id: (r.held_out, r.score, r.predicted) for r in quality.digest(quality.classify(docs, labels)).collect()}
        told.append((toxic, fine))
    assert told[0] == told[1]
    for rows, n, at in zip(told[0], (4, 5), (2, 0), strict=True):
        assert {i: r[0] for i, r in rows.items()} == {i: fold(i, n) == at for i in range(240)}
        assert all(p == int(s >= 0.3) for _, s, p in rows.values())


def test_empty_tables_and_clashing_columns(spark, docs, none):
    empty = spark.createDataFrame([], "vec_id long, embedding array<float>, label int, node long, shard int")
    assert embeddings.near_duplicates(empty).count() == 0
    bench = spark.createDataFrame([("1", "x y")], "item_id string, text string")
    assert decontaminate.find_contamination(none, bench).count() == 0
    assert decontaminate.find_contamination(docs, bench.limit(0)).where("n_hit > 0").count() == 0
    more = docs.withColumns({"anchor": docs.n, "content": docs.n, "mark": docs.n, "doc": docs.n, "items": docs.n, "runs": docs.n, "n_hit": docs.n})
    assert suffixes.remove_repeats(more).count() == decontaminate.find_contamination(more, bench.withColumn("doc_id", bench.item_id)).count() == len(TEXTS) + 1


def test_quality_and_toxicity_models_on_tiny_tables(spark, docs):
    labels = spark.createDataFrame([(i, i % 2, i % 2) for i in range(11)] + [(3, None, None)], "doc_id long, quality int, toxic int")
    scored = quality.digest(quality.classify(docs, labels)).collect()
    assert len(scored) == len(TEXTS) + 1 and all(0 <= r.score <= 1 for r in scored)
    model = toxicity.fit(docs, labels, held_out=toxicity.held_out("doc_id"))
    out = toxicity.digest(toxicity.score(docs, model)).collect()
    assert len(out) == len(TEXTS) + 1 and all(0 <= r.score <= 1 for r in out)
    assert {r.doc_id: r.held_out for r in out} == {i: zlib.crc32(str(i).encode()) % 4 == 2 for i in range(len(TEXTS))}


def test_maximal_segments_by_brute_force():
    rng = np.random.default_rng(6)
    for _ in range(200):
        s = rng.integers(-4, 5, rng.integers(1, 12)).astype(float)
        best = max((s[a:b].sum() for a in range(len(s)) for b in range(a + 1, len(s) + 1)), default=0)
        runs = toxicity.maximal_segments(s)
        assert max((r[2] for r in runs), default=0) == max(0, best)
        assert all(abs(s[a:b].sum() - v) < 1e-9 for a, b, v in runs) and all(x[1] <= y[0] for x, y in zip(runs, runs[1:], strict=False))


def test_trees_learn():
    x = np.random.default_rng(0).normal(size=(2000, len(quality.NAMES)))
    y = ((x[:, 3] > 0.2) ^ (x[:, 7] > 0)).astype(float)
    assert ((quality.grow(x, y).probability(x) > 0.5) == y).mean() > 0.95
