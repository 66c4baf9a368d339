"""Every registered operator query against plain Python, on a table with null, empty, long, repeated and odd rows, and on an empty one."""

from __future__ import annotations

import hashlib
import random
import re
import struct
import zlib

import numpy as np
import pytest

from mapforge.llm import bpe, neardup, queries

RNG = random.Random(21)
LONG = " ".join(RNG.choice(["alpha", "beta", "gamma's", "délta", "12", "x!y", "wörd"]) for _ in range(9000))
CARD = "4539 1488 0343 6467"
TEXTS = [
    (1, "Mail a.b@c.org, A_1@x-y.co.uk. or @no.where, call +49 (30) 123-4567 or 10.0.0.255, 1.2.3.4.5, 256.1.1.1, 01.02.03.04"),
    (2, f"card {CARD} and {CARD.replace(' ', '-')} not 4539 1488 0343 6468, id 12345678901234567890 +1.2 +12345678"),
    (3, "Licensed under the Apache License, version 2.0!\nReleased under the MIT License."),
    (4, 'x token = "04dbebab91ab85687d33eeaaf9ac699e1188f962" y'),
    (5, LONG), (6, LONG + " end"), (6, LONG + " end"), (7, None), (8, ""), (8, None), (None, "no id, a@b.cd"), (None, "no id, a@b.cd"),
    (9, "\x00\x01 control\tchars\r\n½ é 中文 <|endoftext|> <|STARTOFTEXT|>"), (10, "a" * 9000), (11, " \n \n"), (12, "same line of enough length\nsame line of enough length\nsame line of enough lengths"),
    (13, "idiot scum " * 9), (14, "+" * 50 + "1" * 50 + "@" * 50 + "." * 50), (15, "a@b@c.d.e@f.g 1.1.1.1.1.1.1.1"),
]


@pytest.fixture(scope="module")
def folders(spark, tmp_path_factory):
    full, empty = (tmp_path_factory.mktemp(n) for n in ("full", "none"))
    docs = spark.createDataFrame([(k, t, "en", "web", 0, "clash") for k, t in TEXTS], "doc_id long, text string, lang string, source string, n_chars long, spans string")
    labels = spark.createDataFrame([(k, 1, int(k == 13)) for k in range(1, 16)] + [(None, 1, 1), (3, 0, None)], "doc_id long, quality int, toxic int")
    rng = np.random.default_rng(1)
    x = rng.normal(size=(12, 8))
    vecs = [(k, v.tolist(), k) for k, v in enumerate(np.concatenate([x, x[:3] * 1.5 + 0.01]))] + [(90, None, 1), (91, [0.0] * 8, 1), (92, [1.0, 2.0], 1), (None, x[0].tolist(), 2)]
    for folder, n in ((full, 10**6), (empty, 0)):
        docs.limit(n).write.parquet(f"{folder}/documents.parquet")
        labels.limit(n).write.parquet(f"{folder}/labels.parquet")
        spark.createDataFrame(vecs, "vec_id long, embedding array<float>, label int").limit(n).write.parquet(f"{folder}/embeddings.parquet")
    return str(full), str(empty)


@pytest.fixture(scope="module")
def run(spark, folders):
    known = {name.split("_")[0]: f for name, f in queries.queries().items()}
    return lambda op: known[op](spark, folders[0]).collect()


def _sorted(rows):
    return sorted(rows, key=lambda r: tuple((x is None, x if x is not None else 0) for x in r))


@pytest.mark.parametrize("op", [f"op{n}" for n in range(1, 11)])
def test_an_empty_table_gives_no_rows(spark, folders, op):
    f = next(f for name, f in queries.queries().items() if name.startswith(f"{op}_"))
    assert f(spark, folders[1]).collect() == []


def _luhn(digits: str) -> bool:
    return sum(int(d) if k % 2 == 0 else sum(divmod(2 * int(d), 10)) for k, d in enumerate(reversed(digits))) % 10 == 0


def base_spans(text: str) -> list[tuple[str, int, int]]:
    digits = lambda m: re.sub("[^0-9]", "", m)
    kinds = {
        "email": (r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+", lambda m: True),
        "ip": (r"[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)", lambda m: all(int(x) <= 255 for x in m.split("."))),
        "card": (r"[0-9]([\x20-]?[0-9])+", lambda m: 16 <= len(digits(m)) <= 19 and _luhn(digits(m))),
        "phone": (r"\+[0-9][\x20().0-9-]+[0-9]", lambda m: 8 <= len(digits(m)) <= 15),
    }
    return [(k, m.start(), m.end()) for k, (p, good) in kinds.items() for m in re.finditer(p, text) if good(m[0])]


def test_op1_reports_planted_notices(run):
    rows = [(r["doc_id"], r["license"], TEXTS[2][1][r["start"] : r["end"]], r["coverage"]) for r in run("op1")]
    assert rows == [(3, "Apache-2.0", "Licensed under the Apache License, version 2.0", 1.0), (3, "MIT", "Released under the MIT License", 1.0)]


def test_op2_base_spans(run):
    want = []
    for k, t in TEXTS:
        spans = base_spans(t or "")
        said = ",".join(f"{x}:{a}:{b}" for x, a, b in spans)
        want.append((k, *[sum(s[0] == x for s in spans) for x in ("email", "ip", "card", "phone")], hashlib.sha256(said.encode()).hexdigest()))
    got = run("op2")
    assert _sorted([tuple(r)[:6] for r in got]) == _sorted(want) and sum(w[3] for w in want) == 2
    for r in got:
        spans = set(filter(None, r["spans"].split(",")))
        text = [t or "" for k, t in TEXTS if k == r["doc_id"]]
        assert any({f"{x}:{a}:{b}" for x, a, b in base_spans(t)} <= spans for t in text) and r["n_spans"] == len(spans)


def test_op3_removes_repeated_lines(run):
    got = {r["doc_id"]: r for r in run("op3")}
    assert (got[12]["removed"], got[12]["removed_near"], got[12]["n_chars"]) == (2, 1, len("same line of enough length"))
    assert got[7]["n_chars"] is None and got[11]["n_chars"] == 4 and got[5]["removed"] == 0 and len(run("op3")) == len(TEXTS)


def test_op4_columns(run):
    rows = run("op4")
    assert len(rows) == len(TEXTS)
    for r in rows:
        assert r["held_out"] == (None if r["doc_id"] is None else zlib.crc32(str(r["doc_id"]).encode()) % 5 == 0)
        assert 0 <= r["score"] <= 1 and r["predicted"] == int(r["score"] >= 0.5)


def test_op5_rows(run):
    rows = {r["vec_id"]: r for r in run("op5")}
    assert len(rows) == 19 and {k for k, r in rows.items() if r["n_links"]} == {0, 1, 2, 12, 13, 14, None}
    assert rows[12]["component_id"] == 0 and not rows[12]["kept"] and rows[None]["component_id"] == 0 and rows[90]["kept"] and rows[92]["n_links"] == 0


def _png_samples(data: bytes) -> bytes:
    at, body = 8, b""
    width, height = struct.unpack(">II", data[16:24])
    while at < len(data):
        (n,) = struct.unpack(">I", data[at : at + 4])
        assert struct.unpack(">I", data[at + 8 + n : at + 12 + n])[0] == zlib.crc32(data[at + 4 : at + 8 + n])
        body += data[at + 8 : at + 8 + n] if data[at + 4 : at + 8] == b"IDAT" else b""
        at += 12 + n
    raw = zlib.decompress(body)
    return b"".join(raw[k * (width + 1) + 1 : (k + 1) * (width + 1)] for k in range(height))


def test_op6_payloads_and_stored_forms(run):
    from mapforge.llm import media

    want = []
    for k, t in TEXTS:
        raw = (t or "").encode()
        payload = raw + b"\xff" * (max(576, -(-len(raw) // 576) * 576) - len(raw))
        stored = media.to_png(payload)
        assert _png_samples(stored) == payload
        want.append((k, len(raw), len(payload), hashlib.sha256(payload).hexdigest(), zlib.crc32(payload[-32:]), len(stored), hashlib.sha256(stored).hexdigest()))
    got = run("op6")
    assert _sorted([tuple(r)[:7] for r in got]) == _sorted(want)
    assert all(r["feature"].startswith(f"png 576x{r['payload_bytes'] // 576}x8") and r["width"] * r["height"] == r["payload_bytes"] for r in got)


def test_op7_classes(run):
    sets = [set(neardup.shingles(t).tolist()) for _, t in TEXTS]
    near = [[bool(s) and bool(o) and 5 * len(s & o) >= 4 * len(s | o) for o in sets] for s in sets]
    home = list(range(len(sets)))
    for _ in sets:
        for i, row in enumerate(near):
            for j, hit in enumerate(row):
                if hit:
                    home[i] = home[j] = min(home[i], home[j])
    least = {h: min((k for (k, _), x in zip(TEXTS, home) if x == h and k is not None), default=None) for h in home}
    want = [(k, least[h], sum(near[i]) - near[i][i]) for i, ((k, _), h) in enumerate(zip(TEXTS, home))]
    assert _sorted([(r["doc_id"], r["class_id"], r["n_links"]) for r in run("op7")]) == _sorted(want)


def _ids(text):
    from tokenizers import Tokenizer

    t = Tokenizer.from_file(bpe.vocabulary_path())
    ids = t.encode(text or "", add_special_tokens=False).ids
    return ids, t.decode(ids, skip_special_tokens=False)


def test_op8_ids_and_texts(run):
    want = []
    for k, t in TEXTS:
        ids, back = _ids(t)
        want.append((k, len(ids), hashlib.sha256(np.array(ids, "<u4").tobytes()).hexdigest(), hashlib.sha256(back.encode()).hexdigest()))
    assert _sorted([tuple(r) for r in run("op8")]) == _sorted(want)


def test_op9_pieces(run):
    rows = run("op9")
    want = []
    for k, t in TEXTS:
        ids = [*_ids(t)[0], 2]
        want += [(k, a, len(ids[a : a + 4096]), zlib.crc32(np.array(ids[a : a + 4096], "<u4").tobytes()), len(ids)) for a in range(0, len(ids), 4096)]
    assert _sorted([tuple(r)[:5] for r in rows]) == _sorted(want) and rows[0].__fields__[:5] == ["doc_id", "start", "length", "ids_crc32", "doc_tokens"]
    filled = {}
    for r in sorted(rows, key=lambda r: (r["sequence_id"], r["offset"])):
        assert r["offset"] == filled.get(r["sequence_id"], 0)
        filled[r["sequence_id"]] = r["offset"] + r["length"]
    assert max(filled.values()) <= 4096


def test_op10_finds_the_planted_secret(run):
    rows = [r for r in run("op10") if r["doc_id"] == 4]
    assert [(r["start"], r["end"]) for r in rows] == [(11, 51)] and rows[0]["secret_sha256"] == hashlib.sha256(TEXTS[3][1][11:51].encode()).hexdigest()


def test_a_vocabulary_of_other_rules_is_refused():
    with pytest.raises(ValueError):
        bpe.Vocabulary(bpe.vocabulary_path("byte_bpe_50k.json"))
