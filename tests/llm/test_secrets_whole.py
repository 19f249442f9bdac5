"""Secrets behind the first piece, the first member and the first line are found."""

import base64
import bz2
import gzip
import lzma
import random
import re
import tracemalloc
import urllib.parse
import zlib

import pytest
import zstandard

from semjoin.llm import secrets

SECRET = b"password=hunter2hunter2"


def b64(data: bytes, width: int = 0, end: str = "\n") -> str:
    text = base64.b64encode(data).decode()
    return end.join(text[i : i + width] for i in range(0, len(text), width)) if width else text


def kinds(text: str) -> set[str]:
    return {x[2] for x in secrets.secrets_in(text)[1]}


PACK = {"gzip": lambda b: gzip.compress(b, mtime=0), "zlib": zlib.compress, "bz2": bz2.compress, "xz": lzma.compress, "zstd": zstandard.compress}


@pytest.mark.parametrize("name", PACK)
def test_all_members_and_what_follows(name):
    pack = PACK[name]
    assert f"assign@base64+{name}" in kinds("see " + b64(pack(b"nothing here. ") + pack(SECRET)))
    assert f"assign@base64+{name}" in kinds("see " + b64(pack(SECRET[:12]) + pack(SECRET[12:])))
    assert f"assign@base64+{name}" in kinds("see " + b64(pack(SECRET)[:-1]))
    assert f"assign@base64+{name}" in kinds("see " + b64(pack(SECRET) + b"\0\0\0\0"))
    assert "assign@base64" in kinds("see " + b64(pack(b"nothing here") + b"\n " + SECRET))
    assert "assign@base64+gzip" in kinds("see " + b64(pack(b"nothing here") + PACK["gzip"](SECRET)))


@pytest.mark.parametrize("name", PACK)
def test_an_inner_stream_is_read_behind_its_first_piece(name, monkeypatch):
    noise = bytes(range(128, 256)) * 400
    for piece in (1 << 12, 1 << 23):
        monkeypatch.setattr(secrets, "PIECE", piece)
        for outer in PACK:
            assert f"assign@base64+{outer}+{name}" in kinds("see " + b64(PACK[outer](PACK[name](noise) + PACK[name](noise + b" " + SECRET + b" " + noise)))), (outer, piece)


def test_an_inner_stream_longer_than_a_real_piece():
    inner = zlib.compressobj(0)  # stored, so the inner stream itself is longer than PIECE
    data = inner.compress(b" " * (secrets.PIECE + 5000) + SECRET) + inner.flush()
    assert len(data) > secrets.PIECE
    assert "assign@base64+gzip+zlib" in kinds("see " + b64(gzip.compress(data, mtime=0)))


@pytest.mark.parametrize("width", [64, 76])
@pytest.mark.parametrize("end", ["\n", "\r\n", "\n    "])
def test_wrapped_base64(width, end):
    plain = b" ".join(b"word%d" % (i * 7919) for i in range(60)) + b" " + SECRET
    for data, name in ((plain, "assign@base64"), (gzip.compress(plain, mtime=0), "assign@base64+gzip")):
        for before, after in (("", ""), ("see: ", "\nthen more"), ("averylongforeignidentifier\n", "\n\nword"), ("short\n", " ok")):
            text = before + b64(data, width, end) + after
            spans = [x for x in secrets.secrets_in(text)[1] if x[2] == name]
            assert spans, (before, after)
            assert all(0 <= s < e <= len(text) for s, e, _ in spans)
            assert (len(before), len(before) + len(b64(data, width, end))) in [(s, e) for s, e, _ in spans] or after == "\nthen more"


def test_text_that_looks_packed():
    assert "assign@base64+gzip" in kinds("see " + b64(gzip.compress(b"x^2 " + SECRET, mtime=0)))


@pytest.mark.parametrize("before", ["blob/", "a", "ab", "abc", "abcd/", "data_x-", "path/to/some/"])
def test_letters_before_and_behind_a_value(before):
    for data, name in ((SECRET + b" end", "assign@base64"), (gzip.compress(SECRET, mtime=0), "assign@base64+gzip"), (zstandard.compress(SECRET), "assign@base64+zstd")):
        text = "see " + before + b64(data).rstrip("=")
        spans = [x for x in secrets.secrets_in(text)[1] if x[2] == name]
        assert spans and spans[0][:2] == (4, len(text)), (before, name)
    assert "assign@base64" in kinds(f"see {b64(SECRET + b'..')}xyz")


@pytest.mark.parametrize("code", ["utf-16-le", "utf-16-be", "utf-16"])
def test_wide_characters(code):
    data = SECRET.decode().encode(code)
    assert "assign@base64" in kinds("see " + b64(data)) and "assign@base64+gzip" in kinds("see " + b64(gzip.compress(data, mtime=0)))
    assert "assign@base64" in kinds("see x" + b64(b"\xff\xfe\xfd" + data))


def slow_layers(text):
    """All texts that the text unwraps to, by trying every decoder on every layer."""
    seen, work = {text}, [text]
    while work:
        t = work.pop()
        new = [urllib.parse.unquote(t), re.sub(r"\\\\u([0-9a-f]{4})", lambda m: chr(int(m[1], 16)), t)]
        for m in re.finditer(r"[A-Za-z0-9+/]{16,}={0,2}", t):
            try:
                data = base64.b64decode(m[0])
            except ValueError:
                continue
            for unpack in (lambda d: d, gzip.decompress, zlib.decompress, bz2.decompress, lzma.decompress, lambda d: zlib.decompress(gzip.decompress(d))):
                try:
                    new.append(unpack(data).decode())
                except Exception:
                    pass
        work += [x for x in new if x not in seen]
        seen.update(new)
    return seen


def test_layers_equal_brute_force():
    """The secrets of decoded layers are those that trying every decoder finds, for random nestings."""
    rng = random.Random(8)
    wrap = [
        lambda t: b64(t.encode()), lambda t: b64(PACK["gzip"](t.encode())), lambda t: b64(PACK["bz2"](t.encode())), lambda t: b64(PACK["gzip"](zlib.compress(t.encode()))),
        lambda t: urllib.parse.quote(t, safe=""), lambda t: "".join(f"\\u{ord(c):04x}" for c in t), lambda t: f"seen at {t} today", lambda t: f"{t} and api_key={rng.randrange(10**9):09d}x",
    ]
    found = lambda texts: {t[s:e] for t in texts for s, e, _ in secrets.scan(t)}
    for _ in range(150):
        text = f"secret={rng.randrange(10**9):09d}k"
        for _ in range(rng.randint(1, 5)):
            text = rng.choice(wrap)(text)
        want, got = found(slow_layers(text)), found(x.text for x in secrets.layers(text))
        assert want <= got and any(x.startswith("secret=") for x in got), text


def test_a_packed_layer_stays_out_of_memory():
    text = "see " + b64(gzip.compress(b" " * (1 << 27) + SECRET, mtime=0))
    tracemalloc.start()
    assert "assign@base64+gzip" in kinds(text)
    assert tracemalloc.get_traced_memory()[1] < 12 * secrets.PIECE
    tracemalloc.stop()


def test_tables(spark):
    assert secrets.scan_documents(spark.createDataFrame([], "doc_id long, text string")).collect() == []
    rows = [(1, "token = abcdef123", "x"), (1, "token = abcdef123", "x"), (None, None, None), (2, "ab " * 400_000 + "token = abcdef123", "y")]
    got = secrets.scan_documents(spark.createDataFrame(rows, "doc_id long, text string, base string")).collect()
    assert sorted(len(r["base"]) for r in got) == [0, 1, 1, 1] and got[0] == got[1]
