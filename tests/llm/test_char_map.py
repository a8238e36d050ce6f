"""The given model with a compiled map put into it: normalisation and spans against the library."""

import random

import numpy as np

from spark_curation.llm import pieces

RULES = {"a": "x", "ab": "yz", "abc": "Q", "é": "e", "ﬀ": "ff", "　": " ", "日本": "J", "①": "1"}


def varint(n):
    out = bytearray()
    while n >= 0x80:
        out.append(n & 0x7F | 0x80)
        n >>= 7
    return bytes([*out, n])


def field(number, value):
    return varint(number << 3) + varint(value) if isinstance(value, int) else varint(number << 3 | 2) + varint(len(value)) + value


def double_array(rules):
    """Units of a trie over byte strings, each node's children at an offset that is free, and the values they point to."""
    trie, values = {}, bytearray()
    for k, v in rules.items():
        node = trie
        for b in k.encode():
            node = node.setdefault(b, {})
        node[-1] = len(values)
        values += v.encode() + b"\0"
    units, used = np.zeros(1 << 14, np.uint32), {0}

    def place(node, at):
        labels = [b for b in node if b >= 0]
        base = next(x for x in range(256, 1 << 13, 256) if not any(x ^ b in used for b in [*labels, 0]))
        used.update(base ^ b for b in [*labels, 0])
        units[at] |= (base ^ at) << 10
        if -1 in node:
            units[at] |= 0x100
            units[base] = node[-1] | 0x80000000
        for b in labels:
            units[base ^ b] |= b
            place(node[b], base ^ b)

    place(trie, 0)
    return units.tobytes(), bytes(values)


def test_map_within_a_model():
    with open(pieces.tokenizer_path(), "rb") as f:
        raw = f.read()
    units, values = double_array(RULES)
    blob = len(units).to_bytes(4, "little") + units + values
    out = bytearray()
    for number, value in pieces._fields(raw):
        if number == 3:
            spec = [(k, v) for k, v in pieces._fields(value) if k != 2]
            value = b"".join(field(k, v) for k, v in [(2, blob), *spec])
        out += field(number, value)
    enc = pieces.Encoder(bytes(out))
    r = random.Random(2)
    for _ in range(300):
        text = "".join(r.choice(["a", "b", "c", "é", "ﬀ", "　", "日", "本", "①", " ", "z", "語", "\n"]) for _ in range(r.randrange(25)))
        plain, origin = enc.map.apply(text.encode())
        assert "▁" + plain.decode().replace(" ", "▁") == enc.library.normalize(text) or not text
        ids = enc.encode([text])[0]
        assert ids.tolist() == enc.library.encode(text, add_bos=True, add_eos=True)
        begin, end = enc.spans(text, ids)
        assert (begin <= end).all() and (begin[1:] == end[:-1]).all() and end[-1] == len(text.encode())
        assert (np.diff(origin) >= 0).all() and origin[-1] == len(text.encode())
    assert enc.map.apply("xabcab日本日".encode())[0] == "xQyzJ日".encode()
