"""The small worked examples: infixes, a packed block and its queries, codes, tries and their updates, splits."""

import random
from collections import Counter

import numpy as np
import pytest

from rangesieve.functions.entropy import alphabetic_codes, bisection_codes, entropy_bits, huffman_lengths, mean_length
from rangesieve.functions.geometry import Geometry, infix_len, remainder_len
from rangesieve.operators.blocks import Block, rank, select
from rangesieve.operators.dynamic import DynamicBlock, ShardFilter, pad_remainder, unpad_remainder
from rangesieve.operators.enhanced import EnhancedBlock
from rangesieve.operators.tailtrie import Entry, TailTrie, pack_run, parse_run


def bits(text: str, width: int) -> int:
    return int(text.replace(" ", "").ljust(width, "0"), 2)


def test_infix_without_redundant_bits():
    g = Geometry(bits("01010011011101", 16), bits("010111101110011", 16), 16, 7)
    assert (g.shared, g.redundant, g.infix(bits("0101010100111", 16))) == (4, 0, 41)


def test_infix_past_redundant_bits():
    g = Geometry(bits("0101 0 1111 011011 101", 20), bits("0101 1 0000 110111 0011", 20), 20, 7)
    key = bits("0101 0 1111 101001 11", 20)
    assert (g.shared, g.redundant, format(g.infix(key), "07b")) == (4, 4, "0101001")
    back, known = g.rebuild(g.infix(key))
    assert key >> (20 - known) == back >> (20 - known)


def test_lengths():
    assert infix_len(1024, 2 ** -7) == 18 and remainder_len(2 ** -7) == 8


def test_packed_block():
    infixes = np.array([0b000010, 0b001110, 0b001111, 0b011001, 0b011011, 0b100000, 0b110100])
    b = Block.pack(infixes, 0, 0b111111, 3)
    text = lambda x: "".join(str(int(v)) for v in x)
    assert text(b.occupieds) == "11011010" and text(b.runends) == "1010111" and b.matched()
    assert rank(b.occupieds, 3) == 2 and select(b.runends, 2) == 4 and rank(b.occupieds, 6) == 4 and select(b.runends, 4) == 6
    assert b.probe(0b001111, 0b011000) != "none" and b.probe(0b110101, 0b110110) == "none"
    assert list(b.infixes()) == list(infixes)
    assert list(Block.from_bytes(3, 0, 8, 7, *b.to_bytes()).infixes()) == list(infixes)


def test_bisection_code():
    f = [(ord(c), n) for c, n in sorted(Counter("SIGKDDSIGMODVLDB").items())]
    codes = {chr(s): c for s, c in bisection_codes(f).items()}
    assert codes == {"B": "000", "D": "001", "G": "01", "I": "100", "K": "1010", "L": "1011", "M": "1100", "O": "1101", "S": "1110", "V": "1111"}
    assert mean_length(f, bisection_codes(f)) == 3.3125 and entropy_bits(f) == 3.125 == mean_length(f, huffman_lengths(f))
    assert mean_length(f, alphabetic_codes(f)) <= mean_length(f, bisection_codes(f)) <= entropy_bits(f) + 2


def test_coded_query_turns_negative():
    f = [(ord(c), n) for c, n in sorted(Counter("SIGKDDSIGMODVLDB").items())]
    code = bisection_codes(f)
    enc = lambda w: int("".join(code[ord(c)] for c in w).ljust(40, "0"), 2)
    g = Geometry(enc("SIGKDD"), enc("VLDB"), 40, 16)
    assert g.shared == 3 and format(g.infix(enc("SIGMOD")), "016b") == "0100011100110100"
    assert (format(g.infix(enc("SIGO")), "016b"), format(g.infix(enc("SIGS")), "016b")) == ("0100011101000000", "0100011110000000")


def test_trie_codes():
    t = TailTrie.build(["100010101", "10010000", "11011"], 3)
    assert t.encode("0") == "0 0 01 1 0 01 0 1 1 1".replace(" ", "") and t.trailing() == "101000011"
    g = TailTrie.build(["1011100101", "1011101010"], 3)
    assert g.encode() == "1 0 001 11 101110 1 1".replace(" ", "") and g.trailing() == "101010"
    assert parse_run(pack_run(0b100000000011, 12, t.encode()), 12) == (0b100000000011, t.encode())
    assert pack_run(0b100000000011, 12, "1").endswith("01")


def test_trie_updates():
    t = TailTrie([Entry("10", False, "011"), Entry("11", False, "100")], 3)
    assert t.encode("0") == "0001111"
    assert t.insert("1000110") == 2 and t.encode("0") == "000110010111" and t.trailing(3) == "1101" + "1100" + "1001"
    assert t.insert("111000001") == 3
    assert t.encode() == "1 0 01,0 1 0 01,1 0 1 1 0 1,0 001,01 100 10 1".replace(" ", "").replace(",", "")
    assert TailTrie.decode(t.encode()).encode() == t.encode() and TailTrie.skip(t.encode() + "01") == len(t.encode())
    assert t.delete("11100011") and t.encode("0") == "000110010111" and t.trailing(3) == "1101" + "1100" + "1001"


@pytest.mark.parametrize("value,n,slot", [(0, 1, 0b0100), (1, 2, 0b0110), (7, 3, 0b1111), (0, 0, 0b1000)])
def test_padding(value, n, slot):
    assert pad_remainder(value, n, 4) == slot and unpad_remainder(slot, 4) == (value, n)


def test_trie_holds_every_key():
    r = random.Random(1)
    for _ in range(200):
        keys = {format(r.randrange(1 << n), f"0{n}b") for n in (r.choice([3, 6, 12]) for _ in range(r.randrange(2, 12)))}
        t = TailTrie.build(sorted(keys), r.randrange(4))
        assert all(t.positive(x, x) for x in keys)
        assert TailTrie.decode(t.encode()).encode() == t.encode() and TailTrie.skip(t.encode()) == len(t.encode())


@pytest.mark.parametrize("seed", range(4))
def test_dynamic_filter_never_forgets(seed):
    r = random.Random(seed)
    keys = sorted({r.randrange(1 << 60) if seed % 2 else int(r.gauss(1 << 60, 1 << 40)) for _ in range(1200)})
    f, live = ShardFilter.build(keys[::6], 0, (1 << 62) - 1, 32, 8), set(keys[::6])
    for i, key in enumerate(x for x in keys if x not in set(keys[::6])):
        f.insert(key)
        live.add(key)
        if i % 5 == 4:
            gone = r.choice(sorted(live))
            assert f.delete(gone, clean_copies=seed > 1)
            live.discard(gone)
    assert all(f.positive(x, x) for x in live)
    again = ShardFilter.from_rows(f.rows(0, 0), 32, 8)
    assert again.stats() == f.stats() and all(again.positive(x, x) for x in live)
    assert all(len(b.entries) <= b.n_slots and len(set(b.layout())) == len(b.entries) for b in f.blocks)


def test_stretching_wastes_less_than_doubling():
    filled = {}
    for expansion in ("stretch", "double"):
        b = DynamicBlock(Geometry(0, (1 << 30) - 1, 30, 16), 8)
        b.fill()
        for key in random.Random(2).sample(range(1, (1 << 30) - 1), 3000):
            b.insert(key, 1.05, 0.95, expansion)
        filled[expansion] = len(b.entries) / b.n_slots
    assert filled["stretch"] >= 0.9 > filled["double"]


def test_enhanced_block_never_forgets():
    r = random.Random(3)
    e, live = EnhancedBlock(Geometry(1 << 100, (1 << 101) + 12345, 110, 16), 6), set()
    base = [r.randrange(1 << 100, 1 << 101) for _ in range(20)]
    for i in range(400):
        key = r.choice(base) + r.randrange(1, 1 << r.choice([5, 30, 70]))
        if key not in live:
            e.insert(key)
            live.add(key)
        if i % 4 == 3:
            gone = r.choice(sorted(live))
            e.delete(gone)
            live.discard(gone)
    assert all(e.positive(x, x) for x in live) and e.cases["3"] and e.cases["2"] and e.cases["1"]
