import random

import public_tokenizers
import regex
import tiktoken

from chronoweave.llm import bpe


def oracle():
    r = bpe.Ranks(bpe.rank_file())
    return tiktoken.Encoding("own", pat_str=public_tokenizers.PATTERN, mergeable_ranks=r.rank, special_tokens={})


def test_pieces_match_the_pattern():
    rng = random.Random(5)
    alphabet = ["a", "B", "é", "1", "٣", " ", "  ", "\n", "\t", " ", "　", "'", "'s", "'ll", "'re", "'d", "'x", "!", "…", "語", "l", "r", "e", "\U0001f600", "½", "\x1c", "\x85"]
    texts = ["".join(rng.choice(alphabet) for _ in range(rng.randrange(40))) for _ in range(4000)] + ["", " ", "'s", "''s's", " 's", "\n's", "x" * 500 + "'ve"]
    for t, got in zip(texts, bpe.split(texts), strict=True):
        assert got == regex.findall(public_tokenizers.PATTERN, t), repr(t)


def test_ids_and_round_trip():
    rng = random.Random(6)
    enc, want = bpe.Encoder(bpe.rank_file()), oracle()
    texts = ["".join(rng.choice("abcdeéß 'stlrv\n12語!é") for _ in range(rng.randrange(300))) for _ in range(300)] + ["aaaa" * 600, "<|endoftext|>", "", None]
    for t, ids in zip(texts, enc.encode(texts), strict=True):
        assert ids == want.encode_ordinary(t or "")
        assert enc.decode(ids) == (t or "").encode()
        off = enc.offsets(ids).tolist()
        assert all(enc.decode(ids[:i]) == (t or "").encode()[: off[i]] for i in range(0, len(ids), 7))


def test_every_code_point_has_tiktokens_class():
    enc, want = bpe.Encoder(bpe.rank_file()), oracle()
    cps = [c for c in range(0x110000) if not 0xD800 <= c < 0xE000]
    for at in range(0, len(cps), 50_000):
        part = cps[at : at + 50_000]
        text = "".join(f"a{chr(c)}b1{chr(c)}2 {chr(c)}!" for c in part[::7])
        assert enc.encode([text])[0] == want.encode_ordinary(text), hex(part[0])
