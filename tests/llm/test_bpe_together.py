import random

import public_tokenizers
import regex
from tokenizers import Tokenizer

from sparkgraphs.llm import bpe_codec

PATH = public_tokenizers.path("byte_bpe_50k.json")


def made_up(dice: random.Random) -> str:
    parts = ["".join(dice.choice("etaoinshrdlüéß日語'7.x") for _ in range(dice.randint(1, 30))) for _ in range(dice.randint(0, 40))]
    gaps = [" "] * 12 + ["  ", "\n", " \n", "  ", "\x1c", "<|endoftext|>", " <|endoftext|> "]
    return dice.choice(["", " "]) + "".join(p + dice.choice(gaps) for p in parts) + dice.choice(["", "aaaaaaa", "x" * 60])


def test_new_short_words_are_merged_together_as_the_library_does(monkeypatch):
    alone = bpe_codec.ByteBpe.merged

    def merged(self, word):
        assert len(word) > bpe_codec.SHORT, "merged on its own"
        return alone(self, word)

    lexicon = bpe_codec.build_lexicon(["the", " the", " then", "th"], PATH)
    monkeypatch.setattr(bpe_codec.ByteBpe, "merged", merged)
    library, dice = Tokenizer.from_file(PATH), random.Random(11)
    texts = [None, "", " ", "the then th thenx\n the", *(made_up(dice) for _ in range(120))]
    expected = [library.encode(t or "", add_special_tokens=False).ids for t in texts]
    for run, entries in ((7, 20), (1 << 16, 20), (1 << 16, 1 << 19)):
        monkeypatch.setattr(bpe_codec, "RUN", run)
        codec = bpe_codec.Codec(PATH, lexicon, entries)
        for size in (1, 50):
            found = [x for at in range(0, len(texts), size) for x in codec.encode_all(texts[at : at + size])]
            assert found == [",".join(map(str, ids)) for ids in expected]
            assert [codec.decode(x) for x in found] == [library.decode(ids, skip_special_tokens=False) for ids in expected]
        assert codec.encode_all([]) == []


def test_words_of_one_kind_of_letters_are_not_split():
    for i in range(ord(bpe_codec.LATIN_END)):
        assert bpe_codec.one_word(chr(i)) == bool(regex.fullmatch(r"\p{L}", chr(i)))
    assert not bpe_codec.one_word("日") and not bpe_codec.one_word("a1") and not bpe_codec.one_word("it's") and bpe_codec.one_word("über")
