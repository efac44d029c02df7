import random

import public_tokenizers
from tokenizers import Tokenizer

from sparkgraphs.llm import bpe_codec


def test_rare_words_are_merged_to_names_of_ids_as_the_library_does():
    """Words outside the lexicon become the texts of their ids without ids in between."""
    path = public_tokenizers.path("byte_bpe_50k.json")
    codec, library = bpe_codec.Codec(path, bpe_codec.build_lexicon(["the", " the"], path)), Tokenizer.from_file(path)
    dice = random.Random(7)
    words = [dice.choice(["", " "]) + "".join(dice.choice("etaoinshrdlüéß日語") for _ in range(dice.randint(1, 40))) for _ in range(400)]
    for w in ["the", " the", *words]:
        ids = library.encode(w, add_special_tokens=False).ids
        assert codec.encode(w) == ",".join(map(str, ids)) and codec.decode(codec.encode(w)) == w
        assert [codec.bpe.names[s] for s in codec.bpe.merged(w.strip().encode())] == list(map(str, codec.bpe.merge(w.strip())))
