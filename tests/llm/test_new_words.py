"""Words that no table has yet: the encoder asks the library for each of them once."""

import random

from rankgrid.llm.pretokens import Encoder, default_tokenizer, vocabulary


def test_ids_of_many_new_words():
    v = vocabulary(default_tokenizer())
    e = Encoder(v)
    asked, batch = [], e._store
    e._store = lambda words: (asked.extend(words), batch(words))[1]
    rng = random.Random(4)
    words = ["".join(rng.choices("abcxyz0189éßж漢!", k=rng.randint(3, 14))) for _ in range(4000)]
    texts = [" ".join(words[k : k + 200]) for k in range(0, 4000, 200)] * 2
    flat, at = e.ids(texts)
    for k, t in enumerate(texts):
        assert flat[at[k] : at[k + 1]].tolist() == e.tokenizer.encode(t, add_special_tokens=False).ids
    assert len(asked) == len(set(asked)) > 3000


def test_new_words_go_to_the_library_as_texts_of_many():
    e = Encoder(vocabulary(default_tokenizer()))
    asked, library = [], e.tokenizer
    words = [f" {'xq' * (k % 5)}w{k}" for k in range(2500)] + ["漢ß", " <|endoftext", "|>", "'s", "\n\n", " "]

    class Counted:
        def encode_batch_fast(self, texts, **options):
            asked.append(len(texts))
            return library.encode_batch_fast(texts, **options)

    e.tokenizer = Counted()
    want = [x.ids for x in library.encode_batch(words, add_special_tokens=False)]
    for between in (e.between, None):
        e.between = between
        lengths, ids = e._encode(words)
        assert lengths.tolist() == [len(x) for x in want] and ids.tolist() == [i for x in want for i in x]
    assert asked == [3, len(words)]
    e.between = (" xq", 5)  # one that is no special token: the pieces are not those of the words
    assert e._encode(words)[1].tolist() == ids.tolist()
