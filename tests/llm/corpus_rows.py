"""Schemas and made-up texts for the tests of the corpus operators."""

from __future__ import annotations

#: Extra columns with names that operators use inside.
EXTRA = "start long, node long, key long, block long, score double, held boolean, word string, shard int, _draw long, class_id long, toxic int"
SCHEMA = f"doc_id long, text string, lang string, source string, n_chars long, {EXTRA}"
DOCS = "doc_id long, text string, lang string, source string, n_chars long"

WORDS = "the of and to house river stone light people garden winter number music letter window morning teacher village market bridge".split()
MOTS = "le la les des maison rivière pierre lumière peuple jardin hiver été musique lettre fenêtre matin école château pêche forêt".split()


def prose(n: int, seed: int, words=WORDS) -> str:
    import random

    r = random.Random(seed)
    return " ".join(r.choice(words) for _ in range(n))
