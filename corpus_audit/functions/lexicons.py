"""Small side tables. Pass your own to the analyses; these fit the synthetic tables and hold no slurs."""

from __future__ import annotations

#: Term -> category.
TOXIC_TERMS = {
    "scum": "offensive_other", "stupid": "offensive_other", "loser": "offensive_other", "moron": "offensive_other", "disgusting": "offensive_other",
    "pathetic": "offensive_other", "worthless": "offensive_other", "idiot": "offensive_other", "clown": "offensive_other", "trash": "offensive_other",
    "thend": "offensive_minority", "erst": "offensive_minority", "tionen": "harmless_minority", "ouan": "harmless_minority", "thand": "harmless_minority",
}
OFFENSIVE = ("offensive_minority", "offensive_other")
#: Fixed values: (group, term); terms may have two words.
GROUP_TERMS = [("gender", "he"), ("gender", "she"), ("gender", "it"), ("origin", "tionen"), ("origin", "ouan"), ("belief", "thand"), ("belief", "to the"), ("belief", "of the")]
#: Polarity of words in [-1, 1].
POLARITY = {"best": 1.0, "good": 0.7, "great": 0.8, "nice": 0.6, "happy": 0.8, "with": 0.1, "and": 0.05, "not": -0.2, "no": -0.2} | {t: -0.8 for t, c in TOXIC_TERMS.items() if c == "offensive_other"}
PUBLIC_SUFFIXES = ["com", "net", "org", "co.uk", "example.net"]
