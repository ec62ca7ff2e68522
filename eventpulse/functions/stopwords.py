"""Function words that are never events."""

from __future__ import annotations

#: Frequent function words of four languages.
STOPWORDS = {
    "en": "a an and are as at be by for from had has have he her his i in is it its not of on or she that the their they this to was we were will with you".split(),
    "fr": "au aux ce ces dans de des du elle en est et il ils je la le les leur mais ne nous on ou par pas pour qui que sa se ses son sur un une vous".split(),
    "de": "als am auf aus bei das dem den der des die ein eine einer es für ich im in ist mit nicht sich sie sind und von war wie wir zu zum zur".split(),
    "es": "al como con de del el ella en es esta este la las lo los más no o para pero por que se su sus un una y ya".split(),
}


def stopwords(langs: tuple[str, ...] = ("en", "fr", "de", "es")) -> list[str]:
    """The words of the given languages, sorted, without repeats."""
    return sorted({w for lang in langs for w in STOPWORDS[lang]})
