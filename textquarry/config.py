"""Parameters of the curation methods. Thresholds without a published value are calibrated on the given tables."""

from __future__ import annotations

LANGUAGES = ("en", "fr", "de", "es")
#: English words that mark a document as not safe for work in the test corpus.
NSFW_EN = ("idiot", "clown", "trash", "scum", "worthless", "moron", "pathetic", "loser", "stupid", "disgusting")
NSFW = {"en": NSFW_EN, "fr": (), "de": (), "es": ()}

#: Flag thresholds per language; "*" is the default row.
THRESHOLDS = {"*": {"nsfw_ratio": 0.005, "non_target_ratio": 0.2, "min_lines": 2, "min_mean_len": 3.0, "word_rep": 0.2, "char_rep": 0.2, "symbol_ratio": 0.08}, "fr": {"min_mean_len": 2.5}}

#: Fixed values of deduplication and perplexity filtering.
DEDUP_NGRAM, DEDUP_THRESHOLD = 5, 0.7
#: Probability that a pair at the threshold is proposed.
DEDUP_RECALL = 0.999
LM_ORDER, PPL_QUANTILE, LM_TRAIN_DOCS, LM_VALID_DOCS = 5, 0.8, 200_000, 100_000
#: Fixed values of the PDF selection.
PDF_MAX_PAGES, PDF_MIN_PAGES, PDF_MIN_PPI, PDF_RUN, PDF_MAX_AREA, PDF_MIN_BRIGHTNESS = 2000, 25, 300, 10, 0.5, 200

#: Splits by source number: 0-11 verified, 12-17 unverified (12-14 corpus A, 15-17 corpus B), 18-19 synthetic.
VERIFIED_UPTO, UNVERIFIED_UPTO, CORPUS_A_UPTO = 11, 17, 14

#: Fixed values of the alignment data: words of a context passage, templates per word, combinations of the safety axes, prompts for verbs and nouns.
PASSAGE_WORDS, TEMPLATES_PER_WORD, COMBINATIONS, VERB_PROMPTS = 1000, 100, 100_000, 20_000
