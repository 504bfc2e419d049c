"""String similarity and the lexicon."""
