"""Operations of a training-data pipeline: near-duplicates, packing, mixing, language, tokens, formatting."""
