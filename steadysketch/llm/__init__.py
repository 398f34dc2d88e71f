"""Operations of a training-data pipeline: language, duplicates, tokens, licences, vectors, quality and mixing."""
