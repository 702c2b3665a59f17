"""Training-data operators: filtering, de-duplication, tokens, extraction and packing over DataFrames of documents."""
