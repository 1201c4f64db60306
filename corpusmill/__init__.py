"""corpusmill: curation of text and code corpora on Spark DataFrames."""
