"""assetmill: DataFrame programs for curating training corpora and studying sparse routing."""
