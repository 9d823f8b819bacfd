"""The queries: each a function of (spark, sf_dir), with SQL where SQL can say it."""
