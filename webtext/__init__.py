"""webtext: page extraction, template-aware scaling, formatting and corpus curation on Spark DataFrames."""
