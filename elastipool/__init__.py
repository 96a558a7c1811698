"""elastipool: elastic pools of classification workers, studied with Spark DataFrames."""
