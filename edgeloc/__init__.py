"""Root-cause localization on service graphs, decentralized by cluster, on Spark DataFrames."""
