"""talkdigest: divide-and-conquer condensing of long multi-party transcripts on Spark DataFrames."""
