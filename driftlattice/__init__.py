"""Mining the most frequent episodes of event streams over a sliding window of batches, on Spark."""
