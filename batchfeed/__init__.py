"""batchfeed: feeding training data to distributed consumers, and its time and energy."""
