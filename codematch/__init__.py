"""codematch: matching vectors by counting equal quantization codes, on Spark."""
