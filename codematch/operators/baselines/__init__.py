"""The methods that are compared with: exact search, binary codes, quantized distances, tags."""
