"""Entity-resolution training-data transfer as DataFrame, SQL, MLlib and streaming plans."""
