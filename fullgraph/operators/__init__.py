"""The method's operators: partitioning, covers, exchange, aggregation, quantization, training, measures."""
