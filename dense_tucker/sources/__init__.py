"""Where tensors come from: tables, generators and metadata benchmarks."""
