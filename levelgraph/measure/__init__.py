"""Cost, balance, locality and throughput measures."""
