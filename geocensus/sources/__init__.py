"""Tables, the derived crawl index, byte-range reads, and the planted population."""
