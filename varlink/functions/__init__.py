"""Column functions: vectors, match scores, bits, text, sampling; all inside Catalyst."""
