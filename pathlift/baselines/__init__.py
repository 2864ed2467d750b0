"""Re-implementations, in our own words, of the systems that the method is compared with."""
