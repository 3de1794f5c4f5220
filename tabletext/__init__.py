"""Tables turned into text-extraction benchmarks, and the scoring of what is extracted."""
