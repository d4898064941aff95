"""Evolution memory: weekly notes that hold only checked numbers and are withdrawn when a correction overlaps them."""
