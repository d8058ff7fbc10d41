"""Cost, memory, overlap and fill models as functions of numbers and of columns; text hashing."""
