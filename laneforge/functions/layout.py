"""Layout rules that the byte plane and the relational plane share."""

#: Largest number of integers of a chunk, and of a page of the patched codes.
CHUNK = 1 << 16
#: Integers of a block: vertical and patched codes; scalar packing.
BLOCK, SCALAR_BLOCK = 128, 32
LANES = 4
#: Blocks of a meta-block, by integers of a block; each has one byte of width in the descriptor.
META = {128: 16, 32: 4, 16: 4, 8: 4}
#: Integers are unsigned and of 32 bits.
LIMIT = 1 << 32
#: An exception costs its location, so many bits, besides its high part.
LOCATION_BITS = 8
#: Simple-8b, fixed values: integers of a word and bits of each, by selector.
WORD_LAYOUTS = [(240, 0), (120, 0), (60, 1), (30, 2), (20, 3), (15, 4), (12, 5), (10, 6), (8, 7), (7, 8), (6, 10), (5, 12), (4, 15), (3, 20), (2, 30), (1, 60)]
#: Run lengths that the split-vector code may use; its width and length codes take four bits each.
SPLIT_LENGTHS = [1, 2, 3, 4, 5, 6, 7, 8, 9, 10, 11, 12, 13, 14, 16, 32]
#: The widths that its width code names: widths in between round up.
SPLIT_WIDTHS = [0, 1, 2, 3, 4, 5, 6, 7, 8, 10, 12, 14, 16, 20, 24, 32]
#: The most exceptions of a block, in tenths, that the fast per-block rule accepts.
EXCEPTION_TENTHS = 1
#: Integers at the start of a page that the page-wide width is chosen from.
PAGE_SAMPLE = 2048
