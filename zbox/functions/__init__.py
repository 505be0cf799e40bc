from .curve import cell_start, in_box, in_ranges, next_cell, z_bits, z_decode, z_encode, z_encode_wide, z_in_box, z_of

__all__ = ["cell_start", "in_box", "in_ranges", "next_cell", "z_bits", "z_decode", "z_encode", "z_encode_wide", "z_in_box", "z_of"]
