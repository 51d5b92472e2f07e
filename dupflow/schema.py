"""Record schemas and flag bits."""

from __future__ import annotations

#: Fixed values of the public text alignment format.
PAIRED, PROPER, UNMAPPED, MATE_UNMAPPED, REVERSE, MATE_REVERSE, END1, END2, SECONDARY, DUPLICATE, SUPPLEMENTARY = 1, 2, 4, 8, 16, 32, 64, 128, 256, 1024, 2048

TAG = "struct<tag:string,type:string,value:string>"
ALIGNMENT = (
    "seq decimal(38,0), tid decimal(38,0), qname string, flag int, ref_id int, pos long, mapq int, cigar string, mate_ref_id int, "
    f"mate_pos long, tlen long, bases string, quals string, tags array<{TAG}>, lib string"
)
RECORD = ["seq", "tid", "qname", "flag", "ref_id", "pos", "mapq", "cigar", "mate_ref_id", "mate_pos", "tlen", "bases", "quals", "tags", "lib"]
#: The narrow summary kept for analyzers: numbers only, no long strings.
DIGEST = ["seq", "tid", "end_no", "flag", "ref_id", "pos", "u5", "rev", "score", "lib", "rec_bytes"]
BLOCK = "file_id int, block_id long, start long, bytes binary"
LINE = "file_id int, block_id long, line_no int, start long, length int, value string"
BAF_BLOCK = "part int, block_no long, n_rec int, raw_len int, first_ref int, first_pos long, last_ref int, last_pos long, payload binary"
STAGE_METRIC = "stage string, rows long, bytes_in long, bytes_out long, millis long, peak_kb long"
