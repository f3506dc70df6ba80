"""Names and schemas of the data model."""

from __future__ import annotations

ONE_TO_ONE, FIXED, HYBRID, UNI_MODAL = "one_to_one", "fixed", "hybrid", "uni_modal"

LAYOUTS = ("loose", "path_table", "pair_record", "bundle")

PAIRS = "pair_ord long, media string, text string, src_id long"
TEXTS = "array<struct<pair_ord:bigint,text:string,src_id:bigint>>"
INDEX = "bundle_id long, start_idx long, end_idx long, byte_offset long, byte_len long"

#: Bytes that frame a bundle: the lengths of its media and of its list, and of each text.
MEDIA_FRAME, LIST_FRAME, TEXT_FRAME = 4, 4, 4
