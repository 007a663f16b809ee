"""Fixed schemas of the engine's tables."""

ARCHIVE = "file_id long, path string, size long"
SLOT = "file_id long, path string, size long, slot_no long, guess_bit long, limit_bit long"
CANDIDATE = "file_id long, slot_no long, start_bit long, last_bit long, kind string"
PIECE = "array<struct<n:long,crc:long,ends:boolean,footer_crc:long,isize:long>>"
SPAN = f"file_id long, path string, size long, start_bit long, end_bit long, kind string, end_kind string, ok boolean, reason string, out_len long, n_markers long, last_marker long, fallback_pos long, tail_map binary, pieces {PIECE}"
INDEX = "file_id long, path string, size long, point_no long, start_bit long, end_bit long, kind string, end_kind string, out_start long, out_len long, window binary"
STREAM = "file_id long, point_no long, out_start long, bytes binary"
