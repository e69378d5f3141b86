"""Schemas of the derived tables."""

#: A header: position in its document (0: the root), style key, rank of its true level, own text, words of the text that follows it.
HEADERS = "doc_id bigint, pos int, style string, rk int, title string, body_words bigint"
#: A style group: number by first use, first position, group of the header just before that.
GROUPS = "doc_id bigint, style string, g int, opener int, prev_g int, n_nodes bigint"
DEPTHS = "doc_id bigint, style string, sd double, band int"
#: A header tree: parent (null at the root) and the first position after the header's span.
TREE = "doc_id bigint, pos int, parent_pos int, span_end int"
