"""The scenario schemas: tables, columns, keys, references and lineage, as metadata text.

A line is ``table @anchor: column type [pk] [>table.column] [=lineage]; ...``. Columns of different schemas match if they have the same
lineage; directly if their tables have the same anchor, else contextually.
"""

from __future__ import annotations

SCHEMAS = {
    "star": """
region @region: r_regionkey int pk =r_regionkey; r_name string =r_name
nation @nation: n_nationkey int pk =n_nationkey; n_name string =n_name; n_regionkey int >region.r_regionkey =n_regionkey
customer @customer: c_custkey bigint pk =c_custkey; c_name string =c_name; c_nationkey int >nation.n_nationkey =c_nationkey; c_acctbal double =c_acctbal; c_mktsegment string =c_mktsegment
supplier @supplier: s_suppkey bigint pk =s_suppkey; s_name string =s_name; s_nationkey int >nation.n_nationkey =s_nationkey; s_acctbal double =s_acctbal
part @part: p_partkey bigint pk =p_partkey; p_name string =p_name; p_brand string =p_brand; p_type string =p_type; p_size int =p_size; p_retailprice double =p_retailprice
orders @orders: o_orderkey bigint pk =o_orderkey; o_custkey bigint >customer.c_custkey =o_custkey; o_orderstatus string =o_orderstatus; o_totalprice double =o_totalprice; o_orderdate timestamp =o_orderdate; o_orderpriority string =o_orderpriority
lineitem @lineitem: l_orderkey bigint >orders.o_orderkey =l_orderkey; l_partkey bigint >part.p_partkey =l_partkey; l_suppkey bigint >supplier.s_suppkey =l_suppkey; l_linenumber int =l_linenumber; l_quantity double =l_quantity; l_extendedprice double =l_extendedprice; l_discount double =l_discount; l_tax double =l_tax; l_returnflag string =l_returnflag; l_linestatus string =l_linestatus; l_shipdate timestamp =l_shipdate
""",
    "desk": """
clients @customer: client_id bigint pk =c_custkey; full_name string =c_name; account_balance double =c_acctbal; market_group string =c_mktsegment
branches @supplier: branch_id bigint pk =s_suppkey; branch_name string =s_name
deliveries @delivery: delivery_id bigint pk; client_id bigint >clients.client_id =o_custkey; branch_id bigint >branches.branch_id =l_suppkey; delivery_country string =n_name; delivery_date timestamp =l_shipdate
goods @part: good_id bigint pk =p_partkey; good_title string =p_name; maker_label string =p_brand; list_price double =p_retailprice
purchases @orders: purchase_id bigint pk =o_orderkey; client_id bigint >clients.client_id =o_custkey; placed_at timestamp =o_orderdate; state_code string =o_orderstatus; amount_total double =o_totalprice
purchase_lines @lineitem: purchase_id bigint >purchases.purchase_id =l_orderkey; good_id bigint >goods.good_id =l_partkey; delivery_id bigint >deliveries.delivery_id; line_no int =l_linenumber; units double =l_quantity; line_amount double =l_extendedprice
stock @stock: branch_id bigint >branches.branch_id =l_suppkey; good_id bigint >goods.good_id =l_partkey; units_available double
""",
    "dealer": """
product_families @family: family_code string pk =p_type; n_products bigint
products @part: product_code bigint pk =p_partkey; product_label string =p_name; family_code string >product_families.family_code =p_type; brand_mark string =p_brand; scale_size int =p_size; msrp double =p_retailprice
offices @office: office_code int pk; office_name string; territory string =r_name; country_label string =n_name
staff @staff: staff_no bigint pk; staff_name string; office_code int >offices.office_code; boss_no bigint >staff.staff_no
accounts @customer: account_no bigint pk =c_custkey; account_name string =c_name; rep_no bigint >staff.staff_no; country string =n_name; credit_amount double =c_acctbal
bookings @orders: booking_no bigint pk =o_orderkey; account_no bigint >accounts.account_no =o_custkey; booked_on timestamp =o_orderdate; shipped_on timestamp =l_shipdate; progress string =o_orderstatus
booking_items @lineitem: booking_no bigint >bookings.booking_no =l_orderkey; product_code bigint >products.product_code =l_partkey; item_seq int =l_linenumber; quantity_ordered double =l_quantity; price_total double =l_extendedprice
receipts @receipt: receipt_no bigint pk; account_no bigint >accounts.account_no =o_custkey; paid_amount double =o_totalprice; paid_on timestamp
""",
    "rental": """
continents @region: continent_id int pk =r_regionkey; continent_name string =r_name
countries @nation: country_id int pk =n_nationkey; country_name string =n_name; continent_id int >continents.continent_id =n_regionkey
places @place: place_id bigint pk; country_id int >countries.country_id =c_nationkey
tiers @tier: tier_id int pk; tier_name string =c_mktsegment
outlets @supplier: outlet_id bigint pk =s_suppkey; outlet_name string =s_name; country_id int >countries.country_id =s_nationkey; outlet_balance double =s_acctbal
members @customer: member_id bigint pk =c_custkey; member_name string =c_name; place_id bigint >places.place_id; outlet_id bigint >outlets.outlet_id; tier_id int >tiers.tier_id
balances @balance: member_id bigint pk >members.member_id; balance double =c_acctbal
kinds @family: kind_id int pk; kind_name string =p_type
imprints @imprint: imprint_id int pk; imprint_name string =p_brand
titles @part: title_id bigint pk =p_partkey; title_name string =p_name; kind_id int >kinds.kind_id; imprint_id int >imprints.imprint_id; run_size int =p_size; rate double =p_retailprice
holdings @holding: holding_id bigint pk; title_id bigint >titles.title_id =l_partkey; outlet_id bigint >outlets.outlet_id =l_suppkey
urgencies @urgency: urgency_id int pk; urgency_name string =o_orderpriority
hires @orders: hire_id bigint pk =o_orderkey; member_id bigint >members.member_id =o_custkey; hire_date timestamp =o_orderdate; state_code string =o_orderstatus; urgency_id int >urgencies.urgency_id
hire_lines @lineitem: hire_id bigint >hires.hire_id =l_orderkey; holding_id bigint >holdings.holding_id; seq int =l_linenumber; copies double =l_quantity; return_date timestamp =l_shipdate
charges @receipt: charge_id bigint pk; hire_id bigint >hires.hire_id; member_id bigint >members.member_id =o_custkey; amount double =o_totalprice
""",
    "corpus": """
documents @documents: doc_id bigint pk; text string; lang string; source string; n_chars bigint
labels @labels: doc_id bigint pk >documents.doc_id; quality int; toxic int
pages @pages: page_id bigint pk; url string; html string
benchmark @benchmark: item_id bigint pk; text string
conversations @conversations: conv_id bigint pk; turn bigint pk; role string; text string
embeddings @embeddings: vec_id bigint pk; embedding array<float>; label int
events @events: event_id bigint pk; ts timestamp; user_id bigint; event_type string; value double; props string
""",
}
